"""Sessions, and getting this package to the Python workers."""

from __future__ import annotations

import atexit
import os
import shutil
import tempfile
import uuid
import zipfile

from py4j.protocol import Py4JError
from pyspark.sql import DataFrame, SparkSession

_shipped: set[str] = set()
_local_dir: str | None = None


def shared_dir(spark: SparkSession) -> str:
    """Folder that the driver and all executors share: the one that the cluster names in ``spark.checkpoint.dir``.

    Only where that is unset, in a local session, a temporary folder takes its place.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    global _local_dir
    if _local_dir is None:
        if spark.sparkContext.master.split("[")[0] != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        folder = tempfile.mkdtemp(prefix="kgreason-")
        atexit.register(shutil.rmtree, folder, ignore_errors=True)
        _local_dir = "file://" + folder
    return _local_dir


def scratch_path(spark: SparkSession, label: str) -> str:
    """A new path in the shared folder; what lies there goes when the process ends."""
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    local = path.removeprefix("file://").removeprefix("file:")
    if local.startswith("/") and spark.sparkContext.master.split("[")[0] == "local":
        atexit.register(shutil.rmtree, local, ignore_errors=True)
    else:
        atexit.register(remove, spark, path)
    return path


def remove(spark: SparkSession, path: str) -> None:
    """Deletes a folder of any file system, if it is there and the session still lives."""
    try:
        jvm = spark.sparkContext._jvm
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    except (AttributeError, OSError, Py4JError):  # the session has ended: the cluster's own rules for old files apply
        return


class Scratch:
    """Tables that one operator writes on its way to a result, and that go once the result is written."""

    def __init__(self, spark: SparkSession):
        self.spark, self.paths = spark, []

    def write(self, df: DataFrame, label: str) -> DataFrame:
        """df as Parquet in the shared folder, read again: lineage ends in a file that survives the loss of any executor."""
        path = scratch_path(self.spark, label)
        df.write.parquet(path)
        self.paths.append(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self) -> None:
        for path in self.paths:
            remove(self.spark, path)
        self.paths = []

    def finish(self, df: DataFrame, label: str) -> DataFrame:
        """Writes the result and removes what it came from; its own table goes when the process ends."""
        out = Scratch(self.spark).write(df, label)
        self.drop()
        return out


def local_session(cores: int | str = "*", **conf: str) -> SparkSession:
    """A local session for tests and benchmarks."""
    base = {
        "spark.sql.shuffle.partitions": "8",
        "spark.sql.session.timeZone": "UTC",
        "spark.ui.enabled": "false",
        "spark.ui.showConsoleProgress": "false",
        "spark.driver.memory": "6g",
        "spark.driver.host": "127.0.0.1",
    }
    spark = SparkSession.builder.master(f"local[{cores}]").config(map=base | conf).getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def ship(spark: SparkSession) -> None:
    """Sends the sources of this package to the Python workers, once for each application.

    Workers import it to run Arrow functions; they need no installation for that.
    """
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    _shipped.add(app)
    root = os.path.dirname(os.path.abspath(__file__))
    target = os.path.join(tempfile.mkdtemp(prefix="kgreason-"), "kgreason-src.zip")
    with zipfile.ZipFile(target, "w") as z:
        for folder, _, names in os.walk(root):
            for name in names:
                if name.endswith(".py"):
                    path = os.path.join(folder, name)
                    z.write(path, os.path.relpath(path, os.path.dirname(root)))
    spark.sparkContext.addPyFile(target)
