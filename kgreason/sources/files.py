"""Triples and vectors in files, and answers into files.

Schemas are given, never inferred; malformed rows are kept apart for a look, not dropped unseen.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..session import ship

FORMATS = ("parquet", "orc", "csv", "tsv", "json", "text")
TRIPLE_SCHEMA = "r string, h bigint, t bigint"


def _known(fmt: str) -> None:
    if fmt not in FORMATS:
        raise ValueError(f"unknown format {fmt!r}; known: {', '.join(FORMATS)}")


def read_triples(spark: SparkSession, path: str, fmt: str = "parquet", mode: str = "PERMISSIVE") -> tuple[DataFrame, DataFrame]:
    """(triples, rejected): distinct (r, h_type, h, t_type, t) and the rows that have no such reading.

    Text formats hold relation, head, tail; rejected has the raw line, or the row with nulls of a columnar format, in ``raw``.
    """
    ship(spark)
    _known(fmt)
    if fmt in ("parquet", "orc"):
        rows = spark.read.schema(TRIPLE_SCHEMA).format(fmt).load(path).withColumn("raw", F.to_json(F.struct("r", "h", "t")))
    else:
        # one line each, parsed by expressions: the reader's own record of corrupt lines cannot be asked for alone
        lines = spark.read.text(path).where("trim(value) <> ''")
        if fmt == "json":
            parsed = F.from_json("value", TRIPLE_SCHEMA)
        else:
            parts = F.split("value", "\t" if fmt == "tsv" else "," if fmt == "csv" else r"\s+")
            parsed = F.struct(
                F.when(F.size(parts) == 3, F.trim(F.get(parts, F.lit(0)))).alias("r"), F.expr("try_cast(trim(get(__p, 1)) as bigint)").alias("h"), F.expr("try_cast(trim(get(__p, 2)) as bigint)").alias("t")
            )
            lines = lines.withColumn("__p", parts)
        rows = lines.select(parsed.alias("x"), F.col("value").alias("raw")).select("x.*", "raw")
    good = F.col("r").isNotNull() & F.col("h").isNotNull() & F.col("t").isNotNull()
    rejected = rows.where(~F.coalesce(good, F.lit(False))).select("raw")
    if mode == "FAILFAST":
        rows = rows.withColumn("r", F.when(good, F.col("r")).otherwise(F.raise_error(F.concat(F.lit("not a triple: "), F.col("raw")))))
    elif mode != "PERMISSIVE":
        raise ValueError("mode must be PERMISSIVE or FAILFAST")
    triples = rows.where(good).select("r", F.lit("entity").alias("h_type"), "h", F.lit("entity").alias("t_type"), "t").distinct()
    return triples, rejected


def read_vectors(spark: SparkSession, path: str, fmt: str = "parquet", dim: int | None = None, keep: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(vectors, rejected): (eid, vec) in doubles, and the ids of vectors of another length than dim or seen twice.

    Text lines hold the id and the numbers, apart by white space; of an id that occurs twice, no vector is kept.  keep trims to the leading coordinates.
    """
    ship(spark)
    _known(fmt)
    if fmt in ("parquet", "orc"):
        rows = spark.read.format(fmt).load(path)
        first, second = rows.columns[:2]
        rows = rows.select(F.col(first).cast("bigint").alias("eid"), F.transform(second, lambda x: x.cast("double")).alias("vec"))
    elif fmt == "json":
        rows = spark.read.schema("eid bigint, vec array<double>").json(path)
    else:
        parts = F.split(F.trim("value"), "\t" if fmt == "tsv" else "," if fmt == "csv" else r"\s+")
        rows = spark.read.text(path).where("trim(value) <> ''").select(parts.alias("p"))
        rows = rows.select(F.expr("try_cast(p[0] as bigint)").alias("eid"), F.expr("transform(slice(p, 2, size(p)), x -> try_cast(x as double))").alias("vec"))
    counted = rows.groupBy("eid").agg(F.count("*").alias("n"), F.first("vec").alias("vec"))
    good = F.col("eid").isNotNull() & (F.col("n") == 1) & F.col("vec").isNotNull() & ~F.exists("vec", lambda x: x.isNull())
    if dim is not None:
        good = good & (F.size("vec") == dim)
    good = F.coalesce(good, F.lit(False))
    kept = counted.where(good).select("eid", (F.slice("vec", 1, keep) if keep else F.col("vec")).alias("vec"))
    return kept, counted.where(~good).select("eid")


def write_relation_tables(triples: DataFrame, path: str, buckets: int | None = None, table: str | None = None) -> None:
    """Triples in a folder per relation; with buckets and a table name, bucketed and sorted by head for joins without a shuffle.

    Heads of many edges can fill a folder by themselves, so files are dealt by relation and hash of the edge.
    """
    dealt = triples.repartition("r", F.pmod(F.xxhash64("h", "t"), F.lit(16)))
    if table:
        triples.write.mode("overwrite").partitionBy("r").bucketBy(buckets or 8, "h").sortBy("h").option("path", path).saveAsTable(table)
    else:
        dealt.write.mode("overwrite").partitionBy("r").parquet(path)


def write_vector_table(vectors: DataFrame, path: str, head_dim: int = 8, buckets: int | None = None, table: str | None = None) -> None:
    """Vectors with their leading coordinates as a column of their own, so that trimmed questions read a fraction of the bytes."""
    split = vectors.select("eid", F.slice("vec", 1, head_dim).alias("vec_head"), "vec")
    if table:
        split.write.mode("overwrite").bucketBy(buckets or 8, "eid").sortBy("eid").option("path", path).saveAsTable(table)
    else:
        split.repartitionByRange("eid").sortWithinPartitions("eid").write.mode("overwrite").parquet(path)


def write_answers(answers: DataFrame, path: str, fmt: str = "json") -> None:
    """An answer as JSON, CSV or Parquet; arrays become strings in CSV."""
    if fmt == "csv":
        flat = [F.concat_ws(">", F.transform(c, lambda x: x.cast("string"))).alias(c) if isinstance(answers.schema[c].dataType, T.ArrayType) else F.col(c) for c in answers.columns]
        answers.select(*flat).write.mode("overwrite").option("header", True).csv(path)
    elif fmt in ("json", "parquet"):
        answers.write.mode("overwrite").format(fmt).save(path)
    else:
        raise ValueError("answers are written as json, csv or parquet")
