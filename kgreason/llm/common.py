"""Helpers shared by the training-data operators."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import Scratch, scratch_path, ship

__all__ = ["SLICE_ROWS", "SPACE_BYTES", "Scratch", "arrow", "keyed", "materialize", "mix64", "renamed_back", "row_keys", "same_row", "signed", "slices", "spare", "table"]

#: Bytes in [\x20\x09-\x0D]; bytes.split() and bytes.strip() use exactly these.
SPACE_BYTES = b"\t\n\x0b\x0c\r "

#: Rows of an Arrow batch that are turned into Python strings at once.
SLICE_ROWS = 256


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def materialize(df: DataFrame, label: str = "t") -> DataFrame:
    """Writes df as Parquet to the shared folder and reads it again: lineage ends in a file that
    survives the loss of any executor."""
    spark = df.sparkSession
    path = scratch_path(spark, label)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def arrow(df: DataFrame, scan, schema) -> DataFrame:
    """mapInArrow, with this package at hand in the workers whatever session df comes from."""
    ship(df.sparkSession)
    return df.mapInArrow(scan, schema)


def spare(df: DataFrame, names: tuple[str, ...]) -> DataFrame:
    """df with columns that bear one of the names, in any case, renamed to ``input_<name>`` (and further underscores while that is taken)."""
    taken, wanted = {c.lower() for c in df.columns}, {n.lower() for n in names}
    for c in df.columns:
        if c.lower() in wanted:
            new = f"input_{c}"
            while new.lower() in taken or new.lower() in wanted:
                new += "_"
            taken.add(new.lower())
            df = df.withColumnRenamed(c, new)
    return df


def renamed_back(df: DataFrame, names: list[str]) -> DataFrame:
    """df, which begins with columns that ``spare`` may have renamed, under the given names of those alone."""
    return df.select(*[F.col(f"`{c}`").alias(n) for c, n in zip(df.columns, names, strict=False)])


def keyed(docs: DataFrame) -> DataFrame:
    """(doc_id, text, text_hash): id and hash stand for a row where ids may be null or repeated; rows that share both have the same text."""
    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text", F.xxhash64("text").alias("text_hash"))


def row_keys(df: DataFrame, *others: str) -> DataFrame:
    """The right side of a join by ``same_row``."""
    return df.select(F.col("doc_id").alias("__id"), F.col("text_hash").alias("__hash"), *others)


def same_row(left: DataFrame, right: DataFrame) -> Column:
    return left["doc_id"].cast("bigint").eqNullSafe(right["__id"]) & (left["text_hash"] == right["__hash"])


def slices(batch, rows: int = SLICE_ROWS):
    """Cuts an Arrow batch, so that few Python strings live at a time."""
    for i in range(0, batch.num_rows, rows):
        yield batch.slice(i, rows)


def mix64(x: np.ndarray, seed: int = 0) -> np.ndarray:
    """A bijection of 64-bit words (the finaliser of splitmix64), vectorised."""
    x = x.astype(np.uint64, copy=True)
    x += np.uint64((0x9E3779B97F4A7C15 * (seed + 1)) & 0xFFFFFFFFFFFFFFFF)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def signed(x: np.ndarray) -> np.ndarray:
    return np.asarray(x, dtype=np.uint64).view(np.int64)
