"""Entity ids: one BIGINT holds the type and the key, so that joins never compare strings."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .session import Scratch

SPAN = 10**12

# Type codes, and the offsets by which types are bound to vectors.
CODES = {
    "region": 1, "nation": 2, "customer": 3, "supplier": 4, "part": 5, "order": 6, "segment": 7, "brand": 8, "ptype": 9, "user": 10, "etype": 11,
    "bucket": 12, "doc": 13, "lang": 14, "source": 15, "token": 16, "page": 17, "domain": 18, "target": 19, "conv": 20, "role": 21,
}
OFFSETS = {
    "nation": 0, "segment": 31, "customer": 67, "supplier": 131, "part": 211, "brand": 307, "ptype": 331, "user": 353, "etype": 379, "bucket": 401, "region": 421,
    "order": 431, "doc": 439, "lang": 449, "source": 457, "token": 461, "page": 463, "domain": 467, "target": 479, "conv": 487, "role": 491,
}


def code_of(etype: str) -> int:
    if etype not in CODES:
        raise ValueError(f"unknown entity type {etype!r}; known: {', '.join(sorted(CODES))}")
    return CODES[etype]


def eid(etype: str, key: Column | int) -> Column:
    return F.lit(code_of(etype) * SPAN) + (F.lit(key) if isinstance(key, int) else key).cast("bigint")


def eid_value(etype: str, key: int) -> int:
    return code_of(etype) * SPAN + key


def key_of(column: str | Column) -> Column:
    return (F.col(column) if isinstance(column, str) else column) % F.lit(SPAN)


def code_column(column: str | Column) -> Column:
    return F.expr(f"{column} div {SPAN}") if isinstance(column, str) else (column - column % F.lit(SPAN)) / F.lit(SPAN)


def dense_keys(df: DataFrame, column: str, wide: bool = False) -> DataFrame:
    """(column, key): keys 0, 1, ... of the sorted distinct strings.

    Enumerations (types, languages, segments) are numbered by one window.  ``wide`` is for strings that grow with the data: they are sorted by range
    into a table, whatever prefixes they share, and numbered within their part of it; what precedes a part comes from the counts of parts.
    """
    distinct = df.select(column).where(F.col(column).isNotNull()).distinct()
    if not wide:
        return distinct.withColumn("key", (F.row_number().over(Window.orderBy(column)) - 1).cast("bigint"))
    # written, as each run of a sort by range draws its bounds anew
    placed = distinct.repartitionByRange(column).sortWithinPartitions(column).withColumn("__at", F.monotonically_increasing_id())
    placed = Scratch(df.sparkSession).write(placed, "keys").withColumn("__part", F.shiftright("__at", 33))
    counts = placed.groupBy("__part").agg(F.count("*").alias("__n"))  # a row for each partition
    before = counts.select("__part", (F.sum("__n").over(Window.orderBy("__part")) - F.col("__n")).alias("__before"))
    return placed.join(F.broadcast(before), "__part").select(column, (F.col("__before") + F.col("__at").bitwiseAND(F.lit(2**33 - 1))).cast("bigint").alias("key"))
