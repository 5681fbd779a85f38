"""Vectors of given entities: the join that stands for a concurrent hash table."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

STRATEGIES = {"auto": None, "broadcast": "broadcast", "shuffle_hash": "shuffle_hash", "sortmerge": "merge"}


def lookup_vectors(ids: DataFrame, vectors: DataFrame, strategy: str = "auto", missing: str = "drop") -> DataFrame:
    """(…, vec) of rows with ``eid``; missing vectors are dropped, or null with ``neg_inf`` (they then score minus infinity).

    Rows that bring their vectors along, as the roles of a graph from files do, are not looked up.  auto leaves the choice to Spark, which broadcasts by measured size; the others are hints, for comparison.
    """
    if strategy not in STRATEGIES:
        raise ValueError(f"unknown strategy {strategy!r}; known: {', '.join(STRATEGIES)}")
    if missing not in ("drop", "neg_inf"):
        raise ValueError("missing must be 'drop' or 'neg_inf'")
    if "vec" in ids.columns:  # a role that the graph keeps with its vectors
        return ids.where(F.col("vec").isNotNull()) if missing == "drop" else ids
    right = vectors.hint(STRATEGIES[strategy]) if STRATEGIES[strategy] else vectors
    return ids.join(right, "eid", "inner" if missing == "drop" else "left")


def lookup_salted(ids: DataFrame, vectors: DataFrame, salts: int = 8) -> DataFrame:
    """The same where few entities are asked for by most rows: each vector is copied to ``salts`` buckets and rows are dealt over them."""
    left = ids.withColumn("__salt", (F.rand(7) * salts).cast("int"))
    right = vectors.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return left.join(right, ["eid", "__salt"]).drop("__salt")
