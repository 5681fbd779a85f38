"""Translation scores: gamma minus the distance between head + relation and tail."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .vectors import Numeric, sum_columns

GAMMA = 1.0
#: Up to so many dimensions the distance is written out, which stays inside generated code; above, a higher-order function is faster.
UNROLL_TO = 16
MINUS_INFINITY = float("-inf")


def compose(head: str | Column, relation: str | Column, sign: int = 1) -> Column:
    """head + relation; sign -1 for a relation read from tail to head."""
    return F.zip_with(head, relation, (lambda x, y: x + y) if sign > 0 else (lambda x, y: x - y))


def distance(a: Column, b: Column, dim: int, norm: int = 1, impl: str = "auto") -> Column:
    """L1, or squared-then-rooted L2, distance of two arrays."""
    if norm not in (1, 2):
        raise ValueError("norm must be 1 or 2")
    if impl == "auto":
        impl = "unrolled" if dim <= UNROLL_TO else "hof"
    if impl == "unrolled":
        d = [a[i] - b[i] for i in range(dim)]
        total = sum_columns([F.abs(x) if norm == 1 else x.cast("double") * x.cast("double") for x in d])
    elif impl == "hof":
        cell = (lambda x, y: F.abs(x - y)) if norm == 1 else (lambda x, y: (x - y).cast("double") * (x - y).cast("double"))
        zero = F.lit(0).cast("bigint") if norm == 1 else F.lit(0.0)
        pieces = F.zip_with(a, b, cell)
        total = F.aggregate(F.transform(pieces, lambda x: x.cast("double")), F.lit(0.0), lambda s, x: s + x) if norm == 2 else F.aggregate(pieces, zero, lambda s, x: s + x)
    else:
        raise ValueError(f"unknown scorer {impl!r}")
    return total if norm == 1 else F.sqrt(total)


def translation_score(composite: Column, candidate: Column, dim: int, numeric: Numeric = Numeric(), gamma: float = GAMMA, norm: int = 1, impl: str = "auto") -> Column:
    """gamma - distance in vector units; null if either side has no vector."""
    if numeric.mode == "double" and impl == "auto" and dim > UNROLL_TO:
        pieces = F.zip_with(composite, candidate, lambda x, y: F.abs(x - y) if norm == 1 else (x - y) * (x - y))
        total = F.aggregate(pieces, F.lit(0.0), lambda s, x: s + x)
        return F.lit(gamma) - (total if norm == 1 else F.sqrt(total))
    return F.lit(gamma) - distance(composite, candidate, dim, norm, impl).cast("double") / F.lit(numeric.unit)


def or_minus_infinity(score: Column) -> Column:
    return F.coalesce(score, F.lit(MINUS_INFINITY))


def arrow_scorer(composites: np.ndarray, heads: np.ndarray, numeric: Numeric, gamma: float = GAMMA):
    """For mapInArrow over (eid, vec): (head, eid, score) of every head with every candidate, in numpy blocks.

    composites is K x D, K bounded by the caller's K; a missing vector scores minus infinity.
    """
    unit = numeric.unit

    def scan(batches):
        for batch in batches:
            column = batch.column(batch.schema.names.index("vec"))
            ids = batch.column(batch.schema.names.index("eid")).to_numpy()
            known = np.array(column.is_valid())
            dim = composites.shape[1]
            table = np.zeros((len(ids), dim), composites.dtype)
            if known.any():
                table[known] = column.drop_null().flatten().to_numpy(zero_copy_only=False).reshape(-1, dim)
            for k in range(len(heads)):
                score = gamma - np.abs(table - composites[k]).sum(axis=1) / unit
                score[~known] = -math.inf
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(ids), heads[k])), pa.array(ids), pa.array(score.astype(np.float64))], ["head", "eid", "score"])

    return scan


def score_with_arrow(candidates: DataFrame, composites: np.ndarray, heads: np.ndarray, numeric: Numeric = Numeric(), gamma: float = GAMMA) -> DataFrame:
    return candidates.select("eid", "vec").mapInArrow(arrow_scorer(composites, heads, numeric, gamma), "head bigint, eid bigint, score double")


__all__ = ["GAMMA", "arrow_scorer", "compose", "distance", "or_minus_infinity", "score_with_arrow", "translation_score"]
