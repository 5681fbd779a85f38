"""The three kinds of hop: score a role against an anchor, re-rank survivors, expand survivors into a role.

Each is a lazy plan; composites of head and relation are computed once, on a side of 1 or K rows that is broadcast
(its size is bounded by K), and never once for each candidate.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.scoring import compose, or_minus_infinity, translation_score
from ..session import ship
from .graph import KnowledgeGraph
from .lookup import lookup_vectors
from .topk import TREE_FROM, check_k, topk, topk_grouped, topk_native

CANDIDATES = ("role", "linked", "unlinked")
COMBINE = ("replace", "sum", "min", "keep_first")
OUTPUTS = ("per_head", "merged_pairs", "merged_entities")


def _one_of(name: str, value: str, known: tuple[str, ...]) -> None:
    if value not in known:
        raise ValueError(f"unknown {name} {value!r}; known: {', '.join(known)}")


def _vec(df: DataFrame) -> list[str]:
    return ["vec"] if "vec" in df.columns else []


def composite_of(kg: KnowledgeGraph, anchor: int, relation: str) -> DataFrame:
    """One row (comp): vector of anchor + relation."""
    head = kg.vectors.where(F.col("eid") == anchor).select(F.col("vec").alias("hv"))
    rel = kg.relations.where(F.col("r") == relation).select(F.col("vec").alias("rv"))
    return head.crossJoin(F.broadcast(rel)).select(compose("hv", "rv").alias("comp"))


def score_column(kg: KnowledgeGraph, impl: str = "auto", norm: int = 1) -> Column:
    return or_minus_infinity(translation_score(F.col("comp"), F.col("vec"), kg.dim, kg.numeric, kg.gamma, norm, impl))


def anchor_scores(kg: KnowledgeGraph, anchor: int, relation: str, role: DataFrame, candidates: str = "role", missing: str = "drop", impl: str = "auto", keep: bool = False) -> DataFrame:
    """(eid, score[, vec]) of every candidate of a role, before any list is cut."""
    _one_of("candidates", candidates, CANDIDATES)
    own = role.select("eid", *_vec(role))
    if candidates != "role":
        linked = kg.edges(relation).where(F.col("h") == anchor).select(F.col("t").alias("eid"))
        own = own.join(linked, "eid", "left_semi" if candidates == "linked" else "left_anti")
    placed = lookup_vectors(own, kg.vectors, missing=missing)
    return placed.crossJoin(F.broadcast(composite_of(kg, anchor, relation))).select("eid", score_column(kg, impl).alias("score"), *(["vec"] if keep else []))


def anchor_hop(kg: KnowledgeGraph, anchor: int, relation: str, role: DataFrame, k: int, candidates: str = "role", missing: str = "drop", form: str = "auto", fan_in: int = 2, workers: int | None = None, impl: str = "auto", keep: bool = False) -> DataFrame:
    """(eid, score, rank): the K best of a role for (anchor, relation).

    keep hands their vectors on as ``vec``, where the list is Spark's own, so that later hops need not look them up.
    """
    native = form == "native" or form == "auto" and (workers or 0) < TREE_FROM
    return topk(anchor_scores(kg, anchor, relation, role, candidates, missing, impl, keep and native), check_k(k), form, fan_in, workers)


def anchor_hop_pruned(kg: KnowledgeGraph, anchor: int, relation: str, role: DataFrame, k: int, prefix: int = 2, share: float = 0.05) -> DataFrame:
    """Hop 1 in two phases, with the same answer: the K-th score of a share of the role bounds what the rest has to reach, and the
    distance over leading coordinates, which never exceeds the whole one, drops who cannot before the whole vector is scored.

    Pays where vectors are wide and their leading coordinates are a column of their own.  A share of fewer than K members bounds nothing.
    """
    if not 0 < prefix <= kg.dim:
        raise ValueError(f"prefix must be between 1 and {kg.dim}")
    comp = F.broadcast(composite_of(kg, anchor, relation))
    placed = lookup_vectors(role.select("eid"), kg.vectors).crossJoin(comp)
    some = placed.where(F.pmod(F.xxhash64("eid"), F.lit(10_000)) < int(share * 10_000)).select("eid", score_column(kg).alias("score"))
    bound = topk_native(some, check_k(k)).agg(F.when(F.count("*") >= k, F.min("score")).otherwise(F.lit(float("-inf"))).alias("bound"))
    head = translation_score(F.col("comp"), F.col("vec"), prefix, kg.numeric, kg.gamma)
    # both distances fall as coordinates are left out, so that equal ones stay
    left = placed.crossJoin(F.broadcast(bound)).where(head >= F.col("bound"))
    return topk_native(left.select("eid", score_column(kg).alias("score")), k)


def rerank_hop(kg: KnowledgeGraph, previous: DataFrame, anchor: int, relation: str, k2: int, combine: str = "replace", missing: str = "drop", keep: bool = False) -> DataFrame:
    """(eid, score, rank): survivors in the order of a second anchor; k2 below their number also filters.

    Survivors that were scored with ``drop`` all have vectors, so their K rows are broadcast to the vectors; only with ``neg_inf`` an outer join is needed.

    combine: the new score alone, sum or minimum of both, or the first score kept while the order is that of the new one.
    """
    _one_of("combine", combine, COMBINE)
    own = previous.select("eid", F.col("score").alias("first"), *_vec(previous))
    placed = lookup_vectors(F.broadcast(own) if missing == "drop" and not _vec(previous) else own, kg.vectors, missing=missing)
    placed = placed.crossJoin(F.broadcast(composite_of(kg, anchor, relation)))
    kept = ["vec"] if keep else []
    both = placed.select("eid", "first", score_column(kg).alias("second"), *kept)
    score = {"replace": F.col("second"), "sum": F.col("first") + F.col("second"), "min": F.least("first", "second"), "keep_first": F.col("second")}[combine]
    best = topk_native(both.select("eid", "first", score.alias("score"), *kept), check_k(k2))
    return best.select("eid", (F.col("first") if combine == "keep_first" else F.col("score")).alias("score"), "rank", *kept)


def expansion_scores(kg: KnowledgeGraph, heads: DataFrame, relation: str, role: DataFrame, candidates: str = "role", missing: str = "drop", impl: str = "auto", k: int | None = None, bound_share: float = 0.0) -> DataFrame:
    """(head, eid, score): every survivor with every candidate; the survivors' composites are the broadcast side.

    With bound_share and K, rows that cannot be among a head's K best are left out as they are scored: the K-th score of a share of
    the role bounds them.  Tasks then sort about K / share rows a head in place of the whole role; the K best stay the same.
    """
    _one_of("candidates", candidates, CANDIDATES)
    rel = kg.relations.where(F.col("r") == relation).select(F.col("vec").alias("rv"))
    own = heads.select("eid", *_vec(heads))
    comps = lookup_vectors(own if _vec(heads) else F.broadcast(own), kg.vectors).crossJoin(F.broadcast(rel)).select(F.col("eid").alias("head"), compose("vec", "rv").alias("comp"))
    placed = lookup_vectors(role.select("eid", *_vec(role)), kg.vectors, missing=missing)
    if candidates == "linked":
        links = kg.edges(relation).select(F.col("h").alias("head"), F.col("t").alias("eid"))
        pairs = links.join(F.broadcast(comps), "head").join(placed, "eid")
    elif bound_share and k and candidates == "role":
        some = placed.where(F.pmod(F.xxhash64("eid"), F.lit(10_000)) < max(1, int(bound_share * 10_000))).crossJoin(F.broadcast(comps))
        best = topk_grouped(some.select("head", "eid", score_column(kg, impl).alias("score")), k, ["head"])
        bounds = best.groupBy("head").agg(F.min("score").alias("bound"), F.count("*").alias("n")).where(F.col("n") >= k).select("head", "bound")
        bounded = comps.join(F.broadcast(bounds), "head", "left").select("head", "comp", F.coalesce("bound", F.lit(float("-inf"))).alias("bound"))
        pairs = placed.crossJoin(F.broadcast(bounded))
        return pairs.select("head", "eid", score_column(kg, impl).alias("score"), "bound").where("score >= bound").drop("bound")
    else:
        pairs = placed.crossJoin(F.broadcast(comps))
    scored = pairs.select("head", "eid", score_column(kg, impl).alias("score"))
    if candidates == "unlinked":
        known = kg.edges(relation).join(F.broadcast(heads.select(F.col("eid").alias("h"))), "h", "left_semi").select(F.col("h").alias("head"), F.col("t").alias("eid"))
        scored = scored.join(known, ["head", "eid"], "left_anti")
    return scored


def shape_output(per_head: DataFrame, k: int, output: str) -> DataFrame:
    """K lists as they are, the K best pairs, or the K best entities by their best head."""
    _one_of("output", output, OUTPUTS)
    if output == "per_head":
        return per_head.select("head", "eid", "score", "rank")
    if output == "merged_pairs":
        order = [F.col("score").desc(), F.col("eid").asc(), F.col("head").asc()]
        return per_head.orderBy(*order).limit(k).withColumn("rank", F.row_number().over(Window.orderBy(*order))).select("head", "eid", "score", "rank")
    return topk_native(per_head.groupBy("eid").agg(F.max("score").alias("score")), k).select("eid", "score", "rank")


def expand_hop(
    kg: KnowledgeGraph, heads: DataFrame, relation: str, role: DataFrame, k: int, candidates: str = "role", output: str = "per_head", missing: str = "drop", impl: str = "auto", bound_share: float = 0.0,
    form: str = "native", fan_in: int = 2, workers: int | None = None,
) -> DataFrame:
    """The K best candidates of each survivor, shaped as asked; form, fan_in and workers say how the lists of a survivor are merged."""
    scored = expansion_scores(kg, heads, relation, role, candidates, missing, impl, k, bound_share)
    return shape_output(topk_grouped(scored, check_k(k), ["head"], form, fan_in, workers), k, output)


def expand_hop_loop(kg: KnowledgeGraph, heads: list[int], relation: str, role: DataFrame, k: int) -> DataFrame:
    """The baseline with one plan for each survivor; heads is the driver's list of at most K ids."""
    out = None
    for head in heads:
        own = topk_native(anchor_scores(kg, head, relation, role), k).withColumn("head", F.lit(head).cast("bigint"))
        out = own if out is None else out.unionByName(own)
    if out is None:
        raise ValueError("no heads to expand")
    return out.select("head", "eid", "score", "rank")


#: Heads or candidates that one group of suggest_links scores against each other, about.
BLOCK = 4096


def _suggest_block(k: int, dim: int, gamma: float, unit: float):
    """For applyInArrow over a block of heads, a block of candidates and the links between them: K best unlinked ones of each head."""

    def run(rows: pa.Table) -> pa.Table:
        what, ids, other = (rows[c].to_numpy() for c in ("what", "eid", "other"))
        vectors = rows["vec"].combine_chunks()

        def side(kind: int) -> tuple[np.ndarray, np.ndarray]:
            at = np.flatnonzero(what == kind)
            at = at[np.argsort(ids[at], kind="stable")]
            return ids[at], vectors.take(pa.array(at)).flatten().to_numpy(zero_copy_only=False).reshape(len(at), -1)[:, :dim]

        (heads, comps), (tails, places) = side(0), side(1)
        out: list[tuple] = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))]
        if len(heads) and len(tails):
            links = what == 2
            h, t = np.searchsorted(heads, ids[links]), np.searchsorted(tails, other[links])
            known = (heads[np.minimum(h, len(heads) - 1)] == ids[links]) & (tails[np.minimum(t, len(tails) - 1)] == other[links])
            h, t = h[known], t[known]
            order = np.argsort(h, kind="stable")
            h, t = h[order], t[order]
            for a in range(0, len(heads), 256):
                b = min(a + 256, len(heads))
                total = np.zeros((b - a, len(tails)), comps.dtype)
                for i in range(dim):
                    total += np.abs(comps[a:b, i, None] - places[None, :, i])
                score = gamma - total / unit
                free = np.ones(score.shape, bool)
                x, y = np.searchsorted(h, (a, b))
                free[h[x:y] - a, t[x:y]] = False
                # linked ones last; candidates lie by id, which a stable sort keeps among equal scores
                best = np.lexsort((-score, ~free), axis=1)[:, :k]
                line = np.repeat(np.arange(b - a), best.shape[1])
                best = best.ravel()
                own = free[line, best]
                line, best = line[own], best[own]
                out.append((heads[a + line], tails[best], score[line, best].astype(np.float64)))
        return pa.table(dict(zip(("head", "eid", "score"), (pa.array(np.concatenate(c)) for c in zip(*out, strict=True)), strict=True)))

    return run


def suggest_links(kg: KnowledgeGraph, relation: str, heads: DataFrame, role: DataFrame, k: int, block: int = BLOCK) -> DataFrame:
    """Missing links: the K best candidates that a head is not linked with yet, for any number of heads.

    Heads and candidates are counted and dealt to blocks; each pair of blocks is a group that scores its own pairs and hands on K rows a
    head.  What is shuffled is each head once for each block of candidates, the other way round, and the links, never the pairs.
    """
    check_k(k)
    ship(kg.spark)
    rel = kg.relations.where(F.col("r") == relation).select(F.col("vec").alias("rv"))
    n_heads, n_tails = (max(1, math.ceil(x.count() / block)) for x in (heads, role))
    deal = lambda column, n: F.pmod(F.xxhash64(column), F.lit(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    none = F.lit(None).cast("bigint")
    comps = lookup_vectors(heads.select("eid"), kg.vectors).crossJoin(F.broadcast(rel))
    comps = comps.select(deal("eid", n_heads).alias("a"), every(n_tails).alias("b"), F.lit(0).alias("what"), "eid", none.alias("other"), compose("vec", "rv").alias("vec"))
    placed = lookup_vectors(role.select("eid"), kg.vectors)
    placed = placed.select(every(n_heads).alias("a"), deal("eid", n_tails).alias("b"), F.lit(1).alias("what"), "eid", none.alias("other"), "vec")
    links = kg.edges(relation).select(deal("h", n_heads).alias("a"), deal("t", n_tails).alias("b"), F.lit(2).alias("what"), F.col("h").alias("eid"), F.col("t").alias("other"), F.lit(None).cast(f"array<{kg.numeric.element}>").alias("vec"))
    pairs = comps.unionByName(placed).unionByName(links)
    scored = pairs.groupBy("a", "b").applyInArrow(_suggest_block(k, kg.dim, kg.gamma, kg.numeric.unit), "head bigint, eid bigint, score double")
    return shape_output(topk_grouped(scored, k, ["head"]), k, "per_head")
