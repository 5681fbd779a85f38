"""The K best paths of at most H edges from a source to a target, by beam search.

One plan: a level is a join of the frontier with the edges, the vectors of the new ends, a score, and a cut of the
frontier - K per path, K in all, or none (which is the exact enumeration).  Paths that reach the target leave the
frontier and are not counted against the cut.  At the last level only edges into the target are scored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.scoring import translation_score
from .graph import KnowledgeGraph, undirected
from .lookup import lookup_vectors
from .topk import check_k

PRUNE = ("per_path", "global", "none")
SCORERS = ("translate_sum", "translate_end", "untyped", "bottleneck")
#: Levels from which the frontier is written out, so that the plan does not grow further.
CHECKPOINT_FROM = 4


def frontier_bound(k: int, hops: int, policy: str = "per_path") -> int:
    """Size of a path buffer by the published estimate, (K^(H-1) - 1) / (K - 1), which has no value at K = 1, where each of the H - 1 levels holds one path;
    with one beam for all paths it is K a level.  See frontier_limit for what a level can really hold."""
    check_k(k)
    if policy == "per_path":
        return hops - 1 if k == 1 else (k ** (hops - 1) - 1) // (k - 1)
    if policy == "global":
        return k * max(0, hops - 1)
    raise ValueError("there is no bound without pruning")


def frontier_limit(k: int, level: int, policy: str = "per_path") -> int:
    """Most paths that leave a level: K^level when K are kept per path, K when K are kept in all."""
    check_k(k)
    if policy not in ("per_path", "global"):
        raise ValueError("there is no limit without pruning")
    return k**level if policy == "per_path" else k


def frontier_sizes(widths: DataFrame, hops: list[int]) -> DataFrame:
    """widths with (hops, policy, bound, level_limit) for every number of edges and either policy: frontier_bound and frontier_limit of its column k, whole numbers of 1 or more.

    In whole numbers, so that sizes are exact; in ANSI mode one beyond a BIGINT raises.
    """
    k, cells = F.col("k").cast("bigint"), []
    for h in hops:
        bound, limit = F.lit(0).cast("bigint"), k
        for _ in range(h - 1):
            bound, limit = bound * k + 1, limit * k
        for policy, b, n in (("per_path", bound, limit), ("global", k * max(0, h - 1), k)):
            cells.append(F.struct(F.lit(h).cast("bigint").alias("hops"), F.lit(policy).alias("policy"), b.alias("bound"), n.alias("level_limit")))
    return widths.select("*", F.inline(F.array(*cells)))


def _expand(kg: KnowledgeGraph, frontier: DataFrame, edges: DataFrame, scorer: str, dim: int, keys: list[str] | None = None, last: bool = False) -> DataFrame:
    """All simple one-edge extensions with their scores; keys go along, and at the last level of many pairs only edges into the goal count."""
    on = frontier["last"] == edges["h"]
    if last:
        on = on & (frontier["__goal"] == edges["t"])
    step = frontier.join(edges, on).where(~F.array_contains("path", F.col("t")))
    ends = lookup_vectors(step.withColumn("eid", F.col("t")), kg.vectors.withColumnRenamed("vec", "tv"))
    if scorer != "untyped":
        ends = ends.join(F.broadcast(kg.relations.select(F.col("r").alias("r"), F.col("vec").alias("rv"))), "r")
    if scorer == "translate_end":
        base = F.zip_with("pvec", "rv", lambda x, y: x + y)  # source + relations so far + this one
    elif scorer == "untyped":
        base = F.col("pvec")
    else:
        base = F.zip_with("lvec", "rv", lambda x, y: x + y)  # last vertex + relation
    # as a column of its own: the unrolled distance reads it once per dimension
    ends = ends.withColumn("base", base)
    hop = translation_score(F.col("base"), F.col("tv"), dim, kg.numeric, kg.gamma)
    if scorer == "translate_sum":
        score = F.col("score") + hop
    elif scorer == "bottleneck":
        score = F.when(F.size("rels") == 0, hop).otherwise(F.least("score", hop))
    else:
        score = hop
    if scorer == "translate_end":
        pvec = F.col("base")
    elif scorer == "untyped":  # running mean of the vertices, floored in fixed numbers
        n = F.size("path").cast("bigint")
        if kg.numeric.mode == "fixed":
            pvec = F.expr("transform(zip_with(pvec, tv, (x, y) -> x * size(path) + y), s -> (s - pmod(s, size(path) + 1)) div (size(path) + 1))")
        else:
            pvec = F.zip_with("pvec", "tv", lambda x, y: (x * n + y) / (n + 1))
    else:
        pvec = F.col("pvec")
    return ends.select(
        *(keys or []),
        F.array_append("path", F.col("t")).alias("path"),
        F.array_append("rels", F.col("r")).alias("rels"),
        pvec.alias("pvec"),
        F.col("tv").alias("lvec"),
        F.col("t").alias("last"),
        F.col("path").alias("parent"),
        F.col("rels").alias("parent_rels"),
        score.alias("score"),
    )


def _cut(grown: DataFrame, k: int, prune: str) -> DataFrame:
    order = [F.col("score").desc(), F.col("path").asc(), F.col("rels").asc()]
    if prune == "per_path":
        # the hash keeps the shuffle key narrow; the path itself settles collisions
        grown = grown.withColumn("__p", F.xxhash64("parent", "parent_rels"))
        w = Window.partitionBy("__p", "parent", "parent_rels").orderBy(*order)
        grown = grown.withColumn("__r", F.row_number().over(w)).where(F.col("__r") <= k).drop("__r", "__p")
    elif prune == "global":
        grown = grown.orderBy(*order).limit(k)
    return grown.drop("parent", "parent_rels")


def _reach(kg: KnowledgeGraph, target: int, hops: int) -> list[DataFrame]:
    """For each number of edges left, the entities from which the target can still be reached."""
    sets, own = [], kg.spark.createDataFrame([(target,)], "eid bigint")
    for _ in range(hops):
        sets.append(own)
        back = kg.triples.join(own.withColumnRenamed("eid", "t"), "t", "left_semi").select(F.col("h").alias("eid"))
        own = own.union(back).distinct()
    return sets


def k_best_paths(
    kg: KnowledgeGraph,
    source: int,
    target: int,
    hops: int,
    k: int,
    prune: str = "per_path",
    scorer: str = "translate_sum",
    direction: str = "out",
    reach_prune: bool = False,
    target_role: DataFrame | None = None,
    typed: bool = True,
) -> DataFrame:
    """(path, rels, score, hops, rank), best first; ties by path, then relations.

    direction 'both' reads edges either way; typed=False merges parallel edges, which then have no relation and the untyped score; target_role (eid) asks
    for any of its members instead of one target.  A source that is its own target has no path.
    """
    check_k(k)
    if hops < 1:
        raise ValueError("a path needs one hop at least")
    for name, value, known in (("prune", prune, PRUNE), ("scorer", scorer, SCORERS), ("direction", direction, ("out", "both"))):
        if value not in known:
            raise ValueError(f"unknown {name} {value!r}; known: {', '.join(known)}")
    if not typed:
        scorer = "untyped"
    if direction == "both":
        kg = undirected(kg)
    edges = kg.triples.select("h", "r", "t") if typed else kg.triples.select("h", F.lit("").alias("r"), "t").distinct()
    is_hit = F.col("last") == target if target_role is None else F.col("is_target")
    reach = _reach(kg, target, hops) if reach_prune and target_role is None else None
    dim = kg.dim
    start = kg.vectors.where(F.col("eid") == source)
    frontier = start.select(
        F.array("eid").alias("path"), F.expr("cast(array() as array<string>)").alias("rels"), F.col("vec").alias("pvec"), F.col("vec").alias("lvec"), F.col("eid").alias("last"), F.lit(0.0).alias("score")
    )
    hits = None
    for level in range(1, hops + 1):
        own = edges
        if level == hops:  # nothing goes on from here, so only edges into the target need scores
            own = edges.where(F.col("t") == target) if target_role is None else edges.join(target_role.select(F.col("eid").alias("t")), "t", "left_semi")
        elif reach is not None:
            own = edges.join(reach[hops - level].select(F.col("eid").alias("t")), "t", "left_semi")
        grown = _expand(kg, frontier, own, scorer, dim)
        if target_role is not None:
            grown = grown.join(target_role.select(F.col("eid").alias("last"), F.lit(True).alias("is_target")), "last", "left").withColumn("is_target", F.coalesce("is_target", F.lit(False)))
        found = grown.where(is_hit).select("path", "rels", "score", F.lit(level).alias("hops"))
        hits = found if hits is None else hits.unionByName(found)
        if level < hops:
            frontier = _cut(grown.where(~is_hit), k, prune)
            if "is_target" in frontier.columns:
                frontier = frontier.drop("is_target")
            if level >= CHECKPOINT_FROM and kg.spark.sparkContext.getCheckpointDir():
                frontier = frontier.checkpoint(eager=False)
    order = [F.col("score").desc(), F.col("path").asc(), F.col("rels").asc()]
    best = hits.orderBy(*order).limit(k) if prune != "none" else hits
    return best.withColumn("rank", F.row_number().over(Window.orderBy(*order)))


def exact_paths(kg: KnowledgeGraph, source: int, target: int, hops: int, direction: str = "out", scorer: str = "translate_sum") -> DataFrame:
    """Every simple path of at most so many edges, ranked: the ground truth of the beam."""
    return k_best_paths(kg, source, target, hops, 1, prune="none", scorer=scorer, direction=direction)


def k_best_paths_many(kg: KnowledgeGraph, pairs: DataFrame, hops: int, k: int, prune: str = "per_path", scorer: str = "translate_sum", direction: str = "out") -> DataFrame:
    """(source, target, path, rels, score, hops, rank) for every pair (source, target), as one plan: pairs run beside each other, each with its own beam."""
    check_k(k)
    for name, value, known in (("prune", prune, PRUNE), ("scorer", scorer, SCORERS), ("direction", direction, ("out", "both"))):
        if value not in known:
            raise ValueError(f"unknown {name} {value!r}; known: {', '.join(known)}")
    if direction == "both":
        kg = undirected(kg)
    edges = kg.triples.select("h", "r", "t")
    keys = ["source", "target"]
    frontier = (
        pairs.select(*keys)
        .distinct()
        .join(kg.vectors.withColumnRenamed("eid", "source"), "source")
        .select(*keys, F.array("source").alias("path"), F.expr("cast(array() as array<string>)").alias("rels"), F.col("vec").alias("pvec"), F.col("vec").alias("lvec"), F.col("source").alias("last"), F.lit(0.0).alias("score"))
    )
    order = [F.col("score").desc(), F.col("path").asc(), F.col("rels").asc()]
    hits = None
    for level in range(1, hops + 1):
        # the pair travels inside the path's row; at the last level its target is part of the join
        own = frontier.withColumn("__goal", F.col("target")) if level == hops else frontier
        grown = _expand(kg, own, edges, scorer, kg.dim, keys, last=level == hops)
        found = grown.where("last = target").select(*keys, "path", "rels", "score", F.lit(level).alias("hops"))
        hits = found if hits is None else hits.unionByName(found)
        if level < hops:
            rest = grown.where("last <> target")
            if prune != "none":
                by = [*keys, "parent", "parent_rels"] if prune == "per_path" else keys
                rest = rest.withColumn("__r", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col("__r") <= k).drop("__r")
            frontier = rest.drop("parent", "parent_rels")
    ranked = hits.withColumn("rank", F.row_number().over(Window.partitionBy(*keys).orderBy(*order)))
    return ranked if prune == "none" else ranked.where(F.col("rank") <= k)
