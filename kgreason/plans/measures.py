"""Costs and accuracy: run times, speedups, scaling, work counters, overlap and recall."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.graph import KnowledgeGraph
from ..operators.topk import merge_rounds
from .query import ThreeHopQuery, hop1, hop2, hop3


def run_noop(df: DataFrame) -> None:
    """Runs a plan whole and throws its rows away."""
    df.write.format("noop").mode("overwrite").save()


def timed_run(query: Callable[[], DataFrame], repeats: int = 3) -> float:
    """Best wall-clock seconds of building and running a plan."""
    best = float("inf")
    for _ in range(repeats):
        t = time.perf_counter()
        run_noop(query())
        best = min(best, time.perf_counter() - t)
    return best


def timed_hops(kg: KnowledgeGraph, q: ThreeHopQuery, repeats: int = 1) -> dict[str, float]:
    """Seconds of each hop alone, its predecessors' K rows being at hand."""
    spark, out = kg.spark, {}
    first = hop1(kg, q)
    out["hop1"] = timed_run(lambda: first, repeats)
    kept = spark.createDataFrame(first.collect(), first.schema)  # K rows
    second = hop2(kg, q, kept)
    out["hop2"] = timed_run(lambda: second, repeats)
    kept = spark.createDataFrame(second.collect(), second.schema)
    third = hop3(kg, q, kept)
    out["hop3"] = timed_run(lambda: third, repeats)
    return out


def speedup(baseline: float, variant: float) -> float:
    return baseline / variant


def scaling_curve(run: Callable[[int], float], cores: list[int]) -> list[tuple[int, float, float]]:
    """(cores, seconds, speedup over the first) of a run that opens its own session of so many cores."""
    times = [(c, run(c)) for c in cores]
    return [(c, t, times[0][1] / t) for c, t in times]


def work_counters(kg: KnowledgeGraph, q: ThreeHopQuery) -> DataFrame:
    """(hop, evaluations): score evaluations that each hop makes - the whole role, K, and K times the last role."""
    known = kg.vectors.select("eid")
    p = kg.role(q.role1 or q.relation1, q.role1_end).select("eid").join(known, "eid").count()
    u = kg.role(q.role3 or q.relation3, q.role3_end).select("eid").join(known, "eid").count()
    kept = min(q.k, p)
    last = min(q.k2 or q.k, kept)
    return kg.spark.createDataFrame([("hop1", p), ("hop2", kept), ("hop3", last * u)], "hop string, evaluations bigint")


def retained_rows(partitions: int, k: int, population: int) -> dict[str, int]:
    """Rows that the shared list and the bounded lists hold."""
    return {"shared_list": population, "bounded_lists": min(population, partitions * k)}


def merge_cost_table(members: DataFrame, workers: list[int], fan_ins: list[int], k: int = 50) -> DataFrame:
    """(workers, k, fan_in, rounds, rows_moved, rows_in_a_task): what merging the lists of a role by tree costs, counted on its members, (eid), dealt to workers by id.

    A list holds the K best of the members below it, or all where they are fewer; merge_cost gives the costs of lists that are all full.
    """
    spark = members.sparkSession
    shapes = [(t, f, merge_rounds(t, f)) for t in workers for f in fan_ins if f <= max(2, t)]
    rounds = spark.createDataFrame([(t, f, r, f**r) for t, f, n in shapes for r in range(n)], "workers bigint, fan_in bigint, round bigint, width bigint")
    dealt = members.select("eid", F.explode(F.array(*[F.lit(t).cast("bigint") for t in workers])).alias("workers"))
    private = dealt.groupBy("workers", F.expr("pmod(eid, workers)").alias("worker")).agg(F.count("*").alias("n"))
    lists = private.join(F.broadcast(rounds), "workers").groupBy("workers", "fan_in", "round", F.expr("worker div width").alias("list")).agg(F.sum("n").alias("n"))
    tasks = lists.groupBy("workers", "fan_in", "round", F.expr("list div fan_in").alias("task")).agg(F.sum(F.least("n", F.lit(k))).alias("rows"))
    cost = tasks.groupBy("workers", "fan_in").agg(F.sum("rows").alias("rows_moved"), F.max("rows").alias("rows_in_a_task"))
    shown = [F.coalesce(F.col(c), F.lit(0)).cast("bigint").alias(c) for c in ("rows_moved", "rows_in_a_task")]
    return spark.createDataFrame(shapes, "workers bigint, fan_in bigint, rounds bigint").join(cost, ["workers", "fan_in"], "left").select("workers", F.lit(k).cast("bigint").alias("k"), "fan_in", "rounds", *shown)


def overlap_at_k(a: DataFrame, b: DataFrame, k: int) -> DataFrame:
    """One row (k, overlap): how many of the first K ids of two ranked lists agree."""
    left, right = a.where(F.col("rank") <= k).select("eid"), b.where(F.col("rank") <= k).select("eid")
    return left.join(right, "eid", "left_semi").agg(F.count("*").alias("overlap")).select(F.lit(k).alias("k"), "overlap")


def rank_equal(a: DataFrame, b: DataFrame, columns: list[str]) -> bool:
    """Whether two answers are the same rows, repeats counted."""
    a, b = a.select(*columns), b.select(*columns)
    return a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def recall_at_k(found: DataFrame, exact: DataFrame, k: int) -> DataFrame:
    """One row (k, hits, truth, recall): share of the K best true paths that a beam found."""
    truth = exact.where(F.col("rank") <= k).select("path", "rels")
    own = found.where(F.col("rank") <= k).select("path", "rels", F.lit(1).alias("hit"))
    return (
        truth.join(own, ["path", "rels"], "left")
        .agg(F.count("hit").alias("hits"), F.count("*").alias("truth"))
        .select(F.lit(k).alias("k"), "hits", "truth", (F.col("hits") / F.col("truth")).alias("recall"))
    )


def link_metrics(scored: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """One row (hits_at_k, mrr): per head, the rank of its true tail among all (head, eid, score) rows; truth is (head, eid)."""
    true_rows = scored.join(truth, ["head", "eid"]).select("head", F.col("eid").alias("te"), F.col("score").alias("ts"))
    better = scored.join(true_rows, "head").where((F.col("score") > F.col("ts")) | ((F.col("score") == F.col("ts")) & (F.col("eid") <= F.col("te"))))
    ranks = better.groupBy("head", "te").agg(F.count("*").alias("rank"))
    return ranks.agg(F.avg((F.col("rank") <= k).cast("double")).alias("hits_at_k"), F.avg(1 / F.col("rank")).alias("mrr"))


def partition_skew(df: DataFrame) -> DataFrame:
    """One row (partitions, largest, median): rows of the partitions of a plan's result."""
    sizes = df.groupBy(F.spark_partition_id().alias("p")).agg(F.count("*").alias("n"))
    return sizes.agg(F.count("*").alias("partitions"), F.max("n").alias("largest"), F.percentile_approx("n", 0.5).alias("median"))


def stage_totals(spark: SparkSession) -> dict[str, int]:
    """Shuffle bytes and records, spilled bytes, tasks and their milliseconds over all stages that the session still remembers."""
    sc = spark.sparkContext
    stages = sc._jsc.sc().statusStore().stageList(None, False, False, sc._gateway.new_array(sc._jvm.double, 0), None).iterator()
    out = dict.fromkeys(("shuffle_bytes", "shuffle_records", "spilled_bytes", "tasks", "task_ms"), 0)
    while stages.hasNext():
        s = stages.next()
        out["shuffle_bytes"] += s.shuffleWriteBytes()
        out["shuffle_records"] += s.shuffleReadRecords()
        out["spilled_bytes"] += s.diskBytesSpilled()
        out["tasks"] += s.numCompleteTasks()
        out["task_ms"] += s.executorRunTime()
    return out


def moved(spark: SparkSession, run: Callable[[], object]) -> dict[str, int]:
    """What a run adds to those totals."""
    before = stage_totals(spark)
    run()
    after = stage_totals(spark)
    return {k: after[k] - before[k] for k in after}
