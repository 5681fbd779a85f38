"""Top-K lists: private bounded heaps, tree merging, and the forms they are compared with.

All forms share one total order (score descending, then id ascending), so that
top-K(A + B) = top-K(top-K(A) + top-K(B)) and every form, partitioning and merge tree gives the same rows.
Input has ``eid, score`` and any key columns; output has ``rank`` from 1 beside them.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

FORMS = ("auto", "native", "heap_tree", "heap_funnel", "shared_list", "full_sort")
#: Partitions from which ``auto`` merges by tree: below, one reducer of partitions * K rows is cheaper than rounds.
TREE_FROM = 10_000
#: The largest K for which Spark keeps bounded lists in windows; above, Arrow heaps do it.
WINDOW_LIMIT = 1000


def _order() -> list:
    return [F.col("score").desc(), F.col("eid").asc()]


def check_k(k: int) -> int:
    if not isinstance(k, int) or k <= 0:
        raise ValueError(f"K must be a positive integer, not {k!r}")
    return k


def topk_native(scored: DataFrame, k: int) -> DataFrame:
    """Spark's own: bounded queues in the tasks, merged by one reducer."""
    best = scored.orderBy(*_order()).limit(check_k(k))
    return best.withColumn("rank", F.row_number().over(Window.orderBy(*_order())))


def topk_grouped(scored: DataFrame, k: int, keys: list[str], form: str = "native", fan_in: int = 2, workers: int | None = None) -> DataFrame:
    """K best of each key; the rank bound lets Spark cut lists before the shuffle.

    heap_tree merges the lists of each key in rounds, so that no task sees more than fan_in lists of a key however many tasks there are; native and
    heap_funnel bring the lists of a key together at once; shared_list brings all of its rows together.
    """
    check_k(k)
    if form == "shared_list":
        all_ = scored.groupBy(*keys).agg(F.sort_array(F.collect_list(F.struct(F.col("score"), (-F.col("eid")).alias("minus"))), asc=False).alias("all"))
        cut = all_.select(*keys, F.posexplode(F.slice("all", 1, k)).alias("at", "x"))
        return cut.select(*keys, (-F.col("x.minus")).alias("eid"), F.col("x.score").alias("score"), (F.col("at") + 1).alias("rank"))
    if form == "heap_tree":
        return publish(merge_tree(private_lists(scored, k, keys, workers), k, fan_in, keys, workers), keys)
    if form not in ("auto", "native", "heap_funnel"):
        raise ValueError(f"form {form!r} does not go by key")
    if k > WINDOW_LIMIT:
        return publish(merge_funnel(topk_local(scored, k, keys), k, keys), keys)
    w = Window.partitionBy(*keys).orderBy(*_order())
    return scored.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def _workers(df: DataFrame, workers: int | None) -> int:
    """So many as are named; else as the session shuffles to."""
    return workers or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def private_lists(scored: DataFrame, k: int, keys: list[str] | None = None, workers: int | None = None) -> DataFrame:
    """Rows with the number of the task that scored them as ``worker`` (folded to so many workers); no row moves for that.

    Up to WINDOW_LIMIT the first merge cuts each task's rows to K a key before its shuffle; above, Arrow heaps do so here.
    """
    if check_k(k) > WINDOW_LIMIT:
        return topk_local(scored, k, keys, workers)
    return scored.select(*(keys or []), "eid", "score").withColumn("worker", F.spark_partition_id() % F.lit(_workers(scored, workers)))


def topk_local(scored: DataFrame, k: int, keys: list[str] | None = None, workers: int | None = None) -> DataFrame:
    """Bounded list of each task and key, through Arrow, with the task's number (folded to so many workers) as ``worker``.

    A task holds K rows for each key that it meets, so the keys that meet in a task bound its memory; the engine's are heads, of which there are K.
    """
    keys = keys or []
    check_k(k)
    names, folded = [*keys, "eid", "score"], _workers(scored, workers)
    schema = T.StructType([T.StructField("worker", T.IntegerType()), *[T.StructField(f.name, f.dataType) for f in scored.select(*names).schema]])

    def best(table: pa.Table) -> pa.Table:
        score, ids = table["score"].to_numpy(), table["eid"].to_numpy()
        if not keys:
            return table.take(np.lexsort((ids, -score))[:k])
        codes = [np.unique(table[c].to_numpy(), return_inverse=True)[1] for c in keys]
        order = np.lexsort((ids, -score, *codes))
        new = np.ones(len(order), bool)
        new[1:] = np.any([c[order][1:] != c[order][:-1] for c in codes], axis=0)
        start = np.maximum.accumulate(np.where(new, np.arange(len(order)), 0))
        return table.take(order[np.arange(len(order)) - start < k])

    def scan(batches):
        from pyspark import TaskContext

        worker, kept = TaskContext.get().partitionId() % folded, None
        for batch in batches:
            own = best(pa.Table.from_batches([batch]))
            kept = own if kept is None else best(pa.concat_tables([kept, own]))
        if kept is not None:
            for batch in kept.combine_chunks().to_batches():
                yield pa.RecordBatch.from_arrays([pa.array(np.full(batch.num_rows, worker, np.int32)), *batch.columns], ["worker", *names])

    return scored.select(*names).mapInArrow(scan, schema)


def merge_rounds(workers: int, fan_in: int) -> int:
    if fan_in < 2:
        raise ValueError("fan-in must be 2 or more")
    rounds = 0
    while workers > 1:
        workers = -(-workers // fan_in)
        rounds += 1
    return rounds


def merge_tree(local: DataFrame, k: int, fan_in: int = 2, keys: list[str] | None = None, workers: int | None = None) -> DataFrame:
    """Merges lists in rounds of fan_in; a task never sees more than fan_in * K rows of a key and worker, in the first round of as many tasks as share a number."""
    keys = keys or []
    rounds = merge_rounds(_workers(local, workers), fan_in)
    for _ in range(max(1, rounds)):
        local = local.withColumn("worker", F.expr(f"cast(worker div {fan_in} as int)") if rounds else F.lit(0))
        w = Window.partitionBy(*keys, "worker").orderBy(*_order())
        local = local.withColumn("__r", F.row_number().over(w)).where(F.col("__r") <= k).drop("__r")
    return local.drop("worker")


def merge_funnel(local: DataFrame, k: int, keys: list[str] | None = None) -> DataFrame:
    """All lists into one reducer a key; the rank bound cuts each task's rows before."""
    w = Window.partitionBy(*(keys or [])).orderBy(*_order())
    return local.drop("worker").withColumn("__r", F.row_number().over(w)).where(F.col("__r") <= k).drop("__r")


def publish(merged: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """Adds ranks to merged lists."""
    w = Window.partitionBy(*keys).orderBy(*_order()) if keys else Window.orderBy(*_order())
    return merged.withColumn("rank", F.row_number().over(w))


def topk_shared_list(scored: DataFrame, k: int, max_rows: int | None = 50_000_000) -> DataFrame:
    """The baseline: every scored row goes into one list, which is then sorted and cut.

    One reducer holds everything, on purpose; max_rows refuses input that no reducer could hold.
    """
    check_k(k)
    if max_rows is not None and scored.count() > max_rows:
        raise ValueError(f"the shared list is a baseline for up to {max_rows} rows")
    listed = scored.groupBy().agg(F.sort_array(F.collect_list(F.struct(F.col("score"), (-F.col("eid")).alias("minus"))), asc=False).alias("all"))
    cut = listed.select(F.posexplode(F.slice("all", 1, k)).alias("at", "x"))
    return cut.select((-F.col("x.minus")).alias("eid"), F.col("x.score").alias("score"), (F.col("at") + 1).alias("rank"))


def topk_full_sort(scored: DataFrame, k: int) -> DataFrame:
    """The baseline with a sort of all rows by range.

    A row's number in the sorted order is that of its partition and its place there, which no limit can be pushed below; of each partition the first K are ranked.
    """
    whole = scored.sort(*_order()).withColumn("__at", F.monotonically_increasing_id())
    place = F.col("__at").bitwiseAND(F.lit(2**33 - 1))
    ranked = whole.where(place < check_k(k)).withColumn("rank", F.row_number().over(Window.orderBy("__at")))
    return ranked.where(F.col("rank") <= k).drop("__at")


def topk(scored: DataFrame, k: int, form: str = "auto", fan_in: int = 2, workers: int | None = None) -> DataFrame:
    if form == "auto":
        form = "heap_tree" if (workers or 0) >= TREE_FROM else "native"
    if form == "native":
        return topk_native(scored, k)
    if form == "heap_tree":
        return publish(merge_tree(private_lists(scored, k, workers=workers), k, fan_in, workers=workers))
    if form == "heap_funnel":
        return publish(merge_funnel(private_lists(scored, k, workers=workers), k))
    if form == "shared_list":
        return topk_shared_list(scored, k)
    if form == "full_sort":
        return topk_full_sort(scored, k)
    raise ValueError(f"unknown form {form!r}; known: {', '.join(FORMS)}")


def merge_cost(workers: int, k: int, fan_in: int) -> dict[str, int]:
    """Rounds of a merge tree, rows it moves at most, and most rows in a task; fan_in = workers is the funnel."""
    rounds, moved, left = merge_rounds(workers, max(2, fan_in)), 0, workers
    for _ in range(rounds):
        moved += left * k
        left = math.ceil(left / max(2, fan_in))
    return {"workers": workers, "k": k, "fan_in": fan_in, "rounds": rounds, "rows_moved": moved, "rows_in_a_task": min(fan_in, workers) * k}
