"""Edges over time: windows, sessions, as-of and range joins, and answers kept up to date over a stream.

Batch functions take any frame, streaming or not; ``event_time`` gives the zone-less times of the given tables the type
that watermarks need.  A stream run to its end gives what the batch gives on the same rows, in update or complete mode.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming import StreamingQuery

from ..ids import dense_keys, eid, eid_value
from ..session import scratch_path
from ..sources.tables import Tables, read_table


def event_time(events: DataFrame) -> DataFrame:
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def windowed_edges(events: DataFrame, length: str, slide: str | None = None, lateness: str | None = None) -> DataFrame:
    """(event_type, first, last, edges): distinct (type, user) edges in each window."""
    own = event_time(events)
    if lateness:
        own = own.withWatermark("ts", lateness)
    windows = F.window("ts", length, slide) if slide else F.window("ts", length)
    # streams have no exact distinct count over windows: there, a set of users a type and window is kept, bounded by the users of a window
    distinct = F.size(F.collect_set("user_id")).cast("bigint") if events.isStreaming else F.countDistinct("user_id")
    grouped = own.groupBy("event_type", windows.alias("w")).agg(distinct.alias("edges"))
    return grouped.select("event_type", F.col("w.start").cast("timestamp_ntz").alias("first"), F.col("w.end").cast("timestamp_ntz").alias("last"), "edges")


def session_edges(events: DataFrame, gap: str, lateness: str | None = None) -> DataFrame:
    """(user_id, first, last, events): sessions of a user."""
    own = event_time(events)
    if lateness:
        own = own.withWatermark("ts", lateness)
    grouped = own.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("events"))
    return grouped.select("user_id", F.col("w.start").cast("timestamp_ntz").alias("first"), F.col("w.end").cast("timestamp_ntz").alias("last"), "events")


def as_of(left: DataFrame, right: DataFrame, key: str, time: str, value: str) -> DataFrame:
    """left with the ``value`` of the latest right row of its key at or before its time (the largest value of equal times), or null.

    One union and one window by key, no join of all earlier rows.
    """
    l = left.withColumns({"__side": F.lit(1), value: F.lit(None).cast(right.schema[value].dataType)})  # noqa: E741
    others = [c for c in left.columns if c not in (key, time)]
    r = right.select(key, time, value).withColumn("__side", F.lit(0)).withColumns({c: F.lit(None).cast(left.schema[c].dataType) for c in others})
    w = Window.partitionBy(key).orderBy(F.col(time), F.col("__side"), F.col(value)).rowsBetween(Window.unboundedPreceding, 0)
    both = l.unionByName(r).withColumn(value, F.last(value, ignorenulls=True).over(w))
    return both.where("__side = 1").drop("__side")


def within(left: DataFrame, right: DataFrame, key: str, time: str, hours: int) -> DataFrame:
    """Pairs of a key whose right time is at or up to so many hours after the left one.

    Times are binned by that length, so that it is an equi-join on (key, bin) with at most two bins a row.
    """
    seconds = hours * 3600
    number = lambda c: F.expr(f"unix_micros(cast({c} as timestamp)) div {seconds * 1_000_000}")
    r = right.withColumnRenamed(time, "__time").withColumn("__bin", number("__time"))
    l = left.withColumn("__bin", F.explode(F.array(number(time), number(time) + 1)))  # noqa: E741
    joined = l.join(r, [key, "__bin"])
    return joined.where((F.col("__time") >= F.col(time)) & (F.col("__time") <= F.col(time) + F.expr(f"interval {hours} hours"))).drop("__bin")


# ---------------------------------------------------------------- streams


def read_stream(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def triple_stream(events: DataFrame) -> DataFrame:
    """(event_type, user_id) the first time each pair occurs; state is bounded by types times users."""
    return events.select("event_type", "user_id").dropDuplicates(["event_type", "user_id"])


def click_purchase_stream(events: DataFrame, within_: str = "1 day", lateness: str = "1 hour") -> DataFrame:
    """Interval join of a user's clicks and the purchases that follow in time."""
    own = event_time(events).withWatermark("ts", lateness)
    c = own.where("event_type = 'click'").select(F.col("user_id").alias("cu"), F.col("ts").alias("ct"), F.col("event_id").alias("click_id"))
    p = own.where("event_type = 'purchase'").select(F.col("user_id").alias("pu"), F.col("ts").alias("pt"), F.col("event_id").alias("purchase_id"))
    return c.join(p, F.expr(f"cu = pu and pt >= ct and pt <= ct + interval {within_}")).select(F.col("cu").alias("user_id"), "click_id", "purchase_id")


HEAP_STATE = "scores array<double>, ids array<bigint>"
HEAP_OUT = "anchor string, eid bigint, score double, rank int"


def bounded_heap(k: int):
    """For applyInPandasWithState over (anchor, eid, score): the K best of each anchor so far, as state of 2 K numbers."""

    def update(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        scores, ids = state.get if state.exists else ([], [])
        best = pd.DataFrame({"eid": pd.Series(ids, dtype="int64"), "score": pd.Series(scores, dtype="float64")})
        for batch in batches:
            best = pd.concat([best, batch[["eid", "score"]]], ignore_index=True).drop_duplicates("eid").sort_values(["score", "eid"], ascending=[False, True]).head(k)
        state.update((best["score"].tolist(), best["eid"].tolist()))
        yield pd.DataFrame({"anchor": key[0], "eid": best["eid"], "score": best["score"], "rank": range(1, len(best) + 1)})

    return update


def heap_stream(scored: DataFrame, k: int) -> DataFrame:
    return scored.groupBy("anchor").applyInPandasWithState(bounded_heap(k), HEAP_OUT, HEAP_STATE, "update", "NoTimeout")


def run_to_end(df: DataFrame, mode: str, name: str | None = None) -> StreamingQuery:
    """Runs a stream over all that is there, into an in-memory table of the given name; for tests and small answers."""
    where = scratch_path(df.sparkSession, "stream")
    q = df.writeStream.format("memory").queryName(name or f"s{uuid.uuid4().hex}").outputMode(mode).option("checkpointLocation", where).trigger(availableNow=True).start()
    q.awaitTermination()
    return q


def run_to_files(df: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """Runs a stream over all that is there into Parquet in the shared folder, beside its checkpoint, and reads that back.

    Without keys rows are appended; with keys, (update mode) the rows of a key replace those that it had before.
    """
    spark, path = df.sparkSession, scratch_path(df.sparkSession, "answers")
    checkpoint = scratch_path(spark, "stream")
    if keys:
        q = upsert_answers(df, path, keys, checkpoint)
    else:
        q = df.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination()
    others = [f for f in df.schema.fields if f.name not in (keys or [])]
    schema = T.StructType([*others, *[f for f in df.schema.fields if f.name in (keys or [])]])
    return spark.read.schema(schema).parquet(path).select(*df.columns)


def upsert_answers(answers: DataFrame, path: str, keys: list[str], checkpoint: str) -> StreamingQuery:
    """Standing answers: each micro-batch replaces the partitions of the keys it changed, through foreachBatch."""

    def put(batch: DataFrame, _: int) -> None:
        batch.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(*keys).parquet(path)

    return answers.writeStream.outputMode("update").foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def stream_triples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The distinct (type, user) triples of the event stream, with entity ids."""
    events = read_table(spark, sf_dir, "events")
    found = run_to_files(triple_stream(spark.readStream.schema(events.schema).parquet(f"{sf_dir}/events.parquet*")))
    keys = dense_keys(events.select("event_type"), "event_type")
    return found.join(keys, "event_type").select(eid("etype", F.col("key")).alias("h"), eid("user", F.col("user_id")).alias("t"))


def stream_topk(spark: SparkSession, sf_dir: str, k: int, files_per_trigger: int | None = None) -> DataFrame:
    """For each event type the K best users by hop-1 score, kept in state while their triples stream in."""
    from ..operators.hops import anchor_scores
    from ..plans.workloads import workload_graph

    kg = workload_graph(spark, sf_dir, "w4")
    keys = dense_keys(Tables(spark, sf_dir).events.select("event_type"), "event_type").collect()  # a handful of types
    role = kg.edges("type_attracts_user").select(F.col("t").alias("eid")).distinct()
    scores = None
    for r in keys:
        own = anchor_scores(kg, eid_value("etype", r["key"]), "type_attracts_user", role).withColumn("event_type", F.lit(r["event_type"]))
        scores = own if scores is None else scores.unionByName(own)
    events = read_table(spark, sf_dir, "events")
    source = spark.readStream.schema(events.schema)
    stream = (source.option("maxFilesPerTrigger", files_per_trigger) if files_per_trigger else source).parquet(f"{sf_dir}/events.parquet*")
    scored = triple_stream(stream).withColumn("eid", eid("user", F.col("user_id"))).join(scores, ["event_type", "eid"]).select(F.col("event_type").alias("anchor"), "eid", "score")
    return run_to_files(heap_stream(scored, k), ["anchor"])
