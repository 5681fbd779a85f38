"""Files, SQL functions, aggregates, table functions, streams."""

import datetime as dt

import pytest
from helpers import rows_of
from pyspark.sql import functions as F

from kgreason.functions import sqlfn
from kgreason.functions.vectors import Numeric
from kgreason.ids import eid_value
from kgreason.operators.graph import adjacency, neighbourhood, one_hop, open_graph
from kgreason.operators.hops import anchor_hop
from kgreason.operators.lookup import lookup_salted, lookup_vectors
from kgreason.operators.graph import role_members
from kgreason.operators.paths import exact_paths
from kgreason.plans import measures
from kgreason.plans import workloads as w
from kgreason.sources.files import read_triples, read_vectors, write_answers, write_relation_tables, write_vector_table
from kgreason.streaming import edges


@pytest.mark.parametrize("fmt,lines", [("tsv", "a\t1\t2\na\t1\t2\nbad\tx\t3\nc\t4\n\nd\t5\t6"), ("csv", "a,1,2\na,1,2\nbad,x,3\nc,4\nd,5,6"), ("text", "a 1 2\na 1 2\nbad x 3\nc 4\nd  5 6"), ("json", '{"r":"a","h":1,"t":2}\n{"r":"a","h":1,"t":2}\n{"r":"bad","h":"x","t":3}\n{nonsense\n{"r":"d","h":5,"t":6}')])
def test_triple_files(spark, tmp_path, fmt, lines):
    (tmp_path / "t.txt").write_text(lines)
    good, bad = read_triples(spark, str(tmp_path / "t.txt"), fmt)
    assert sorted((r["r"], r["h"], r["t"]) for r in good.collect()) == [("a", 1, 2), ("d", 5, 6)]
    assert bad.count() == 2
    with pytest.raises(Exception, match="not a triple"):
        read_triples(spark, str(tmp_path / "t.txt"), fmt, "FAILFAST")[0].collect()


def test_triple_columns(spark, tmp_path):
    spark.createDataFrame([("a", 1, 2), ("a", 1, 2), ("b", None, 1), (None, 1, 1)], "r string, h bigint, t bigint").write.parquet(f"{tmp_path}/p")
    good, bad = read_triples(spark, f"{tmp_path}/p")
    assert good.count() == 1 and bad.count() == 2


def test_vector_files(spark, tmp_path):
    (tmp_path / "v.txt").write_text("1 0.5 1\n2 1 2\n2 1 2\n3 1\n4 x 1\nx 1 1\n5 1e3 -2\n")
    good, bad = read_vectors(spark, str(tmp_path / "v.txt"), "text", dim=2)
    assert {r["eid"]: r["vec"] for r in good.collect()} == {1: [0.5, 1.0], 5: [1000.0, -2.0]}
    assert sorted(r["eid"] or 0 for r in bad.collect()) == [0, 2, 3, 4]
    trimmed, _ = read_vectors(spark, str(tmp_path / "v.txt"), "text", dim=2, keep=1)
    assert {len(r["vec"]) for r in trimmed.collect()} == {1}
    with pytest.raises(ValueError):
        read_vectors(spark, "x", "xml")


def test_sinks(spark, sf, tmp_path):
    kg = w.workload_graph(spark, sf, "w1")
    write_relation_tables(kg.triples, f"{tmp_path}/r")
    assert rows_of(spark.read.parquet(f"{tmp_path}/r").select("r", "h", "t")) == rows_of(kg.triples.select("r", "h", "t"))
    write_vector_table(kg.vectors, f"{tmp_path}/v", 4)
    assert "vec_head" in (p := spark.read.parquet(f"{tmp_path}/v").select("eid", "vec_head")).columns and p.count() == kg.vectors.count()
    answers = exact_paths(open_graph(spark, sf, w.G3_RELATIONS[1:3]), eid_value("nation", 3), eid_value("part", 5), 2)
    for fmt in ("json", "csv", "parquet"):
        write_answers(answers, f"{tmp_path}/{fmt}", fmt)
        assert len(list((tmp_path / fmt).iterdir())) > 0
    with pytest.raises(ValueError):
        write_answers(answers, "x", "xls")


def test_bucketed_tables(spark, sf, tmp_path):
    kg = w.workload_graph(spark, sf, "w1")
    spark.sql("drop table if exists t_vec")
    write_vector_table(kg.vectors, f"{tmp_path}/b", 4, 4, "t_vec")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = spark.table("t_vec").alias("a").join(spark.table("t_vec").alias("b"), "eid")._jdf.queryExecution().executedPlan().toString()
        assert "Exchange" not in plan  # both sides lie in buckets of the key
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        spark.sql("drop table t_vec")


def test_lookups(spark, sf):
    kg = w.workload_graph(spark, sf, "w1")
    ids = kg.vectors.select("eid").union(spark.createDataFrame([(77,)], "eid bigint"))
    base = rows_of(lookup_vectors(ids, kg.vectors).select("eid"))
    for strategy in ("broadcast", "shuffle_hash", "sortmerge"):
        assert rows_of(lookup_vectors(ids, kg.vectors, strategy).select("eid")) == base
    assert rows_of(lookup_salted(ids, kg.vectors).select("eid")) == base
    assert lookup_vectors(ids, kg.vectors, missing="neg_inf").where("vec is null").count() == 1
    with pytest.raises(ValueError):
        lookup_vectors(ids, kg.vectors, "guess")


def test_sql_surface(spark, sf):
    kg = open_graph(spark, sf, w.WORKLOADS["w1"].relations(), numeric=Numeric("double"))
    sqlfn.register(spark)
    sqlfn.create_views(kg)
    q = w.WORKLOADS["w1"]
    own = sqlfn.hop_sql(spark, eid_value(*q.anchor1), q.relation1, q.relation1, 10).collect()
    api = anchor_hop(kg, eid_value(*q.anchor1), q.relation1, role_members(kg.triples, q.relation1), 10).orderBy("rank").collect()
    assert [r["eid"] for r in own] == [r["eid"] for r in api] and [r["score"] for r in own] == pytest.approx([r["score"] for r in api])
    scored = spark.createDataFrame([("x", 1, 0.5), ("x", 2, 0.75), ("x", 3, 0.75), ("y", 4, 1.0)], "g string, eid bigint, score double")
    scored.createOrReplaceTempView("scored")
    top = {r["g"]: [(x["eid"], x["score"]) for x in r["best"]] for r in spark.sql("select g, kg_top(eid, score, 2) as best from scored group by g").collect()}
    assert top == {"x": [(2, 0.75), (3, 0.75)], "y": [(4, 1.0)]}
    rows = spark.sql("select * from kg_topk(table(select * from scored) partition by (g), 2)").collect()
    assert sorted((r["g"], r["rank"], r["eid"]) for r in rows) == [("x", 1, 2), ("x", 2, 3), ("y", 1, 4)]
    arrow = spark.sql("select array(0D, 1D) a, array(1D, 1D) b").select(sqlfn.translation_score_arrow("a", "b").alias("s")).first()["s"]
    assert arrow == 0.0


def test_recursion_equals_exact(spark, sf):
    kg = open_graph(spark, sf, w.G3_RELATIONS[1:])
    sqlfn.create_views(kg)
    s, t = eid_value("nation", 3), eid_value("supplier", 5)
    a = {tuple(r["path"]) for r in spark.sql(sqlfn.recursive_paths_sql(s, t, 3)).collect()}
    assert a == {tuple(r["path"]) for r in exact_paths(kg, s, t, 3).collect()} and len(a) == 149


def test_neighbourhood(spark, sf):
    kg = w.workload_graph(spark, sf, "w1")
    near = {r["hops"]: r["count"] for r in neighbourhood(kg, eid_value("nation", 3), 2).groupBy("hops").count().collect()}
    assert near[0] == 1 and near[1] == one_hop(kg, eid_value("nation", 3), "nation_hosts_customer").count() and near[2] > 0
    assert adjacency(kg.triples, typed=False).where(F.col("h") == eid_value("nation", 3)).first()["neighbours"]


def test_measures(spark, sf):
    kg = w.workload_graph(spark, sf, "w1")
    times = measures.timed_hops(kg, w.WORKLOADS["w1"])
    assert set(times) == {"hop1", "hop2", "hop3"} and all(t > 0 for t in times.values())
    assert measures.scaling_curve(lambda c: 8 / c, [1, 2, 4]) == [(1, 8.0, 1.0), (2, 4.0, 2.0), (4, 2.0, 4.0)]
    big, small = (measures.moved(spark, lambda n=n: spark.range(n).repartition(5).count()) for n in (20_000, 200))
    assert big["shuffle_records"] >= 20_000 > small["shuffle_records"] and big["tasks"] > 0
    skew = measures.partition_skew(spark.range(100).repartition(4)).first()
    assert skew["partitions"] == 4 and skew["largest"] >= skew["median"]


@pytest.fixture(scope="module")
def slices(spark, sf, tmp_path_factory):
    """The event table as ten files of ascending time, and two late rows in an eleventh."""
    path = tmp_path_factory.mktemp("events")
    rows = spark.read.parquet(f"{sf}/events.parquet").orderBy("ts").collect()
    schema = spark.read.parquet(f"{sf}/events.parquet").schema
    step = -(-len(rows) // 10)
    for i in range(10):
        spark.createDataFrame(rows[i * step : (i + 1) * step], schema).coalesce(1).write.mode("append").parquet(str(path / f"{i:02d}"))
    late = [rows[0].asDict() | {"event_id": 10**6 + i, "ts": rows[0]["ts"] - dt.timedelta(days=9)} for i in range(2)]
    spark.createDataFrame([tuple(x.values()) for x in late], schema).coalesce(1).write.parquet(str(path / "late"))
    return path, schema


def test_stream_equals_batch(spark, sf, slices):
    path, schema = slices
    batch = spark.read.parquet(f"{sf}/events.parquet")
    stream = edges.read_stream(spark, str(path / "0*"), schema)
    q = edges.run_to_end(edges.windowed_edges(stream, "1 day"), "complete")
    assert rows_of(spark.table(q.name)) == rows_of(edges.windowed_edges(batch, "1 day"))
    q = edges.run_to_end(edges.triple_stream(edges.read_stream(spark, str(path / "0*"), schema)), "append")
    assert rows_of(spark.table(q.name)) == rows_of(batch.select("event_type", "user_id").distinct())
    q = edges.run_to_end(edges.windowed_edges(stream, "1 day", lateness="1 hour"), "append")
    closed = spark.table(q.name)
    whole = edges.windowed_edges(batch, "1 day")
    assert closed.exceptAll(whole).isEmpty() and closed.count() < whole.count()  # windows still open are missing


def test_click_purchase(spark, sf, slices):
    path, schema = slices
    q = edges.run_to_end(edges.click_purchase_stream(edges.read_stream(spark, str(path / "0*"), schema)), "append")
    batch = spark.read.parquet(f"{sf}/events.parquet")
    left = batch.where("event_type = 'click'").selectExpr("event_id as click_id", "user_id", "ts")
    right = batch.where("event_type = 'purchase'").selectExpr("event_id as purchase_id", "user_id", "ts")
    assert rows_of(spark.table(q.name)) == rows_of(edges.within(left, right, "user_id", "ts", 24).select("user_id", "click_id", "purchase_id"))


def test_standing_answers(spark, tmp_path):
    for i, rows in enumerate([[("a", 1, 1.0), ("a", 2, 3.0), ("b", 1, 0.5)], [("a", 3, 2.0), ("a", 2, 3.0)]]):
        spark.createDataFrame(rows, "anchor string, eid bigint, score double").coalesce(1).write.parquet(f"{tmp_path}/in/{i}")
    stream = spark.readStream.schema("anchor string, eid bigint, score double").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in/*")
    q = edges.upsert_answers(edges.heap_stream(stream, 2), f"{tmp_path}/out", ["anchor"], f"{tmp_path}/ck")
    q.awaitTermination()
    got = sorted((r["anchor"], r["rank"], r["eid"]) for r in spark.read.parquet(f"{tmp_path}/out").collect())
    assert got == [("a", 1, 2), ("a", 2, 3), ("b", 1, 1)]
