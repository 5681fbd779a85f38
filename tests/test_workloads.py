"""Golden values, plans, counters, bad input, numeric modes, planted accuracy."""

from dataclasses import replace

import pytest
from helpers import duck, duck_rows, rows_of

from kgreason import oracles as sql
from kgreason.functions.vectors import Numeric, bind_planted
from kgreason.ids import eid_value
from kgreason.ids import dense_keys
from kgreason.operators.topk import topk_grouped
from kgreason.operators.graph import inverse_edges, load_graph, open_graph, role_members, sample_triples, save_graph
from kgreason.operators.hops import expansion_scores
from kgreason.plans import measures
from kgreason.plans import workloads as w
from kgreason.plans.query import Hop, ThreeHopQuery, hop1, hop2, hop_plan, three_hop, three_hop_simple
from kgreason.registry import oracle_sql, queries
from kgreason.sources.tables import RELATIONS, build_triples

W1 = w.WORKLOADS["w1"]


def test_golden_rows(spark, sf):
    kg = w.workload_graph(spark, sf, "w1")
    first = [(r["eid"] % 10**12, r["score"]) for r in hop1(kg, W1).orderBy("rank").limit(3).collect()]
    assert first == [(45, 0.340609073638916), (42, 0.21335911750793457), (6, 0.1947956085205078)]
    second = [(r["eid"] % 10**12, r["score"]) for r in hop2(kg, W1, hop1(kg, W1)).orderBy("rank").limit(2).collect()]
    assert second == [(62, 0.5789575576782227), (25, 0.28937268257141113)]
    third = three_hop(kg, W1).where(f"head = {eid_value('customer', 62)}").orderBy("rank").limit(2).collect()
    assert [(r["eid"] % 10**12, r["score"]) for r in third] == [(2, 0.28069210052490234), (4, 0.2466413974761963)]


@pytest.mark.parametrize("relation,counts", [("nation_hosts_customer", (150, 25, 150)), ("customer_buys_from_supplier", (1444, 150, 10)), ("order_contains_part", (5942, 1473, 200))])
def test_golden_relations(spark, sf, relation, counts):
    from kgreason.operators.graph import relation_profile

    r = relation_profile(build_triples(spark, sf, [relation])).first()
    assert (r["edges"], r["heads"], r["tails"]) == counts


@pytest.mark.parametrize("name", ["relation_vectors_mean", "hop1_missing_vectors", "three_hop_w1", "three_hop_w4", "two_hop_w8", "paths_beam_per_path_g1", "edges_asof", "stream_triples"])
def test_sql_agrees(spark, sf, name):
    assert rows_of(queries()[name](spark, sf)) == duck_rows(duck(sf), oracle_sql()[name])


def test_simple_is_optimised(spark, sf):
    kg = w.workload_graph(spark, sf, "w1")
    assert measures.rank_equal(three_hop(kg, W1), three_hop_simple(kg, W1), ["head", "eid", "score", "rank"])


def test_plans(spark, sf):
    kg = w.workload_graph(spark, sf, "w1")
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    first, whole = plan(hop1(kg, W1)), plan(three_hop(kg, W1))
    assert "TakeOrderedAndProject" in first and "aggregate(" not in first
    assert "WindowGroupLimit" in whole and "CartesianProduct" not in whole and "Python" not in whole
    assert "PartitionFilters: [isnotnull(r" in whole  # only the relations asked for are read


def test_counters_and_retained(spark, sf):
    kg = w.workload_graph(spark, sf, "w1")
    own = {r["hop"]: r["evaluations"] for r in measures.work_counters(kg, W1).collect()}
    assert own == {"hop1": 150, "hop2": 10, "hop3": 100}
    assert expansion_scores(kg, hop2(kg, W1, hop1(kg, W1)), W1.relation3, role_members(kg.triples, W1.relation3)).count() == 100
    assert measures.retained_rows(64, 50, 15000) == {"shared_list": 15000, "bounded_lists": 3200}


def test_double_mode(spark, sf):
    fixed, double = (open_graph(spark, sf, W1.relations(), numeric=Numeric(m)) for m in ("fixed", "double"))
    a = {r["eid"]: r["score"] for r in hop1(fixed, W1).collect()}
    b = {r["eid"]: r["score"] for r in hop1(double, W1).collect()}
    assert a.keys() == b.keys() and all(abs(a[k] - b[k]) <= 4 * 8 / 2**20 for k in a)


def test_scorers_agree(spark, sf):
    from kgreason.operators.hops import anchor_scores

    kg = w.workload_graph(spark, sf, "w1")
    role = role_members(kg.triples, W1.relation1)
    a, b = (rows_of(anchor_scores(kg, eid_value(*W1.anchor1), W1.relation1, role, impl=i)) for i in ("unrolled", "hof"))
    assert a == b


def test_arrow_scorer(spark, sf):
    import numpy as np

    from kgreason.functions.scoring import score_with_arrow
    from kgreason.operators.hops import anchor_scores, composite_of

    kg = w.workload_graph(spark, sf, "w1")
    role = role_members(kg.triples, W1.relation1)
    anchor = eid_value(*W1.anchor1)
    comp = np.array([composite_of(kg, anchor, W1.relation1).first()["comp"]])
    own = score_with_arrow(role.join(kg.vectors, "eid"), comp, np.array([anchor]), kg.numeric).select("eid", "score")
    assert rows_of(own) == rows_of(anchor_scores(kg, anchor, W1.relation1, role))


def test_files(spark, sf, tmp_path):
    kg = w.workload_graph(spark, sf, "w1")
    save_graph(kg, str(tmp_path))
    again = load_graph(spark, str(tmp_path))
    assert rows_of(three_hop(again, W1)) == rows_of(three_hop(kg, W1))


def test_metamorphic(spark, sf):
    kg = w.workload_graph(spark, sf, "w1")
    base = rows_of(three_hop(kg, W1))
    twice = type(kg)(kg.triples.union(kg.triples).repartition(7), kg.vectors.repartition(3), kg.relations, kg.dim, kg.numeric)
    assert rows_of(three_hop(twice, W1)) == base
    shifted = type(kg)(kg.triples, kg.vectors, kg.relations, kg.dim, kg.numeric, 3.0)
    assert [(r[0], r[1], r[2]) for r in rows_of(three_hop(shifted, W1))] == [(r[0], r[1], r[2]) for r in base]


def test_chain_is_question(spark, sf):
    kg = w.workload_graph(spark, sf, "w1")
    steps = [Hop("anchor", W1.relation1, 10, W1.anchor1), Hop("rerank", W1.relation2, 10, W1.anchor2), Hop("expand", W1.relation3, 10, output="per_head")]
    assert rows_of(hop_plan(kg, steps)) == rows_of(three_hop(kg, W1))
    with pytest.raises(ValueError):
        hop_plan(kg, steps[1:])
    with pytest.raises(ValueError):
        hop_plan(kg, [])


def test_bad_questions(spark, sf):
    for bad in (replace(W1, k=0), replace(W1, combine="x"), replace(W1, anchor1=("planet", 1)), replace(W1, output="x")):
        with pytest.raises(ValueError):
            bad.validate()
    with pytest.raises(ValueError, match="relation"):
        build_triples(spark, sf, ["no_such"])
    with pytest.raises(ValueError, match="unknown parts"):
        ThreeHopQuery.from_spec({"anchor": 1})
    spec = {"anchor1": ["nation", 3], "relation1": "nation_hosts_customer", "anchor2": ["segment", 1], "relation2": "segment_covers_customer", "relation3": "customer_buys_from_supplier", "k": 10}
    assert ThreeHopQuery.from_spec(spec) == W1


def test_planted_links_score_high(spark, sf):
    kg = open_graph(spark, sf, ["supplier_in_nation", "nation_hosts_customer"], numeric=Numeric("double"))
    edges = kg.edges("nation_hosts_customer").select("h", "t")
    rel = kg.relations.where("r = 'nation_hosts_customer'").select("vec")
    planted = bind_planted(kg.vectors, edges, rel, kg.vectors)
    customers = edges.select("t").distinct().withColumnRenamed("t", "eid")
    heads = edges.select("h").distinct().withColumnRenamed("h", "eid")
    truth = edges.groupBy("h").agg({"t": "min"}).toDF("head", "eid")
    better = type(kg)(kg.triples, planted, kg.relations, kg.dim, kg.numeric)
    own = {}
    for name, g in (("planted", better), ("composed", kg)):
        own[name] = measures.link_metrics(expansion_scores(g, heads, "nation_hosts_customer", customers), truth, 10).first()
    assert own["planted"]["hits_at_k"] > 0.7 and own["planted"]["mrr"] > 3 * own["composed"]["mrr"]


def test_helpers(spark, sf):
    triples = build_triples(spark, sf, ["nation_in_region"])
    back = inverse_edges(inverse_edges(triples))
    assert back.select("h", "t").exceptAll(triples.select("h", "t")).isEmpty()
    some = build_triples(spark, sf, ["customer_buys_part"])
    n = sample_triples(some, 0.3).count()
    assert 0.2 < n / some.count() < 0.4 and n == sample_triples(some.repartition(5), 0.3).count()


def test_every_oracle_has_a_query():
    assert set(oracle_sql()) <= set(queries())


@pytest.mark.parametrize("name", ["graph_cube", "graph_rollup"])
def test_cube_covers_all_relations(spark, sf, name):
    assert sql.triples_sql(list(RELATIONS)) in (whole := oracle_sql()[name])
    assert rows_of(queries()[name](spark, sf)) == duck_rows(duck(sf), whole)


@pytest.mark.parametrize("name", ["lookup_salted", "three_hop_w1_tree4_k50", "three_hop_w2_simple", "three_hop_w7", "paths_to_role_g2", "merge_cost_table", "work_counters", "frontier_bounds", "retained_rows"])
def test_queries_against_sql(spark, sf, name):
    assert rows_of(queries()[name](spark, sf)) == duck_rows(duck(sf), oracle_sql()[name])


def test_relation_vectors_come_from_the_tables(spark, sf):
    """Also in a session that has built the graph, whose own file of relation vectors has a row for each relation."""
    w.workload_graph(spark, sf, "w1")

    def rows_read():
        sc = spark.sparkContext
        stages = sc._jsc.sc().statusStore().stageList(None, False, False, sc._gateway.new_array(sc._jvm.double, 0), None).iterator()
        read = 0
        while stages.hasNext():
            read += stages.next().inputRecords()
        return read

    before = rows_read()
    queries()["relation_vectors_mean"](spark, sf).collect()
    assert rows_read() - before >= sum(spark.read.parquet(f"{sf}/{t}.parquet").count() for t in ("customer", "orders", "lineitem"))


def test_merge_cost_of_a_role(spark, sf):
    from kgreason.operators.topk import merge_cost

    assert "customer.parquet" in {f.rsplit("/", 1)[-1] for f in queries()["merge_cost_table"](spark, sf).inputFiles()}
    ids = spark.range(0, 64 * 50, 1, 5).toDF("eid")  # 50 for each of 64 workers: all lists are full
    for r in measures.merge_cost_table(ids, [2, 16, 64], [2, 4, 64]).collect():
        assert r.asDict() == merge_cost(r["workers"], 50, r["fan_in"])
    few = {r["workers"]: (r["rounds"], r["rows_moved"], r["rows_in_a_task"]) for r in measures.merge_cost_table(ids.where("eid < 5"), [2, 4], [2], 2).collect()}
    assert few == {2: (1, 4, 4), 4: (2, 2 + 1 + 1 + 1 + 2 + 2, 4)}
    none = measures.merge_cost_table(ids.where("eid < 0"), [2, 4], [2], 2).collect()
    assert {(r["workers"], r["rounds"], r["rows_moved"], r["rows_in_a_task"]) for r in none} == {(2, 1, 0, 0), (4, 2, 0, 0)}


def test_keys_of_strings_with_one_prefix(spark):
    words = [f"https://example.com/{i:05d}" for i in range(3000)]
    df = spark.createDataFrame([(x,) for x in words + words[:500] + [None]], "word string").repartition(7)
    for wide in (False, True):
        assert {r["word"]: r["key"] for r in dense_keys(df, "word", wide).collect()} == {x: i for i, x in enumerate(words)}


def test_tree_cuts_in_the_task(spark, sf):
    """Hop 3 by tree: each task's rows are cut before they move, and no shuffle deals the scored rows to workers."""
    df = spark.range(0, 100_000, 1, 16).selectExpr("id % 5 as head", "id as eid", "cast(hash(id) as double) as score")
    plan = topk_grouped(df, 10, ["head"], "heap_tree", 2, 8)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 4 and "Partial" in plan.split("Exchange")[-1]
    native = sorted(map(tuple, topk_grouped(df, 10, ["head"]).collect()))
    assert native == sorted((r["head"], r["eid"], r["score"], r["rank"]) for r in topk_grouped(df, 10, ["head"], "heap_tree", 2, 8).collect())


@pytest.mark.parametrize("members", [1, 7, 400])
def test_generated_roles(spark, members):
    kg = w.generated_graph(spark, members)
    assert kg.role("generated_first").count() == members and kg.role("generated_third").count() == max(1, members // 5)
    plain = rows_of(three_hop(kg, w.GENERATED))
    assert plain == rows_of(three_hop_simple(kg, w.GENERATED)) == rows_of(three_hop(kg, replace(w.GENERATED, bound_share=0.2)))
    assert len(plain) == min(members, 10) * min(max(1, members // 5), 10)
