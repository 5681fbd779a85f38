"""The hand fixture: every score follows from the definition."""

import math
import random

import pytest
from helpers import duck, duck_rows, hand_graph, rows_of

from kgreason.operators.hops import anchor_hop, anchor_hop_pruned, expand_hop, expand_hop_loop, rerank_hop, suggest_links
from kgreason.registry import oracle_sql, queries

A, B, P1, P2, P3, P4, U1, U2, U3 = range(1, 10)
EDGES = [("r1", A, P1), ("r1", A, P2), ("r1", A, P3), ("r1", A, P4), ("r2", B, P2), ("r3", P1, U1), ("r3", P2, U2), ("r3", P3, U3)]
VECTORS = {A: (0, 0), B: (0, 1), P1: (1, 0), P2: (1, 1), P3: (3, 0), U1: (1, 1), U2: (1, 2), U3: (5, 5)}
RELATIONS = {"r1": (1, 0), "r2": (1, 0), "r3": (0, 1)}


@pytest.fixture(scope="module")
def kg(spark):
    return hand_graph(spark, EDGES, VECTORS, RELATIONS, 2)


def role(spark, *ids):
    return spark.createDataFrame([(i,) for i in ids], "eid bigint")


def got(df, *columns):
    return [tuple(r[c] for c in columns) for r in df.orderBy("rank").collect()]


def test_first_hop(spark, kg):
    persons = role(spark, P1, P2, P3, P4)
    assert got(anchor_hop(kg, A, "r1", persons, 4, missing="neg_inf"), "eid", "score") == [(P1, 1.0), (P2, 0.0), (P3, -1.0), (P4, -math.inf)]
    assert got(anchor_hop(kg, A, "r1", persons, 4), "eid") == [(P1,), (P2,), (P3,)]
    assert got(anchor_hop(kg, A, "r1", persons, 2), "eid") == [(P1,), (P2,)]


def test_candidates(spark, kg):
    everyone = role(spark, P1, P2, P3, U1)
    assert {r["eid"] for r in anchor_hop(kg, A, "r1", everyone, 9, "linked").collect()} == {P1, P2, P3}
    assert {r["eid"] for r in anchor_hop(kg, A, "r1", everyone, 9, "unlinked").collect()} == {U1}


def test_second_hop(spark, kg):
    first = anchor_hop(kg, A, "r1", role(spark, P1, P2, P3), 2)
    assert got(rerank_hop(kg, first, B, "r2", 2), "eid", "score") == [(P2, 1.0), (P1, 0.0)]
    assert got(rerank_hop(kg, first, B, "r2", 2, "sum"), "eid", "score") == [(P1, 1.0), (P2, 1.0)]
    assert got(rerank_hop(kg, first, B, "r2", 2, "min"), "eid", "score") == [(P1, 0.0), (P2, 0.0)]
    assert got(rerank_hop(kg, first, B, "r2", 2, "keep_first"), "eid", "score") == [(P2, 0.0), (P1, 1.0)]
    assert got(rerank_hop(kg, first, B, "r2", 1), "eid") == [(P2,)]


def test_third_hop(spark, kg):
    heads, targets = role(spark, P1, P2), role(spark, U1, U2, U3)
    lists = expand_hop(kg, heads, "r3", targets, 3)
    by_head = {h: [(r["eid"], r["score"]) for r in lists.where(f"head = {h}").orderBy("rank").collect()] for h in (P1, P2)}
    assert by_head == {P2: [(U2, 1.0), (U1, 0.0), (U3, -6.0)], P1: [(U1, 1.0), (U2, 0.0), (U3, -7.0)]}
    assert got(expand_hop(kg, heads, "r3", targets, 2, output="merged_entities"), "eid", "score") == [(U1, 1.0), (U2, 1.0)]
    assert got(expand_hop(kg, heads, "r3", targets, 2, output="merged_pairs"), "head", "eid") == [(P1, U1), (P2, U2)]
    loop = expand_hop_loop(kg, [P1, P2], "r3", targets, 3)
    assert sorted(map(tuple, loop.collect())) == sorted(map(tuple, lists.collect()))
    assert got(suggest_links(kg, "r3", role(spark, P2), targets, 3), "eid", "score") == [(U1, 0.0), (U3, -6.0)]
    assert got(expand_hop(kg, role(spark, P2), "r3", targets, 3, "linked"), "eid") == [(U2,)]


def test_bad_parts(spark, kg):
    with pytest.raises(ValueError, match="candidates"):
        anchor_hop(kg, A, "r1", role(spark, P1), 1, "some")
    with pytest.raises(ValueError, match="positive"):
        anchor_hop(kg, A, "r1", role(spark, P1), 0)
    with pytest.raises(ValueError, match="combine"):
        rerank_hop(kg, role(spark, P1), B, "r2", 1, "mix")
    assert anchor_hop(kg, A, "r1", role(spark), 3).count() == 0
    assert anchor_hop(kg, 999, "r1", role(spark, P1), 3).count() == 0


def test_pruning_is_exact(spark, sf):
    from kgreason.operators.graph import role_members
    from kgreason.plans import workloads as w
    from kgreason.ids import eid_value

    kg, q = w.workload_graph(spark, sf, "w1"), w.WORKLOADS["w1"]
    everyone = role_members(kg.triples, q.relation1)
    whole = sorted(map(tuple, anchor_hop(kg, eid_value(*q.anchor1), q.relation1, everyone, 10).collect()))
    for prefix, share in ((1, 0.3), (4, 0.5), (8, 0.01)):
        assert sorted(map(tuple, anchor_hop_pruned(kg, eid_value(*q.anchor1), q.relation1, everyone, 10, prefix, share).collect())) == whole
    with pytest.raises(ValueError):
        anchor_hop_pruned(kg, 1, q.relation1, everyone, 10, 9)


def test_bound_keeps_the_best(spark, sf):
    from dataclasses import replace

    from kgreason.plans import workloads as w
    from kgreason.plans.query import three_hop

    kg, q = w.workload_graph(spark, sf, "w6"), w.WORKLOADS["w6"]
    plain, bounded = (sorted(map(tuple, three_hop(kg, replace(q, bound_share=x)).collect())) for x in (0.0, 0.1))
    assert plain == bounded and len(plain) == 100


@pytest.mark.parametrize("block", [3, 4096])
def test_links_for_all_heads(spark, block):
    rng = random.Random(6)
    heads, tails = list(range(1, 24)), list(range(101, 118))
    vectors = {i: (rng.randrange(5), rng.randrange(5)) for i in heads + tails if i not in (5, 105)}
    edges = [("r", h, t) for h in heads for t in tails if rng.random() < 0.3 or h == 7]
    own = hand_graph(spark, edges, vectors, {"r": (1, 0)}, 2)
    found = suggest_links(own, "r", role(spark, *heads), role(spark, *tails), 3, block).collect()
    expected = []
    for h in set(heads) - {5}:
        scores = [(-(1.0 - abs(vectors[h][0] + 1 - vectors[t][0]) - abs(vectors[h][1] - vectors[t][1])), t) for t in tails if t in vectors and ("r", h, t) not in edges]
        expected += [(h, t, -s, i + 1) for i, (s, t) in enumerate(sorted(scores)[:3])]
    assert sorted((r["head"], r["eid"], r["score"], r["rank"]) for r in found) == sorted(expected)


def test_links_query_covers_all_customers(spark, sf):
    found = queries()["suggest_links"](spark, sf)
    whole = oracle_sql()["suggest_links"]
    assert found.where("head % 1000000000000 >= 20").count() > 0
    assert rows_of(found) == duck_rows(duck(sf), whole)
