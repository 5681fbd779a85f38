"""Paths by hand, against enumeration, and the traps of the beam."""

import itertools

import numpy as np
import pytest
from helpers import hand_graph

from kgreason.operators.paths import exact_paths, frontier_bound, frontier_limit, frontier_sizes, k_best_paths, k_best_paths_many

S, A, B, T = 1, 2, 3, 4
EDGES = [("e", S, A), ("e", A, T), ("e", S, T), ("e", A, B), ("e", B, S), ("e", B, T), ("e", S, B)]
VECTORS = {S: (0, 0), A: (1, 0), B: (0, 1), T: (1, 1)}


@pytest.fixture(scope="module")
def kg(spark):
    return hand_graph(spark, EDGES, VECTORS, {"e": (1, 1)}, 2)


def paths(df):
    return {tuple(r["path"]) for r in df.collect()}


def test_simple_paths(kg):
    assert paths(exact_paths(kg, S, T, 1)) == {(S, T)}
    assert paths(exact_paths(kg, S, T, 2)) == {(S, T), (S, A, T), (S, B, T)}
    assert paths(exact_paths(kg, S, T, 3)) == {(S, T), (S, A, T), (S, B, T), (S, A, B, T)}
    assert paths(exact_paths(kg, S, S, 3)) == set()
    assert paths(exact_paths(kg, T, S, 3)) == set()


def test_scores(kg):
    best = {tuple(r["path"]): r["score"] for r in exact_paths(kg, S, T, 2).collect()}
    assert best == {(S, T): 1.0, (S, A, T): 0.0 + 0.0, (S, B, T): 0.0}
    worst = {tuple(r["path"]): r["score"] for r in exact_paths(kg, S, T, 2, scorer="bottleneck").collect()}
    assert worst == {(S, T): 1.0, (S, A, T): 0.0, (S, B, T): 0.0}


def test_parallel_edges(spark):
    kg = hand_graph(spark, [("e", S, T), ("f", S, T)], {S: (0,), T: (1,)}, {"e": (1,), "f": (0,)}, 1)
    both = k_best_paths(kg, S, T, 1, 5)
    assert [(r["rels"], r["score"]) for r in both.orderBy("rank").collect()] == [(["e"], 1.0), (["f"], 0.0)]
    assert k_best_paths(kg, S, T, 1, 5, typed=False).count() == 1


def test_beam_trap(spark):
    # the K + 1 neighbours of 0 but the worst are dead ends
    edges = [("e", 0, i) for i in range(1, 5)] + [("e", 4, 9)]
    vectors = {0: (0,), 1: (1,), 2: (1.1,), 3: (1.2,), 4: (5,), 9: (6,)}
    kg = hand_graph(spark, edges, vectors, {"e": (1,)}, 1)
    assert paths(k_best_paths(kg, 0, 9, 2, 3)) == set()
    assert paths(k_best_paths(kg, 0, 9, 2, 3, prune="none")) == {(0, 4, 9)}
    assert paths(k_best_paths(kg, 0, 9, 2, 3, reach_prune=True)) == {(0, 4, 9)}
    assert paths(k_best_paths(kg, 0, 9, 2, 4)) == {(0, 4, 9)}


def brute(edges, vec, rel, s, t, hops):
    out = {}
    nodes = [n for n in vec if n not in (s, t)]
    have = {(h, x): r for r, h, x in edges}
    for n in range(hops):
        for mid in itertools.permutations(nodes, n):
            p = (s, *mid, t)
            if all((a, b) in have for a, b in zip(p, p[1:], strict=False)):
                out[p] = sum(1 - abs(vec[a][0] + rel[have[a, b]][0] - vec[b][0]) for a, b in zip(p, p[1:], strict=False))
    return out


def test_against_enumeration(spark):
    rng = np.random.default_rng(5)
    vec = {i: (float(rng.integers(0, 9)),) for i in range(7)}
    edges = [("e", a, b) for a in vec for b in vec if a != b and rng.random() < 0.45]
    rel = {"e": (1.0,)}
    kg = hand_graph(spark, edges, vec, rel, 1)
    truth = brute(edges, vec, rel, 0, 6, 3)
    found = {tuple(r["path"]): r["score"] for r in exact_paths(kg, 0, 6, 3).collect()}
    assert found == pytest.approx(truth)
    wide = k_best_paths(kg, 0, 6, 3, 100)  # K above every degree: nothing is cut
    assert {tuple(r["path"]) for r in wide.collect()} == set(truth)
    for prune in ("per_path", "global"):
        own = k_best_paths(kg, 0, 6, 3, 3, prune=prune).collect()
        assert len(own) <= 3 and all(tuple(r["path"]) in truth for r in own)


def test_bounds():
    assert frontier_bound(50, 3) == 51 and frontier_bound(1, 4) == 3 and frontier_bound(10, 3, "global") == 20
    assert frontier_limit(50, 2) == 2500 and frontier_limit(50, 2, "global") == 50
    with pytest.raises(ValueError):
        frontier_bound(5, 3, "none")


def test_sizes_of_every_width(spark):
    widths = spark.createDataFrame([(1, 4), (2, 1), (50, 7), (3000, 1)], "k bigint, entities bigint")
    own = {(r["k"], r["entities"], r["hops"], r["policy"]): (r["bound"], r["level_limit"]) for r in frontier_sizes(widths, [1, 2, 3, 4]).collect()}
    assert own == {(k, n, h, p): (frontier_bound(k, h, p), frontier_limit(k, h, p)) for k, n in ((1, 4), (2, 1), (50, 7), (3000, 1)) for h in (1, 2, 3, 4) for p in ("per_path", "global")}


def test_bounds_come_from_the_tables(spark, sf):
    from kgreason.registry import queries

    own = queries()["frontier_bounds"](spark, sf)
    assert {"orders.parquet", "lineitem.parquet"} <= {f.rsplit("/", 1)[-1] for f in own.inputFiles()}
    assert own.where("hops = 1 and policy = 'global'").agg({"entities": "sum"}).first()[0] == spark.read.parquet(f"{sf}/orders.parquet").select("o_custkey").distinct().count()


def test_many_and_roles(spark, kg):
    pairs = spark.createDataFrame([(S, T), (A, T), (A, T), (T, A)], "source bigint, target bigint")
    for prune in ("per_path", "global", "none"):
        many = k_best_paths_many(kg, pairs, 2, 2, prune)
        for s, t in ((S, T), (A, T)):
            own = [(tuple(r["path"]), r["score"]) for r in many.where(f"source = {s}").orderBy("rank").collect()]
            assert own == [(tuple(r["path"]), r["score"]) for r in k_best_paths(kg, s, t, 2, 2, prune).orderBy("rank").collect()]
    many = k_best_paths_many(kg, pairs, 2, 5)
    assert {(r["source"], tuple(r["path"])) for r in many.collect()} == {(S, (S, T)), (S, (S, A, T)), (S, (S, B, T)), (A, (A, T)), (A, (A, B, T))}
    role = spark.createDataFrame([(T,), (B,)], "eid bigint")
    assert paths(k_best_paths(kg, S, T, 2, 9, target_role=role)) == {(S, T), (S, B), (S, A, T), (S, A, B)}
    with pytest.raises(ValueError):
        k_best_paths(kg, S, T, 0, 5)
    with pytest.raises(ValueError):
        k_best_paths(kg, S, T, 2, 5, prune="all")
