"""All top-K forms give the same rows, whatever the partitioning, the tree and K."""

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from kgreason.operators.topk import merge_cost, merge_rounds, topk, topk_grouped, topk_local


def frame(spark, scores, partitions=3):
    return spark.createDataFrame([(i, float(s)) for i, s in enumerate(scores)], "eid bigint, score double").repartition(partitions)


def expected(scores, k):
    order = sorted(range(len(scores)), key=lambda i: (-scores[i], i))[:k]
    return [(i, float(scores[i]), r + 1) for r, i in enumerate(order)]


def answer(df):
    return [(r["eid"], r["score"], r["rank"]) for r in df.orderBy("rank").collect()]


FORMS = [("native", 2, None), ("heap_tree", 2, 7), ("heap_tree", 4, 16), ("heap_tree", 3, 1), ("heap_funnel", 2, 5), ("shared_list", 2, None), ("full_sort", 2, None)]


@pytest.mark.parametrize("form,fan_in,workers", FORMS)
@pytest.mark.parametrize("k", [1, 5, 60])
def test_forms(spark, form, fan_in, workers, k):
    rng = np.random.default_rng(3)
    scores = [float(x) for x in rng.integers(0, 12, 40) / 4]
    scores[7] = -math.inf
    assert answer(topk(frame(spark, scores), k, form, fan_in, workers)) == expected(scores, k)


@pytest.mark.parametrize("form,fan_in,workers", FORMS)
def test_no_rows(spark, form, fan_in, workers):
    assert answer(topk(frame(spark, []), 3, form, fan_in, workers)) == []


def test_local_lists_are_bounded(spark):
    local = topk_local(frame(spark, range(1000)), 5, workers=4)
    assert local.count() <= 20
    assert local.groupBy("worker").count().agg({"count": "max"}).first()[0] <= 5


def test_groups(spark):
    df = frame(spark, [1, 5, 3, 5, 2, 4]).selectExpr("eid % 2 as g", "eid", "score")
    rows = sorted((r["g"], r["rank"], r["eid"]) for r in topk_grouped(df, 2, ["g"]).collect())
    assert rows == [(0, 1, 2), (0, 2, 4), (1, 1, 1), (1, 2, 3)]
    big = sorted((r["g"], r["rank"], r["eid"]) for r in topk_grouped(df, 2000, ["g"]).collect())
    assert [x for x in big if x[1] <= 2] == rows and len(big) == 6


@given(st.integers(1, 10**6), st.integers(2, 64))
@settings(max_examples=200, deadline=None)
def test_rounds(workers, fan_in):
    rounds = merge_rounds(workers, fan_in)
    assert fan_in**rounds >= workers and (rounds == 0 or fan_in ** (rounds - 1) < workers)


def test_cost():
    assert merge_cost(64, 50, 4) == {"workers": 64, "k": 50, "fan_in": 4, "rounds": 3, "rows_moved": 50 * (64 + 16 + 4), "rows_in_a_task": 200}
    assert merge_cost(64, 50, 64)["rounds"] == 1


def test_prefix(spark):
    scores = [3, 1, 4, 1, 5, 9, 2, 6]
    for k in range(1, 8):
        assert answer(topk(frame(spark, scores), k)) == answer(topk(frame(spark, scores), k + 1))[:k]
    with pytest.raises(ValueError):
        topk(frame(spark, scores), 0)
    with pytest.raises(ValueError):
        topk(frame(spark, scores), 3, "best")
