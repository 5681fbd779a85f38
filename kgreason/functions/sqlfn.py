"""The engine's functions for SQL: inlined SQL functions, an aggregate, a table function, and views of a graph."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from ..operators.graph import KnowledgeGraph

HEAP = "array<struct<score:double,eid:bigint>>"


def register(spark: SparkSession) -> None:
    """kg_compose(h, r), kg_l1(a, b), kg_score(h, r, t) - SQL functions that Spark inlines - kg_top(eid, score, k), an aggregate, and kg_topk, a table function."""
    spark.sql("create or replace temporary function kg_compose(h array<double>, r array<double>) returns array<double> return zip_with(h, r, (x, y) -> x + y)")
    spark.sql("create or replace temporary function kg_l1(a array<double>, b array<double>) returns double return aggregate(zip_with(a, b, (x, y) -> abs(x - y)), cast(0 as double), (s, x) -> s + x)")
    spark.sql(
        "create or replace temporary function kg_score(h array<double>, r array<double>, t array<double>) returns double return 1 - aggregate(zip_with(zip_with(h, r, (x, y) -> x + y), t, (x, y) -> abs(x - y)), cast(0 as double), (s, x) -> s + x)"
    )
    spark.udf.register("kg_top", bounded_heap_aggregate())
    spark.udtf.register("kg_topk", topk_table_function())


def bounded_heap_aggregate():
    """Grouped aggregate: the K best (score, eid) of a group as an array, best first."""

    @F.pandas_udf(HEAP, F.PandasUDFType.GROUPED_AGG)
    def kg_top(eid, score, k):
        order = np.lexsort((eid.to_numpy(), -score.to_numpy()))[: int(k.iloc[0])]
        return [{"score": float(score.iloc[i]), "eid": int(eid.iloc[i])} for i in order]

    return kg_top


def topk_table_function():
    """TABLE(scored) PARTITION BY g: rows (g, eid, score, rank) of the K best of each partition, through a bounded heap."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="g string, eid bigint, score double, rank int")
    class KgTopK:
        def __init__(self):
            self.heap, self.g, self.k = [], None, 0

        def eval(self, row, k: int):
            import heapq

            self.g, self.k = row["g"], k
            item = (row["score"], -row["eid"])
            if len(self.heap) < k:
                heapq.heappush(self.heap, item)
            elif item > self.heap[0]:
                heapq.heapreplace(self.heap, item)

        def terminate(self):
            for i, (score, minus) in enumerate(sorted(self.heap, reverse=True)):
                yield None if self.g is None else str(self.g), -minus, score, i + 1

    return KgTopK


def create_views(kg: KnowledgeGraph, prefix: str = "kg") -> None:
    """Temporary views <prefix>_triples, <prefix>_entity_vec, <prefix>_relation_vec."""
    kg.triples.createOrReplaceTempView(f"{prefix}_triples")
    kg.vectors.createOrReplaceTempView(f"{prefix}_entity_vec")
    kg.relations.createOrReplaceTempView(f"{prefix}_relation_vec")


def hop_sql(spark: SparkSession, anchor: int, relation: str, role_relation: str, k: int) -> DataFrame:
    """Hop 1 as one parameterised statement over the views of a graph in doubles."""
    return spark.sql(
        """
        select v.eid, kg_score(a.vec, w.vec, v.vec) as score
        from (select distinct t as eid from kg_triples where r = :role) x join kg_entity_vec v on v.eid = x.eid,
             (select vec from kg_entity_vec where eid = :anchor) a, (select vec from kg_relation_vec where r = :relation) w
        order by score desc, eid limit :k
        """,
        args={"anchor": anchor, "relation": relation, "role": role_relation, "k": k},
    )


@F.pandas_udf(DoubleType())
def translation_score_arrow(comp: pd.Series, vec: pd.Series) -> pd.Series:
    """1 - L1(comp, vec) in Arrow batches, for wide vectors of plain columns."""
    return pd.Series(1 - np.abs(np.stack(comp.to_numpy()) - np.stack(vec.to_numpy())).sum(axis=1)) if len(comp) else pd.Series([], dtype="float64")


def recursive_paths_sql(source: int, target: int, hops: int) -> str:
    """Every simple path of at most so many edges by WITH RECURSIVE over kg_triples."""
    return f"""
        with recursive walk(path, rels, last, n) as (
          select array(cast({source} as bigint)), cast(array() as array<string>), cast({source} as bigint), 0
          union all
          select array_append(w.path, e.t), array_append(w.rels, e.r), e.t, w.n + 1
          from walk w join kg_triples e on e.h = w.last
          where w.n < {hops} and w.last <> {target} and not array_contains(w.path, e.t))
        select path, rels, n as hops from walk where last = {target} and n > 0
    """
