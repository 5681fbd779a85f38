"""The published experiments on the given tables: python experiments.py [SF_DIR] [NAME...] prints one JSON line per row.

x1 simple against optimised lists; x2 scaling over cores with the share of each hop; x3 partitions at fixed cores; x4 scorers and
dimensions; x5 merges of bounded lists; x6 construction; x7 data sheet; x8 trimmed dimensions; x9 placement of skewed
lookups; x10 other domains; x11 K and hops; x12 generated roles up to a million members, and partitions of the whole question.  Data is loaded before the clock starts, as in the published runs, but for x6.
"""

from __future__ import annotations

import json
import os
import sys
import time
import uuid
from dataclasses import replace

import numpy as np
from pyspark.sql import functions as F

from kgreason.functions.scoring import score_with_arrow
from kgreason.ids import eid_value
from kgreason.operators.graph import graph_profile, open_graph, role_members
from kgreason.operators.hops import anchor_scores, composite_of
from kgreason.operators.lookup import lookup_salted, lookup_vectors
from kgreason.operators.paths import exact_paths, frontier_bound, k_best_paths
from kgreason.operators.topk import merge_cost, topk
from kgreason.plans import measures
from kgreason.plans import workloads as w
from kgreason.plans.measures import run_noop, timed_run
from kgreason.plans.query import hop1, three_hop, three_hop_simple
from kgreason.session import local_session, scratch_path, ship
from kgreason.sources.files import write_vector_table

K = 50


def say(name: str, **row) -> None:
    print(json.dumps({"experiment": name} | {k: round(v, 4) if isinstance(v, float) else v for k, v in row.items()}), flush=True)


class Bench:
    def __init__(self, sf: str):
        self.sf, self.spark = sf, None

    def session(self, cores: int, **conf):
        if self.spark:
            self.spark.stop()
        self.spark = local_session(cores, **{"spark.sql.shuffle.partitions": str(max(2, cores))} | conf)
        return self.spark

    def graph(self, name: str = "w1", dim: int = 8):
        return w.workload_graph(self.spark, self.sf, name, dim)

    def x1(self) -> None:
        for cores in (2, 4, 8):
            self.session(cores)
            for name in ("w1", "w2", "w3", "w6"):
                kg, q = self.graph(name), replace(w.WORKLOADS[name], k=K)
                simple, best = timed_run(lambda: three_hop_simple(kg, q), 4), timed_run(lambda: three_hop(kg, q), 4)
                say("x1", cores=cores, workload=name, simple_s=simple, optimised_s=best, speedup=measures.speedup(simple, best))

    def x2(self) -> None:
        def run(cores: int) -> float:
            self.session(cores)
            kg, q = self.graph("w6"), replace(w.WORKLOADS["w6"], k=K)
            measures.timed_hops(kg, q)
            hops = measures.timed_hops(kg, q, 2)
            say("x2", cores=cores, **hops)
            return timed_run(lambda: three_hop(kg, q), 3)

        for cores, seconds, gain in measures.scaling_curve(run, [1, 2, 4, 8]):
            say("x2", cores=cores, whole_s=seconds, speedup=gain)

    def x3(self) -> None:
        self.session(8)
        kg, q = self.graph("w6"), replace(w.WORKLOADS["w6"], k=K)
        role = role_members(kg.triples, q.relation3)
        base = anchor_scores(kg, eid_value("doc", 3), q.relation3, role)
        for parts in (1, 2, 4, 8, 16, 32, 64):
            say("x3", partitions=parts, seconds=timed_run(lambda: topk(base.repartition(parts, "eid"), K, "heap_funnel"), 3))

    def x4(self) -> None:
        self.session(8)
        for dim in (8, 16, 32, 64):
            kg = self.graph("w6", dim)
            role = role_members(kg.triples, "doc_mentions_token").join(kg.vectors, "eid").select("eid").persist()
            role.count()
            for impl in ("unrolled", "hof"):
                say("x4", dim=dim, scorer=impl, seconds=timed_run(lambda: topk(anchor_scores(kg, eid_value("doc", 3), "doc_mentions_token", role, impl=impl), K), 4))
            ship(self.spark)
            comp = np.array([composite_of(kg, eid_value("doc", 3), "doc_mentions_token").first()["comp"]])
            arrow = lambda: score_with_arrow(lookup_vectors(role, kg.vectors), comp, np.array([eid_value("doc", 3)]), kg.numeric)
            say("x4", dim=dim, scorer="arrow", seconds=timed_run(lambda: topk(arrow().select("eid", "score"), K), 4))

    def x5(self) -> None:
        spark = self.session(8)
        rows = spark.range(2_000_000).select(F.col("id").alias("eid"), (F.pmod(F.xxhash64("id"), F.lit(10**9)) / 1e9).alias("score")).persist()
        rows.count()
        say("x5", form="native", seconds=timed_run(lambda: topk(rows, K), 4))
        say("x5", form="shared_list", seconds=timed_run(lambda: topk(rows, K, "shared_list"), 2))
        say("x5", form="full_sort", seconds=timed_run(lambda: topk(rows, K, "full_sort"), 2))
        for workers in (16, 64, 256):
            own = rows.repartition(workers).persist()  # a task for each worker
            own.count()
            say("x5", form="lock_funnel", workers=workers, seconds=timed_run(lambda: topk(own, K, "heap_funnel"), 2))
            for fan_in in (2, 4):
                cost = merge_cost(workers, K, fan_in)
                say("x5", form="tree", moved_records=measures.moved(spark, lambda: run_noop(topk(own, K, "heap_tree", fan_in, workers)))["shuffle_records"], workers=workers, fan_in=fan_in, rounds=cost["rounds"], rows_in_a_task=cost["rows_in_a_task"], seconds=timed_run(lambda: topk(own, K, "heap_tree", fan_in, workers), 2))
        for workers in (65536, 1_048_576):  # rows that one reducer takes, against a tree's
            say("x5", form="model", workers=workers, funnel_rows=workers * K, tree64_rows=merge_cost(workers, K, 64)["rows_in_a_task"])

    def x6(self) -> None:
        spark = self.session(8)
        for name in ("w1", "w6"):
            t = time.perf_counter()
            kg = open_graph(spark, self.sf, w.WORKLOADS[name].relations())
            run_noop(kg.triples)
            triples = time.perf_counter() - t
            t = time.perf_counter()
            run_noop(kg.relations)
            say("x6", workload=name, triples_s=triples, vectors_and_relations_s=time.perf_counter() - t)

    def x7(self) -> None:
        self.session(8)
        say("x7", **{r["property"]: r["value"] for r in graph_profile(self.graph()).collect()})

    def x8(self) -> None:
        self.session(8)
        whole = hop1(self.graph(dim=64), w.WORKLOADS["w1"])
        for dim in (8, 16, 32, 64):
            own = self.graph(dim=dim)
            shared = measures.overlap_at_k(hop1(own, w.WORKLOADS["w1"]), whole, 10).first()["overlap"]
            say("x8", dim=dim, overlap_at_10=shared, seconds=timed_run(lambda: three_hop(own, replace(w.WORKLOADS["w1"], k=K)), 3))

    def x9(self) -> None:
        spark = self.session(8, **{"spark.sql.autoBroadcastJoinThreshold": "-1"})
        kg = self.graph()
        hot = eid_value("nation", 3)
        asked = spark.range(1_000_000).select(F.when(F.col("id") % 10 < 7, F.lit(hot)).otherwise(eid_value("customer", 0) + F.col("id") % 15000).alias("eid")).persist()
        asked.count()
        tables = [f"x9_{side}_{uuid.uuid4().hex}" for side in ("asked", "vectors")]  # both in 8 buckets by entity: no shuffle
        asked.write.bucketBy(8, "eid").sortBy("eid").option("path", scratch_path(spark, "asked")).saveAsTable(tables[0])
        write_vector_table(kg.vectors, scratch_path(spark, "vectors"), buckets=8, table=tables[1])
        ways = {
            "by key": lambda: lookup_vectors(asked, kg.vectors, "shuffle_hash"),
            "salted": lambda: lookup_salted(asked, kg.vectors),
            "bucketed": lambda: lookup_vectors(spark.table(tables[0]), spark.table(tables[1]).select("eid", "vec"), "shuffle_hash"),
            "broadcast": lambda: lookup_vectors(asked, kg.vectors, "broadcast"),
        }
        for name, run in ways.items():
            skew = measures.partition_skew(run()).first()
            say("x9", placement=name, seconds=timed_run(run, 3), largest_partition=skew["largest"], median_partition=skew["median"])

    def x10(self) -> None:
        self.session(8)
        for name in w.WORKLOADS:
            kg, q = self.graph(name), replace(w.WORKLOADS[name], k=K)
            if q.bound_share:
                whole = timed_run(lambda: three_hop(kg, replace(q, bound_share=0.0)), 3)
                say("x10", workload=name, without_bound_s=whole)
            say("x10", workload=name, seconds=timed_run(lambda: three_hop(kg, q), 3), **{r["hop"]: r["evaluations"] for r in measures.work_counters(kg, q).collect()})

    def x11(self) -> None:
        self.session(8)
        kg = self.graph()
        for k in (1, 5, 10, 50):
            say("x11", k=k, three_hop_s=timed_run(lambda: three_hop(kg, replace(w.WORKLOADS["w1"], k=k)), 3))
        small = os.path.join(os.path.dirname(self.sf), "sf0.001")
        kg = w.shared_graph(self.spark, small, w.G1_RELATIONS)
        s, far, _ = w.G1
        near = kg.edges("nation_hosts_customer").where(F.col("h") == s).agg(F.min("t")).first()[0]  # has a path of one edge
        for pair, t, lengths in (("near", near, (1, 2, 3, 4)), ("far", far, (1, 2, 3, 4))):
            for hops in lengths:
                exact = exact_paths(kg, s, t, hops, "both").persist()
                n = exact.count()
                for prune in ("per_path", "global") if n else ():
                    for k in (5, 10, 50):
                        own = k_best_paths(kg, s, t, hops, k, prune, direction="both")
                        say("x11", pair=pair, hops=hops, k=k, prune=prune, paths=n, recall=measures.recall_at_k(own, exact, k).first()["recall"], frontier_bound=frontier_bound(k, hops, prune))
                if not n:
                    say("x11", pair=pair, hops=hops, paths=0)

    def x12(self) -> None:
        spark = self.session(8, **{"spark.sql.files.openCostInBytes": "65536"})
        q = replace(w.GENERATED, k=K)
        for members in (10_000, 100_000, 1_000_000):
            kg = w.generated_graph(spark, members)
            bounded = replace(q, bound_share=0.02)
            simple, plain, best = (timed_run(run, 2) for run in (lambda: three_hop_simple(kg, q), lambda: three_hop(kg, q), lambda: three_hop(kg, bounded)))
            say("x12", members=members, simple_s=simple, optimised_s=plain, with_bound_s=best, speedup=measures.speedup(simple, best))
        for parts in (1, 2, 4, 8, 16, 32, 64):
            spark.conf.set("spark.sql.files.minPartitionNum", parts)
            spark.conf.set("spark.sql.shuffle.partitions", parts)
            tasks = kg.role(q.relation1).select(F.spark_partition_id().alias("p")).distinct().count()
            say("x12", partitions=parts, tasks_of_the_scan=tasks, whole_s=timed_run(lambda: three_hop(kg, bounded), 2))


def main() -> None:
    sf = sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.1"
    bench = Bench(sf.rstrip("/"))
    for name in sys.argv[2:] or [f"x{i}" for i in range(1, 13)]:
        getattr(bench, name)()


if __name__ == "__main__":
    main()
