"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

Each query runs once to warm up and build its graph, then is timed; the time is that of the question with the
graph at hand, as in the published runs.  ``build_*`` entries time graph construction itself.
"""

from __future__ import annotations

import json
import os
import sys
import time

from kgreason.operators.graph import open_graph
from kgreason.plans import workloads as w
from kgreason.plans.measures import run_noop
from kgreason.registry import queries
from kgreason.session import local_session

HEADLINE = [
    "hop1_anchor_native", "hop1_anchor_heap_tree2", "hop1_anchor_heap_tree4", "hop1_anchor_funnel", "hop1_shared_list_baseline", "hop1_full_sort_baseline",
    "hop2_rerank_replace", "three_hop_w1", "three_hop_w2", "three_hop_w3", "three_hop_w4", "three_hop_w5", "three_hop_w6", "three_hop_w1_simple",
    "three_hop_w1_dim64", "suggest_links", "paths_beam_per_path_g1", "paths_beam_global_g1", "paths_exact_g1", "triples_profile", "events_tumbling", "edges_asof",
]


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = local_session(os.environ.get("BENCH_CPUS", "8"))
    found, times = queries(), {}

    def once(run) -> float:
        t = time.perf_counter()
        run()
        return time.perf_counter() - t

    times["build_w1"] = once(lambda: open_graph(spark, sf, w.WORKLOADS["w1"].relations()).relations.collect())
    for name in sys.argv[1:] or HEADLINE:
        run = lambda name=name: run_noop(found[name](spark, sf))
        run()
        times[name] = min(once(run), once(run))
    total = sum(times.values())
    print(json.dumps({"metric": "total seconds of the headline queries", "value": round(total, 3), "unit": "sec", "queries": {k: round(v, 3) for k, v in times.items()}, "sf": os.path.basename(sf.rstrip("/"))}))


if __name__ == "__main__":
    main()
