"""Queries of the reasoning engine, and their DuckDB SQL where SQL expresses them."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import oracles as sql
from .functions.vectors import load_entity_vectors, relation_vectors_of_members
from .ids import eid, eid_value
from .operators.graph import degrees, graph_profile, one_hop, open_graph, relation_profile, role_members, type_cube
from .operators.hops import anchor_hop_pruned, expand_hop_loop, suggest_links
from .operators.lookup import lookup_salted, lookup_vectors
from .operators.paths import exact_paths, frontier_sizes, k_best_paths, k_best_paths_many
from .plans import measures
from .plans import workloads as w
from .plans.query import hop1, hop2, three_hop, three_hop_simple
from .session import Scratch
from .sources.tables import RELATIONS, Tables, build_triples

K = 10
Query = Callable[[SparkSession, str], DataFrame]

W1, W2, W4 = w.WORKLOADS["w1"], w.WORKLOADS["w2"], w.WORKLOADS["w4"]
W7 = replace(W2, k=600, missing="neg_inf")


def _shown(df: DataFrame) -> DataFrame:
    """An answer with path arrays as strings, which every engine writes alike."""
    return df.withColumns({"path": F.array_join(F.transform("path", lambda x: x.cast("string")), ">"), "rels": F.array_join("rels", ">")})


def _long(query: Query) -> Query:
    """The query with INT columns as BIGINT, which is what counting and ranking give in SQL."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        df = query(spark, sf_dir)
        return df.withColumns({c: F.col(c).cast("bigint") for c, kind in df.dtypes if kind == "int"})

    return run


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return w.run_workload(spark, sf_dir, "w1")


# ---------------------------------------------------------------- graph

def triples_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return relation_profile(build_triples(spark, sf_dir, list(RELATIONS)))


def relation_degrees(spark: SparkSession, sf_dir: str) -> DataFrame:
    own = degrees(build_triples(spark, sf_dir, ["nation_hosts_customer", "customer_buys_from_supplier", "page_links_target"]))
    return own.groupBy("r", "end").agg(F.count("*").alias("entities"), F.max("degree").alias("max_degree"), F.sum("degree").cast("bigint").alias("edges"))


def graph_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    return type_cube(build_triples(spark, sf_dir, list(RELATIONS)))


def graph_data_sheet(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graph_profile(w.workload_graph(spark, sf_dir, "w1"))


def graph_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges by head type and relation, with subtotals."""
    own = build_triples(spark, sf_dir, list(RELATIONS)).rollup("h_type", "r").agg(F.count("*").alias("edges"))
    return own


def degree_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Largest degree of each relation at either end, side by side."""
    own = degrees(build_triples(spark, sf_dir, ["nation_hosts_customer", "customer_buys_from_supplier", "brand_has_part"]))
    return own.groupBy("r").pivot("end", ["h", "t"]).agg(F.max("degree"))


def score_gaps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hop 1's list with the gap to the next score, the running sum and the share of the best."""
    kg = w.workload_graph(spark, sf_dir, "w1")
    order = Window.orderBy("rank")
    best = hop1(kg, W1)
    return best.select(
        "eid", "rank", (F.col("score") - F.coalesce(F.lead("score").over(order), F.col("score"))).alias("gap"), F.sum("score").over(order.rowsBetween(Window.unboundedPreceding, 0)).alias("running"), (F.col("score") - F.first("score").over(order)).alias("behind")
    )


def role_set_operations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers that buy from supplier 1 and not from supplier 2, those that buy from both, and the rest of either."""
    edges = build_triples(spark, sf_dir, ["customer_buys_from_supplier"])
    one, two = (edges.where(F.col("t") == eid_value("supplier", i)).select(F.col("h").alias("eid")) for i in (1, 2))
    named = [("only", one.exceptAll(two)), ("both", one.intersect(two)), ("either", one.union(two).distinct())]
    out = None
    for name, df in named:
        own = df.withColumn("part", F.lit(name))
        out = own if out is None else out.unionByName(own)
    return out


def role_customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return role_members(build_triples(spark, sf_dir, ["nation_hosts_customer"]), "nation_hosts_customer")


def role_union(spark: SparkSession, sf_dir: str) -> DataFrame:
    triples = build_triples(spark, sf_dir, ["brand_has_part", "type_has_part", "customer_buys_part"])
    return role_members(triples, ["brand_has_part", "type_has_part", "customer_buys_part"])


def one_hop_lookup(spark: SparkSession, sf_dir: str) -> DataFrame:
    kg = w.workload_graph(spark, sf_dir, "w1")
    return one_hop(kg, eid_value("customer", 7), "customer_buys_from_supplier")


def adjacency_by_head(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .operators.graph import adjacency

    own = adjacency(build_triples(spark, sf_dir, ["user_did_type", "bucket_attracts_user"]))
    return own.select("h", F.size("neighbours").cast("bigint").alias("degree"), F.array_join(F.transform("neighbours", lambda x: F.concat_ws(":", x["r"], x["t"])), ",").alias("neighbours"))


# ---------------------------------------------------------------- vectors


def _flat(vectors: DataFrame, key: str) -> DataFrame:
    return vectors.select(key, F.posexplode("vec").alias("i", "x"))


def entity_vectors_composed(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _flat(w.workload_graph(spark, sf_dir, "w1").vectors, "eid")


def entity_vectors_native(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _flat(w.workload_graph(spark, sf_dir, "w2", binding="native").vectors, "eid")


def relation_vectors_mean(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Worked out from the tables, not taken from a graph that another query has built; edges are counted once, into a file."""
    ends = Scratch(spark).write(degrees(build_triples(spark, sf_dir, W1.relations())), "ends")
    vectors = load_entity_vectors(ends.select("eid").distinct(), Tables(spark, sf_dir).embeddings)
    return _flat(relation_vectors_of_members(ends.join(vectors, "eid"), 8), "r")


def relation_vectors_median(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _flat(open_graph(spark, sf_dir, W1.relations(), method="median").relations, "r")


# ---------------------------------------------------------------- hops


def _hop1(spark: SparkSession, sf_dir: str, q=W1, name: str = "w1", binding: str = "composed", **options) -> DataFrame:
    return hop1(w.workload_graph(spark, sf_dir, name, binding=binding), q, **options)


def hop1_pruned_by_prefix(spark: SparkSession, sf_dir: str) -> DataFrame:
    kg = w.workload_graph(spark, sf_dir, "w1")
    return anchor_hop_pruned(kg, eid_value(*W1.anchor1), W1.relation1, kg.role(W1.relation1), W1.k)


def paths_many_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    kg = w.shared_graph(spark, sf_dir, w.G1_RELATIONS)
    pairs = spark.createDataFrame([w.G1[:2], w.G2[:2]], "source bigint, target bigint")
    return _shown(k_best_paths_many(kg, pairs, 3, 5, direction="both"))


def _many_sql() -> str:
    parts = [f"select cast({s} as bigint) as source, cast({t} as bigint) as target, * from ({sql.path_sql(w.G1_RELATIONS, s, t, 3, 5, 'per_path', True)})" for s, t, _ in (w.G1, w.G2)]
    return " union all ".join(parts)


def _hop2(spark: SparkSession, sf_dir: str, q) -> DataFrame:
    kg = w.workload_graph(spark, sf_dir, "w1")
    return hop2(kg, q, hop1(kg, q))


def _three(spark: SparkSession, sf_dir: str, q) -> DataFrame:
    return three_hop(w.workload_graph(spark, sf_dir, "w1"), q)


def three_hop_w1_simple(spark: SparkSession, sf_dir: str) -> DataFrame:
    return three_hop_simple(w.workload_graph(spark, sf_dir, "w1"), W1)


def three_hop_w1_dim64(spark: SparkSession, sf_dir: str) -> DataFrame:
    return w.run_workload(spark, sf_dir, "w1", dim=64)


def hop3_one_plan_per_head(spark: SparkSession, sf_dir: str) -> DataFrame:
    kg = w.workload_graph(spark, sf_dir, "w1")
    heads = [r["eid"] for r in hop2(kg, W1, hop1(kg, W1)).collect()]  # K ids
    return expand_hop_loop(kg, heads, W1.relation3, kg.role(W1.relation3), W1.k)


def suggest_links_l1(spark: SparkSession, sf_dir: str) -> DataFrame:
    kg = w.workload_graph(spark, sf_dir, "w1")
    heads = kg.role("nation_hosts_customer")
    return suggest_links(kg, "customer_buys_from_supplier", heads, kg.role("customer_buys_from_supplier"), 3)


# ---------------------------------------------------------------- paths


def paths_to_role(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The best paths from a customer to any supplier of a nation."""
    kg = w.shared_graph(spark, sf_dir, w.G1_RELATIONS)
    role = kg.triples.where((F.col("r") == "supplier_in_nation") & (F.col("t") == ROLE_NATION)).select(F.col("h").alias("eid"))
    return _shown(k_best_paths(kg, w.G2[0], 0, 2, K, target_role=role))


ROLE_NATION = eid_value("nation", 3)


def _paths(spark: SparkSession, sf_dir: str, relations: list[str], pair: tuple[int, int, int], k: int, prune: str, both: bool, scorer: str = "translate_sum", **options) -> DataFrame:
    kg = w.shared_graph(spark, sf_dir, relations)
    s, t, hops = pair
    return _shown(k_best_paths(kg, s, t, hops, k, prune, scorer, "both" if both else "out", **options))


def beam_recall_g1(spark: SparkSession, sf_dir: str) -> DataFrame:
    kg = w.shared_graph(spark, sf_dir, w.G1_RELATIONS)
    s, t, hops = w.G1
    exact = exact_paths(kg, s, t, hops, "both").persist()
    rows = [measures.recall_at_k(k_best_paths(kg, s, t, hops, k, prune, direction="both"), exact, k).withColumn("prune", F.lit(prune)) for prune in ("per_path", "global") for k in (5, 10)]
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out


def _recall_sql() -> str:
    parts = []
    s, t, hops = w.G1
    base = sql.graph_ctes(w.G1_RELATIONS, both=True)
    ctes = list(base)
    for name, prune, k in [("x", "none", 1), *[(f"{p[0]}{k}", p, k) for p in ("per_path", "global") for k in (5, 10)]]:
        own = sql.path_ctes(s, t, hops, k, prune)
        names = [c.split(" as ", 1)[0] for c in own]
        text = own
        for n in sorted(names, key=len, reverse=True):
            text = [_rename(c, n, f"{name}_{n}") for c in text]
        ctes += text
        if name != "x":
            parts.append(
                f"select cast({k} as bigint) as k, count(b.path) as hits, count(*) as truth, count(b.path) / count(*) as recall, '{prune}' as prune from x_found a left join {name}_found b on a.path = b.path and a.rels = b.rels and b.rank <= {k} where a.rank <= {k}"
            )
    return sql.statement(ctes, " union all ".join(parts))


def _rename(text: str, old: str, new: str) -> str:
    import re

    return re.sub(rf"(?<![\w.]){old}(?=\b(?!\.))", new, text) if old not in ("hits", "found") else re.sub(rf"(?<![\w.]){old}\b", new, text)


# ---------------------------------------------------------------- measures


def dim_overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Of the first 10 at 64 dimensions, how many are among the first 10 at fewer."""
    whole = hop1(w.workload_graph(spark, sf_dir, "w1", dim=64), W1)
    out = None
    for dim in (8, 16, 32):
        own = measures.overlap_at_k(hop1(w.workload_graph(spark, sf_dir, "w1", dim=dim), W1), whole, K).withColumn("dim", F.lit(dim))
        out = own if out is None else out.unionByName(own)
    return out


def _dim_overlap_sql() -> str:
    tables, parts = [], []
    for dim in (8, 16, 32, 64):
        tables.append(f"d{dim} as ({sql.question_sql(W1, 1, dim)})")
    for dim in (8, 16, 32):
        parts.append(f"select cast({K} as bigint) as k, count(*) as overlap, cast({dim} as bigint) as dim from d{dim} where eid in (select eid from d64)")
    return sql.statement(tables, " union all ".join(parts))


def work_counters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.work_counters(w.workload_graph(spark, sf_dir, "w1"), W1)


WORKERS, FAN_INS = [2, 16, 256, 65536], [2, 4, 64]


def merge_cost_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Of the lists that hop 1 of W1 keeps over its role."""
    return measures.merge_cost_table(role_members(build_triples(spark, sf_dir, [W1.relation1]), W1.relation1), WORKERS, FAN_INS)


def _merge_cost_sql() -> str:
    """Lists left after each round, level by level, until one is left; and of each round the members below its lists."""
    return f"""
        with recursive t as (select unnest({WORKERS}) as workers), f as (select unnest({FAN_INS}) as fan_in),
        r as (select workers, fan_in, cast(workers as bigint) as lists, cast(1 as bigint) as width, 0 as round from t, f where fan_in <= greatest(2, workers)
              union all select workers, fan_in, (lists + fan_in - 1) // fan_in, width * fan_in, round + 1 from r where lists > 1),
        m as (select distinct t as eid from ({sql.edge_sql(W1.relation1)})),
        l as (select workers, fan_in, round, (eid % workers) // width as list, count(*) as n from m, r where lists > 1 group by all),
        j as (select workers, fan_in, round, list // fan_in as task, sum(least(n, 50)) as held from l group by all),
        c as (select workers, fan_in, sum(held) as moved, max(held) as most from j group by all)
        select cast(workers as bigint) as workers, cast(50 as bigint) as k, cast(fan_in as bigint) as fan_in, cast(rounds as bigint) as rounds,
               cast(coalesce(moved, 0) as bigint) as rows_moved, cast(coalesce(most, 0) as bigint) as rows_in_a_task
        from (select workers, fan_in, max(round) as rounds from r group by all) left join c using (workers, fan_in)"""


def retained_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows that the shared list and the bounded lists hold at hop 1 of W1, by number of workers."""
    members = w.workload_graph(spark, sf_dir, "w1").role(W1.relation1).count()
    rows = [(t, *measures.retained_rows(t, K, members).values()) for t in WORKERS]
    return spark.createDataFrame(rows, "workers bigint, shared_list bigint, bounded_lists bigint")


PATH_HOPS = [1, 2, 3, 4]


def frontier_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The published estimate of path buffers, and what a level can hold, for beams as wide as customers have parts: K that keeps all edges of a path's end.

    A row for each such K with the customers that have so many parts."""
    parts = build_triples(spark, sf_dir, ["customer_buys_part"]).groupBy("h").agg(F.count("*").alias("k"))
    return frontier_sizes(parts.groupBy("k").agg(F.count("*").alias("entities")), PATH_HOPS)


_FRONTIER_SQL = f"""
    with d as (select h, count(*) as k from ({sql.edge_sql("customer_buys_part")}) group by h), w as (select k, count(*) as entities from d group by k),
    g as (select k, entities, hops, policy from w, (select unnest({PATH_HOPS}) as hops), (values ('per_path'), ('global')) p(policy))
    select k, entities, cast(hops as bigint) as hops, policy,
           cast(case when policy = 'global' then k * (hops - 1) else case hops when 1 then 0 when 2 then 1 when 3 then 1 + k else 1 + k + k * k end end as bigint) as bound,
           cast(case when policy = 'global' then k else case hops when 1 then k when 2 then k * k when 3 then k * k * k else k * k * k * k end end as bigint) as level_limit from g"""


# ---------------------------------------------------------------- lookups


def _lookup(spark: SparkSession, sf_dir: str, strategy: str) -> DataFrame:
    """Vectors of the customers that placed each order, most of them asked for many times."""
    kg = w.workload_graph(spark, sf_dir, "w1")
    asked = Tables(spark, sf_dir).orders.select("o_orderkey", eid("customer", F.col("o_custkey")).alias("eid"))
    found = lookup_salted(asked, kg.vectors) if strategy == "salted" else lookup_vectors(asked, kg.vectors, strategy)
    return found.select("o_orderkey", "eid", F.aggregate("vec", F.lit(0).cast("bigint"), lambda a, x: a + x).alias("total"))


# ---------------------------------------------------------------- streams and time


def events_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .streaming.edges import windowed_edges

    return windowed_edges(Tables(spark, sf_dir).events, "1 day").select("event_type", F.col("first").cast("string").alias("first"), "edges")


def events_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .streaming.edges import windowed_edges

    return windowed_edges(Tables(spark, sf_dir).events, "1 day", "6 hours").select("event_type", F.col("first").cast("string").alias("first"), "edges")


def events_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .streaming.edges import session_edges

    own = session_edges(Tables(spark, sf_dir).events, "30 minutes")
    return own.withColumns({c: F.col(c).cast("string") for c in ("first", "last")})


def edges_asof(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .streaming.edges import as_of

    events = Tables(spark, sf_dir).events
    left = events.where("event_type = 'purchase'").select("event_id", "user_id", "ts")
    right = events.where("event_type = 'click'").select(F.col("event_id").alias("click_id"), "user_id", "ts")
    return as_of(left, right, "user_id", "ts", "click_id").select("event_id", "user_id", F.coalesce("click_id", F.lit(-1).cast("bigint")).alias("click_id"))


def edges_in_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .streaming.edges import within

    events = Tables(spark, sf_dir).events
    left = events.where("event_type = 'click'").select(F.col("event_id").alias("click_id"), "user_id", "ts")
    right = events.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", "ts")
    return within(left, right, "user_id", "ts", 24).select("user_id", "click_id", "purchase_id")


def stream_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .streaming.edges import stream_topk as run

    return run(spark, sf_dir, K)


def stream_triples(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .streaming.edges import stream_triples as run

    return run(spark, sf_dir)


# ---------------------------------------------------------------- registry


def queries() -> dict[str, Query]:
    def q1(q, **options) -> Query:
        return lambda s, d: _hop1(s, d, q, **options)

    def q2(q) -> Query:
        return lambda s, d: _hop2(s, d, q)

    def q3(q) -> Query:
        return lambda s, d: _three(s, d, q)

    def work(name: str) -> Query:
        return lambda s, d: w.run_workload(s, d, name)

    def path(*args, **options) -> Query:
        return lambda s, d: _paths(s, d, *args, **options)

    def look(strategy: str) -> Query:
        return lambda s, d: _lookup(s, d, strategy)

    def whole(name: str, **options) -> Query:
        return lambda s, d: w.run_workload(s, d, name, **options)

    def simple(name: str) -> Query:
        return lambda s, d: three_hop_simple(w.workload_graph(s, d, name), w.WORKLOADS[name])

    own = {
        **{f"lookup_{x}": look(x) for x in ("auto", "broadcast", "shuffle_hash", "sortmerge", "salted")},
        **{f"three_hop_{n}_simple": simple(n) for n in ("w2", "w3", "w4", "w5", "w6")},
        "three_hop_w1_k50": whole("w1", k=50),
        "three_hop_w1_tree2": whole("w1", form="heap_tree", fan_in=2, workers=16),
        "three_hop_w1_tree4_k50": whole("w1", k=50, form="heap_tree", fan_in=4, workers=16),
        "three_hop_w1_funnel": whole("w1", form="heap_funnel", workers=16),
        "three_hop_w7": lambda s, d: three_hop(w.workload_graph(s, d, "w2", binding="native"), W7),
        "paths_to_role_g2": paths_to_role,
        "paths_reach_pruned_g1": path(w.G1_RELATIONS, w.G1, 1, "none", True, reach_prune=True),
        "paths_beam_k1_g1": path(w.G1_RELATIONS, w.G1, 1, "per_path", True),
        "retained_rows": retained_rows,
        "frontier_bounds": frontier_bounds,
        "triples_profile": triples_profile,
        "relation_degrees": relation_degrees,
        "graph_cube": graph_cube,
        "graph_rollup": graph_rollup,
        "degree_pivot": degree_pivot,
        "score_gaps": score_gaps,
        "role_set_operations": role_set_operations,
        "graph_data_sheet": graph_data_sheet,
        "role_customers": role_customers,
        "role_union": role_union,
        "one_hop_lookup": one_hop_lookup,
        "adjacency_by_head": adjacency_by_head,
        "entity_vectors_composed": entity_vectors_composed,
        "entity_vectors_native": entity_vectors_native,
        "relation_vectors_mean": relation_vectors_mean,
        "relation_vectors_median": relation_vectors_median,
        "hop1_anchor_native": q1(W1),
        "hop1_anchor_heap_tree2": q1(W1, form="heap_tree", fan_in=2, workers=16),
        "hop1_anchor_heap_tree4": q1(W1, form="heap_tree", fan_in=4, workers=16),
        "hop1_anchor_funnel": q1(W1, form="heap_funnel", workers=16),
        "hop1_shared_list_baseline": q1(W1, form="shared_list"),
        "hop1_full_sort_baseline": q1(W1, form="full_sort"),
        "hop1_pruned_by_prefix": hop1_pruned_by_prefix,
        "hop1_linked_only": q1(replace(W1, candidates1="linked")),
        "hop1_unlinked_only": q1(replace(W1, candidates1="unlinked")),
        "hop1_missing_vectors": q1(W7, name="w2", binding="native"),
        "hop2_rerank_replace": q2(W1),
        "hop2_rerank_sum": q2(replace(W1, combine="sum")),
        "hop2_rerank_min": q2(replace(W1, combine="min")),
        "hop2_rerank_keep_first": q2(replace(W1, combine="keep_first")),
        "hop2_filter_k2": q2(replace(W1, k2=4)),
        "hop3_expand_per_head": q3(W1),
        "hop3_expand_linked": q3(replace(W1, candidates3="linked")),
        "hop3_merged_pairs": q3(replace(W1, output="merged_pairs")),
        "hop3_merged_entities": q3(replace(W1, output="merged_entities")),
        "hop3_one_plan_per_head": hop3_one_plan_per_head,
        **{f"three_hop_{n}": work(n) for n in w.WORKLOADS},
        "three_hop_w1_simple": three_hop_w1_simple,
        "three_hop_w1_dim64": three_hop_w1_dim64,
        "two_hop_w8": work("w8"),
        "suggest_links": suggest_links_l1,
        "paths_exact_g1": path(w.G1_RELATIONS, w.G1, 1, "none", True),
        "paths_beam_per_path_g1": path(w.G1_RELATIONS, w.G1, K, "per_path", True),
        "paths_beam_global_g1": path(w.G1_RELATIONS, w.G1, K, "global", True),
        "paths_bottleneck_g1": path(w.G1_RELATIONS, w.G1, K, "per_path", True, "bottleneck"),
        "paths_translate_end_g1": path(w.G1_RELATIONS, w.G1, K, "per_path", True, "translate_end"),
        "paths_untyped_g2": path(w.G1_RELATIONS, w.G2, K, "per_path", True, "untyped", typed=False),
        "paths_beam_h4_g3": path(w.G3_RELATIONS, w.G3, K, "global", False),
        "paths_many_pairs": paths_many_pairs,
        "beam_recall_g1": beam_recall_g1,
        "dim_overlap": dim_overlap,
        "work_counters": work_counters,
        "merge_cost_table": merge_cost_table,
        "events_tumbling": events_tumbling,
        "events_sliding": events_sliding,
        "events_session": events_session,
        "edges_asof": edges_asof,
        "edges_in_range": edges_in_range,
        "stream_topk": stream_topk,
        "stream_triples": stream_triples,
    }
    return {name: _long(q) for name, q in own.items()}


def oracle_sql() -> dict[str, str]:
    g, st, ask = sql.graph_ctes, sql.statement, sql.question_sql
    w1 = W1.relations()
    flat = "unnest(range(0, 8)) as i, unnest(vec) as x"
    s8 = st(
        g(w.W8_RELATIONS)
        + sql.hop1_ctes(replace(W1, anchor1=w.W8[0].anchor, relation1=w.W8[0].relation))
        + sql.hop2_ctes(replace(W1, anchor2=w.W8[1].anchor, relation2=w.W8[1].relation)),
        "select * from hop2",
    )
    links = st(
        [
            *g(w1),
            "hop2 as (select distinct t as eid from triples where r = 'nation_hosts_customer')",
            *sql.hop3_ctes(replace(W1, k=3, candidates3="unlinked")),
        ],
        "select * from hop3",
    )
    hop1_same = {n: ask(W1, 1) for n in ("hop1_anchor_native", "hop1_anchor_heap_tree2", "hop1_anchor_heap_tree4", "hop1_anchor_funnel", "hop1_shared_list_baseline", "hop1_full_sort_baseline", "hop1_pruned_by_prefix")}
    whole_same = {n: ask(W1) for n in ("hop3_expand_per_head", "three_hop_w1_simple", "hop3_one_plan_per_head")}
    median = "d as (select r, i, cast(floor(median(vt.vec[i] - vh.vec[i])) as bigint) as x from base join vec vh on vh.eid = h join vec vt on vt.eid = t, (select unnest(range(1, 9)) as i) group by r, i)"
    heap = [
        "et as (select distinct event_type, dense_rank() over (order by event_type) - 1 as k from events)",
        "cs as (select et.event_type, list_transform(range(1, 9), lambda i: v.vec[i] + w.vec[i]) as comp from et join vec v on v.eid = 11000000000000 + et.k, relv w where w.r = 'type_attracts_user')",
        f"st as (select c.event_type as anchor, v.eid, {sql._score('c.comp', 'v.vec', 8)} as score from (select distinct event_type, 10000000000000 + user_id as eid from events) e join cs c on c.event_type = e.event_type join vec v on v.eid = e.eid)",
    ]
    sessions = (
        "with e as (select *, case when ts <= lag(ts) over (partition by user_id order by ts) + interval 30 minute then 0 else 1 end as new from events), "
        "s as (select *, sum(new) over (partition by user_id order by ts rows unbounded preceding) as n from e) "
        "select user_id, cast(cast(min(ts) as timestamp) as varchar) as first, cast(cast(max(ts) + interval 30 minute as timestamp) as varchar) as last, count(*) as events from s group by user_id, n"
    )
    windows = "select event_type, cast(cast(first as timestamp) as varchar) as first, count(distinct user_id) as edges from ({}) group by event_type, first"
    role = f"select h from base where r = 'supplier_in_nation' and t = {ROLE_NATION}"
    asked = st(
        g(w1),
        f"select o_orderkey, eid, cast(list_sum(vec) as bigint) as total from orders join vec on eid = {eid_value('customer', 0)} + o_custkey",
    )
    return {
        **{f"lookup_{x}": asked for x in ("auto", "broadcast", "shuffle_hash", "sortmerge", "salted")},
        **{f"three_hop_{n}_simple": ask(w.WORKLOADS[n]) for n in ("w2", "w3", "w4", "w5", "w6")},
        "three_hop_w1_k50": ask(replace(W1, k=50)),
        "three_hop_w1_tree2": ask(W1),
        "three_hop_w1_tree4_k50": ask(replace(W1, k=50)),
        "three_hop_w1_funnel": ask(W1),
        "three_hop_w7": ask(W7, binding="native"),
        "paths_to_role_g2": sql.path_sql(w.G1_RELATIONS, w.G2[0], role, 2, K, "per_path", False),
        "paths_reach_pruned_g1": sql.path_sql(w.G1_RELATIONS, *w.G1, 1, "none", True),
        "paths_beam_k1_g1": sql.path_sql(w.G1_RELATIONS, *w.G1, 1, "per_path", True),
        "retained_rows": f"select cast(t as bigint) as workers, n as shared_list, least(n, t * {K}) as bounded_lists from (select unnest({WORKERS}) as t), (select count(distinct c_custkey) as n from customer)",
        "frontier_bounds": _FRONTIER_SQL,
        "triples_profile": f"select r, count(*) as edges, count(distinct h) as heads, count(distinct t) as tails from ({sql.triples_sql(list(RELATIONS))}) group by r",
        "relation_degrees": "with e as ({}), d as (select r, 'h' as \"end\", h, count(*) as degree from e group by r, h union all select r, 't', t, count(*) from e group by r, t) select r, \"end\", count(*) as entities, max(degree) as max_degree, cast(sum(degree) as bigint) as edges from d group by r, \"end\"".format(
            sql.triples_sql(["nation_hosts_customer", "customer_buys_from_supplier", "page_links_target"])
        ),
        "graph_cube": f"select h_type, t_type, count(*) as edges, cast(grouping(h_type, t_type) as bigint) as grouping from ({sql.triples_sql(list(RELATIONS))}) group by cube (h_type, t_type)",
        "graph_rollup": f"select h_type, r, count(*) as edges from ({sql.triples_sql(list(RELATIONS))}) group by rollup (h_type, r)",
        "degree_pivot": "with e as ({}) select r, (select max(n) from (select count(*) as n from e x where x.r = e.r group by x.h)) as h, (select max(n) from (select count(*) as n from e x where x.r = e.r group by x.t)) as t from (select distinct r from e) e".format(
            sql.triples_sql(["nation_hosts_customer", "customer_buys_from_supplier", "brand_has_part"])
        ),
        "score_gaps": st(
            g(w1) + sql.hop1_ctes(W1),
            "select eid, rank, score - coalesce(lead(score) over (order by rank), score) as gap, sum(score) over (order by rank rows unbounded preceding) as running, score - first_value(score) over (order by rank) as behind from hop1",
        ),
        "role_set_operations": "with e as ({}), a as (select h as eid from e where t = {}), b as (select h as eid from e where t = {}) select eid, 'only' as part from (select * from a except select * from b) union all select eid, 'both' from (select * from a intersect select * from b) union all select eid, 'either' from (select * from a union select * from b)".format(
            sql.edge_sql("customer_buys_from_supplier"), eid_value("supplier", 1), eid_value("supplier", 2)
        ),
        "graph_data_sheet": st(
            g(w1),
            "select 'edges' as property, count(*) as value from triples union all select 'entities', count(*) from ent union all select 'relations', count(*) from relv union all select 'elements', (select count(*) from triples) + (select count(*) from ent) union all select * from (values ('dimensions', 8), ('edge_record_bytes', 24), ('vector_record_bytes', 72)) x(p, v)",
        ),
        "role_customers": "select distinct t as eid from ({})".format(sql.edge_sql("nation_hosts_customer")),
        "role_union": "select distinct t as eid from ({})".format(sql.triples_sql(["brand_has_part", "type_has_part", "customer_buys_part"])),
        "one_hop_lookup": "select t as eid from ({}) where h = {}".format(sql.edge_sql("customer_buys_from_supplier"), eid_value("customer", 7)),
        "adjacency_by_head": "select h, count(*) as degree, string_agg(r || ':' || t, ',' order by r, t) as neighbours from ({}) group by h".format(sql.triples_sql(["user_did_type", "bucket_attracts_user"])),
        "entity_vectors_composed": st(g(w1), f"select eid, {flat} from vec"),
        "entity_vectors_native": st(g(W2.relations(), binding="native"), f"select eid, {flat} from vec"),
        "relation_vectors_mean": st(g(w1), f"select r, {flat} from relv"),
        "relation_vectors_median": st([*g(w1), median], "select r, i - 1 as i, x from d"),
        "events_session": sessions,
        "stream_topk": st(g(W4.relations()) + heap, f"select anchor, eid, score, row_number() over (partition by anchor order by score desc, eid) as rank from st qualify row_number() over (partition by anchor order by score desc, eid) <= {K}"),
        **hop1_same,
        "hop1_linked_only": ask(replace(W1, candidates1="linked"), 1),
        "hop1_unlinked_only": ask(replace(W1, candidates1="unlinked"), 1),
        "hop1_missing_vectors": ask(W7, 1, binding="native"),
        "hop2_rerank_replace": ask(W1, 2),
        **{f"hop2_rerank_{c}": ask(replace(W1, combine=c), 2) for c in ("sum", "min", "keep_first")},
        "hop2_filter_k2": ask(replace(W1, k2=4), 2),
        **whole_same,
        "hop3_expand_linked": ask(replace(W1, candidates3="linked")),
        **{f"hop3_{o}": ask(replace(W1, output=o)) for o in ("merged_pairs", "merged_entities")},
        **{f"three_hop_{n}": ask(q) for n, q in w.WORKLOADS.items()},
        "three_hop_w1_dim64": ask(W1, 3, 64),
        "two_hop_w8": s8,
        "suggest_links": links,
        "paths_exact_g1": sql.path_sql(w.G1_RELATIONS, *w.G1, 1, "none", True),
        "paths_beam_per_path_g1": sql.path_sql(w.G1_RELATIONS, *w.G1, K, "per_path", True),
        "paths_beam_global_g1": sql.path_sql(w.G1_RELATIONS, *w.G1, K, "global", True),
        "paths_bottleneck_g1": sql.path_sql(w.G1_RELATIONS, *w.G1, K, "per_path", True, "bottleneck"),
        "paths_translate_end_g1": sql.path_sql(w.G1_RELATIONS, *w.G1, K, "per_path", True, "translate_end"),
        "paths_untyped_g2": sql.path_sql(w.G1_RELATIONS, *w.G2, K, "per_path", True, "untyped"),
        "paths_beam_h4_g3": sql.path_sql(w.G3_RELATIONS, *w.G3, K, "global", False),
        "paths_many_pairs": _many_sql(),
        "beam_recall_g1": _recall_sql(),
        "dim_overlap": _dim_overlap_sql(),
        "work_counters": st(
            g(w1) + sql.hop1_ctes(W1) + sql.hop2_ctes(W1),
            "select 'hop1' as hop, count(*) as evaluations from s1 union all select 'hop2', (select count(*) from hop1) union all select 'hop3', (select count(*) from hop2) * (select count(distinct t) from triples where r = 'customer_buys_from_supplier')",
        ),
        "merge_cost_table": _merge_cost_sql(),
        "events_tumbling": windows.format("select event_type, user_id, date_trunc('day', ts) as first from events"),
        "events_sliding": windows.format("select event_type, user_id, date_trunc('day', ts) + to_hours(cast((date_part('hour', ts) // 6 - s) * 6 as bigint)) as first from events, range(0, 4) x(s)"),
        "edges_asof": "select p.event_id, p.user_id, coalesce(c.event_id, -1) as click_id from (select * from events where event_type = 'purchase') p asof left join (select user_id, ts, max(event_id) as event_id from events where event_type = 'click' group by user_id, ts) c on p.user_id = c.user_id and p.ts >= c.ts",
        "edges_in_range": "select c.user_id, c.event_id as click_id, p.event_id as purchase_id from events c join events p on c.user_id = p.user_id and c.event_type = 'click' and p.event_type = 'purchase' and p.ts >= c.ts and p.ts <= c.ts + interval 24 hour",
        "stream_triples": "select {} + dense_rank() over (order by event_type) - 1 as h, {} + user_id as t from (select distinct event_type, user_id from events)".format(11 * 10**12, 10 * 10**12),
    }


