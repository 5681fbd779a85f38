"""The experiment's question on the given tables, and questions of other domains."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.vectors import Numeric
from ..ids import eid, eid_value
from ..operators.graph import KnowledgeGraph, build_graph, entities_of, load_graph, save_graph
from ..session import scratch_path
from .query import Hop, ThreeHopQuery, hop_plan, three_hop

WORKLOADS: dict[str, ThreeHopQuery] = {
    # customers of a nation, then of a segment, then their suppliers
    "w1": ThreeHopQuery(("nation", 3), "nation_hosts_customer", ("segment", 1), "segment_covers_customer", "customer_buys_from_supplier", k=10),
    # parts of a brand, then of a type, then their suppliers
    "w2": ThreeHopQuery(("brand", 7), "brand_has_part", ("ptype", 0), "type_has_part", "part_supplied_by", k=10),
    # suppliers of a nation, then by part type, then customers: the last hop dominates
    "w3": ThreeHopQuery(("nation", 3), "nation_hosts_supplier", ("ptype", 3), "ptype_sold_by_supplier", "supplier_sells_to_customer", k=10),
    # users by event type, then by property bucket, then event types: fewer candidates than K
    "w4": ThreeHopQuery(("etype", 2), "type_attracts_user", ("bucket", 9), "bucket_attracts_user", "user_did_type", k=10),
    # pages of a domain, then of a language, then link targets
    "w5": ThreeHopQuery(("domain", 0), "domain_has_page", ("lang", 1), "lang_has_page", "page_links_target", k=10),
    # documents of a language, then of a source, then tokens: the largest expansion
    "w6": ThreeHopQuery(("lang", 1), "lang_has_doc", ("source", 0), "source_has_doc", "doc_mentions_token", k=10, bound_share=0.02),
}

#: Conversations in which users speak, re-ranked by the assistant: a chain of two hops.
W8 = [
    Hop("anchor", "role_speaks_in_conversation", 10, anchor=("role", 2)),
    Hop("rerank", "role_speaks_in_conversation", 10, anchor=("role", 0)),
]
W8_RELATIONS = ["role_speaks_in_conversation"]

G1_RELATIONS = ["nation_hosts_customer", "customer_buys_part", "part_supplied_by", "supplier_in_nation"]
G1 = (eid_value("nation", 3), eid_value("supplier", 5), 3)
G2 = (eid_value("customer", 7), eid_value("supplier", 2), 3)
G3_RELATIONS = ["region_has_nation", "nation_hosts_customer", "customer_buys_part", "part_supplied_by"]
G3 = (eid_value("region", 1), eid_value("supplier", 5), 4)


#: The question of generated graphs: a role against one anchor, then another, then a role a fifth as large.
GENERATED = ThreeHopQuery(("nation", 0), "generated_first", ("nation", 1), "generated_second", "generated_third", k=10)


def generated_graph(spark: SparkSession, members: int, dim: int = 8, numeric: Numeric = Numeric()) -> KnowledgeGraph:
    """A graph for GENERATED with so many customers in the first role and a fifth as many suppliers in the last, vectors hashed from ids; through files, as others are."""
    if members < 1:
        raise ValueError("a role has one member or more")
    ids = spark.range(members)
    customer = eid("customer", F.col("id"))

    def edges(r: str, h_type: str, h, t_type: str, t) -> DataFrame:
        return ids.select(F.lit(r).alias("r"), F.lit(h_type).alias("h_type"), h.alias("h"), F.lit(t_type).alias("t_type"), t.alias("t"))

    triples = edges(GENERATED.relation1, "nation", F.lit(eid_value(*GENERATED.anchor1)), "customer", customer)
    triples = triples.union(edges(GENERATED.relation2, "nation", F.lit(eid_value(*GENERATED.anchor2)), "customer", customer))
    triples = triples.union(edges(GENERATED.relation3, "customer", customer, "supplier", eid("supplier", F.col("id") % max(1, members // 5))))

    def vector(key: str):
        cells = [F.pmod(F.xxhash64(key, F.lit(i)), F.lit(2**22)) - 2**21 for i in range(dim)]
        return F.array(*(cells if numeric.mode == "fixed" else [c / Numeric().unit for c in cells]))

    vectors = entities_of(triples).select("eid", vector("eid").alias("vec"))
    relations = spark.createDataFrame([(r,) for r in GENERATED.relations()], "r string").select("r", vector("r").alias("vec"))
    path = scratch_path(spark, "generated")
    save_graph(KnowledgeGraph(triples, vectors, relations, dim, numeric), path)
    return load_graph(spark, path, dim, numeric)


#: Graphs built in this process, by session and parameters.
_built: dict[tuple, KnowledgeGraph] = {}


def shared_graph(spark: SparkSession, sf_dir: str, relations: list[str], dim: int = 8, binding: str = "composed", numeric: Numeric = Numeric()) -> KnowledgeGraph:
    """The graph of these relations, built once into the shared folder for all questions of a session."""
    key = (spark.sparkContext.applicationId, sf_dir, tuple(relations), dim, binding, numeric)
    if key not in _built:
        _built[key] = build_graph(spark, sf_dir, scratch_path(spark, "graph"), relations, dim, binding, numeric)
    return _built[key]


def workload_graph(spark: SparkSession, sf_dir: str, name: str, dim: int = 8, binding: str = "composed", numeric: Numeric = Numeric()) -> KnowledgeGraph:
    relations = W8_RELATIONS if name == "w8" else WORKLOADS[name].relations()
    return shared_graph(spark, sf_dir, relations, dim, binding, numeric)


def run_workload(spark: SparkSession, sf_dir: str, name: str, k: int | None = None, dim: int = 8, **options) -> DataFrame:
    kg = workload_graph(spark, sf_dir, name, dim)
    if name == "w8":
        return hop_plan(kg, W8)
    q = WORKLOADS[name]
    return three_hop(kg, replace(q, k=k) if k else q, **options)
