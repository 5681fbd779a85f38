"""The knowledge graph that lies in the given tables: relations as (h, t) pairs of entity ids."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..ids import dense_keys, eid
from ..session import Scratch, ship


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


class Tables:
    """Lazy access to the given tables under one folder."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.sf_dir = spark, sf_dir
        self.reuse_order_lines, self._order_lines = False, None

    def __getattr__(self, name: str) -> DataFrame:
        if name.startswith("_"):
            raise AttributeError(name)
        return read_table(self.spark, self.sf_dir, name)

    # helper frames with keys for strings

    def keyed(self, df: DataFrame, column: str, wide: bool = False) -> DataFrame:
        """df with the dense key of a string column as ``<column>_key``; wide for strings that grow with the data."""
        return df.join(dense_keys(df, column, wide).withColumnRenamed("key", f"{column}_key"), column)

    def order_lines(self) -> DataFrame:
        """Orders with their lines; written once where several relations are made of them."""
        if self.reuse_order_lines and self._order_lines is None:
            self._order_lines = Scratch(self.spark).write(self._joined_order_lines(), "order-lines")
        return self._joined_order_lines() if self._order_lines is None else self._order_lines

    def _joined_order_lines(self) -> DataFrame:
        return self.orders.select("o_orderkey", "o_custkey").join(self.lineitem.select("l_orderkey", "l_partkey", "l_suppkey"), F.col("o_orderkey") == F.col("l_orderkey"))

    def pages_parsed(self) -> DataFrame:
        return self.pages.select(
            "page_id",
            F.regexp_extract("url", r"(example\.(?:com|net|org))", 1).alias("domain"),
            F.regexp_extract("url", r"^https?://[^/]+/([a-z]+)/", 1).alias("lang"),
            "html",
        )

    def tokens(self) -> DataFrame:
        return self.documents.select("doc_id", F.explode(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit("([a-z]+)"), F.lit(1)))).alias("token"))

    def targets(self) -> DataFrame:
        return self.pages.select("page_id", F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1)))).alias("target"))


def _brand() -> Column:
    return F.regexp_extract("p_brand", r"(\d+)", 1).cast("bigint")


def _bucket() -> Column:
    return F.get_json_object("props", "$.k").cast("bigint")


def _pairs(df: DataFrame, h: Column, t: Column) -> DataFrame:
    return df.select(h.alias("h"), t.alias("t"))


#: Relation -> (head type, tail type, frame of head and tail keys).
RELATIONS: dict[str, tuple[str, str, Callable[[Tables], DataFrame]]] = {
    "nation_hosts_customer": ("nation", "customer", lambda x: _pairs(x.customer, F.col("c_nationkey"), F.col("c_custkey"))),
    "segment_covers_customer": ("segment", "customer", lambda x: _pairs(x.keyed(x.customer.select("c_custkey", "c_mktsegment"), "c_mktsegment"), F.col("c_mktsegment_key"), F.col("c_custkey"))),
    "customer_buys_from_supplier": ("customer", "supplier", lambda x: _pairs(x.order_lines(), F.col("o_custkey"), F.col("l_suppkey"))),
    "customer_buys_part": ("customer", "part", lambda x: _pairs(x.order_lines(), F.col("o_custkey"), F.col("l_partkey"))),
    "customer_placed_order": ("customer", "order", lambda x: _pairs(x.orders, F.col("o_custkey"), F.col("o_orderkey"))),
    "order_contains_part": ("order", "part", lambda x: _pairs(x.lineitem, F.col("l_orderkey"), F.col("l_partkey"))),
    "part_supplied_by": ("part", "supplier", lambda x: _pairs(x.lineitem, F.col("l_partkey"), F.col("l_suppkey"))),
    "brand_has_part": ("brand", "part", lambda x: _pairs(x.part, _brand(), F.col("p_partkey"))),
    "type_has_part": ("ptype", "part", lambda x: _pairs(x.keyed(x.part.select("p_partkey", "p_type"), "p_type"), F.col("p_type_key"), F.col("p_partkey"))),
    "supplier_in_nation": ("supplier", "nation", lambda x: _pairs(x.supplier, F.col("s_suppkey"), F.col("s_nationkey"))),
    "nation_hosts_supplier": ("nation", "supplier", lambda x: _pairs(x.supplier, F.col("s_nationkey"), F.col("s_suppkey"))),
    "nation_in_region": ("nation", "region", lambda x: _pairs(x.nation, F.col("n_nationkey"), F.col("n_regionkey"))),
    "region_has_nation": ("region", "nation", lambda x: _pairs(x.nation, F.col("n_regionkey"), F.col("n_nationkey"))),
    "user_did_type": ("user", "etype", lambda x: _pairs(x.keyed(x.events.select("user_id", "event_type"), "event_type"), F.col("user_id"), F.col("event_type_key"))),
    "type_attracts_user": ("etype", "user", lambda x: _pairs(x.keyed(x.events.select("user_id", "event_type"), "event_type"), F.col("event_type_key"), F.col("user_id"))),
    "bucket_attracts_user": ("bucket", "user", lambda x: _pairs(x.events, _bucket(), F.col("user_id"))),
    "ptype_sold_by_supplier": ("ptype", "supplier", lambda x: _pairs(
        x.keyed(x.part.select("p_partkey", "p_type"), "p_type").join(x.lineitem.select("l_partkey", "l_suppkey"), F.col("p_partkey") == F.col("l_partkey")), F.col("p_type_key"), F.col("l_suppkey"))),
    "supplier_sells_to_customer": ("supplier", "customer", lambda x: _pairs(x.order_lines(), F.col("l_suppkey"), F.col("o_custkey"))),
    "lang_has_doc": ("lang", "doc", lambda x: _pairs(x.keyed(x.documents.select("doc_id", "lang"), "lang"), F.col("lang_key"), F.col("doc_id"))),
    "source_has_doc": ("source", "doc", lambda x: _pairs(x.keyed(x.documents.select("doc_id", "source"), "source"), F.col("source_key"), F.col("doc_id"))),
    "doc_mentions_token": ("doc", "token", lambda x: _pairs(x.keyed(x.tokens(), "token", wide=True), F.col("doc_id"), F.col("token_key"))),
    "domain_has_page": ("domain", "page", lambda x: _pairs(x.keyed(x.pages_parsed().select("page_id", "domain"), "domain"), F.col("domain_key"), F.col("page_id"))),
    "lang_has_page": ("lang", "page", lambda x: _pairs(x.keyed(x.pages_parsed().select("page_id", "lang"), "lang"), F.col("lang_key"), F.col("page_id"))),
    "page_links_target": ("page", "target", lambda x: _pairs(x.keyed(x.targets(), "target", wide=True), F.col("page_id"), F.col("target_key"))),
    "role_speaks_in_conversation": ("role", "conv", lambda x: _pairs(x.keyed(x.conversations.select("conv_id", "role"), "role"), F.col("role_key"), F.col("conv_id"))),
}


OF_ORDER_LINES = frozenset(["customer_buys_from_supplier", "customer_buys_part", "supplier_sells_to_customer"])


def relation_edges(tables: Tables, relation: str) -> DataFrame:
    """(r, h_type, h, t_type, t): distinct edges of one relation, ids instead of keys; ``inv:<name>`` turns it round."""
    if relation.startswith("inv:"):
        own = relation_edges(tables, relation[4:])
        return own.select(F.lit(relation).alias("r"), F.col("t_type").alias("h_type"), F.col("t").alias("h"), F.col("h_type").alias("t_type"), F.col("h").alias("t"))
    if relation not in RELATIONS:
        raise ValueError(f"unknown relation {relation!r}; known: {', '.join(sorted(RELATIONS))}")
    h_type, t_type, frame = RELATIONS[relation]
    pairs = frame(tables).where("h is not null and t is not null").distinct()
    return pairs.select(F.lit(relation).alias("r"), F.lit(h_type).alias("h_type"), eid(h_type, F.col("h")).alias("h"), F.lit(t_type).alias("t_type"), eid(t_type, F.col("t")).alias("t"))


def build_triples(spark: SparkSession, sf_dir: str, relations: list[str]) -> DataFrame:
    """Distinct typed triples of the named relations."""
    tables = Tables(spark, sf_dir)
    tables.reuse_order_lines = len(OF_ORDER_LINES & {r.removeprefix("inv:") for r in relations}) > 1
    return reduce(DataFrame.unionByName, [relation_edges(tables, r) for r in relations])
