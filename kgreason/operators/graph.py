"""The graph a question is asked of, and helpers over its triples."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.vectors import Numeric, load_entity_vectors, relation_vectors, relation_vectors_of_members
from ..ids import code_column
from ..sources.tables import Tables, build_triples


@dataclass
class KnowledgeGraph:
    """Triples (r, h_type, h, t_type, t), entity vectors (eid, vec), relation vectors (r, vec), and the roles in them.

    members, (r, end, eid, degree, vec), are the entities at either end of each relation with their vectors, from which a question scans the role it asks of;
    a graph without them finds a role among its triples.
    """

    triples: DataFrame
    vectors: DataFrame
    relations: DataFrame
    dim: int = 8
    numeric: Numeric = field(default_factory=Numeric)
    gamma: float = 1.0
    members: DataFrame | None = None
    _entities: int | None = None

    def role(self, relation: str, end: str = "t") -> DataFrame:
        """(eid[, vec]): distinct entities at one end of a relation."""
        if self.members is None:
            return role_members(self.triples, relation, end)
        return self.members.where((F.col("r") == relation) & (F.col("end") == end)).select("eid", "vec")

    def entity_count(self) -> int:
        """Entities with vectors, counted once."""
        if self._entities is None:
            self._entities = self.vectors.count()
        return self._entities

    @property
    def spark(self) -> SparkSession:
        return self.triples.sparkSession

    def edges(self, relation: str | list[str]) -> DataFrame:
        names = [relation] if isinstance(relation, str) else list(relation)
        return self.triples.where(F.col("r").isin(names))


def entities_of(triples: DataFrame) -> DataFrame:
    return triples.select(F.col("h").alias("eid")).union(triples.select(F.col("t").alias("eid"))).distinct()


def _relation_vectors(triples: DataFrame, vectors: DataFrame, members: DataFrame, dim: int, binding: str, numeric: Numeric, method: str) -> DataFrame:
    if method == "mean" and binding == "composed":  # every entity has a vector
        return relation_vectors_of_members(members, dim, numeric)
    return relation_vectors(triples, vectors, dim, numeric, method)


def open_graph(spark: SparkSession, sf_dir: str, relations: list[str], dim: int = 8, binding: str = "composed", numeric: Numeric = Numeric(), method: str = "mean", gamma: float = 1.0) -> KnowledgeGraph:
    """The graph of the named relations of the given tables, with derived relation vectors."""
    triples, embeddings = build_triples(spark, sf_dir, relations), Tables(spark, sf_dir).embeddings
    vectors = load_entity_vectors(entities_of(triples), embeddings, dim, binding, numeric)
    ends = degrees(triples)
    members = ends.join(load_entity_vectors(ends.select("eid").distinct(), embeddings, dim, binding, numeric), "eid")
    return KnowledgeGraph(triples, vectors, _relation_vectors(triples, vectors, members, dim, binding, numeric, method), dim, numeric, gamma)


def _write_vectors(vectors: DataFrame, path: str) -> None:
    vectors.repartitionByRange("eid").sortWithinPartitions("eid").write.mode("overwrite").parquet(f"{path}/vectors")


def _write_members(members: DataFrame, path: str) -> None:
    members.select("r", "end", "eid", "degree", "vec").write.mode("overwrite").partitionBy("r", "end").parquet(f"{path}/members")


def save_graph(kg: KnowledgeGraph, path: str) -> None:
    """Writes the graph's tables: triples and roles in a folder per relation (a question reads only its own), vectors in id order, so
    that a lookup of one entity skips all row groups but one."""
    kg.triples.write.mode("overwrite").partitionBy("r").parquet(f"{path}/triples")
    _write_vectors(kg.vectors, path)
    _write_members(kg.members if kg.members is not None else degrees(kg.triples).join(kg.vectors, "eid", "left"), path)
    kg.relations.coalesce(1).write.mode("overwrite").parquet(f"{path}/relations")


def load_graph(spark: SparkSession, path: str, dim: int = 8, numeric: Numeric = Numeric(), gamma: float = 1.0) -> KnowledgeGraph:
    element = numeric.element
    triples = spark.read.schema("h_type string, h bigint, t_type string, t bigint, r string").parquet(f"{path}/triples")
    vectors = spark.read.schema(f"eid bigint, vec array<{element}>").parquet(f"{path}/vectors")
    relations = spark.read.schema(f"r string, vec array<{element}>").parquet(f"{path}/relations")
    members = spark.read.schema(f"eid bigint, degree bigint, vec array<{element}>, r string, end string").parquet(f"{path}/members")
    return KnowledgeGraph(triples.select("r", "h_type", "h", "t_type", "t"), vectors, relations, dim, numeric, gamma, members)


def build_graph(spark: SparkSession, sf_dir: str, path: str, relations: list[str], dim: int = 8, binding: str = "composed", numeric: Numeric = Numeric(), method: str = "mean", gamma: float = 1.0) -> KnowledgeGraph:
    """open_graph through files: triples first, then the ends of relations with their degrees, vectors of their entities, roles with vectors, and relation vectors, each from what is written."""
    build_triples(spark, sf_dir, relations).write.mode("overwrite").partitionBy("r").parquet(f"{path}/triples")
    triples = spark.read.schema("h_type string, h bigint, t_type string, t bigint, r string").parquet(f"{path}/triples")
    degrees(triples).write.mode("overwrite").parquet(f"{path}/ends")
    ends = spark.read.schema("r string, end string, eid bigint, degree bigint").parquet(f"{path}/ends")
    _write_vectors(load_entity_vectors(ends.select("eid").distinct(), Tables(spark, sf_dir).embeddings, dim, binding, numeric), path)
    vectors = spark.read.schema(f"eid bigint, vec array<{numeric.element}>").parquet(f"{path}/vectors")
    _write_members(ends.join(vectors, "eid", "left"), path)
    members = spark.read.schema(f"eid bigint, degree bigint, vec array<{numeric.element}>, r string, end string").parquet(f"{path}/members")
    _relation_vectors(triples, vectors, members, dim, binding, numeric, method).coalesce(1).write.mode("overwrite").parquet(f"{path}/relations")
    return load_graph(spark, path, dim, numeric, gamma)


def adjacency(triples: DataFrame, by: str = "h", typed: bool = True) -> DataFrame:
    """(h, tails): all neighbours of an entity in one row; for graphs without hubs, as joins use the flat edges."""
    other = "t" if by == "h" else "h"
    item = F.struct("r", other) if typed else F.col(other)
    return triples.groupBy(by).agg(F.sort_array(F.collect_set(item)).alias("neighbours"))


def role_members(triples: DataFrame, relations: str | list[str], endpoint: str = "t") -> DataFrame:
    """(eid): distinct entities at one end of one or several relations."""
    names = [relations] if isinstance(relations, str) else list(relations)
    return triples.where(F.col("r").isin(names)).select(F.col(endpoint).alias("eid")).distinct()


def one_hop(kg: KnowledgeGraph, head: int, relation: str) -> DataFrame:
    """Plain lookup: the tails of one head."""
    return kg.edges(relation).where(F.col("h") == head).select(F.col("t").alias("eid"))


def inverse_edges(triples: DataFrame) -> DataFrame:
    return triples.select(F.concat(F.lit("inv:"), "r").alias("r"), F.col("t_type").alias("h_type"), F.col("t").alias("h"), F.col("h_type").alias("t_type"), F.col("h").alias("t"))


def inverse_relations(relations: DataFrame) -> DataFrame:
    return relations.select(F.concat(F.lit("inv:"), "r").alias("r"), F.transform("vec", lambda x: -x).alias("vec"))


def undirected(kg: KnowledgeGraph) -> KnowledgeGraph:
    """The graph with every edge also turned round, its relation's vector negated."""
    return KnowledgeGraph(kg.triples.unionByName(inverse_edges(kg.triples)), kg.vectors, kg.relations.unionByName(inverse_relations(kg.relations)), kg.dim, kg.numeric, kg.gamma)


def degrees(triples: DataFrame) -> DataFrame:
    """(r, end, eid, degree)."""
    out = triples.groupBy("r", F.col("h").alias("eid")).agg(F.count("*").alias("degree")).withColumn("end", F.lit("h"))
    back = triples.groupBy("r", F.col("t").alias("eid")).agg(F.count("*").alias("degree")).withColumn("end", F.lit("t"))
    return out.unionByName(back).select("r", "end", "eid", "degree")


def relation_profile(triples: DataFrame) -> DataFrame:
    """(r, edges, heads, tails), from the degrees at either end: two distinct counts at once would copy every edge for each."""
    at = lambda end, value: F.sum(F.when(F.col("end") == end, value).otherwise(0)).cast("bigint")
    return degrees(triples).groupBy("r").agg(at("h", F.col("degree")).alias("edges"), at("h", F.lit(1)).alias("heads"), at("t", F.lit(1)).alias("tails"))


def graph_profile(kg: KnowledgeGraph) -> DataFrame:
    """(property, value): counts, record bytes, dimensions and elements of a graph, as a data sheet."""
    edges = kg.triples.agg(F.count("*").alias("value")).withColumn("property", F.lit("edges"))
    ents = entities_of(kg.triples).agg(F.count("*").alias("value")).withColumn("property", F.lit("entities"))
    rels = kg.relations.agg(F.count("*").alias("value")).withColumn("property", F.lit("relations"))
    fixed = kg.spark.createDataFrame([("dimensions", kg.dim), ("edge_record_bytes", 24), ("vector_record_bytes", 8 + 8 * kg.dim)], "property string, value bigint")
    counted = edges.unionByName(ents).unionByName(rels)
    elements = counted.where("property in ('edges', 'entities')").agg(F.sum("value").alias("value")).withColumn("property", F.lit("elements"))
    return counted.unionByName(elements).unionByName(fixed).select("property", "value")


def type_cube(triples: DataFrame) -> DataFrame:
    """Edge counts by head type and tail type with all totals; grouping tells which are."""
    return triples.cube("h_type", "t_type").agg(F.count("*").alias("edges"), F.grouping_id().cast("int").alias("grouping"))


def neighbourhood(kg: KnowledgeGraph, start: int, hops: int) -> DataFrame:
    """(eid, hops): entities within so many edges, with their distance."""
    reached = kg.spark.createDataFrame([(start, 0)], "eid bigint, hops int")
    frontier = reached
    for i in range(1, hops + 1):
        step = frontier.join(kg.triples.select(F.col("h").alias("eid"), F.col("t")), "eid").select(F.col("t").alias("eid")).distinct()
        frontier = step.join(reached.select("eid"), "eid", "left_anti").withColumn("hops", F.lit(i))
        reached = reached.unionByName(frontier)
    return reached


def sample_triples(triples: DataFrame, share: float, seed: int = 1) -> DataFrame:
    """A share of the edges by hash: the same edges at every call and partitioning."""
    return triples.where(F.pmod(F.xxhash64("r", "h", "t", F.lit(seed)), F.lit(1_000_000)) < int(share * 1_000_000))


def entity_types(df: DataFrame, column: str = "eid") -> DataFrame:
    return df.withColumn("type_code", code_column(column).cast("int"))
