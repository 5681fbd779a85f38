"""Vectors of entities and relations.

``fixed`` numbers are BIGINT coordinates (floor of x * 2^20, of which a composed vector holds four and a quarter
parts, unit 2^22): sums are exact in any order, so that every engine and every partitioning gives the same scores.
``double`` is plain floating point.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..ids import CODES, OFFSETS, SPAN, code_of, eid

QUANTUM = 2**20
#: Embedding tables up to so many bytes are broadcast to the entities they are bound to; larger ones are joined by shuffle.
MAX_BROADCAST = 64 << 20


@dataclass(frozen=True)
class Numeric:
    mode: str = "fixed"  # or "double"

    def __post_init__(self) -> None:
        if self.mode not in ("fixed", "double"):
            raise ValueError(f"unknown numeric mode {self.mode!r}")

    @property
    def unit(self) -> float:
        return 4.0 * QUANTUM if self.mode == "fixed" else 1.0

    @property
    def element(self) -> str:
        return "bigint" if self.mode == "fixed" else "double"


def trim_vectors(vectors: DataFrame, dim: int, column: str = "vec") -> DataFrame:
    """Leading dim coordinates."""
    return vectors.withColumn(column, F.slice(column, 1, dim))


def base_vectors(embeddings: DataFrame, dim: int, numeric: Numeric) -> DataFrame:
    """(vec_id, q): the leading coordinates of the embedding table in the numeric mode."""
    if numeric.mode == "fixed":
        q = F.transform(F.slice("embedding", 1, dim), lambda x: F.floor(x.cast("double") * QUANTUM).cast("bigint"))
    else:
        q = F.transform(F.slice("embedding", 1, dim), lambda x: x.cast("double"))
    return embeddings.select("vec_id", q.alias("q"))


def _small(df: DataFrame, rows: int, dim: int) -> DataFrame:
    return F.broadcast(df) if rows * dim * 8 <= MAX_BROADCAST else df


def bind_composed(entities: DataFrame, embeddings: DataFrame, dim: int, numeric: Numeric = Numeric()) -> DataFrame:
    """(eid, vec): each entity gets one embedding plus a quarter of another, chosen by type and key."""
    n = embeddings.count()
    q = base_vectors(embeddings, dim, numeric)
    offset = F.create_map(*[F.lit(x) for t, c in CODES.items() for x in (c, OFFSETS[t])])
    code = F.expr(f"cast(eid div {SPAN} as int)")
    k, o = F.col("eid") % F.lit(SPAN), offset[code]
    places = entities.select("eid", ((k + o) % n).alias("a"), ((F.expr(f"(eid % {SPAN}) div {n}") * 17 + k + o + 1) % n).alias("b"))
    one, two = _small(q.select(F.col("vec_id").alias("a"), F.col("q").alias("qa")), n, dim), _small(q.select(F.col("vec_id").alias("b"), F.col("q").alias("qb")), n, dim)
    both = places.join(one, "a").join(two, "b")
    mix = (lambda x, y: x * 4 + y) if numeric.mode == "fixed" else (lambda x, y: x + y / 4)
    return both.select("eid", F.zip_with("qa", "qb", mix).alias("vec"))


def bind_native(entities: DataFrame, embeddings: DataFrame, dim: int, numeric: Numeric = Numeric()) -> DataFrame:
    """(eid, vec) of the entities whose key is an embedding's id; the others have none."""
    n = embeddings.count()
    q = base_vectors(embeddings, dim, numeric)
    scale = 4 if numeric.mode == "fixed" else 1
    own = _small(q.select(F.col("vec_id").alias("__k"), F.transform("q", lambda x: x * scale).alias("vec")), n, dim)
    return entities.select("eid", (F.col("eid") % F.lit(SPAN)).alias("__k")).join(own, "__k").select("eid", "vec")


def bind_planted(vectors: DataFrame, edges: DataFrame, relation_vector: DataFrame, noise: DataFrame) -> DataFrame:
    """(eid, vec) of the tails of edges (h, t), made of parent + relation + noise/8, so that true links score high; heads keep theirs.

    relation_vector is one row (vec); noise is (eid, vec).  A tail with several heads takes the smallest.
    """
    parent = edges.groupBy("t").agg(F.min("h").alias("h"))
    planted = (
        parent.join(vectors.select(F.col("eid").alias("h"), F.col("vec").alias("pv")), "h")
        .join(noise.select(F.col("eid").alias("t"), F.col("vec").alias("nv")), "t")
        .crossJoin(F.broadcast(relation_vector.select(F.col("vec").alias("rv"))))
        .select(F.col("t").alias("eid"), F.zip_with(F.zip_with("pv", "rv", lambda x, y: x + y), "nv", lambda x, y: x + y / 8).alias("vec"))
    )
    heads = edges.select(F.col("h").alias("eid")).distinct().join(vectors, "eid")
    return heads.unionByName(planted)


def load_entity_vectors(entities: DataFrame, embeddings: DataFrame, dim: int = 8, binding: str = "composed", numeric: Numeric = Numeric()) -> DataFrame:
    if binding == "composed":
        return bind_composed(entities, embeddings, dim, numeric)
    if binding == "native":
        return bind_native(entities, embeddings, dim, numeric)
    raise ValueError(f"unknown binding {binding!r}")


def relation_vectors(triples: DataFrame, vectors: DataFrame, dim: int, numeric: Numeric = Numeric(), method: str = "mean") -> DataFrame:
    """(r, vec): mean (least squares) or median (least absolute error) of vec(t) - vec(h) over the distinct triples of a relation.

    One aggregation with a column for each coordinate; fixed sums are decimals, which hold 10^12 triples and more.
    """
    ends = (
        triples.select("r", "h", "t")
        .join(vectors.select(F.col("eid").alias("h"), F.col("vec").alias("vh")), "h")
        .join(vectors.select(F.col("eid").alias("t"), F.col("vec").alias("vt")), "t")
    )
    parts = []
    for i in range(dim):
        d = F.col("vt")[i] - F.col("vh")[i]
        if method == "median":
            middle = F.percentile(d, 0.5)
            parts.append(F.floor(middle).cast("bigint") if numeric.mode == "fixed" else middle)
        elif method != "mean":
            raise ValueError(f"unknown method {method!r}")
        elif numeric.mode == "fixed":
            parts.append(F.sum(d.cast("decimal(38,0)")))
        else:
            parts.append(F.avg(d))
    summed = ends.groupBy("r").agg(F.count("*").alias("n"), *[p.alias(f"s{i}") for i, p in enumerate(parts)])
    if method == "mean" and numeric.mode == "fixed":
        cells = [F.expr(f"cast((s{i} - pmod(s{i}, n)) div n as bigint)") for i in range(dim)]
    else:
        cells = [F.col(f"s{i}") for i in range(dim)]
    return summed.select("r", F.array(*cells).alias("vec"))


def relation_vectors_of_members(members: DataFrame, dim: int, numeric: Numeric = Numeric()) -> DataFrame:
    """(r, vec): the mean of vec(t) - vec(h) from the ends of the relations, (r, end, eid, degree, vec), all of which have vectors.

    A sum over edges of a vector at one end is the sum over entities of degree times vector: entities are joined with vectors once, edges never.
    """
    signed = F.when(F.col("end") == "t", F.col("degree")).otherwise(-F.col("degree"))
    sums = []
    for i in range(dim):
        d = F.col("vec")[i] * signed
        sums.append(F.sum(d.cast("decimal(38,0)") if numeric.mode == "fixed" else d).alias(f"s{i}"))
    summed = members.groupBy("r").agg(F.sum(F.when(F.col("end") == "t", F.col("degree")).otherwise(0)).alias("n"), *sums)
    cells = [F.expr(f"cast((s{i} - pmod(s{i}, n)) div n as bigint)") if numeric.mode == "fixed" else F.col(f"s{i}") / F.col("n") for i in range(dim)]
    return summed.select("r", F.array(*cells).alias("vec"))


def vector_of(vectors: DataFrame, etype: str, key: int) -> DataFrame:
    """One row (vec), or none."""
    code_of(etype)
    return vectors.where(F.col("eid") == eid(etype, key)).select("vec")


def check_dimension(vectors: DataFrame, dim: int) -> DataFrame:
    """vectors; a row of another length raises when it is read."""
    wrong = F.raise_error(F.concat(F.lit(f"vector of other length than {dim}: id "), F.col("eid").cast("string")))
    return vectors.withColumn("vec", F.when(F.size("vec") == dim, F.col("vec")).otherwise(wrong.cast(vectors.schema["vec"].dataType)))


def sum_columns(columns: list[Column]) -> Column:
    total = columns[0]
    for c in columns[1:]:
        total = total + c
    return total
