"""Near-duplicate detection by circulant MinHash.

A document's set holds the 64-bit hashes of its distinct 5-word shingles.  Two permutations of the 32-bit
circle make the whole signature: the first scatters the set, the second ranks it, and coordinate k
ranks the set rotated by k steps.  Coordinates are banded; documents that share a band are candidates, and each
link is confirmed on the full sets by exact counts.

Documents of one shingle set collapse into a class before banding, so exact copies cost nothing more.  Within
a band bucket no all-pairs list is made: members are first compared with the bucket's smallest id, links are merged
into components, and later rounds compare only members of *different* components - the smallest of
each component first, then whatever is left across components and can reach the threshold by sketches of the sets.  Members already in one component need no
further comparison, so that large groups of copies cost rows in proportion to their size, and
no candidate pair between different components is left unchecked.  What is left of a large bucket is dealt to blocks, and each
pair of blocks is a group of its own, so that no task tests more than BLOCK^2 pairs of sketches at a time.

With bands of 4 coordinates and 40 bands, a pair of similarity 0.75 misses all bands with probability (1 - 0.75^4)^40 = 2.5e-7.

Defined results: every row gives a row; null or empty text has an empty set, is linked with nothing and is kept; a text of fewer
than 5 words is one shingle; rows repeating a doc_id, and rows without one, are linked each by its own text; a component's id is its
smallest doc_id, null where none of its rows has one, and then the row of the smallest text hash is kept; an empty table gives an empty
table; further columns are ignored by ``near_duplicates`` and pass through ``drop_near_duplicates``, whatever their names.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import Scratch, arrow, keyed, mix64, renamed_back, row_keys, same_row, signed, slices, spare, table

SHINGLE = 5
BANDS, ROWS = 40, 4
THRESHOLD = 75  # in hundredths
CELLS = 1024  # of the sketch that bounds intersections
BUCKET = 1024  # members from which on a bucket is dealt to blocks
BLOCK = 4096  # members of a block, about
SIEVE_BITS = 16  # for each row wanted, in the bit table that rows meet before their texts move
SIEVE_WORDS = 1 << 21  # of 64 bits, at most: about 80 MB broadcast; more rows wanted then share the bits

_WORD_FACTOR = int(mix64(np.ones(1, dtype=np.uint64), 7)[0] | np.uint64(1))


def shingle_set(text: str | None, size: int = SHINGLE) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the shingles of a text."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    h = mix64(np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words)))
    n = max(1, len(words) - size + 1)
    out = np.full(n, len(words) if len(words) < size else size, np.uint64)
    for j in range(min(size, len(words))):
        out = out * np.uint64(_WORD_FACTOR) + h[j : j + n]
        out ^= out >> np.uint64(29)
    return np.unique(mix64(out))


# ---------------------------------------------------------------- signature


def _permute(x: np.ndarray, a: int, b: int) -> None:
    """A permutation of the 32-bit circle, in place."""
    x *= np.uint32(a)
    x ^= x >> np.uint32(16)
    x *= np.uint32(b)
    x ^= x >> np.uint32(15)


_SIGMA, _PI = (0x7FEB352D, 0x846CA68B), (0x2C1B3C6D, 0x297A2D39)
_STEP = 0x9E3779B1  # rotation from one coordinate to the next; odd, so that no two coordinates rotate alike


def signature(shingles: np.ndarray, coordinates: int = BANDS * ROWS, block: int = 4096) -> np.ndarray:
    """Circulant MinHash coordinates of a set; the set is folded to 32 bits for them alone."""
    out = np.full(coordinates, 0xFFFFFFFF, np.uint32)
    turns = (np.arange(coordinates, dtype=np.uint64) * np.uint64(_STEP)).astype(np.uint32)[:, None]
    for i in range(0, len(shingles), block):
        x = (shingles[i : i + block] >> np.uint64(32)).astype(np.uint32)
        _permute(x, *_SIGMA)
        y = x[None, :] - turns
        _permute(y, *_PI)
        np.minimum(out, y.min(axis=1), out=out)
    return out


def band_keys(sig: np.ndarray, bands: int = BANDS) -> np.ndarray:
    rows = sig.reshape(bands, -1).astype(np.uint64)
    key = np.arange(bands, dtype=np.uint64)
    for j in range(rows.shape[1]):
        key = mix64(key ^ (rows[:, j] * np.uint64(0x9E3779B97F4A7C15) + np.uint64(j)))
    return key


def _digest(shingles: np.ndarray) -> tuple[int, int]:
    d = xxhash.xxh3_128_intdigest(shingles.tobytes())
    return d >> 64, d & (2**64 - 1)


def signatures(docs: DataFrame, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """(doc_id, text_hash, n_shingles, s1, s2, bands) of every row: size and 128-bit digest of its set, and its band keys."""

    def scan(batches):
        for batch in batches:
            for part in slices(batch):
                n, s1, s2, keys = [], [], [], []
                for text in part.column(1).to_pylist():
                    own = shingle_set(text)
                    a, b = _digest(own)
                    n.append(len(own))
                    s1.append(a)
                    s2.append(b)
                    keys.append(signed(band_keys(signature(own, bands * rows), bands)) if len(own) else np.zeros(0, np.int64))
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), part.column(2), pa.array(n, pa.int64()), pa.array(signed(np.array(s1, np.uint64))), pa.array(signed(np.array(s2, np.uint64))), pa.array(keys, pa.list_(pa.int64()))],
                    ["doc_id", "text_hash", "n_shingles", "s1", "s2", "bands"],
                )

    return arrow(keyed(docs), scan, "doc_id bigint, text_hash bigint, n_shingles bigint, s1 bigint, s2 bigint, bands array<bigint>")


# ---------------------------------------------------------------- exact confirmation


def sifted(own: DataFrame, wanted: DataFrame, bits: int = SIEVE_BITS, most: int = SIEVE_WORDS) -> DataFrame:
    """The rows of own, (doc_id, text_hash, ...), that a broadcast bit table does not rule out: all rows wanted, (__id, __hash), and few others.

    A row's bit goes by id and hash, so that copies of a wanted text are ruled out too.
    """
    words = min(most, wanted.count() * bits // 64 + 1)
    place = lambda key, doc: F.pmod(F.xxhash64(key, doc), F.lit(64 * words))
    sieve = wanted.select(place("__hash", "__id").alias("__at")).groupBy(F.expr("__at div 64").alias("__word")).agg(F.expr("bit_or(shiftleft(1L, cast(__at % 64 as int)))").alias("__bits"))
    met = own.withColumn("__at", place("text_hash", "doc_id")).withColumn("__word", F.expr("__at div 64")).join(F.broadcast(sieve), "__word")
    return met.where("bit_get(__bits, cast(__at % 64 as int)) = 1").select(*own.columns)


def _sets(docs: DataFrame, wanted: DataFrame, repeated: bool) -> DataFrame:
    """(id, set, bits, over) of the rows wanted, (__id, __hash, id): sets as bytes of sorted 64-bit hashes, and their sketches.

    repeated: some rows share id and text, so that one of them has to be taken.
    """

    def scan(batches):
        for batch in batches:
            for part in slices(batch):
                sets = [shingle_set(t) for t in part.column(1).to_pylist()]
                sketches = [sketch_of(x) for x in sets]
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), pa.array([x.tobytes() for x in sets], pa.binary()), pa.array([b for b, _ in sketches], pa.list_(pa.int64())), pa.array([o for _, o in sketches], pa.int64())],
                    ["id", "set", "bits", "over"],
                )

    own = sifted(keyed(docs), wanted)  # where the join shuffles, it moves the texts wanted, not all of them
    texts = own.join(wanted, same_row(own, wanted)).select("id", "text")
    return arrow(texts.dropDuplicates(["id"]) if repeated else texts, scan, "id bigint, set binary, bits array<bigint>, over bigint")


def confirm(pairs: DataFrame, sets: DataFrame, threshold: int = THRESHOLD) -> DataFrame:
    """The pairs (a, b) with 100 * intersection >= threshold * union, counted on the full sets."""

    def scan(batches):
        for batch in batches:
            for part in slices(batch, 1024):
                a, b = [], []
                for x, y, p, q in zip(*(c.to_pylist() for c in part.columns), strict=True):
                    p, q = np.frombuffer(p, np.uint64), np.frombuffer(q, np.uint64)
                    if 100 * min(len(p), len(q)) >= threshold * max(len(p), len(q)):
                        both = np.concatenate((p, q))
                        both.sort(kind="stable")  # merges two sorted runs
                        common = int((both[1:] == both[:-1]).sum())
                        if 100 * common >= threshold * (len(p) + len(q) - common):
                            a.append(x)
                            b.append(y)
                yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    left = pairs.join(sets.select(F.col("id").alias("a"), F.col("set").alias("sa")), "a")
    both = left.join(sets.select(F.col("id").alias("b"), F.col("set").alias("sb")), "b")
    return arrow(both.select("a", "b", "sa", "sb"), scan, "a bigint, b bigint")


# ---------------------------------------------------------------- components


def components(labels: DataFrame, links: DataFrame, work: Scratch) -> DataFrame:
    """(id, label) after merging labels along links (a, b); a label is the smallest id of its component.

    Works on the graph of labels: rounds of taking the smallest neighbour and following labels to labels, until none changes.
    """
    ends = links.join(labels.select(F.col("id").alias("a"), F.col("label").alias("la")), "a").join(labels.select(F.col("id").alias("b"), F.col("label").alias("lb")), "b")
    edges = work.write(ends.where("la <> lb").select(F.least("la", "lb").alias("u"), F.greatest("la", "lb").alias("v")).distinct(), "edges")
    if edges.isEmpty():
        return labels
    both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    roots = work.write(both.groupBy("u").agg(F.least(F.col("u"), F.min("v")).alias("r")), "roots")
    while True:
        # smallest root among the neighbours, then the root of that root
        near = both.join(roots.select(F.col("u").alias("v"), F.col("r").alias("rv")), "v").groupBy("u").agg(F.min("rv").alias("rv"))
        step = roots.join(near, "u").select("u", F.least("r", "rv").alias("n"), F.col("r").alias("old"))
        jump = roots.select(F.col("u").alias("n"), F.col("r").alias("rr"))
        new = work.write(step.join(jump, "n", "left").select("u", F.least("n", F.coalesce("rr", "n")).alias("r"), "old"), "roots")
        roots = new.select("u", "r")
        if new.where("r <> old").isEmpty():
            break
    merged = labels.join(roots.select(F.col("u").alias("label"), "r"), "label", "left")
    return work.write(merged.select("id", F.coalesce("r", "label").alias("label")), "labels")


def sketch_of(shingles: np.ndarray) -> tuple[np.ndarray, int]:
    """(bits, over): for each of CELLS cells one bit if a shingle falls there and one if two do; over counts the rest.

    Of two sets, the common bits plus the smaller ``over`` are never fewer than the common shingles.
    """
    count = np.bincount((shingles & np.uint64(CELLS - 1)).astype(np.int64), minlength=CELLS)
    bits = np.packbits(np.concatenate((count > 0, count > 1)), bitorder="little").view(np.int64)
    return bits, int(np.maximum(count - 2, 0).sum())


def block_pairs(threshold: int = THRESHOLD):
    """For applyInArrow over (i, j, block, id, label, n, bits, over): pairs (x, y) of different labels, one from block i and one from block j, that can reach the threshold by their sketches."""

    def run(rows: pa.Table) -> pa.Table:
        rows = rows.combine_chunks()
        ids, label, n, over, block = (rows[c].to_numpy() for c in ("id", "label", "n", "over", "block"))
        bits = rows["bits"].combine_chunks().flatten().to_numpy().reshape(len(ids), -1).view(np.uint64)
        i, j = rows["i"][0].as_py(), rows["j"][0].as_py()
        out = [(np.zeros(0, np.int64), np.zeros(0, np.int64))]

        def side(which: int) -> np.ndarray:
            at = np.flatnonzero(block == which)
            return at[np.argsort(label[at], kind="stable")]

        left, right = side(i), side(j)
        for a in left:
            # within one block each pair is met from its smaller label, across blocks from either side
            others = right[np.searchsorted(label[right], label[a], side="right") :] if i == j else right[label[right] != label[a]]
            small, large = np.minimum(n[others], n[a]), np.maximum(n[others], n[a])
            others = others[100 * small >= threshold * large]
            most = np.bitwise_count(bits[others] & bits[a]).sum(axis=1, dtype=np.int64) + np.minimum(over[others], over[a])
            hit = others[(100 + threshold) * most >= threshold * (n[others] + n[a])]
            if len(hit):
                out.append((np.full(len(hit), ids[a]), ids[hit]))
        x, y = (np.concatenate(c) for c in zip(*out, strict=True))
        return pa.table({"x": pa.array(x, pa.int64()), "y": pa.array(y, pa.int64())})

    return run


def _cross_pairs(members: DataFrame, labels: DataFrame, sketches: DataFrame, whole: bool, threshold: int, work: Scratch, bucket: int = BUCKET, block: int = BLOCK) -> DataFrame:
    """Distinct pairs (a, b) of different components that share a bucket and can reach the threshold.

    Not whole: the smallest member of each bucket against the members of its other components.  Whole: all of them, unless the bound
    on the intersection that sketches give is too low: inside the join's condition for buckets of up to ``bucket`` members,
    in groups of two blocks for larger ones, so that neither rows nor the work of a task grow with the square of a bucket.
    """
    own = members.join(labels, "id")
    stats = own.groupBy("key").agg(F.min("label").alias("lo"), F.max("label").alias("hi"), F.min(F.struct("id", "label")).alias("first"), F.count("*").alias("size"))
    open_ = work.write(stats.where("lo <> hi").select("key", "first", "size"), "open")
    own = own.join(open_, "key")
    if not whole:
        pairs = own.where("label <> first.label").select(F.col("first.id").alias("x"), F.col("id").alias("y"))
    else:
        # plain columns without nulls: as an array, each access adds checks, and the condition outgrows what the JIT compiles
        words = [F.coalesce(F.col("bits")[i], F.lit(0).cast("bigint")).alias(f"w{i}") for i in range(CELLS // 32)]
        few = own.where(F.col("size") <= bucket).select("key", "id", "n", "label")
        few = few.join(sketches.select("id", *words, F.coalesce("over", F.lit(0).cast("bigint")).alias("over")), "id")
        other = few.select("key", *[F.col(c).alias(f"{c}_") for c in few.columns if c != "key"])
        most = " + ".join(f"bit_count(w{i} & w{i}_)" for i in range(CELLS // 32)) + " + least(over, over_)"
        pairs = few.join(other, "key").where("label < label_").where(f"{100 + threshold} * ({most}) >= {threshold} * (n + n_)").select(F.col("id").alias("x"), F.col("id_").alias("y"))
        many = own.where(F.col("size") > bucket)
        if not many.isEmpty():
            blocks = F.ceil(F.col("size") / block).cast("int")
            dealt = many.withColumn("block", F.pmod(F.xxhash64("id"), blocks).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), blocks - 1)))
            dealt = dealt.select("key", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "id", "label", "n").join(sketches.select("id", "bits", "over"), "id")
            large = dealt.groupBy("key", "i", "j").applyInArrow(block_pairs(threshold), "x bigint, y bigint")
            pairs = pairs.unionByName(large)
    return pairs.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()


def _linked(docs: DataFrame, work: Scratch, bands: int, rows: int, threshold: int, bucket: int, block: int) -> tuple[DataFrame, DataFrame]:
    """(signatures of every row; (doc_id, text_hash, copies, component_id, first) of each distinct pair of id and text with a set).

    first: whether the pair is the one of its component that stays; copies: the rows that share it.
    """
    found = work.write(signatures(docs, bands, rows), "signatures")
    real = found.where("n_shingles > 0")
    keys = work.write(real.groupBy("doc_id", "text_hash", "s1", "s2").agg(F.count("*").alias("copies")), "keys")
    repeated = not keys.where("copies > 1").isEmpty()
    # A class: the rows of one set; one of them stands for it, under a number that the written table fixes.
    stands = keys.groupBy("s1", "s2").agg(F.min(F.struct("doc_id", "text_hash")).alias("one"))
    classes = work.write(stands.select("s1", "s2", F.col("one.doc_id").alias("__id"), F.col("one.text_hash").alias("__hash"), F.monotonically_increasing_id().alias("id")), "classes")
    named = classes.select("__id", "__hash", "id")
    buckets = real.join(named, same_row(real, named)).select("id", F.col("n_shingles").alias("n"), F.explode("bands").alias("key"))
    # by window, so that band keys move once, and not for an aggregate and again for a join with it
    bucket_of = Window.partitionBy("key")
    shared = buckets.withColumns({"lo": F.min("id").over(bucket_of), "hi": F.max("id").over(bucket_of)}).where("lo <> hi")
    members = work.write(shared.select("key", "id", "n").distinct(), "members")
    labels = work.write(members.select("id").distinct().withColumn("label", F.col("id")), "labels")
    # written, as the sieve and the join both read it, and so that the join knows its size
    wanted = work.write(named.join(labels.select("id"), "id", "left_semi"), "wanted")
    sets = work.write(_sets(docs, wanted, repeated), "sets")
    # First each member with one partner: the smallest id that it shares a bucket with.
    lows = members.groupBy("key").agg(F.min("id").alias("a"))
    pairs = members.join(lows, "key").where("a <> id").groupBy(F.col("id").alias("b")).agg(F.min("a").alias("a")).select("a", "b")
    checked = work.write(pairs, "checked")
    labels = components(labels, work.write(confirm(checked, sets, threshold), "links"), work)
    for whole in (False, False, True):
        pairs = work.write(_cross_pairs(members, labels, sets.drop("set"), whole, threshold, work, bucket, block).join(checked, ["a", "b"], "left_anti"), "pairs")
        if not pairs.isEmpty():
            labels = components(labels, work.write(confirm(pairs, sets, threshold), "links"), work)
            checked = checked.union(pairs)
    by_class = classes.join(labels, "id", "left").select("s1", "s2", F.coalesce("label", "id").alias("label"))
    linked = work.write(keys.join(by_class, ["s1", "s2"]).select("doc_id", "text_hash", "copies", "label"), "linked")
    heads = linked.groupBy("label").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "text_hash")).alias("head"))
    placed = linked.join(heads, "label")
    is_first = F.col("doc_id").eqNullSafe(F.col("head.doc_id")) & (F.col("text_hash") == F.col("head.text_hash"))
    return found, placed.select("doc_id", "text_hash", "copies", F.col("head.doc_id").alias("component_id"), is_first.alias("first"))


def near_duplicates(docs: DataFrame, bands: int = BANDS, rows: int = ROWS, threshold: int = THRESHOLD, bucket: int = BUCKET, block: int = BLOCK) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) of every row."""
    work = Scratch(docs.sparkSession)
    found, linked = _linked(docs, work, bands, rows, threshold, bucket, block)
    right = row_keys(linked, "component_id", "first")
    own = found.join(right, same_row(found, right), "left")
    kept = F.coalesce(F.col("doc_id") == F.col("component_id"), F.col("first"), F.lit(True))
    return work.finish(own.select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"), kept.alias("kept")), "near-duplicates")


def drop_near_duplicates(docs: DataFrame) -> DataFrame:
    """docs with one row of each component: that of the smallest doc_id, of equal ones that of the smallest text hash, of equal texts any."""
    work = Scratch(docs.sparkSession)
    linked = work.finish(_linked(docs, work, BANDS, ROWS, THRESHOLD, BUCKET, BLOCK)[1].where("not first or copies > 1"), "decisions")
    own = spare(docs, ("text_hash", "__id", "__hash", "__n")).withColumn("text_hash", F.xxhash64("text"))
    gone = row_keys(linked.where("not first"))
    out = own.join(gone, same_row(own, gone), "left_anti")
    twins = row_keys(linked.where("first"))
    if not twins.isEmpty():  # rows that share id and text: one of each stays
        first = out.join(twins, same_row(out, twins), "left_semi").withColumn("__n", F.row_number().over(Window.partitionBy("doc_id", "text_hash").orderBy("doc_id"))).where("__n = 1").drop("__n")
        out = out.join(twins, same_row(out, twins), "left_anti").unionByName(first)
    return renamed_back(out, docs.columns)


def op5_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))


OP5_SQL = r"""
with recursive w as (
  select doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') as words
  from documents),
s as (
  select distinct doc_id, unnest(case when len(words) < 5 then [array_to_string(words, ' ')] else list_transform(range(1, len(words) - 3), lambda i: array_to_string(words[i:i + 4], ' ')) end) as shingle
  from w where len(words) > 0),
n as (select doc_id, count(*) as n from s group by doc_id),
p as (select a.doc_id as x, b.doc_id as y, count(*) as c from s a join s b on a.shingle = b.shingle and a.doc_id <> b.doc_id group by all),
l as (select x, y from p join n nx on nx.doc_id = x join n ny on ny.doc_id = y where 100 * c >= 75 * (nx.n + ny.n - c)),
r as (select doc_id as x, doc_id as root from documents union select l.y, r.root from r join l on l.x = r.x where r.root < l.y),
m as (select x as doc_id, min(root) as component_id from r group by x)
select w.doc_id, coalesce(n.n, 0) as n_shingles, m.component_id, m.component_id = w.doc_id as kept
from w left join n using (doc_id) join m using (doc_id)
"""
