"""Line de-duplication by a sharded minimal perfect hash over distinct line hashes.

Pass 1 hashes the lines of each document once (128 bits of the stripped, A-Z lower-cased line) and counts the rows and
the documents of each hash.  Hashes that stand in one row only need no place, as not being found says the same; all others are
dealt to shards, and each shard becomes one binary row: a minimal perfect hash with arrays of fingerprints, document counts and
last documents beside it.  Pass 2 scans the documents and probes those arrays; the counts found there decide, so that
texts are neither shuffled nor joined with lines.  The index goes to the tasks as a broadcast only while it measures at most
``max_index_bytes``; a larger one is probed shard by shard: the (hash, document) pairs travel to the shard and stream
past its arrays in sorted partitions, so that a task holds one shard and one batch, and a shard whose lines stand in very many rows is
copied to as many partitions as its rows ask for.  Only hits come back to the documents.  Both ways give the same rows.

Defined results: null or empty text is one empty line; rows repeating a doc_id count as one document; rows with a null
doc_id are never holders and lose every line that min_docs documents hold; an empty table gives an empty table;
further columns pass through, one that has the name of an added column as ``input_<name>``.
"""

from __future__ import annotations

import math
import struct

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import SPACE_BYTES, Scratch, arrow, mix64, signed, slices, spare, table

SHARD_KEYS = 100_000  # keys of a shard, at which it is about 2 MB
MAX_INDEX_BYTES = 96 << 20
SHARD_ROWS = 2_000_000  # rows of indexed lines that one copy of a shard is meant to see


def line_key(line: bytes, min_chars: int) -> bytes | None:
    """The key of a line, or None if it has fewer than min_chars code points."""
    key = line.strip(SPACE_BYTES).lower()
    if len(key) < min_chars or (len(key) < 4 * min_chars and not key.isascii() and len(key.decode()) < min_chars):
        return None
    return key


def line_hashes(text: str | None, min_chars: int) -> tuple[list[str], list[int], list[int]]:
    """Lines of a text; the positions of those with a key; their 128-bit hashes."""
    lines = (text or "").split("\n")
    at, hashes = [], []
    for i, line in enumerate(lines):
        if len(line) >= min_chars and (key := line_key(line.encode("utf-8", "surrogatepass"), min_chars)) is not None:
            at.append(i)
            hashes.append(xxhash.xxh3_128_intdigest(key))
    return lines, at, hashes


def _split(hashes: list[int]) -> tuple[np.ndarray, np.ndarray]:
    both = np.frombuffer(b"".join(h.to_bytes(16, "little") for h in hashes), dtype=np.uint64).reshape(-1, 2)
    return both[:, 1].copy(), both[:, 0].copy()


# ---------------------------------------------------------------- minimal perfect hash


class Shard:
    """Minimal perfect hash of distinct 128-bit keys, with arrays of fingerprint, count and last document.

    Level by level, keys that have a bit of the level's bit array to themselves stay and the rest go to the next level;
    a key's index is the number of set bits before its own.
    """

    GAMMA = 2.0

    def __init__(self, levels: list[np.ndarray], fingerprints: np.ndarray, counts: np.ndarray, last: np.ndarray):
        self.levels, self.fingerprints, self.counts, self.last = levels, fingerprints, counts, last
        self.ranks, base = [], 0
        for bits in levels:
            ones = np.bitwise_count(bits).astype(np.int64)
            before = np.cumsum(ones) - ones + base
            self.ranks.append(before)
            base += int(ones.sum())

    @staticmethod
    def _place(h1: np.ndarray, level: int, bits: int) -> np.ndarray:
        return (mix64(h1, level) % np.uint64(bits)).astype(np.int64)

    @classmethod
    def build(cls, h1: np.ndarray, h2: np.ndarray, counts: np.ndarray, last: np.ndarray) -> Shard:
        levels, left, level = [], h1 ^ mix64(h2, 99), 0
        while len(left):
            size = max(64, -(-int(cls.GAMMA * len(left)) // 64) * 64)
            at = cls._place(left, level, size)
            alone = np.bincount(at, minlength=size) == 1
            levels.append(np.packbits(alone, bitorder="little").view(np.uint64))
            left = left[~alone[at]]
            level += 1
            if level > 200:
                raise ValueError("keys of a shard must be distinct")
        n = len(h1)
        out = cls(levels, np.zeros(n, np.uint64), np.zeros(n, np.uint32), np.zeros(n, np.int64))
        at = out.index(h1, h2)
        out.fingerprints[at], out.counts[at], out.last[at] = h2, counts, last
        return out

    def index(self, h1: np.ndarray, h2: np.ndarray) -> np.ndarray:
        """The index of each key; of a key that is not in the shard, -1 or any index."""
        key = h1 ^ mix64(h2, 99)
        found, open_ = np.full(len(key), -1, np.int64), np.arange(len(key))
        for level, (bits, ranks) in enumerate(zip(self.levels, self.ranks, strict=True)):
            if not len(open_):
                break
            at = self._place(key[open_], level, 64 * len(bits))
            word, bit = at >> 6, (at & 63).astype(np.uint64)
            hit = (bits[word] >> bit) & np.uint64(1) == 1
            below = np.bitwise_count(bits[word] & ((np.uint64(1) << bit) - np.uint64(1))).astype(np.int64)
            found[open_[hit]] = (ranks[word] + below)[hit]
            open_ = open_[~hit]
        return found

    def probe(self, h1: np.ndarray, h2: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Whether each key is in the shard, its count and its last document."""
        at = self.index(h1, h2)
        known = at >= 0
        known[known] = self.fingerprints[at[known]] == h2[known]
        safe = np.where(known, at, 0)
        if not len(self.last):
            return known, np.zeros(len(h1), np.uint32), np.zeros(len(h1), np.int64)
        return known, self.counts[safe], self.last[safe]

    def to_bytes(self) -> bytes:
        head = [len(self.levels), len(self.last), *(len(b) for b in self.levels)]
        return b"".join([struct.pack(f"<{len(head)}q", *head), *(b.tobytes() for b in self.levels), self.fingerprints.tobytes(), self.counts.tobytes(), self.last.tobytes()])

    @classmethod
    def from_bytes(cls, blob: bytes) -> Shard:
        k, n = struct.unpack_from("<2q", blob)
        sizes, at, levels = struct.unpack_from(f"<{k}q", blob, 16), 16 + 8 * k, []
        for size in sizes:
            levels.append(np.frombuffer(blob, np.uint64, size, at))
            at += 8 * size
        fingerprints = np.frombuffer(blob, np.uint64, n, at)
        counts = np.frombuffer(blob, np.uint32, n, at + 8 * n)
        return cls(levels, fingerprints, counts, np.frombuffer(blob, np.int64, n, at + 12 * n))


# ---------------------------------------------------------------- plans


def _copy_of() -> Column:
    """What stands for the id of rows without one: a hash of their text, null in others.

    Rows that share it lose the same lines: without an id, every repeated line goes.
    """
    return F.when(F.col("doc_id").isNull(), F.xxhash64(F.col("text")))


def _holders(docs: DataFrame, min_chars: int, salts: np.ndarray | None = None) -> DataFrame:
    """(h1, h2, doc_id, copy[, shard, salt]): each key of a row once; ``salts`` says how many copies each shard has."""
    sent = docs.sparkSession.sparkContext.broadcast(salts) if salts is not None else None

    def scan(batches):
        copies = sent.value if sent is not None else None
        for batch in batches:
            for part in slices(batch, 1024):
                ids, stand_ins, hashes = [], [], []
                for doc_id, text, copy in zip(*(part.column(i).to_pylist() for i in range(3)), strict=True):
                    if text:
                        own = set(line_hashes(text, min_chars)[2])
                        hashes.extend(own)
                        ids.extend([doc_id] * len(own))
                        stand_ins.extend([copy] * len(own))
                if not ids:
                    continue
                h1, h2 = _split(hashes)
                arrays = [pa.array(signed(h1)), pa.array(signed(h2)), pa.array(ids, pa.int64()), pa.array(stand_ins, pa.int64())]
                if copies is not None:
                    who = np.array([x if x is not None else y for x, y in zip(ids, stand_ins, strict=True)], np.int64).view(np.uint64)
                    shard = _shard_of(h1, len(copies))
                    salt = mix64(who, 3) % copies[shard].astype(np.uint64)
                    arrays += [pa.array(shard.astype(np.int32)), pa.array(salt.astype(np.int32))]
                yield pa.RecordBatch.from_arrays(arrays, ["h1", "h2", "doc_id", "copy", "shard", "salt"][: len(arrays)])

    own = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text").withColumn("copy", _copy_of())
    return arrow(own, scan, "h1 bigint, h2 bigint, doc_id bigint, copy bigint" + (", shard int, salt int" if salts is not None else ""))


def counted_lines(docs: DataFrame, min_chars: int = 20) -> DataFrame:
    """(h1, h2, n_docs, last_doc, n_rows) of the keys that stand in two rows or more."""
    counted = _holders(docs, min_chars).groupBy("h1", "h2").agg(F.countDistinct("doc_id").alias("n_docs"), F.max("doc_id").alias("last_doc"), F.count("*").alias("n_rows"))
    return counted.where(F.col("n_rows") >= 2)


def build_index(lines: DataFrame, n_shards: int) -> DataFrame:
    """(shard, blob, n_rows) of (h1, h2, n_docs, last_doc, n_rows)."""

    def build(key, rows):
        h1, h2 = (rows[c].to_numpy().astype(np.int64).view(np.uint64) for c in ("h1", "h2"))
        shard = Shard.build(h1, h2, np.minimum(rows["n_docs"].to_numpy(), 2**32 - 1), rows["last_doc"].fill_null(0).to_numpy())
        total = int(rows["n_rows"].to_numpy().sum())
        return pa.table({"shard": pa.array([key[0].as_py()], pa.int32()), "blob": pa.array([shard.to_bytes()], pa.binary()), "n_rows": pa.array([total], pa.int64())})

    dealt = lines.withColumn("shard", F.pmod("h1", F.lit(n_shards)).cast("int"))
    return dealt.groupBy("shard").applyInArrow(build, "shard int, blob binary, n_rows bigint")


def _shard_of(h1: np.ndarray, n_shards: int) -> np.ndarray:
    return np.mod(h1.view(np.int64), n_shards)


def _dropped(shard: Shard, h1: np.ndarray, h2: np.ndarray, ids: np.ndarray, null: np.ndarray, min_docs: int) -> np.ndarray:
    """Whether each (key, document) goes: the count at the key's place reaches min_docs and the document is not the last there."""
    known, count, last = shard.probe(h1, h2)
    return known & (count >= min_docs) & ((last != ids) | null)


def _reduced(part: pa.RecordBatch, texts: list, gone: list[set[int]], drop: tuple[str, ...] = ()) -> pa.RecordBatch:
    """part with the lines at the given places taken out of its texts, and counts of lines added."""
    n_lines, kept = [], []
    for text, places in zip(texts, gone, strict=True):
        lines = (text or "").split("\n")
        n_lines.append(len(lines))
        kept.append("\n".join([x for i, x in enumerate(lines) if i not in places]) if places else (text or ""))
    columns = {n: part.column(i) for i, n in enumerate(part.schema.names) if n not in drop}
    columns |= {"text": pa.array(kept, pa.string()), "n_lines": pa.array(n_lines, pa.int64()), "n_dropped": pa.array([len(x) for x in gone], pa.int64())}
    return pa.RecordBatch.from_arrays(list(columns.values()), list(columns))


def _out_schema(docs: DataFrame):
    base = docs.select("*", F.lit(0).cast("bigint").alias("n_lines"), F.lit(0).cast("bigint").alias("n_dropped")).schema
    for f in base.fields:
        f.nullable = True
    return base


def _probe_broadcast(docs: DataFrame, index: DataFrame, n_shards: int, min_chars: int, min_docs: int) -> DataFrame:
    blobs = docs.sparkSession.sparkContext.broadcast({r["shard"]: bytes(r["blob"]) for r in index.select("shard", "blob").collect()})

    def scan(batches):
        shards = {k: Shard.from_bytes(v) for k, v in blobs.value.items()}
        for batch in batches:
            for part in slices(batch, 1024):
                names = part.schema.names
                texts = part.column(names.index("text")).to_pylist()
                ids = part.column(names.index("doc_id")).to_pylist()
                owner, place, flat = [], [], []
                for k, text in enumerate(texts):
                    _, at, hashes = line_hashes(text, min_chars)
                    owner.extend([k] * len(at))
                    place.extend(at)
                    flat.extend(hashes)
                gone: list[set[int]] = [set() for _ in texts]
                if flat:
                    h1, h2 = _split(flat)
                    who = np.array([ids[k] or 0 for k in owner], np.int64)
                    null = np.array([ids[k] is None for k in owner], bool)
                    shard = _shard_of(h1, n_shards)
                    for s in np.unique(shard):
                        if (own := shards.get(int(s))) is not None:
                            at = np.flatnonzero(shard == s)
                            for i in at[_dropped(own, h1[at], h2[at], who[at], null[at], min_docs)]:
                                gone[owner[i]].add(place[i])
                yield _reduced(part, texts, gone)

    return arrow(docs, scan, _out_schema(docs))


def _hits_by_shard(docs: DataFrame, index: DataFrame, n_shards: int, min_chars: int, min_docs: int, shard_rows: int) -> DataFrame:
    """(doc_id, copy, h1, h2) of the lines that go: keys travel to a copy of their shard and stream past it."""
    salts = np.ones(n_shards, np.int32)  # one number for each shard
    for r in index.where(F.col("n_rows") > shard_rows).select("shard", "n_rows").toLocalIterator():
        salts[r["shard"]] = math.ceil(r["n_rows"] / shard_rows)
    sizes = docs.sparkSession.sparkContext.broadcast(salts)

    def copies(batches):
        for batch in batches:
            for one in slices(batch, 1):
                n = int(sizes.value[one.column(0)[0].as_py()])
                for k in range(n):
                    yield pa.RecordBatch.from_arrays([one.column(0), pa.array([k], pa.int32()), one.column(1)], ["shard", "salt", "blob"])

    def probe(batches):
        at, shard = None, None
        for batch in batches:
            where = batch.column(0).to_numpy().astype(np.int64) << 32 | batch.column(1).to_numpy()
            edges = [0, *(np.flatnonzero(where[1:] != where[:-1]) + 1).tolist(), len(where)]
            for a, b in zip(edges, edges[1:], strict=False):
                if a == b:
                    continue
                if where[a] != at:
                    at, shard = where[a], None
                part = batch.slice(a, b - a)
                blobs = part.column(2)
                if blobs[0].is_valid:  # sorts first
                    shard = Shard.from_bytes(blobs[0].as_py())
                    part = part.slice(1)
                if shard is None or not part.num_rows:
                    continue  # a shard without a line that stands twice
                h1, h2 = (part.column(i).to_numpy().astype(np.int64).view(np.uint64) for i in (3, 4))
                ids, null = part.column(5).fill_null(0).to_numpy(), part.column(5).is_null().to_numpy(zero_copy_only=False)
                go = pa.array(_dropped(shard, h1, h2, ids, null, min_docs))
                yield pa.RecordBatch.from_arrays([part.column(i).filter(go) for i in (5, 6, 3, 4)], ["doc_id", "copy", "h1", "h2"])

    nothing = [F.lit(None).cast("bigint").alias(c) for c in ("h1", "h2", "doc_id", "copy")]
    blobs = arrow(index.select("shard", "blob"), copies, "shard int, salt int, blob binary").select("shard", "salt", "blob", *nothing)
    keys = _holders(docs, min_chars, salts).select("shard", "salt", F.lit(None).cast("binary").alias("blob"), "h1", "h2", "doc_id", "copy")
    sorted_ = blobs.unionByName(keys).repartition("shard", "salt").sortWithinPartitions("shard", "salt", F.col("blob").isNull())
    return arrow(sorted_, probe, "doc_id bigint, copy bigint, h1 bigint, h2 bigint")


def _apply_hits(docs: DataFrame, hits: DataFrame, min_chars: int) -> DataFrame:
    by_doc = hits.groupBy(F.col("doc_id").alias("__id"), F.col("copy").alias("__of")).agg(F.collect_set(F.struct("h1", "h2")).alias("__hits"))
    same = F.col("doc_id").cast("bigint").eqNullSafe(F.col("__id")) & F.col("__copy").eqNullSafe(F.col("__of"))
    joined = docs.withColumn("__copy", _copy_of()).join(by_doc, same, "left").drop("__id", "__of", "__copy")

    def scan(batches):
        for batch in batches:
            for part in slices(batch, 1024):
                texts, gone = part.column(part.schema.names.index("text")).to_pylist(), []
                for text, own in zip(texts, part.column(part.schema.names.index("__hits")).to_pylist(), strict=True):
                    bad = {((x["h1"] & (2**64 - 1)) << 64) | (x["h2"] & (2**64 - 1)) for x in own or ()}
                    _, at, hashes = line_hashes(text, min_chars) if bad else ([], [], [])
                    gone.append({i for i, h in zip(at, hashes, strict=True) if h in bad})
                yield _reduced(part, texts, gone, ("__hits",))

    return arrow(joined, scan, _out_schema(docs))


ADDED = ("n_lines", "n_dropped")


def dedup_lines(docs: DataFrame, min_docs: int = 3, min_chars: int = 20, shard_keys: int = SHARD_KEYS, max_index_bytes: int = MAX_INDEX_BYTES, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """docs with ``text`` reduced to its kept lines, and n_lines, n_dropped (counts of lines) added.

    A line whose key is in min_docs documents or more stays in the largest doc_id that holds it alone.  Rows with a
    null doc_id are never the holder and lose such lines, whatever the size of the index.
    """
    docs, work = spare(docs, (*ADDED, "__copy", "__hits", "__id", "__of")), Scratch(docs.sparkSession)
    lines = work.write(counted_lines(docs, min_chars), "lines")
    n_shards = max(1, math.ceil(lines.count() / shard_keys))
    index = work.write(build_index(lines, n_shards), "line-index")
    size = index.agg(F.coalesce(F.sum(F.length("blob")), F.lit(0))).first()[0]
    if size <= max_index_bytes:
        out = _probe_broadcast(docs, index, n_shards, min_chars, min_docs)
        work.drop()
        return out
    return _apply_hits(docs, work.finish(_hits_by_shard(docs, index, n_shards, min_chars, min_docs, shard_rows), "line-hits"), min_chars)


def op6_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    out = dedup_lines(docs)
    return out.select("doc_id", "n_lines", "n_dropped", F.sha2("text", 256).alias("kept_sha256"))


OP6_SQL = r"""
with l as (
  select doc_id, unnest(string_split(coalesce(text, ''), chr(10))) as line,
         generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) as i
  from documents),
k as (
  select doc_id, i, line,
         translate(regexp_replace(regexp_replace(line, '^[\x20\x09-\x0D]+', ''), '[\x20\x09-\x0D]+$', ''),
                   'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as key
  from l),
r as (
  select key, max(doc_id) as last_doc from k where length(key) >= 20
  group by key having count(distinct doc_id) >= 3),
m as (select k.doc_id, k.i, k.line, r.last_doc is not null and r.last_doc <> k.doc_id as gone from k left join r using (key))
select doc_id, count(*) as n_lines, cast(sum(gone::int) as bigint) as n_dropped,
       sha256(coalesce(string_agg(line, chr(10) order by i) filter (where not gone), '')) as kept_sha256
from m group by doc_id
"""
