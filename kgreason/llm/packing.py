"""Best-fit packing by minimum bin slack.

Documents become token ids plus an end id; longer ones than the capacity are cut into full pieces behind
a first, shorter one.  The counts of the piece lengths (at most ``capacity`` numbers, whatever the corpus)
go to the driver, where minimum bin slack runs on them: for the next bin the longest length left is taken,
a bitset subset-sum finds the fullest combination with it, and the combination is removed as often as the
counts allow before the next search; a search ends at least one length, so that their number depends on the
capacity and not on the corpus.  Pieces then find their place from their number among the pieces of their
length, which is dealt out over (length, salt) groups, so that no common length meets in one task.

Defined results: null or empty text is the end id alone; every row is packed, repeated rows and null ids
too; an empty table gives no pieces; ``token_pieces`` ignores further columns; ``pack`` takes any columns beside ``length``, returns one that has the
name of an added column as ``input_<name>``, and refuses lengths below 1 or above the capacity.
"""

from __future__ import annotations

import functools
import json
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import tiktoken
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import arrow, materialize, slices, spare, table

CAPACITY = 2048
#: Groups that the pieces of one length are dealt to: as many as the session shuffles to, within these bounds.  The driver gets capacity * salts counts.
MIN_SALTS, MAX_SALTS = 64, 4096


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


@functools.cache
def encoder(path: str) -> tiktoken.Encoding:
    """A byte-level BPE in the ``tokenizers`` JSON format, run by the faster library; ids are the same (tests compare them)."""
    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    byte_of = {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in set(plain))}
    special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
    ranks = {bytes(byte_of[c] for c in piece): i for piece, i in spec["model"]["vocab"].items() if piece not in special}
    import public_tokenizers

    return tiktoken.Encoding("corpus", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=special)


def token_pieces(docs: DataFrame, capacity: int = CAPACITY, end_id: int = 0, tokenizer: str | None = None, with_ids: bool = True) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32[, ids]) of (doc_id, text)."""
    path = tokenizer or default_tokenizer()

    def scan(batches):
        enc = encoder(path)
        for batch in batches:
            for part in slices(batch):
                rows = []
                for doc_id, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                    ids = np.array([*(enc.encode(text, allowed_special="all") if text else ()), end_id], dtype="<u4")
                    cuts = [0, *range(len(ids) % capacity or capacity, len(ids) + 1, capacity)] if len(ids) > capacity else [0, len(ids)]
                    for k, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)):
                        rows.append((doc_id, k, a, b - a, zlib.crc32(ids[a:b].tobytes()), ids[a:b]))
                cols = list(zip(*rows, strict=True)) if rows else [[]] * 6
                arrays = [pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()), strict=False)]
                names = ["doc_id", "piece", "start", "length", "ids_crc32"]
                if with_ids:
                    arrays.append(pa.array([x.astype(np.int32) for x in cols[5]], pa.list_(pa.int32())))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(arrays, names)

    schema = "doc_id bigint, piece int, start bigint, length bigint, ids_crc32 bigint" + (", ids array<int>" if with_ids else "")
    return arrow(docs.select(F.col("doc_id").cast("bigint"), "text"), scan, schema)


# ---------------------------------------------------------------- minimum bin slack over counts


def fullest(counts: dict[int, int], capacity: int, seed: int) -> dict[int, int]:
    """Length -> how often, of the fullest bin with the seed in it; among equals one with longer pieces."""
    mask = (1 << (capacity + 1)) - 1
    reach, steps = 1 << seed, []
    for length in sorted(counts, reverse=True):
        most = min(counts[length] - (length == seed), (capacity - seed) // length)
        part = 1
        while most > 0:
            part = min(part, most)
            steps.append((length, part, reach))
            reach |= (reach << (length * part)) & mask
            most -= part
            part *= 2
        if reach >> capacity & 1:
            break
    fill, bin_ = reach.bit_length() - 1, {seed: 1}
    for length, part, before in reversed(steps):
        if not before >> fill & 1:
            fill -= length * part
            bin_[length] = bin_.get(length, 0) + part
    return bin_


@dataclass
class Layout:
    """Where the r-th piece of a length goes."""

    starts: dict[int, np.ndarray]  # by length: first number of a piece in each run of equal bins, ascending
    bases: dict[int, np.ndarray]  # first bin of the run
    each: dict[int, np.ndarray]  # pieces of that length in a bin
    offsets: dict[int, np.ndarray]  # place of the first of them
    n_bins: int

    def place(self, length: int, numbers: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        run = np.searchsorted(self.starts[length], numbers, side="right") - 1
        within, each = numbers - self.starts[length][run], self.each[length][run]
        return self.bases[length][run] + within // each, self.offsets[length][run] + within % each * length


def minimum_bin_slack(counts: dict[int, int], capacity: int = CAPACITY) -> Layout:
    left = {k: v for k, v in counts.items() if v > 0}
    runs: dict[int, list[tuple[int, int, int, int]]] = {k: [] for k in left}
    used, n_bins = dict.fromkeys(left, 0), 0
    while left:
        bin_ = fullest(left, capacity, max(left))
        times = min(left[k] // m for k, m in bin_.items())
        at = 0
        for length, m in sorted(bin_.items(), reverse=True):
            runs[length].append((used[length], n_bins, m, at))
            used[length] += m * times
            at += m * length
            left[length] -= m * times
            if not left[length]:
                del left[length]
        n_bins += times
    cols = {k: np.array(v, np.int64).reshape(-1, 4).T for k, v in runs.items()}
    return Layout(*({k: c[i] for k, c in cols.items()} for i in range(4)), n_bins)


def pack(pieces: DataFrame, capacity: int = CAPACITY, salts: int | None = None) -> DataFrame:
    """pieces (any columns, with ``length``) with sequence_id and offset added.

    What the driver gets are counts by (length, salt): capacity * salts numbers at most.
    """
    pieces = spare(pieces, ("sequence_id", "offset", "__salt", "__number"))
    keys = [c for c in pieces.columns if c in ("doc_id", "piece")] or [c for c, kind in pieces.dtypes if "map<" not in kind]
    salts = salts or min(MAX_SALTS, max(MIN_SALTS, int(pieces.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    wrong = F.raise_error(F.concat(F.lit(f"length outside 1 to {capacity}: "), F.coalesce(F.col("length").cast("string"), F.lit("null")))).cast("bigint")
    pieces = pieces.withColumn("length", F.when(F.col("length").between(1, capacity), F.col("length").cast("bigint")).otherwise(wrong))
    dealt = pieces.withColumn("__salt", F.pmod(F.xxhash64(*keys), F.lit(salts)).cast("int"))
    found = dealt.groupBy("length", "__salt").count().toArrow()
    groups = np.zeros((capacity + 1, salts), np.int64)
    if found.num_rows:
        groups[found["length"].to_numpy(), found["__salt"].to_numpy()] = found["count"].to_numpy()
    before = np.cumsum(groups, axis=1) - groups
    layout = minimum_bin_slack({int(k): int(groups[k].sum()) for k in np.flatnonzero(groups.sum(axis=1))}, capacity)
    sent = pieces.sparkSession.sparkContext.broadcast((before, layout))
    numbered = dealt.withColumn("__number", F.row_number().over(Window.partitionBy("length", "__salt").orderBy(*keys)))
    schema = pieces.withColumn("sequence_id", F.lit(0).cast("bigint")).withColumn("offset", F.lit(0).cast("bigint")).schema
    for f in schema.fields:
        f.nullable = True

    def scan(batches):
        before, layout = sent.value
        for batch in batches:
            names = batch.schema.names
            length, salt, number = (batch.column(names.index(c)).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("length", "__salt", "__number"))
            rank = before[length, salt] + number - 1
            seq, off = np.zeros(len(rank), np.int64), np.zeros(len(rank), np.int64)
            for k in np.unique(length):
                at = np.flatnonzero(length == k)
                seq[at], off[at] = layout.place(int(k), rank[at])
            keep = [i for i, n in enumerate(names) if not n.startswith("__")]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in keep), pa.array(seq), pa.array(off)], [*(names[i] for i in keep), "sequence_id", "offset"])

    return arrow(numbered, scan, schema)


def pack_documents(docs: DataFrame, capacity: int = CAPACITY, with_ids: bool = True, tokenizer: str | None = None) -> DataFrame:
    """Pieces of all documents with their sequences; tokenized once, into the shared folder."""
    return pack(materialize(token_pieces(docs, capacity, tokenizer=tokenizer, with_ids=with_ids), "pieces"), capacity)


def op9_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(table(spark, sf_dir, "documents"), with_ids=False)
