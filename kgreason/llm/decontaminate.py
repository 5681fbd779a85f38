"""Benchmark decontamination with DataFrame functions only.

The windows of the benchmark (``n`` words, or all words of a shorter item) are hashed; each document's words
are hashed once and its window hashes are made from them by doubling (pairs, fours, eights, ...), so that a
window costs a few multiplications and no string is built.  Window hashes meet the benchmark's in a
broadcast hash join - only while the benchmark has at most ``max_broadcast_windows`` windows, else in
a shuffled one.  Hits are verified word by word against the item before they count.

Defined results: every row gives a row and is judged by its own text, whether its doc_id is null, repeated or neither; null or
empty text has no words, is never hit and is kept; items without words have no windows; duplicate items count by item_id; empty
tables on either side give no hits; further columns are ignored by ``contamination`` and pass through ``decontaminate``, whatever their names.
"""

from __future__ import annotations

import functools

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, keyed, renamed_back, row_keys, same_row, spare, table

WINDOW = 10
MAX_BROADCAST_WINDOWS = 2_000_000  # 50 bytes each
MAX_BROADCAST_HITS = 1_000_000  # hits to verify, at most 40 bytes each

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_BREAKS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def words_of(text: Column) -> Column:
    """The normalised words of a text, in order; an empty array for null."""
    return F.filter(F.split(F.translate(F.coalesce(text, F.lit("")), _UPPER, _LOWER), _BREAKS), lambda w: w != "")


def _word_hashes(words: Column) -> Column:
    return F.transform(words, lambda w: F.xxhash64(w))


def _join_hashes(left: str, right: str, by: int, n: str) -> Column:
    """Hashes of left windows, each joined with the right window that begins ``by`` words later."""
    return F.expr(f"zip_with(slice({left}, 1, greatest(0, size({right}) - {by})), slice({right}, {by} + 1, greatest(0, size({right}) - {by})), (a, b) -> {_combine('a', 'b', n)})")


def _combine(a: str, b: str, n: str) -> str:
    # modulo 2^64: shifts and xors in place of products, which overflow in ANSI mode
    return f"shiftleft({a}, {n}) ^ shiftrightunsigned({a}, 64 - {n}) ^ shiftleft({b}, 7) ^ shiftrightunsigned({b} ^ shiftleft({b}, 31), 9)"


def window_hashes(df: DataFrame, hashes: str, length: int, out: str) -> DataFrame:
    """Adds ``out``: the hash of every window of ``length`` words, made from the word hashes by doubling."""
    have, df = {1: hashes}, df
    size = 1
    while size * 2 <= length:
        df = df.withColumn(f"__w{size * 2}", _join_hashes(have[size], have[size], size, str(11 + size)))
        have[size * 2] = f"__w{size * 2}"
        size *= 2
    at, left = size, length - size
    name = have[size]
    while left:
        part = 1 << (left.bit_length() - 1)
        df = df.withColumn(f"__w{at + part}_", F.expr(f"zip_with(slice({name}, 1, greatest(0, size({hashes}) - {at + part - 1})), slice({have[part]}, {at} + 1, greatest(0, size({hashes}) - {at + part - 1})), (a, b) -> {_combine('a', 'b', str(5 + part))})"))
        name, at, left = f"__w{at + part}_", at + part, left - part
    return df.withColumn(out, F.col(name)).drop(*[c for c in df.columns if c.startswith("__w")])


def benchmark_windows(benchmark: DataFrame, n: int = WINDOW) -> DataFrame:
    """(item_id, length, hash, gram): distinct windows of each item; gram holds the words, joined by blanks."""
    items = benchmark.select("item_id", words_of(F.col("text")).alias("words")).where(F.size("words") > 0)
    grams = items.select(
        "item_id",
        F.explode(
            F.when(F.size("words") < n, F.array("words")).otherwise(F.expr(f"transform(sequence(1, greatest(1, size(words) - {n - 1})), i -> slice(words, i, {n}))"))
        ).alias("gram"),
    ).distinct()
    return grams.withColumn("length", F.size("gram"))


def _hashed(grams: DataFrame, lengths: list[int]) -> DataFrame:
    """benchmark windows with the hash that a document's window of the same words has."""
    parts = []
    for k in lengths:
        own = grams.where(F.col("length") == k).withColumn("wh", _word_hashes(F.col("gram")))
        parts.append(window_hashes(own, "wh", k, "hs").select("item_id", "length", F.col("hs")[0].alias("hash"), F.array_join("gram", " ").alias("gram")))
    return functools.reduce(DataFrame.unionByName, parts)


def find_hits(docs: DataFrame, benchmark: DataFrame, work: Scratch, n: int = WINDOW, max_broadcast_windows: int = MAX_BROADCAST_WINDOWS) -> tuple[DataFrame, DataFrame]:
    """(doc_id, text_hash, n_words) of every row, and verified hits (doc_id, text_hash, at, length, items): word windows at ``at`` (from 0)."""
    grams = work.write(benchmark_windows(benchmark, n), "grams")
    sizes = {r["length"]: r["count"] for r in grams.groupBy("length").count().collect()}  # n rows at most
    words = keyed(docs).select("doc_id", "text_hash", words_of(F.col("text")).alias("words"))
    if not sizes:
        none = words.select("doc_id", "text_hash", F.lit(0).alias("at"), F.lit(0).alias("length"), F.array(F.lit(None).cast("bigint")).alias("items")).limit(0)
        return words.select("doc_id", "text_hash", F.size("words").cast("bigint").alias("n_words")), none
    hashed = work.write(_hashed(grams, sorted(sizes)), "windows")
    small = sum(sizes.values()) <= max_broadcast_windows
    own = words.select("doc_id", "text_hash", F.size("words").alias("n_words"), _word_hashes(F.col("words")).alias("wh"))
    for k in sorted(sizes):
        own = window_hashes(own, "wh", k, f"h{k}")
    keys = hashed.select("length", "hash").distinct()
    # One row of -1 for each row of documents carries its number of words through the same scan.
    spread = own.select(
        "doc_id",
        "text_hash",
        # the outer form, as the plain one makes Spark push a size() filter below, with every window hash spelt out in it
        F.explode_outer(
            F.concat(
                F.array(F.struct(F.lit(-1).alias("at"), F.lit(0).alias("length"), F.col("n_words").cast("bigint").alias("hash"))),
                *[F.expr(f"transform(h{k}, (h, i) -> struct(i as at, {k} as length, h as hash))") for k in sorted(sizes)],
            )
        ).alias("w"),
    ).select("doc_id", "text_hash", "w.*")
    marked = keys.withColumn("__known", F.lit(True))
    found = spread.join(F.broadcast(marked) if small else marked, ["length", "hash"], "left").where(F.col("__known") | (F.col("at") == -1))
    found = work.write(found.select("doc_id", "text_hash", "at", "length", "hash"), "window-hits")
    counts = found.where(F.col("at") == -1).select("doc_id", "text_hash", F.col("hash").alias("n_words"))
    maybe = found.where(F.col("at") >= 0)
    few = maybe.count() <= MAX_BROADCAST_HITS
    return counts, _verified(docs, maybe, hashed, small, few)


def _verified(docs: DataFrame, maybe: DataFrame, hashed: DataFrame, small: bool, few: bool) -> DataFrame:
    """Keeps the hits whose words are those of the item.  Few hits go to the texts; many make the texts come to them, before they are split into words."""
    by_doc = row_keys(maybe.groupBy("doc_id", "text_hash").agg(F.collect_set(F.struct("at", "length", "hash")).alias("hits")), "hits")
    own = keyed(docs)
    joined = own.join(F.broadcast(by_doc) if few else by_doc, same_row(own, by_doc))
    again = joined.select("doc_id", "text_hash", words_of(F.col("text")).alias("words"), "hits")
    grams = again.select(
        "doc_id",
        "text_hash",
        F.explode(F.expr("transform(hits, h -> struct(h.at as at, h.length as length, h.hash as hash, array_join(slice(words, h.at + 1, h.length), ' ') as gram))")).alias("h"),
    ).select("doc_id", "text_hash", "h.*")
    items = hashed.groupBy("length", "hash", "gram").agg(F.sort_array(F.collect_set("item_id")).alias("items"))
    return grams.join(F.broadcast(items) if small else items, ["length", "hash", "gram"]).select("doc_id", "text_hash", "at", "length", "items")


def covered(spans: Column) -> Column:
    """Words inside the union of spans, an array of (at, length)."""
    return F.aggregate(
        F.sort_array(spans),
        F.expr("cast(struct(0L, 0L) as struct<end:bigint,n:bigint>)"),
        lambda a, s: F.struct(
            F.greatest(a["end"], (s["at"] + s["length"]).cast("bigint")).alias("end"),
            (a["n"] + F.greatest(F.lit(0), s["at"] + s["length"] - F.greatest(a["end"], s["at"].cast("bigint")))).cast("bigint").alias("n"),
        ),
    )["n"]


def merged(spans: Column) -> Column:
    """Spans (at, length) as disjoint, non-adjacent runs (first, last), last exclusive."""
    return F.aggregate(
        F.sort_array(spans),
        F.expr("cast(array() as array<struct<first:int,last:int>>)"),
        lambda a, s: F.when(
            (F.size(a) > 0) & (F.element_at(a, -1)["last"] >= s["at"]),
            F.concat(
                F.slice(a, F.lit(1), F.size(a) - 1),
                F.array(F.struct(F.element_at(a, -1)["first"].alias("first"), F.greatest(F.element_at(a, -1)["last"], (s["at"] + s["length"]).cast("int")).alias("last"))),
            ),
        ).otherwise(F.concat(a, F.array(F.struct(s["at"].cast("int").alias("first"), (s["at"] + s["length"]).cast("int").alias("last"))))),
    )


def _judged(docs: DataFrame, benchmark: DataFrame, work: Scratch, n: int, max_broadcast_windows: int) -> DataFrame:
    counts, hits = find_hits(docs, benchmark, work, n, max_broadcast_windows)
    by_doc = hits.groupBy("doc_id", "text_hash").agg(
        F.collect_set(F.struct("at", "length")).alias("spans"),
        F.array_sort(F.array_distinct(F.transform(F.flatten(F.collect_set("items")), lambda i: i.cast("string")))).alias("items"),
    )
    right = row_keys(by_doc, "spans", "items")
    return counts.join(right, same_row(counts, right), "left").select(
        "doc_id",
        "text_hash",
        "n_words",
        F.coalesce(covered(F.col("spans")), F.lit(0).cast("bigint")).alias("n_hit"),
        F.coalesce("items", F.expr("cast(array() as array<string>)")).alias("items"),
        F.coalesce("spans", F.expr("cast(array() as array<struct<at:int,length:int>>)")).alias("spans"),
    )


def contamination(docs: DataFrame, benchmark: DataFrame, n: int = WINDOW, max_broadcast_windows: int = MAX_BROADCAST_WINDOWS) -> DataFrame:
    """For each row: doc_id, n_words, n_hit (words inside occurrences of windows), items (sorted item_ids as strings), spans."""
    work = Scratch(docs.sparkSession)
    return work.finish(_judged(docs, benchmark, work, n, max_broadcast_windows).drop("text_hash"), "contamination")


def decontaminate(docs: DataFrame, benchmark: DataFrame, mode: str = "documents", max_hit_share: float = 0.0, n: int = WINDOW) -> DataFrame:
    """Removes contaminated documents (``documents``: those of whose words more than max_hit_share are hit) or blanks the hit words (``spans``).

    With ``spans``, the words in hits and what separates them go; the rest of the text stays as it is.
    """
    if mode not in ("documents", "spans"):
        raise ValueError(f"unknown mode {mode}")
    work = Scratch(docs.sparkSession)
    hit = _judged(docs, benchmark, work, n, MAX_BROADCAST_WINDOWS).where(F.col("n_hit") > 0).dropDuplicates(["doc_id", "text_hash"])
    hit = work.finish(hit.select("doc_id", "text_hash", "n_words", "n_hit", F.col("spans").alias("__spans")), "contaminated")
    own = spare(docs, ("text_hash", "__id", "__hash", "__spans", "__pieces", "__runs", "__first")).withColumn("text_hash", F.xxhash64("text"))
    if mode == "documents":
        bad = row_keys(hit.where(F.col("n_hit") > max_hit_share * F.col("n_words")))
        return renamed_back(own.join(bad, same_row(own, bad), "left_anti"), docs.columns)
    spans = row_keys(hit, "__spans")
    joined = own.join(spans, same_row(own, spans), "left")
    word, gap = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]|[A-Z]", r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]"
    pieces = F.regexp_extract_all("text", F.lit(rf"((?:{word})+|(?:{gap})+)"), F.lit(1))
    joined = joined.withColumn("__pieces", F.when(F.col("__spans").isNotNull(), pieces)).withColumn("__runs", F.when(F.col("__spans").isNotNull(), merged(F.col("__spans"))))
    joined = joined.withColumn("__first", F.when(F.col("__pieces")[0].rlike(rf"^(?:{word})"), 0).otherwise(1))
    # piece i is word (i - first) / 2, or what stands between that word and the next
    kept = F.expr(
        "array_join(filter(__pieces, (p, i) -> not exists(__runs, m -> (i - __first) div 2 >= m.first and (i - __first) div 2 + (i - __first) % 2 < m.last and i >= __first)), '')"
    )
    return renamed_back(joined.withColumn("text", F.when(F.col("__spans").isNotNull(), kept).otherwise(F.col("text"))), docs.columns)


def op10_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = contamination(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark").select("item_id", "text"))
    return out.select(
        "doc_id",
        "n_words",
        "n_hit",
        F.size("items").cast("bigint").alias("n_items"),
        F.sha2(F.array_join("items", ","), 256).alias("items_sha256"),
        (F.col("n_hit") > 0).alias("contaminated"),
    )


OP10_SQL = r"""
with lower_docs as (select doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as t from documents),
lower_items as (select item_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as t from benchmark),
dw as (select doc_id, list_filter(regexp_split_to_array(t, '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda w: w <> '') as words from lower_docs),
iw as (select item_id, list_filter(regexp_split_to_array(t, '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda w: w <> '') as words from lower_items),
g as (
  select distinct item_id, least(10, len(words)) as length, unnest(list_transform(range(1, greatest(2, len(words) - 8)), lambda i: array_to_string(words[i:i + 9], ' '))) as gram
  from iw where len(words) > 0),
lengths as (select distinct length from g),
w as (
  select doc_id, length, unnest(range(1, greatest(1, len(words) - length + 2))) as pos, words from dw, lengths),
h as (select w.doc_id, w.pos, w.length, g.item_id from w join g on g.length = w.length and g.gram = array_to_string(w.words[w.pos:w.pos + w.length - 1], ' ')),
c as (select doc_id, count(distinct p) as n_hit from (select doc_id, unnest(range(pos, pos + length)) as p from h) group by doc_id),
i as (select doc_id, count(*) as n_items, string_agg(x, ',' order by x) as ids from (select distinct doc_id, cast(item_id as varchar) as x from h) group by doc_id)
select dw.doc_id, len(words) as n_words, coalesce(n_hit, 0) as n_hit, coalesce(n_items, 0) as n_items,
       sha256(coalesce(ids, '')) as items_sha256, coalesce(n_hit, 0) > 0 as contaminated
from dw left join c using (doc_id) left join i using (doc_id)
"""
