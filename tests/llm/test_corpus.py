"""Line and near-duplicate removal, decontamination, packing and the pipeline against brute force."""

import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from kgreason.llm import decontaminate, linededup, neardup, packing
from kgreason.llm.common import table

SPACE = " \t\n\x0b\x0c\r"
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


# ---------------------------------------------------------------- lines


def brute_lines(rows, min_docs=3, min_chars=20):
    holders = defaultdict(set)
    for i, t in rows:
        for line in (t or "").split("\n"):
            holders[line.strip(SPACE).translate(LOWER)].add(i)
    out = {}
    for i, t in rows:
        lines = (t or "").split("\n")
        gone = [k for k, x in enumerate(lines) if len(key := x.strip(SPACE).translate(LOWER)) >= min_chars and len(holders[key]) >= min_docs and max(holders[key]) != i]
        out[i] = (len(lines), len(gone), "\n".join(x for k, x in enumerate(lines) if k not in gone))
    return out


def line_rows():
    rng = random.Random(6)
    common = ["Licensed under the  Apache License", "é" * 19, "é" * 20, "x" * 19, "Y" * 20, " " + "z" * 20, "", " " * 30]
    rows = [(i, "\n".join(rng.choice(common) if rng.random() < 0.6 else f"own line number {i} {k} of this text" for k in range(rng.randrange(1, 9)))) for i in range(60)]
    rows += [(60, None), (61, ""), (62, "\n\n"), (63, ("  yyyyyyyyyyYYYYYYYYYY\t\r\n" * 400))]
    return rows


@pytest.mark.parametrize("options", [{}, {"max_index_bytes": 0, "shard_keys": 2, "shard_rows": 5}])
def test_lines(spark, make, options):
    rows = line_rows()
    out = linededup.dedup_lines(make(rows), **options)
    assert out.columns[:5] == ["doc_id", "text", "lang", "source", "n_chars"]
    assert {r["doc_id"]: (r["n_lines"], r["n_dropped"], r["text"]) for r in out.collect()} == brute_lines(rows)


def test_lines_odd_rows(spark, make):
    line = "a line of more than twenty signs"
    out = linededup.dedup_lines(make([(1, line), (1, line), (2, line), (None, line)]))
    assert sorted((r["doc_id"] or 0, r["text"]) for r in out.collect()) == sorted([(1, line), (1, line), (2, line), (0, line)])
    assert linededup.dedup_lines(make([])).count() == 0
    named = make([(1, line)]).withColumnRenamed("lang", "h1").withColumnRenamed("source", "shard")
    assert linededup.dedup_lines(named).columns == ["doc_id", "text", "h1", "shard", "n_chars", "n_lines", "n_dropped"]
    for options in ({}, {"max_index_bytes": 0}):
        clash = make([(1, line), (2, line), (3, line)]).withColumnsRenamed({"lang": "N_lines", "source": "__hits", "n_chars": "n_dropped"})
        out = linededup.dedup_lines(clash, **options)
        assert out.columns == ["doc_id", "text", "input_N_lines", "input___hits", "input_n_dropped", "n_lines", "n_dropped"]
        assert sorted((r["doc_id"], r["text"], r["input_N_lines"], r["n_dropped"]) for r in out.collect()) == [(1, "", "en", 1), (2, "", "en", 1), (3, line, "en", 0)]


def test_a_line_in_all_documents(spark, make):
    """Both ways of probing, with one line in every row, in more copies of its shard than one."""
    line = "the very same line of every document"
    rows = [(i if i % 7 else None, f"{line}\nown line of document number {i}\n{line}") for i in range(3000)]
    big, small = (sorted((r["doc_id"] or -1, r["n_dropped"], r["text"]) for r in linededup.dedup_lines(make(rows), **o).collect()) for o in ({"max_index_bytes": 0, "shard_rows": 100}, {}))
    assert big == small and sum(n for _, n, _ in big) == 2 * 2999


def test_counts_of_the_index_decide(spark, make):
    """The index holds lines of two rows as well; the counts that documents find there tell which go."""
    rows = [(1, "a line that two documents hold"), (2, "a line that two documents hold")]
    assert [r["n_docs"] for r in linededup.counted_lines(make(rows)).collect()] == [2]
    assert {r["n_dropped"] for r in linededup.dedup_lines(make(rows)).collect()} == {0}
    assert sorted(r["n_dropped"] for r in linededup.dedup_lines(make(rows), min_docs=2).collect()) == [0, 1]


@pytest.mark.parametrize("options", [{}, {"max_index_bytes": 0, "shard_keys": 2, "shard_rows": 5}])
def test_lines_of_rows_without_id(spark, make, options):
    line, other = "a line of more than twenty signs", "one more line of twenty signs and more"
    rows = [(1, line), (2, line), (2**60 + 1, f"{line}\n{other}"), (None, f"{line}\nown"), (None, f"{line}\n{other}"), (None, f"{line}\n{other}"), (None, None), (0, line)]
    out = [(r["doc_id"], r["n_dropped"], r["text"]) for r in linededup.dedup_lines(make(rows), **options).collect()]
    expected = [(1, 1, ""), (2, 1, ""), (2**60 + 1, 0, f"{line}\n{other}"), (None, 1, "own"), (None, 1, other), (None, 1, other), (None, 0, ""), (0, 1, "")]
    assert sorted(out, key=repr) == sorted(expected, key=repr)


def test_perfect_hash():
    rng = np.random.default_rng(8)
    for n in (0, 1, 2, 65, 5000):
        h1, h2 = (rng.integers(0, 2**63, n, dtype=np.uint64) for _ in range(2))
        s = linededup.Shard.from_bytes(linededup.Shard.build(h1, h2, np.arange(n) + 3, np.arange(n) * 7).to_bytes())
        assert sorted(s.index(h1, h2).tolist()) == list(range(n))  # minimal and perfect
        known, count, last = s.probe(h1, h2)
        assert known.all() and (count == np.arange(n) + 3).all() and (last == np.arange(n) * 7).all()
        other = rng.integers(0, 2**63, 1000, dtype=np.uint64)
        assert not s.probe(other, other)[0].any()


# ---------------------------------------------------------------- near duplicates


def plain_set(text):
    words = [w for w in re.split(r"[\x20\x09-\x0D]+", (text or "").translate(LOWER)) if w]
    if not words:
        return set()
    return {tuple(words)} if len(words) < 5 else {tuple(words[i : i + 5]) for i in range(len(words) - 4)}


def brute_components(rows):
    sets = {i: plain_set(t) for i, t in rows}
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i), find(i) == i) for i in ids}


def near_rows():
    rng = random.Random(9)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(4))
    rows, n = [], 0
    for _ in range(12):
        base = [word() for _ in range(rng.randrange(20, 140))]
        for _ in range(rng.randrange(1, 14)):
            own = list(base)
            for _ in range(rng.randrange(0, max(2, len(base) // 18))):
                own[rng.randrange(len(own))] = word()
            rows.append((n * 3 + 1, " ".join(own)))
            n += 1
    chain = [word() for _ in range(120)]  # each step is near the last one, the ends are far apart
    for k in range(25):
        rows.append((5000 + k, " ".join([*chain[4 * k :], *[f"new{j}" for j in range(4 * k)]])))
    rows += [(9000, None), (9001, ""), (9002, " \n"), (9003, "one two"), (9004, "ONE  two"), (9005, "one two three"), (9006, rows[0][1].upper()), (9007, "Été a b c d e"), (9008, "été a b c d e")]
    return rows


def test_near_duplicates(spark, make):
    rows = near_rows()
    own = {r["doc_id"]: (r["n_shingles"], r["component_id"], r["kept"]) for r in neardup.near_duplicates(make(rows)).collect()}
    assert own == brute_components(rows)
    kept = {r["doc_id"] for r in neardup.drop_near_duplicates(make(rows)).collect()}
    assert kept == {i for i, x in own.items() if x[2]}


def test_near_duplicates_odd_rows(spark, make):
    assert neardup.near_duplicates(make([])).count() == 0
    text = "a b c d e f g h"
    rows = [(2, text), (2, text), (1, text), (None, text), (None, None), (None, None), (3, None)]
    own = [(r["doc_id"], r["n_shingles"], r["component_id"], r["kept"]) for r in neardup.near_duplicates(make(rows)).collect()]
    expected = [(2, 4, 1, False), (2, 4, 1, False), (1, 4, 1, True), (None, 4, 1, False), (None, 0, None, True), (None, 0, None, True), (3, 0, 3, True)]
    assert sorted(own, key=repr) == sorted(expected, key=repr)
    clash = make([*rows, (1, text), (1, text + " i")]).withColumnsRenamed({"lang": "text_hash", "source": "__id", "n_chars": "first"})
    out = neardup.drop_near_duplicates(clash)
    assert out.columns == clash.columns
    kept = [(r["doc_id"], r["text"]) for r in out.collect()]
    assert sorted((i for i, _ in kept), key=repr) == sorted([1, None, None, 3], key=repr) and next(t for i, t in kept if i == 1).startswith(text)
    nobody = [(None, text), (None, text), (None, text + " i"), (None, "x " * 9)]  # of rows without id, too, one stays
    assert len(neardup.drop_near_duplicates(make(nobody)).collect()) == 2


def test_many_unlinked_texts_in_a_bucket(spark, make):
    """10,000 texts that share half of their words: a bucket of many members, of which no two are linked, but for one pair."""
    rng = random.Random(11)
    common = " ".join(f"shared{i}" for i in range(24))
    rows = [(i, common + " " + " ".join(f"w{i}x{rng.randrange(10**6)}" for _ in range(20))) for i in range(10_000)]
    rows.append((20_000, rows[77][1].replace("shared23", "other")))
    own = {r["doc_id"]: r["component_id"] for r in neardup.near_duplicates(make(rows), 8, 1).collect()}  # one coordinate a band: nearly all share some
    assert {i for i, c in own.items() if c != i} == {20_000} and own[20_000] == 77


def test_blocks_of_a_bucket(spark, make):
    rows = near_rows()
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"], r["kept"]) for r in neardup.near_duplicates(make(rows), bucket=1, block=3).collect()} == brute_components(rows)


def test_texts_without_a_partner_stay_where_they_are(spark, make):
    """Where the join with the rows wanted shuffles, it moves their texts, not those of the whole table."""
    from kgreason.plans.measures import moved

    rng = random.Random(13)
    rows = [(i, " ".join("".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(60)) for _ in range(330))) for i in range(300)]
    rows.append((900, rows[7][1] + " end"))
    docs, own, limit = make(rows), {}, spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        bytes_ = moved(spark, lambda: own.update({r["doc_id"]: r["component_id"] for r in neardup.near_duplicates(docs).collect()}))["shuffle_bytes"]
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", limit)
    assert {i for i, c in own.items() if c != i} == {900} and own[900] == 7
    assert bytes_ < sum(len(t) for _, t in rows) / 3


def test_sieve_keeps_rows_wanted(spark, make):
    rows = make([(i % 50 or None, f"text {i}") for i in range(400)] + [(None, None)])
    own = neardup.keyed(rows)
    wanted = neardup.row_keys(own.where("text_hash % 5 = 0 or text is null"))
    for bits, most in ((16, 1 << 21), (1, 1)):  # one word: every row wanted shares its bits
        left = neardup.sifted(own, wanted, bits, most)
        assert left.columns == own.columns
        kept, all_ = ([tuple(r) for r in df.collect()] for df in (left, own))
        assert len(kept) == len(set(kept)) and set(kept) <= set(all_)
        assert {(r["__id"], r["__hash"]) for r in wanted.collect()} <= {(r[0], r[2]) for r in kept}
        assert most == 1 or len(kept) < 200
    assert neardup.sifted(own, wanted.limit(0)).count() == 0


def test_bands_find_pairs_at_the_threshold():
    """Pairs of exactly the least similarity that links, of small and large sets."""
    rng = np.random.default_rng(5)
    for common, own in ((3, 1), (6, 2), (75, 25), (300, 100)):
        for _ in range(100):
            pool = np.unique(neardup.mix64(rng.integers(0, 2**63, common + own, dtype=np.uint64)))
            a, b = pool, pool[rng.permutation(len(pool))[:common]]
            x, y = (neardup.band_keys(neardup.signature(np.sort(s))) for s in (a, b))
            assert (x == y).any()


def test_sketches_never_undercount():
    rng = np.random.default_rng(1)
    for n in (1, 50, 800, 6000):
        a, b = (np.unique(rng.integers(0, 2 * n, n)).astype(np.uint64) for _ in range(2))
        a, b = neardup.mix64(a), neardup.mix64(b)
        (x, p), (y, q) = neardup.sketch_of(a), neardup.sketch_of(b)
        common = int(np.bitwise_count(x & y).sum()) + min(p, q)
        assert common >= len(np.intersect1d(a, b))


def test_signature_estimates():
    rng = np.random.default_rng(2)
    a = neardup.mix64(rng.integers(0, 2**60, 1000).astype(np.uint64))
    b = np.concatenate((a[:600], neardup.mix64(rng.integers(0, 2**60, 400).astype(np.uint64))))
    x, y = (neardup.signature(np.unique(s), 512) for s in (a, b))
    assert abs((x == y).mean() - 600 / 1400) < 0.08


# ---------------------------------------------------------------- decontamination


def plain_words(text):
    return [w for w in re.split(r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+", (text or "").translate(LOWER)) if w]


def brute_hits(rows, items, n=10):
    out = {}
    for i, t in rows:
        words, hit, found = plain_words(t), set(), set()
        for item, x in items:
            w = plain_words(x)
            grams = {tuple(w)} if 0 < len(w) < n else {tuple(w[k : k + n]) for k in range(len(w) - n + 1)}
            for g in grams:
                if g:
                    for k in range(len(words) - len(g) + 1):
                        if tuple(words[k : k + len(g)]) == g:
                            hit |= set(range(k, k + len(g)))
                            found.add(item)
        out[i] = (len(words), len(hit), len(found), hashlib.sha256(",".join(sorted(map(str, found))).encode()).hexdigest(), bool(hit))
    return out


ITEMS = [(1, "The quick brown fox jumps over the lazy dog and runs away."), (2, "tiny item"), (12, "tiny  ITEM!"), (3, None), (4, "!!!"), (5, "äöü sätze sind auch wörter und zählen hier mit dazu heute abend"), (6, "a a a a a a a a a a a a")]
TEXTS = [
    (1, "xx the QUICK brown fox, jumps over the lazy dog and runs away yy"), (2, "quick brown fox jumps over the lazy dog and runs only"), (3, "a tiny item, tiny-item tiny"), (4, None), (5, ""), (6, "a " * 30), (7, "nothing here to see at all today my friend"),
    (8, "Äöü äöü sätze sind auch wörter und zählen hier mit dazu heute abend"), (9, "?!"), (10, "fox " * 3000 + "tiny item" + " fox" * 3000),
]


@pytest.mark.parametrize("limit", [decontaminate.MAX_BROADCAST_WINDOWS, 0])
def test_hits(spark, folder, limit, monkeypatch):
    monkeypatch.setattr(decontaminate.contamination, "__defaults__", (10, limit))
    monkeypatch.setattr(decontaminate, "MAX_BROADCAST_HITS", limit)
    sf = folder(TEXTS, benchmark=ITEMS)
    own = {r["doc_id"]: (r["n_words"], r["n_hit"], r["n_items"], r["items_sha256"], r["contaminated"]) for r in decontaminate.op10_benchmark_decontamination(spark, sf).collect()}
    assert own == brute_hits(TEXTS, ITEMS)


def test_hits_random(spark, folder):
    rng = random.Random(3)
    word = lambda: rng.choice("abc")
    items = [(i, " ".join(word() for _ in range(rng.randrange(1, 14)))) for i in range(20)]
    rows = [(i, " ".join(word() for _ in range(rng.randrange(0, 80)))) for i in range(40)]
    own = {r["doc_id"]: (r["n_words"], r["n_hit"], r["n_items"], r["items_sha256"], r["contaminated"]) for r in decontaminate.op10_benchmark_decontamination(spark, folder(rows, benchmark=items)).collect()}
    assert own == brute_hits(rows, items)


def test_removal(spark, make):
    bench = spark.createDataFrame(ITEMS, "item_id bigint, text string")
    kept = {r["doc_id"] for r in decontaminate.decontaminate(make(TEXTS), bench).collect()}
    assert kept == {4, 5, 7, 9}
    spans = {r["doc_id"]: r["text"] for r in decontaminate.decontaminate(make(TEXTS), bench, "spans").collect()}
    assert spans[7] == TEXTS[6][1] and spans[4] is None and spans[1].split() == ["xx", "yy"]
    again = decontaminate.contamination(make(list(spans.items())), bench)
    assert {r["doc_id"] for r in again.where("n_hit > 0").collect()} <= {3}
    with pytest.raises(ValueError):
        decontaminate.decontaminate(make(TEXTS), bench, "words")


def test_contamination_by_row(spark, make):
    """Rows without an id, or with a repeated one, are judged by their own text."""
    bench = spark.createDataFrame(ITEMS, "item_id bigint, text string")
    bad, good = TEXTS[0][1], "nothing here to see at all today my friend"
    rows = [(None, bad), (None, good), (None, bad), (5, good), (5, bad), (5, bad), (6, None)]
    own = [(r["doc_id"], r["n_words"], r["n_hit"]) for r in decontaminate.contamination(make(rows), bench).collect()]
    assert sorted(own, key=repr) == sorted([(None, 14, 12), (None, 9, 0), (None, 14, 12), (5, 9, 0), (5, 14, 12), (5, 14, 12), (6, 0, 0)], key=repr)
    clash = make(rows).withColumnsRenamed({"lang": "text_hash", "source": "words", "n_chars": "__spans"})
    out = decontaminate.decontaminate(clash, bench)
    assert out.columns == clash.columns and sorted(((r["doc_id"], r["text"]) for r in out.collect()), key=repr) == sorted([(None, good), (5, good), (6, None)], key=repr)
    spans = decontaminate.decontaminate(clash, bench, "spans")
    assert spans.columns == clash.columns and spans.count() == len(rows) and spans.where("text like '%fox%'").count() == 0


def test_removal_empty(spark, make, folder):
    none = spark.createDataFrame([], "item_id bigint, text string")
    assert decontaminate.decontaminate(make(TEXTS), none).count() == len(TEXTS)
    assert decontaminate.decontaminate(make([]), none).count() == 0
    sf = folder([], benchmark=ITEMS)
    assert decontaminate.op10_benchmark_decontamination(spark, sf).count() == 0
    plan = decontaminate.op10_benchmark_decontamination(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan


# ---------------------------------------------------------------- packing


def test_packing(spark, make):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(packing.default_tokenizer())
    rng = random.Random(1)
    rows = [(i, " ".join(f"word{rng.randrange(99)}" for _ in range(rng.randrange(0, 900)))) for i in range(120)]
    rows += [(200, None), (201, ""), (202, "x" * 9000 + " <|endoftext|> tail"), (203, "tok " * 2047), (204, "é\U0001f600\n\n\t  x"), (205, "a"), (205, "a")]
    out = packing.pack_documents(make(rows)).collect()
    by_doc, bins = defaultdict(list), defaultdict(list)
    for r in out:
        by_doc[r["doc_id"]].append(r)
        bins[r["sequence_id"]].append(r)
    for i, t in rows:
        ids = [*tok.encode(t or "", add_special_tokens=False).ids, 0]
        own = sorted(by_doc[i], key=lambda r: r["piece"])
        if i == 205:
            assert len(own) == 2
            continue
        assert [x for r in own for x in r["ids"]] == ids
        assert [r["piece"] for r in own] == list(range(len(own))) and all(r["length"] == 2048 for r in own[1:])
        assert len(own) == -(-len(ids) // 2048)
        for r in own:
            assert r["ids_crc32"] == zlib.crc32(np.array(ids[r["start"] : r["start"] + r["length"]], "<u4").tobytes())
    for rows_ in bins.values():
        at = 0
        for r in sorted(rows_, key=lambda r: r["offset"]):
            assert r["offset"] == at
            at += r["length"]
        assert at <= 2048
    assert len(bins) <= -(-sum(r["length"] for r in out) // 2048) + 1
    assert packing.pack_documents(make([])).count() == 0


def test_fullest_bin_is_fullest():
    rng = random.Random(2)
    for _ in range(60):
        cap = rng.randrange(5, 40)
        counts = {rng.randrange(1, cap + 1): rng.randrange(1, 4) for _ in range(rng.randrange(1, 6))}
        seed = max(counts)
        sums = {seed}
        flat = [k for k, v in counts.items() for _ in range(v - (k == seed))]
        for x in flat:
            sums |= {s + x for s in sums if s + x <= cap}
        bin_ = packing.fullest(counts, cap, seed)
        assert sum(k * v for k, v in bin_.items()) == max(sums) and all(v <= counts[k] for k, v in bin_.items())


def test_slack_is_small():
    rng = random.Random(7)
    counts = Counter(min(2048, int(rng.lognormvariate(6, 1)) + 1) for _ in range(20_000))
    layout = packing.minimum_bin_slack(dict(counts))
    assert layout.n_bins <= 1.002 * -(-sum(k * v for k, v in counts.items()) // 2048)


# ---------------------------------------------------------------- pipeline


def test_pipeline(spark, sf):
    """Every stage against brute force over what the one before kept."""
    import corpus_pipeline as p
    from kgreason.llm.common import materialize

    docs, names = table(spark, sf, "documents"), [n for n, _ in p.STAGES]
    assert names == ["quality_classifier", "line_dedup", "minhash_near_dedup", "benchmark_decontamination", "best_fit_packing"]
    items = [(r["item_id"], r["text"]) for r in table(spark, sf, "benchmark").collect()]
    for name, stage in p.STAGES[:-1]:
        before = {r["doc_id"]: r["text"] for r in docs.collect()}
        out = materialize(stage(spark, docs, sf), "t")
        assert out.dtypes == docs.dtypes
        after = {r["doc_id"]: r["text"] for r in out.collect()}
        rows = sorted(before.items())
        if name == "line_dedup":
            assert after == {i: x[2] for i, x in brute_lines(rows).items()}
        elif name == "minhash_near_dedup":
            assert after == {i: before[i] for i, x in brute_components(rows).items() if x[2]}
        elif name == "benchmark_decontamination":
            assert after == {i: before[i] for i, x in brute_hits(rows, items).items() if not x[4]}
        else:
            assert set(after) < set(before) and len(after) > 0.6 * len(before)
        docs = out
    packed = p.run(spark, sf)
    assert {r["doc_id"] for r in packed.collect()} == {r["doc_id"] for r in docs.collect()}


def test_pipeline_stages_on_odd_rows(spark, folder):
    """Null, empty, repeated and very long texts, null ids, other columns of clashing names: each stage alone, then all of them, then on an empty table."""
    import corpus_pipeline as p

    text = "some words of a text that is long enough to be a text of its own kind"
    rows = [(1, text), (1, text), (2, None), (3, ""), (None, text + " and more"), (None, None), (4, "word " * 300_000), (5, ITEMS[0][1])]
    sf = folder(rows, [(1, 1, 0), (5, 0, 1), (None, 1, 0), (2, None, None)], ITEMS)
    docs = table(spark, sf, "documents").withColumnsRenamed({"lang": "quality_kept", "source": "N_LINES"})
    expected = {"line_dedup": [1, 1, 2, 3, 4, 5, None, None], "minhash_near_dedup": [1, 2, 3, 4, 5, None], "benchmark_decontamination": [1, 1, 2, 3, 4, None, None]}
    for name, stage in p.STAGES[:-1]:
        out = stage(spark, docs, sf)
        assert out.columns == docs.columns and dict(out.dtypes) == dict(docs.dtypes)
        ids = [r["doc_id"] for r in out.collect()]
        if name in expected:
            assert sorted(ids, key=repr) == sorted(expected[name], key=repr), name
        else:
            assert set(ids) <= {1, 2, 3, 4, 5, None}
    pieces = p.packing_stage(spark, docs, sf).collect()
    assert sum(r["piece"] == 0 for r in pieces) == len(rows)
    assert p.run(spark, folder([], [], [])).count() == 0
    assert p.run(spark, sf).count() > 0


def test_packing_of_other_pieces(spark):
    pieces = spark.createDataFrame([(5, "a", 1), (2043, "b", 2), (2048, "c", 3), (5, "a", 1)], "length int, name string, offset int")
    out = packing.pack(pieces)
    assert out.columns == ["length", "name", "input_offset", "sequence_id", "offset"]
    assert len({r["sequence_id"] for r in out.collect()}) == 3
    for wrong in (0, 2049, None):
        with pytest.raises(Exception, match="length outside"):
            packing.pack(spark.createDataFrame([(wrong,)], "length int")).collect()
