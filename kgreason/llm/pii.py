"""Personal data by weak supervision.

One scan of the texts finds the base spans and loose candidates (runs of capitalised words that may be names, local
phone numbers, social security numbers, bank account numbers, spelt-out e-mail addresses), and lets labelers
vote on each: shape, gazetteers, words before it, words against it, and what adjoins it.  Votes make a pattern; the
corpus-wide counts of patterns - a table whose size depends on the labelers, not on the corpus - are all that
expectation-maximisation needs to estimate each labeler's reliability and each pattern's posterior.  The final span classifier
is a logistic regression that never sees the votes: it learns the posteriors from the shape of a span and the words around
it, on at most MAX_SPANS candidates of each kind (those of the smallest hashes), and decides on all candidates.  Base spans stay
whatever it says; accepted candidates overlap neither them nor each other, the likelier of two stays.

Defined results: null text is empty and has no spans; repeated rows are each scanned and counted; a corpus without
candidates needs no model; an empty table gives an empty table; further columns are ignored.
"""

from __future__ import annotations

import bisect
import re
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import arrow, materialize, slices, table

# ---------------------------------------------------------------- base spans

# The base patterns.
LOCAL = re.compile(r"[A-Za-z0-9._%+-]+")
DOMAIN = re.compile(r"[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
# The lookbehinds change nothing, as the leftmost match begins where its run of digits does, but spare trials inside runs.
IP = re.compile(r"(?<![0-9])[0-9]+(?:\.[0-9]+)(?:\.[0-9]+)(?:\.[0-9]+)")
CARD = re.compile(r"(?<![0-9])[0-9](?:[\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_LOCAL_SIGNS = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
BASE_KINDS = ("email", "ip", "card", "phone")


def emails(text: str) -> list[tuple[int, int]]:
    """Leftmost non-overlapping matches of local@domain, in one pass over the @ signs."""
    found, last, at = [], 0, text.find("@")
    while at >= 0:
        a = at
        while a > last and text[a - 1] in _LOCAL_SIGNS:
            a -= 1
        m = DOMAIN.match(text, at + 1) if a < at else None
        if m:
            found.append((a, m.end()))
            last = m.end()
        at = text.find("@", at + 1)
    return found


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = d * 2 - 9 * (d > 4)
        total += d
    return total % 10 == 0


def base_spans(text: str) -> list[tuple[str, int, int]]:
    found = [("email", a, b) for a, b in emails(text)]
    for m in IP.finditer(text):
        if all(len(p) <= 3 and int(p or 0) <= 255 for p in (x.lstrip("0") for x in m[0].split("."))):
            found.append(("ip", m.start(), m.end()))
    for m in CARD.finditer(text):
        digits = m[0].replace(" ", "").replace("-", "")
        if 16 <= len(digits) <= 19 and luhn(digits):
            found.append(("card", m.start(), m.end()))
    if "+" in text:
        for m in PHONE.finditer(text):
            if 8 <= sum(c in "0123456789" for c in m[0]) <= 15:
                found.append(("phone", m.start(), m.end()))
    return found


# ---------------------------------------------------------------- looser candidates

# Gazetteers and cue words.
FIRST_NAMES = frozenset(
    "James Mary John Patricia Robert Jennifer Michael Linda William Elizabeth David Barbara Richard Susan Joseph Jessica Thomas Sarah Charles Karen "
    "Hans Peter Klaus Jürgen Wolfgang Ursula Monika Petra Sabine Renate Jean Pierre Michel André Philippe Marie Nathalie Isabelle Catherine Sophie "
    "José Antonio Manuel Francisco Juan María Carmen Josefa Isabel Ana Carlos Luis Miguel Javier Emma Olivia Liam Noah Anna Paul".split()
)
TITLES = r"(?:Mr|Mrs|Ms|Dr|Prof|Herr|Frau|Monsieur|Madame|Mme|Señor|Señora|Sr|Sra)"
#: Capitalised words that are no part of a person's name, or that stand before one.
NO_NAMES = frozenset(
    "The This That These Those And But For From With When Where What Which Who How Why Not All Any Our Your His Her Their Its Der Die Das Und Les Des Una Los Las "
    "Dear Hello Thank Thanks Regards Contact Contacto Kontakt Name Signed Patient Please Good Best Sincerely Attn Call Write From "
    "General Public License Version Software Foundation Apache Creative Commons University College Institute School Company Corporation Limited Inc Ltd Gmbh Group Bank "
    "Street Avenue Road Square Park City Town County State States United Kingdom Republic North South East West New Great Saint Lake River Mount Island Sea Ocean "
    "January February March April May June July August September October November December Monday Tuesday Wednesday Thursday Friday Saturday Sunday "
    "English French German Spanish European American National International Federal Central Royal Chapter Section Figure Table Page Part Article Order Invoice Serial Project Report "
    "Big Little Red Green Blue Black White Old Young House Barn World War Day Year Time".split()
)
CUES = {
    "name": ("name", "contact", "dear", "patient", "signed", "regards", "sincerely", "attn", "nombre", "nom", "geehrte", "kontakt", "contacto"),
    "local_phone": ("phone", "tel", "call", "fax", "mobile", "cell", "telefon", "téléphone", "teléfono"),
    "ssn": ("ssn", "social security", "security number"),
    "iban": ("iban", "account", "konto", "compte", "cuenta"),
    "spelt_email": ("mail", "contact", "write", "correo", "courriel"),
}
AGAINST = ("version", "isbn", "issn", "order", "invoice", "serial", "figure", "table", "page", "ratio", "coordinates")

_WORD = r"(?:[A-ZÀ-ÖØ-Þ]['’]?[A-ZÀ-ÖØ-Þ]?[a-zß-öø-ÿ]+(?:-[A-ZÀ-ÖØ-Þ][a-zß-öø-ÿ]+)*)"
_CAPITALISED = re.compile(rf"(?<![\w'’-]){_WORD}(?:[ \t]+(?:{_WORD}|[A-Z]\.))*(?![\w'’])")
_TITLE = re.compile(rf"{TITLES}\Z")
_TITLE_BEFORE = re.compile(rf"\b{TITLES}\.?[ \t]+\Z")
MAX_NAME = 4  # words; longer runs are headings and the like
_LOCAL_PHONE = re.compile(r"(?<![\w+.-])(?:\(\d{3}\)\s?|\d{3}[ .-])\d{3}[ .-]\d{4}(?![\w-])")
_SSN = re.compile(r"(?<![\w-])\d{3}-\d{2}-\d{4}(?![\w-])")
_IBAN = re.compile(r"(?<!\w)[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?!\w)")
_SPELT = re.compile(r"(?<!\w)[A-Za-z0-9._-]+\s?[\[(]\s?at\s?[\])]\s?[A-Za-z0-9-]+(?:\s?[\[(]\s?dot\s?[\])]\s?|\.)[A-Za-z]{2,}(?!\w)")
_TWO_DIGITS = re.compile(r"\d\d")


def iban_valid(text: str) -> bool:
    s = text.replace(" ", "")
    return 15 <= len(s) <= 34 and int("".join(str(int(c, 36)) for c in s[4:] + s[:4])) % 97 == 1


def names(text: str) -> list[tuple[int, int, int]]:
    """(start, end, shape vote) of what may be names: behind a title, from a known first name on, or the capitalised words behind those that are no names."""
    found = []
    for m in _CAPITALISED.finditer(text):
        words = [(m.start() + w.start(), m.start() + w.end(), w[0]) for w in re.finditer(r"[^ \t]+", m[0])]
        titled = _TITLE_BEFORE.search(text[max(0, m.start() - 12) : m.start()]) is not None
        first = 0
        for i, (_, _, w) in enumerate(words):
            if _TITLE.match(w):
                first, titled = i + 1, True
        if not titled and len(words) < 2:
            continue
        if not titled:
            known = [i for i, (_, _, w) in enumerate(words) if w in FIRST_NAMES]
            if known and len(words) - known[0] >= 2:
                first = known[0]
            else:
                while first < len(words) and words[first][2] in NO_NAMES:
                    first += 1
        own = words[first:]
        if len(own) >= (1 if titled else 2) and all(len(w) > 1 for _, _, w in own):
            found.append((own[0][0], own[-1][1], 1 if titled else -1 if len(own) > MAX_NAME else 0))
    return found


def loose_candidates(text: str) -> list[tuple[str, int, int, int]]:
    """(kind, start, end, shape vote) of candidates that no base pattern names."""
    found = [("name", a, b, shape) for a, b, shape in names(text)]
    if _TWO_DIGITS.search(text):
        for m in _LOCAL_PHONE.finditer(text):
            found.append(("local_phone", m.start(), m.end(), 1 if m[0][0] == "(" else 0))
        for m in _SSN.finditer(text):
            valid = m[0][:3] not in ("000", "666") and m[0][0] != "9" and m[0][4:6] != "00" and m[0][7:] != "0000"
            found.append(("ssn", m.start(), m.end(), 1 if valid else -1))
        for m in _IBAN.finditer(text):
            found.append(("iban", m.start(), m.end(), 1 if iban_valid(m[0]) else -1))
    if "at" in text and ("[" in text or "(" in text):
        for m in _SPELT.finditer(text):
            found.append(("spelt_email", m.start(), m.end(), 1))
    return found


LOOSE_KINDS = ("iban", "local_phone", "name", "spelt_email", "ssn")
KINDS = BASE_KINDS + LOOSE_KINDS
LABELERS = ("shape", "gazetteer", "context", "against", "adjoining")


def votes(text: str, kind: str, a: int, b: int, shape: int) -> tuple[int, ...]:
    """One vote of each labeler: 1 for, -1 against, 0 none."""
    before = text[max(0, a - 40) : a].lower()
    gazetteer = 0
    if kind == "name":
        words = text[a:b].split()
        gazetteer = -1 if any(w in NO_NAMES for w in words) else 1 if words[0] in FIRST_NAMES else 0
    elif kind == "email":
        gazetteer = 1 if text[a:b].rsplit(".", 1)[-1].lower() in ("com", "org", "net", "edu", "de", "fr", "es", "io") else 0
    context = 1 if any(c in before for c in CUES.get(kind, ())) else 0
    against = -1 if any(c in before for c in AGAINST) else 0
    outside = (text[a - 1] if a else " ") + (text[b] if b < len(text) else " ")
    adjoining = -1 if any(c.isalnum() or c in "_/\\" for c in outside) else 0
    return shape, gazetteer, context, against, adjoining


FEATURES = 1 << 14


def features(text: str, kind: str, a: int, b: int) -> list[int]:
    """Hashed features of a span: its shape, its words, and the words around it, each with the kind."""
    own = text[a:b]
    before, after = text[max(0, a - 60) : a], text[b : b + 30]
    shape = re.sub(r"[^\W\d_]", "a", re.sub(r"\d", "0", re.sub(r"[A-ZÀ-ÖØ-Þ]", "A", own)))
    found = ["", f"shape {re.sub(r'(.)\1+', r'\1', shape)}", f"words {len(own.split())}", f"length {len(own) // 4}"]
    found += [f"word {w}" for w in own.split()[:MAX_NAME]] if kind == "name" else []
    last = re.findall(r"\w+|[^\w\s]", before.lower())[-3:]
    found += [f"near {w}" for w in last] + [f"before {last[-1] if last else ''}"]
    found += [f"after {w}" for w in re.findall(r"\w+|[^\w\s]", after.lower())[:1]]
    if kind == "iban":
        found.append(f"sum {iban_valid(own)}")
    if before.rstrip(" \t").endswith(("\n", ".", "!", "?")) or not before.strip():
        found.append("begins")
    return [zlib.crc32(f"{kind} {f}".encode("utf-8", "replace")) & (FEATURES - 1) for f in found]


def pattern_of(kind: str, vote: tuple[int, ...]) -> int:
    code = KINDS.index(kind)
    for v in vote:
        code = code * 3 + v + 1
    return code


def unpack(code: int) -> tuple[int, tuple[int, ...]]:
    vote = []
    for _ in LABELERS:
        vote.append(code % 3 - 1)
        code //= 3
    return code, tuple(reversed(vote))


UNKNOWN = 0.4  # share of true spans from which each kind starts
N_PATTERNS = len(KINDS) * 3 ** len(LABELERS)

# ---------------------------------------------------------------- model over pattern counts


def expectation_maximisation(patterns: list[int], counts: np.ndarray, rounds: int = 60) -> tuple[np.ndarray, np.ndarray]:
    """(posterior of each pattern, reliability by kind and labeler).

    A labeler that votes on a kind is right with its reliability there, whatever the class; not to vote says nothing.  Each kind has its
    own share of true spans, of one half at most, so that a vote against outweighs it.  Pseudo-counts keep reliabilities within reason where a corpus has few votes.
    Base kinds hold their class, as their patterns are checked exactly.
    """
    kinds = np.array([unpack(p)[0] for p in patterns])
    v = np.array([unpack(p)[1] for p in patterns], dtype=float).reshape(len(patterns), len(LABELERS))
    base, right, share = kinds < len(BASE_KINDS), np.full((len(KINDS), len(LABELERS)), 0.8), np.full(len(KINDS), UNKNOWN)
    post = np.zeros(len(patterns))
    for _ in range(rounds):
        post = 1 / (1 + np.exp(-(np.log(share / (1 - share))[kinds] + (v * np.log(right / (1 - right))[kinds]).sum(axis=1))))
        post = np.where(base, np.maximum(post, 0.95), post)
        for k in range(len(KINDS)):
            own = kinds == k
            agree = ((v[own] > 0) * post[own, None] + (v[own] < 0) * (1 - post[own, None])) * counts[own, None]
            cast = (v[own] != 0) * counts[own, None]
            right[k] = np.clip((agree.sum(axis=0) + 8) / (cast.sum(axis=0) + 10), 0.55, 0.99)
            voted = own & (v != 0).any(axis=1)
            share[k] = np.clip(((post * counts)[voted].sum() + 4) / (counts[voted].sum() + 10), 0.05, 0.5)
    return post, right


def posteriors(counts: dict[int, int]) -> dict[int, float]:
    """Of each vote pattern, given how often each occurs in the corpus."""
    if not counts:
        return {}
    patterns = sorted(counts)
    post, _ = expectation_maximisation(patterns, np.array([counts[p] for p in patterns], float))
    return dict(zip(patterns, post.tolist(), strict=True))


def fit_classifier(rows: list[list[int]], targets: np.ndarray, epochs: int = 60, rate: float = 0.3, decay: float = 3e-4) -> np.ndarray:
    """Weights of a logistic regression of soft labels on hashed features, by full steps scaled by past gradients."""
    sizes = np.array([len(r) for r in rows])
    index, owner = np.array([i for r in rows for i in r], np.int64), np.repeat(np.arange(len(rows)), sizes)
    w, seen = np.zeros(FEATURES), np.full(FEATURES, 1e-8)
    for _ in range(epochs):
        p = 1 / (1 + np.exp(-np.clip(np.bincount(owner, weights=w[index], minlength=len(rows)), -30, 30)))
        g = np.bincount(index, weights=(targets - p)[owner], minlength=FEATURES) / len(rows) - decay * w
        seen += g * g
        w += rate * g / np.sqrt(seen)
    return w


# ---------------------------------------------------------------- plans


MAX_SPANS = 1000  # candidates of each kind that the final classifier learns from
MIN_PROBABILITY = 0.6  # above the one half that a candidate without votes can reach
_SPAN = "struct<kind:int,start:bigint,end:bigint,pattern:int,features:array<int>>"


def candidates(docs: DataFrame) -> DataFrame:
    """(doc_id, spans): base spans and candidates, each (kind, start, end, pattern, features), by kind as listed, then start."""

    def scan(batches):
        kind_type = pa.list_(pa.struct([("kind", pa.int32()), ("start", pa.int64()), ("end", pa.int64()), ("pattern", pa.int32()), ("features", pa.list_(pa.int32()))]))
        for batch in batches:
            for part in slices(batch):
                out = []
                for text in part.column(1).to_pylist():
                    spans = []
                    if text:
                        base = base_spans(text)
                        ends = sorted((a, b) for _, a, b in base)
                        for kind, a, b in base:
                            spans.append({"kind": KINDS.index(kind), "start": a, "end": b, "pattern": pattern_of(kind, votes(text, kind, a, b, 1)), "features": []})
                        for kind, a, b, shape in loose_candidates(text):
                            if not _meets(ends, a, b):
                                spans.append({"kind": KINDS.index(kind), "start": a, "end": b, "pattern": pattern_of(kind, votes(text, kind, a, b, shape)), "features": features(text, kind, a, b)})
                        spans.sort(key=lambda s: (s["kind"], s["start"]))
                    out.append(spans)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(out, kind_type)], ["doc_id", "spans"])

    return arrow(docs.select(F.col("doc_id").cast("bigint"), "text"), scan, f"doc_id bigint, spans array<{_SPAN}>")


def _meets(taken: list[tuple[int, int]], a: int, b: int) -> bool:
    """Whether a span meets one of those taken, which are sorted by start; of base spans few overlap, so that looking back ends soon."""
    i = bisect.bisect_left(taken, (b, -1))
    return any(y > a for _, y in taken[max(0, i - len(BASE_KINDS) - 1) : i])


def pattern_counts(found: DataFrame) -> dict[int, int]:
    """Corpus-wide counts of vote patterns: at most N_PATTERNS rows."""
    rows = found.select(F.explode("spans.pattern").alias("p")).groupBy("p").count().collect()
    return {r["p"]: r["count"] for r in rows}


def train(found: DataFrame, max_spans: int = MAX_SPANS) -> np.ndarray | None:
    """Weights of the final classifier, from the posteriors of at most max_spans candidates of each loose kind."""
    post = posteriors(pattern_counts(found))
    loose = found.select("doc_id", F.explode("spans").alias("s")).where(F.col("s.kind") >= len(BASE_KINDS))
    order = Window.partitionBy("kind").orderBy("place", "features")
    own = loose.select(F.col("s.kind").alias("kind"), "s.pattern", "s.features", F.xxhash64("doc_id", "s.start", "s.end").alias("place"))
    rows = own.withColumn("n", F.row_number().over(order)).where(F.col("n") <= max_spans).select("kind", "place", "pattern", "features").collect()
    rows.sort(key=lambda r: (r["kind"], r["place"], r["features"]))
    return fit_classifier([r["features"] for r in rows], np.array([post[r["pattern"]] for r in rows])) if rows else None


def find_personal_data(docs: DataFrame, max_spans: int = MAX_SPANS, min_probability: float = MIN_PROBABILITY) -> DataFrame:
    """(doc_id, spans): every row with its (kind, start, end, base) spans, by kind as listed, then start."""
    found = materialize(candidates(docs), "pii-candidates")
    weights = train(found, max_spans)
    out_type = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("base", pa.bool_())]))
    least = np.log(min_probability / (1 - min_probability))

    def decide(batches):
        for batch in batches:
            for part in slices(batch, 1024):
                out = []
                for spans in part.column(1).to_pylist():
                    kept = [s for s in spans if s["kind"] < len(BASE_KINDS)]
                    taken: list[tuple[int, int]] = []
                    scored = sorted((-float(weights[s["features"]].sum()), s["start"], s["kind"], s["end"]) for s in spans if s["features"])
                    for minus, a, kind, b in scored:
                        if -minus >= least and not _meets(taken, a, b):
                            bisect.insort(taken, (a, b))
                            kept.append({"kind": kind, "start": a, "end": b})
                    kept.sort(key=lambda s: (s["kind"], s["start"]))
                    out.append([{"kind": KINDS[s["kind"]], "start": s["start"], "end": s["end"], "base": s["kind"] < len(BASE_KINDS)} for s in kept])
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(out, out_type)], ["doc_id", "spans"])

    return arrow(found, decide, "doc_id bigint, spans array<struct<kind:string,start:bigint,end:bigint,base:boolean>>")


def op8_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = find_personal_data(table(spark, sf_dir, "documents"))
    joined = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")
    return found.select(
        "doc_id",
        *[F.size(F.expr(f"filter(spans, s -> s.kind = '{k}')")).cast("bigint").alias(f"n_{k}") for k in BASE_KINDS],
        F.sha2(joined(F.filter("spans", lambda s: s["base"])), 256).alias("base_sha256"),
        joined(F.col("spans")).alias("spans"),
    )
