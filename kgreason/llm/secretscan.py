"""Secret scans: fixed patterns, and novelty under a primed zstandard compressor.

Candidates are token-like strings of 20 characters and more, dots within them included, in sensitive context: a word that speaks of
keys, tokens, passwords and the like stands before them on their line or on the line before, or another candidate that has such a
word before it.  Lines below the opening line of a key block are one candidate.  A compressor is primed with a dictionary
of common identifiers and of the text around the candidate, other copies of the candidate taken out; what the candidate adds to the
compressed size of its line, per byte, is its novelty.  Words, paths and identifiers cost little as they occur around or in
the dictionary; random strings cost almost their full entropy and are reported as ``novel``.  Of a dotted candidate
the stretch from its first novel part to its last is reported, or all of it where only the whole is novel.

Defined results: null text is empty and has no spans; repeated rows are each scanned; no length of a text, a line or a
candidate bounds the search; spans found by novelty never overlap those of the patterns; an empty table gives an empty table;
further columns are ignored by ``scan_secrets`` and pass through ``redact_secrets``.
"""

from __future__ import annotations

import re

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow, slices, table

# The base patterns and the least lengths of what they find.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
MIN_ASSIGN, MIN_ACCESS = 6, 20
KINDS = ("assign", "access", "hex", "novel")

# Words common in code and configuration, which prime the compressor.
IDENTIFIERS = """
access account address admin algorithm api app application array async attribute auth authorization await backend base64
batch bearer begin binary bool boolean boot bucket buffer build byte cache callback catch certificate channel char class client cluster code
column command commit common compile config configuration connect connection console const container content context controller cookie core
count create credential cursor data database date debug decode default define delete deploy description dest device dict directory
display document domain double download driver element email enable encode encrypt endpoint entry enum environment error event example except exception
export expires extend extension factory false field file filter final float folder format from function gateway generate global group
handler hash header host html http https identifier image import include index info init input insert instance int interface internal
item iterator java javascript json kernel key label language length level library license link list load local localhost lock log login
main manager map master match memory merge message meta method migration model module monitor mount name namespace network node
null number object offset open option order origin output override package page param parameter parse parser password path payload
permission platform plugin policy port prefix primary print private process profile project prompt property protocol provider proxy public publish python
query queue random range read record redirect reference refresh region register release remote render replace repository request require reset resource
response result return role root route rule runtime schema scheme scope script search secret security select sequence server service session
""".split()
_PRIMER = " ".join([*map(str.upper, IDENTIFIERS), *map(str.title, IDENTIFIERS), *IDENTIFIERS]).encode()

_CUE = re.compile(r"key|secret|token|passw|passphrase|auth|credential|bearer|private|signature|webhook", re.I | re.A)
MIN_TOKEN = 20
_TOKEN = re.compile(r"[A-Za-z0-9+/_=-]+(?:\.[A-Za-z0-9+/_=-]+)*")
_PART = re.compile(r"[^.]+")
_KEY_BLOCK = re.compile(r"-----BEGIN [^\n-]*(?:PRIVATE|SECRET) KEY[^\n-]*-----[\x20\t\r]*\n")
_KEY_LINE = re.compile(r"[\x20\t]*([A-Za-z0-9+/_=-]+)[\x20\t\r]*(?:\n|$)")
_KEY_HEADER = re.compile(r"[\x20\t\r]*(?:[A-Za-z-]+:[^\n]*)?\n")
AROUND = 1500  # characters of text on each side that prime the compressor
MIN_NOVELTY = 0.72  # marginal compressed bytes a byte, of long candidates: of random base64 0.77 and more, of words about half
SHORT_NOVELTY = 0.2  # what candidates of up to SHORT characters need beyond that, and longer ones in proportion less: literals of short strings are stored as they are
SHORT = 100
MIN_CLASSES = 3  # of lower case, upper case, digits


def base_spans(text: str) -> list[tuple[int, int, str]]:
    found = []
    if ":" in text or "=" in text:
        found += [(m.start(), m.end(), "assign") for m in ASSIGN.finditer(text) if len(m[2]) >= MIN_ASSIGN]
    if "AKIA" in text:
        found += [(m.start(), m.end(), "access") for m in ACCESS.finditer(text) if m.end() - m.start() >= MIN_ACCESS]
    found += [(m.start(), m.end(), "hex") for m in HEX.finditer(text)]
    return found


def key_blocks(text: str) -> list[tuple[int, int]]:
    """Runs of lines below the opening line of a key block, each run as one span; short lines count where the closing line follows."""
    found = []
    for m in _KEY_BLOCK.finditer(text) if "-----BEGIN " in text else ():
        at, start, end, long_end = m.end(), None, None, None
        while not text.startswith("-----", at):
            if line := _KEY_LINE.match(text, at):
                start = line.start(1) if start is None else start
                end = line.end(1)
                long_end = end if end - line.start(1) >= 20 else long_end
            elif start is not None or not (line := _KEY_HEADER.match(text, at)):
                break
            if line.end() == at:
                break
            at = line.end()
        end = end if text.startswith("-----END", at) else long_end
        if end is not None and end - start >= 20:
            found.append((start, end))
    return found


def _classes(s: str) -> int:
    return (s.lower() != s) + (s.upper() != s) + any(c.isdigit() for c in s)


def _reach(text: str, cue: int) -> int:
    """Where the context of a cue ends: with the next line that is not blank."""
    end = text.find("\n", cue)
    while end >= 0:
        after = text.find("\n", end + 1)
        if after < 0 or text[end + 1 : after].strip():
            return after if after >= 0 else len(text)
        end = after
    return len(text)


def candidates(text: str) -> list[tuple[int, int]]:
    """Spans of key blocks and of all long tokens in the context of a cue, or of a candidate before them."""
    cues = [m.end() for m in _CUE.finditer(text)]
    if not cues:
        return []
    blocks = key_blocks(text)
    found, i, j, end = list(blocks), 0, 0, -1
    for m in _TOKEN.finditer(text):
        a, b = m.span()
        if b - a < MIN_TOKEN:
            continue
        fresh = False
        while i < len(cues) and cues[i] <= a:
            i, fresh = i + 1, True
        if fresh:
            end = max(end, _reach(text, cues[i - 1]))
        while j < len(blocks) and blocks[j][1] <= a:
            j += 1
        if a < end and _classes(m[0]) >= MIN_CLASSES:
            if b >= end or text.find("\n", b, end) < 0:
                end = max(end, _reach(text, b))
            if j == len(blocks) or b <= blocks[j][0]:
                found.append((a, b))
    return sorted(found)


def novelty(text: str, start: int, end: int) -> float:
    """Marginal compressed bytes of text[start:end] against its line, for each of its bytes; what surrounds it primes the compressor, copies of it do not."""
    own = text[start:end]
    line = text.rfind("\n", max(0, start - 200), start) + 1 or max(0, start - 200)
    plain = lambda a, b: text[a:b].replace(own, "").encode("utf-8", "replace")
    before, candidate = plain(line, start), own.encode("utf-8", "replace")
    around = plain(max(0, start - AROUND), start) + b"\n" + plain(end, end + AROUND)
    primed = zstandard.ZstdCompressor(
        level=19,
        dict_data=zstandard.ZstdCompressionDict(_PRIMER + b"\n" + around, dict_type=zstandard.DICT_TYPE_RAWCONTENT),
        write_checksum=False,
        write_content_size=False,
        write_dict_id=False,
    )
    return (len(primed.compress(before + candidate)) - len(primed.compress(before))) / max(1, len(candidate))


def least_novelty(length: int) -> float:
    return MIN_NOVELTY + SHORT_NOVELTY * min(1.0, SHORT / length)


def novel_spans(text: str, taken: list[tuple[int, int, str]]) -> list[tuple[int, int, str]]:
    """Novel candidates that overlap no span taken."""

    def novel(a: int, b: int) -> bool:
        return b - a >= MIN_TOKEN and _classes(text[a:b]) >= MIN_CLASSES and all(b <= x or a >= y for x, y, _ in taken) and novelty(text, a, b) >= least_novelty(b - a)

    found = []
    for a, b in candidates(text):
        parts = [(a + m.start(), a + m.end()) for m in _PART.finditer(text[a:b])] if "." in text[a:b] else []
        parts = [x for x in parts if novel(*x)]
        if parts:  # from the first novel part to the last
            found.append((parts[0][0], parts[-1][1], "novel"))
        elif novel(a, b):
            found.append((a, b, "novel"))
    return [s for s in found if all(s[1] <= x or s[0] >= y for x, y, _ in taken)]


def scan_secrets(docs: DataFrame) -> DataFrame:
    """(doc_id, spans): every row with its array of (start, end, kind), by start."""

    def scan(batches):
        kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("kind", pa.string())]))
        for batch in batches:
            for part in slices(batch):
                out = []
                for text in part.column(1).to_pylist():
                    base = base_spans(text) if text else []
                    spans = base + (novel_spans(text, base) if text else [])
                    out.append([{"start": a, "end": b, "kind": k} for a, b, k in sorted(spans, key=lambda s: (s[0], KINDS.index(s[2])))])
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(out, kind)], ["doc_id", "spans"])

    return arrow(docs.select(F.col("doc_id").cast("bigint"), "text"), scan, "doc_id bigint, spans array<struct<start:bigint,end:bigint,kind:string>>")


def redact_secrets(docs: DataFrame, mask: str = "[secret]") -> DataFrame:
    """docs with the found spans in ``text`` replaced."""

    def scan(batches):
        for batch in batches:
            for part in slices(batch):
                at = part.schema.names.index("text")
                out = []
                for text in part.column(at).to_pylist():
                    base = base_spans(text) if text else []
                    pieces, last = [], 0
                    for a, b, _ in sorted(base + (novel_spans(text, base) if text else [])):
                        if b > last:
                            pieces += [text[last : max(a, last)], mask if a >= last else ""]
                            last = b
                    out.append(None if text is None else "".join([*pieces, text[last:]]))
                columns = [pa.array(out, pa.string()) if i == at else part.column(i) for i in range(part.num_columns)]
                yield pa.RecordBatch.from_arrays(columns, part.schema.names)

    return arrow(docs, scan, docs.schema)


def op1_secret_scans(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = scan_secrets(table(spark, sf_dir, "documents"))
    base = F.filter("spans", lambda s: s["kind"] != "novel")
    joined = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")
    return found.select(
        "doc_id",
        *[F.size(F.expr(f"filter(spans, s -> s.kind = '{k}')")).cast("bigint").alias(f"n_{k}") for k in KINDS[:3]],
        F.sha2(joined(base), 256).alias("base_sha256"),
        joined(F.col("spans")).alias("spans"),
    )
