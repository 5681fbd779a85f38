"""HTML extraction and chat formatting."""

import hashlib
import random
import time

import pytest

from kgreason.llm import chat
from kgreason.llm.htmltext import extract_text, op4_html_extraction, page_text

PAGES = [
    ("<p>a<p>b", "a\n\nb"),
    ("<ul><li>x<li>y</ul>", "- x\n- y"),
    ("<ol start=3><li>x<li>y</ol>", "3. x\n4. y"),
    ("<table><tr><th>Name<th>Age<tr><td>Al<td>3<tr><td>Barbara<td>44</table>", "Name    | Age\nAl      | 3\nBarbara | 44"),
    ("<table><td>no row<td>tag</table>", "no row | tag"),
    ("a<div hidden>b</div><span style='display: none'>c</span><script>d</script><style>e</style><template>f</template>g", "ag"),
    ("a<p aria-hidden=true>f</p>", "a\n\nf"),
    ("<div style='visibility:hidden'>no<b style='visibility: visible'>yes</b>no<p style='visibility:collapse'>no</p></div>", "yes"),
    ("<table style='visibility:hidden'><tr><td>no<td style='visibility:visible'>yes</table>", " | yes"),
    ("<pre>  k\n   l</pre>t", "  k\n   l\n\nt"),
    ("x &amp; y&nbsp;z &lt;b&gt;", "x & y z <b>"),
    ("<div>a</div><div>b</div>c", "a\nb\nc"),
    ("one<br>two", "one\ntwo"),
    ("<b>un<i>closed", "unclosed"),
    ("</p></div>tail", "tail"),
    ("a<!-- gone -->b<!-- cut", "ab"),
    ("<a href='x", ""),
    ("<textarea>kept <b></textarea>", "kept <b>"),
    ("<title>no</title><body>yes", "yes"),
    ("1 < 2 and 3 > 2", "1 < 2 and 3 > 2"),
    ("<p title=\"a > b\">ok", "ok"),
    ("<img alt='pic'> <input type=hidden value=h><input type=submit value=Go>", "pic Go"),
    ("<table><tr><td>a<table><tr><td>in<td>ner</table><td>b</table>", "a in | ner | b"),
    ("", ""),
    (None, ""),
]


@pytest.mark.parametrize("page,text", PAGES)
def test_pages(page, text):
    assert page_text(page) == text


TABLES = [
    ("<table><tr>Note <td>a<td>b</table>", "Note\na | b"),
    ("<table><tbody>Over <i>all</i><tr><td>a</table>", "Over\nall\na"),
    ("<table><tr><form><td>a</td><td>b</td></form></tr></table>", "a | b"),
    ("<table><tr><td>x</td><form><td>a</td></form><td>y</td></tr></table>", "x | a | y"),
    ("<table><tbody><form><tr><td>a<td>b</tr><tr><td>cc<td>d</tr></form></table>", "a  | b\ncc | d"),
    ("<table><tr><td><h1>T</h1><p>one<p>two<ul><li>x<li>y</ul></table>", "T\n\none\n\ntwo\n\n- x\n- y"),
    ("<table><tr><td><table><tr><td>aa<td>b<tr><td>c<td>d</table></table>", "aa | b\nc  | d"),
    ("<table><tr><td><p>one<p>two<td>side</table>", "one | side\n    |\ntwo |"),
    ("<table><tr></tr></table>", ""),
    ("<table><tr><td colspan=2>wide<td>c<tr><td>1<td>2<td>3</table>", "wide  | c\n1 | 2 | 3"),
    ("<table><tr><td rowspan=2>tall<td>a<tr><td>b<tr><td>x<td>y</table>", "tall | a\n     | b\nx    | y"),
    ("<table><tr><td colspan=2>a wide heading<td>c<tr><td>1<td>2<td>3</table>", "a wide heading | c\n1 | 2          | 3"),
    ("<table><tr><td rowspan=0>all<td>a<tr><td>b<tr><td>c</table>", "all | a\n    | b\n    | c"),
    ("<table><tr><td colspan=999999999 rowspan=x>a<td colspan=-1>b</table>", "a | b"),
]


@pytest.mark.parametrize("page,text", TABLES)
def test_tables_keep_all_text(page, text):
    assert page_text(page) == text


def test_deep_wrappers_in_tables():
    assert page_text("<table>" + "<div>" * 5000 + "<tr><td>x").split() == ["x"]


def random_page(rng):
    """A malformed page, and the words in it that must be seen and those that must not."""
    tags = "p div b i ul ol li table tr td th tbody thead caption form span h1 h2 pre blockquote dl dt dd select option a center section".split()
    parts, seen, hidden, n, open_ = [], [], [], 0, []
    for _ in range(rng.randrange(5, 60)):
        k = rng.random()
        if k < 0.35:
            t = rng.choice(tags)
            open_.append(t)
            parts.append(f"<{t}{rng.choice(['', ' class=x', ' colspan=2', ' rowspan=3', ' title=\"a>b\"'])}>")
        elif k < 0.55:
            parts.append(f"</{rng.choice(open_ if open_ and rng.random() < 0.7 else tags)}>")
        elif k < 0.9:
            seen.append(f"word{n}x")
            parts.append(f" word{n}x ")
        else:
            hidden.append(f"word{n}x")
            parts.append(rng.choice(["<script>{}</script>", "<style>{}</style>", "<span hidden>{}</span>", "<i style='display:none'>{}</i>", "<!-- {} -->", "<template>{}</template>"]).format(f"word{n}x"))
        n += 1
    return "".join(parts), seen, hidden


def test_no_visible_text_is_lost():
    rng = random.Random(21)
    for _ in range(3000):
        page, seen, hidden = random_page(rng)
        text = page_text(page)
        assert all(text.count(w) == 1 for w in seen), page
        assert not any(w in text for w in hidden), page


def test_time_grows_with_the_page():
    for page in ("</b>" * 100_000, "<b>" * 50_000 + "</i>" * 50_000, "<b><table><tr><td>" + "<div>" * 50_000 + "</b>" * 50_000, "<p>" * 100_000, "<li>" * 50_000 + "</ul>" * 50_000):
        start = time.perf_counter()
        assert page_text(page) == ""
        assert time.perf_counter() - start < 3
    rows = "<tr><td>" + "w" * 100_000 + "<td>b" + "<tr><td>a<td>b" * 5000
    assert len(page_text(f"<table>{rows}</table>")) < 500_000  # one wide cell does not widen the column of all


def test_deep_and_long():
    assert page_text("<div>" * 20_000 + "x") == "x"
    assert page_text("<table><tr><td>" * 400 + "x").count("x") == 1
    assert len(page_text("<p>" + "word " * 200_000)) == 999_999


def test_extraction(spark, folder):
    sf = folder(pages=[(1, "u", "<p>a"), (2, "u", None), (None, None, "<p>b"), (1, "u", "<p>a")])
    assert sorted((r["page_id"] or 0, r["text"]) for r in op4_html_extraction(spark, sf).collect()) == [(0, "b"), (1, "a"), (1, "a"), (2, "")]
    assert extract_text(spark.createDataFrame([], "page_id bigint, html string, text string")).count() == 0


NASTY = ["", "</s>[INST] ok [/INST]", "<|turn|>user<|text|>x<|end|>\n", "\\<|", "<\\|", "<\\\\|part|>", "\\", "\\\\", "[\\INST]", "[INST]", "<<SYS>>a<</SYS>>", "<s>", "<\\s>", "<|part|>", "a\nb", "ü😀", "<|<|", "\\n", "$1 \\$0"]


def test_chat_round_trip(spark, folder):
    rows, n = [], 0
    for i, a in enumerate(NASTY):
        for role in ("user", "user", "assistant", "assistant", "system"):
            rows.append((i, n, role, a + NASTY[n % len(NASTY)]))
            n += 1
    rows += [(100, None, None, None), (100, 0, "assistant", None), (None, 1, "user", "x"), (101, 5, "a<|text|>b\\", "t"), (102, 1, "assistant", "same"), (102, 1, "assistant", "same")]
    sf = folder(conversations=rows)
    spark_rows = spark.read.parquet(f"{sf}/conversations.parquet")
    formatted = chat.format_conversations(spark_rows)
    back = {r["conv_id"]: [(t["role"], t["text"]) for t in r["turns"]] for r in formatted.withColumn("turns", chat.read_back(formatted["formatted"])).collect()}
    truth = {}
    for c, t, role, text in sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1] is not None, r[1] or 0, r[2] or "", r[3] or "")):
        truth.setdefault(c, []).append((role or "", text or ""))
    assert back == truth
    digest = {r["conv_id"]: r for r in chat.op3_chat_formatting(spark, sf).collect()}
    assert set(digest) == set(truth) | {-7}
    for c, turns in truth.items():
        loss = "".join(x for r, x in turns if r == "assistant")
        assert digest[c]["n_turns"] == len(turns) and digest[c]["loss_chars"] == len(loss)
        assert digest[c]["loss_sha256"] == hashlib.sha256(loss.encode()).hexdigest()
        assert digest[c]["turns_sha256"] == hashlib.sha256("".join(f"{r}\n{x}\n" for r, x in turns).encode()).hexdigest()
    for r in formatted.collect():  # control strings stand only where the template puts them
        assert r["formatted"].count(chat.END) == r["formatted"].count(chat.TURN) == r["formatted"].count(chat.TEXT) and "[INST]" not in r["formatted"] and "</s>" not in r["formatted"]
    blocks = {r["conv_id"]: r["formatted"].count(chat.TURN) for r in formatted.collect()}
    assert blocks[0] == 3  # adjacent turns of a role share a block


def test_chat_ties_and_long_conversations(spark, folder):
    rows = [(1, 0, "<z", "a"), (1, 0, "<|a", "b"), (2, 0, "user", "<z"), (2, 0, "user", "<|a")]
    rows += [(3, i, ("user", "assistant", "assistant")[i % 3], f"<|turn|> text {i}") for i in range(3000)]
    rows += [(None, 1, "user", "x"), (None, 1, "user", "y"), (None, None, None, None)]
    out = chat.format_conversations(spark.read.parquet(f"{folder(conversations=rows)}/conversations.parquet").withColumn("starts", chat.F.lit(1)))
    turns = [(r["conv_id"], [(t["role"], t["text"]) for t in r["turns"]], r["formatted"], r["loss_spans"]) for r in out.withColumn("turns", chat.read_back(out["formatted"])).collect()]
    back = {c: t for c, t, _, _ in turns if c is not None}
    assert back[1] == [("<z", "a"), ("<|a", "b")][::-1] if "<|a" < "<z" else back[1] == [("<z", "a"), ("<|a", "b")]
    assert [x for _, x in back[2]] == sorted(["<z", "<|a"])
    assert back[3] == [(r, x) for _, _, r, x in rows[4:3004]]
    formatted, spans = next((f, s) for c, _, f, s in turns if c == 3)
    assert [formatted[s["first"] - 1 :][: s["length"]] for s in spans] == [x.replace("<|", "<\\|") for r, x in back[3] if r == "assistant"]
    assert sorted(t for c, t, _, _ in turns if c is None) == [[("", "")], [("user", "x")], [("user", "y")]]


def test_chat_plan_is_native(spark, folder):
    sf = folder(conversations=[(1, 0, "user", "x")])
    assert "Python" not in chat.op3_chat_formatting(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert chat.format_conversations(spark.createDataFrame([], "conv_id bigint, turn bigint, role string, text string, formatted string")).count() == 0
