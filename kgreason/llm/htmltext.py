"""HTML extraction: a tree builder with implied tags and visibility rules, and a layout-aware renderer.

Tags are tokenized with one pattern; the builder opens and closes what the standard implies (paragraphs before blocks,
list items, table parts, options, head and body) and ignores end tags without a start.  Rendering walks the tree
without recursion: what is not rendered (scripts, styles, templates, ``hidden``, ``display:none``, hidden inputs) gives
nothing; ``visibility:hidden`` hides until a ``visibility:visible`` inside it; blocks stand on lines of their own, paragraphs and
headings between blank lines; list items get bullets or numbers and are indented by depth; table cells are padded to the width of
their columns, of which ``colspan`` and ``rowspan`` take several; ``pre`` keeps its white space.

Defined results: null and empty pages give an empty text; cut-off tags and comments end with the page; text outside any
tag is shown; what stands in a table outside its cells comes before it; cells wider than WIDEST do not widen their column; tables nested
deeper than MAX_DEPTH are laid out as plain blocks, with all their text; repeated rows are each rendered; an empty table gives an empty
table; further columns are ignored.
"""

from __future__ import annotations

import bisect
import html as _html
import re

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow, slices, table

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([A-Za-z][^\s/>]*)((?:[^>\"']|\"[^\"]*(?:\"|\Z)|'[^']*(?:'|\Z))*)(?:>|\Z)", re.S)
_ATTRIBUTE = re.compile(r"""([^\s=/>"']+)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>]+)))?""")
_SPACE = re.compile(r"[\x20\t\n\r\f]+")

# Element classes of the HTML standard.
VOID = frozenset("area base br col embed hr img input link meta source track wbr".split())
RAW = frozenset("script style textarea title xmp noembed noframes iframe noscript".split())
HIDDEN = frozenset("script style template head title meta link noscript noembed noframes iframe object audio video canvas svg math datalist param source track area base col colgroup rp".split())
BLOCK = frozenset(
    "address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol p pre search section summary table ul caption tr tbody thead tfoot option optgroup".split()
)
SPACED = frozenset("p h1 h2 h3 h4 h5 h6 ul ol dl menu dir blockquote pre table figure article section".split())
CLOSES_P = BLOCK - frozenset("li dd dt tr tbody thead tfoot option optgroup body html caption legend summary".split()) | frozenset(["li", "dd", "dt"])
#: By start tag: the open elements it ends, and those that bound the search.
IMPLIED = {
    "li": ({"li"}, {"ul", "ol", "menu", "dir"}),
    "dt": ({"dt", "dd"}, {"dl"}),
    "dd": ({"dt", "dd"}, {"dl"}),
    "tr": ({"tr", "td", "th", "caption"}, {"table"}),
    "td": ({"td", "th", "caption"}, {"table", "tr"}),
    "th": ({"td", "th", "caption"}, {"table", "tr"}),
    "tbody": ({"tbody", "thead", "tfoot", "caption"}, {"table"}),
    "thead": ({"tbody", "thead", "tfoot", "caption"}, {"table"}),
    "tfoot": ({"tbody", "thead", "tfoot", "caption"}, {"table"}),
    "option": ({"option"}, {"select", "datalist", "optgroup"}),
    "optgroup": ({"optgroup", "option"}, {"select"}),
}
_OUT_OF_CELLS = frozenset("table tr tbody thead tfoot body html".split())
_SCOPE = frozenset("table td th caption button object template html".split())


class Node:
    __slots__ = ("attrs", "children", "tag")

    def __init__(self, tag: str, attrs: dict[str, str] | None = None):
        self.tag, self.attrs, self.children = tag, attrs or {}, []


def _attributes(text: str) -> dict[str, str]:
    if not text.strip(" \t\r\n\f/"):
        return {}
    return {m[1].lower(): _html.unescape(m[2] or m[3] or m[4] or "") for m in _ATTRIBUTE.finditer(text)}


def build_tree(page: str) -> Node:
    """The tree of a page; children are nodes and strings."""
    root = Node("html")
    stack = [root]
    places: dict[str, list[int]] = {}  # of open elements by tag, but for the root: no end tag has to search the stack

    def push(node: Node) -> None:
        stack[-1].children.append(node)
        places.setdefault(node.tag, []).append(len(stack))
        stack.append(node)

    def cut(i: int) -> None:
        while len(stack) > i:
            places[stack.pop().tag].pop()

    def last(tags) -> int:
        return max((places[t][-1] for t in tags if places.get(t)), default=0)

    def close(tags: set[str], bounds) -> None:
        while (i := last(tags)) > last(bounds):
            cut(i)

    at, n = 0, len(page)
    while at < n:
        m = _TOKEN.search(page, at)
        if m is None:
            stack[-1].children.append(page[at:])
            break
        if m.start() > at:
            stack[-1].children.append(page[at : m.start()])
        at = m.end()
        tag = m[2]
        if tag is None:
            continue
        tag = tag.lower()
        if m[1]:
            if tag == "p" and not places.get("p"):
                stack[-1].children.append(Node("p"))
            i = last((tag,))
            # an end tag inside a cell does not reach out of it
            if i and (tag in _OUT_OF_CELLS or i >= last(("td", "th", "table"))):
                cut(i)
            continue
        if tag == "html":
            root.attrs = root.attrs | _attributes(m[3])
            continue
        if tag == "body":
            close({"head"}, ())
        elif tag not in ("title", "meta", "link", "style", "script", "base", "template", "noscript", "head") and any(x.tag == "head" for x in stack[1:2]):
            close({"head"}, ())  # content ends an open head
        if tag in CLOSES_P:
            close({"p"}, _SCOPE)
        if tag in ("h1", "h2", "h3", "h4", "h5", "h6") and stack[-1].tag in ("h1", "h2", "h3", "h4", "h5", "h6"):
            cut(len(stack) - 1)
        if tag in IMPLIED:
            close(*IMPLIED[tag])
        if tag in ("td", "th") and stack[-1].tag != "tr":
            push(Node("tr"))
        node = Node(tag, _attributes(m[3]))
        if tag in RAW and tag != "noscript":
            stack[-1].children.append(node)
            end = re.compile(rf"</{tag}(?=[\s/>])[^>]*>", re.I).search(page, at)
            node.children.append(page[at : end.start() if end else n])
            at = end.end() if end else n
        elif tag in VOID or m[3].endswith("/") and tag in ("path", "circle", "rect"):
            stack[-1].children.append(node)
        else:
            push(node)
    return root


_STYLE_HIDES = re.compile(r"display\s*:\s*none", re.I)
_VISIBILITY = re.compile(r"visibility\s*:\s*(visible|hidden|collapse)", re.I)


def visible(node: Node) -> bool:
    """Whether an element is rendered at all."""
    a = node.attrs
    if node.tag in HIDDEN or "hidden" in a:
        return False
    if node.tag == "input" and a.get("type", "").lower() == "hidden":
        return False
    if node.tag == "dialog" and "open" not in a:
        return False
    return not ("style" in a and _STYLE_HIDES.search(a["style"]))


def shown(node: Node, inherited: bool) -> bool:
    """Whether text right below an element is seen; unlike what ``visible`` tells, an element inside can change that."""
    found = _VISIBILITY.findall(node.attrs["style"]) if "style" in node.attrs else ()
    return found[-1].lower() == "visible" if found else inherited


class _Lines:
    """Text as it is laid out: words run into a line until a break is asked for."""

    def __init__(self) -> None:
        self.lines: list[str] = []
        self.line = ""
        self.space = self.blank = False
        self.indent = 0
        self.marker = ""

    def text(self, s: str) -> None:
        s = _SPACE.sub(" ", s)
        if not s:
            return
        if s[0] == " ":
            self.space = True
        body = s.strip(" ")
        if not body:
            return
        if self.line:
            self.line += " " * self.space + body
        else:
            self._begin()
            self.line = " " * (self.indent - len(self.marker)) + self.marker + body
            self.marker = ""
        self.space = s[-1] == " "

    def _begin(self) -> None:
        if self.blank and self.lines and self.lines[-1]:
            self.lines.append("")
        self.blank = False

    def verbatim(self, s: str) -> None:
        for i, x in enumerate(s.split("\n")):
            if i:
                if self.line:
                    self.end()
                else:
                    self.lines.append("")
            if x:
                if not self.line:
                    self._begin()
                self.line += x

    def end(self, blank: bool = False) -> None:
        if self.line:
            self.lines.append(self.line.rstrip())
            self.line = ""
        self.space = False
        self.blank |= blank

    def done(self) -> str:
        self.end()
        return "\n".join(self.lines).strip("\n")


_SECTIONS = ("tbody", "thead", "tfoot")


def _holders_of_cells(node: Node) -> set[int]:
    """Ids of the elements in a table, other than sections, that have rows or cells of it somewhere inside."""
    found: set[int] = set()
    path, stack = [], [iter(node.children)]
    while stack:
        x = next(stack[-1], None)
        if x is None:
            stack.pop()
            if path:
                path.pop()
        elif not isinstance(x, str) and visible(x) and x.tag not in ("table", "caption", "colgroup", "col"):
            if x.tag in ("td", "th", "tr"):
                for y in reversed(path):
                    if y in found:
                        break
                    found.add(y)
            if x.tag not in ("td", "th"):
                path.append(id(x))
                stack.append(iter(x.children))
    return found


Cell = tuple[Node, bool]  # an element, or a string, and whether text there is seen


def _table_parts(node: Node, seen: bool = True) -> tuple[list[list[Cell]], list[Cell], list[Cell]]:
    """Rows of cells, what stands outside them, and captions; forms and the like around rows or cells are looked through.

    Nested tables are left to their cells. A row inside such an element of a row continues that row.
    """
    rows: list[list[Cell]] = []
    stray, captions = [], []
    holders = _holders_of_cells(node)
    stack: list[tuple] = [(iter(node.children), None, seen)]
    while stack:
        children, row, seen = stack[-1]
        x = next(children, None)
        if x is None:
            stack.pop()
        elif isinstance(x, str):
            if x.strip():
                stray.append((x, seen))
        elif not visible(x):
            continue
        elif x.tag in ("td", "th"):
            if row is None:
                rows.append(row := [])
                stack[-1] = (children, row, seen)
            row.append((x, seen))
        elif x.tag == "tr":
            if row is None:
                rows.append(row := [])
            stack.append((iter(x.children), row, shown(x, seen)))
        elif x.tag in _SECTIONS:
            stack.append((iter(x.children), None, shown(x, seen)))
        elif x.tag == "caption":
            captions.append((x, seen))
        elif id(x) in holders:
            stack.append((iter(x.children), row, shown(x, seen)))
        else:
            stray.append((x, seen))
    return [r for r in rows if r], stray, captions


def _runs_on(cell: Node) -> bool:
    """Whether a cell is one line but for nested tables of one row, which run on in it."""
    stack = [cell]
    while stack:
        for x in stack.pop().children:
            if isinstance(x, str) or not visible(x):
                continue
            if x.tag == "table" and len(_table_parts(x)[0]) > 1 or x.tag in ("br", "hr") or x.tag in BLOCK and x.tag not in ("table", "tr", *_SECTIONS):
                return False
            stack.append(x)
    return True


def _span(node: Node, name: str) -> int:
    """How many columns or rows a cell takes, within the standard's bounds; 0 rows are all that follow."""
    value = node.attrs.get(name, "").strip()
    n = int(value) if value.isascii() and value.isdigit() and len(value) < 9 else 1
    return min(n, 65534) if name == "rowspan" else min(max(n, 1), 1000)


def _grid(rows: list[list[Cell]], depth: int) -> list[list[tuple[int, int, list[str]]]]:
    """By row, ascending: (first column, column behind the last, lines) of cells; a cell of several rows leaves its columns empty below the first."""
    out, busy = [], {}  # column -> first row in which it is free again
    for r, row in enumerate(rows):
        placed, at = [], 0
        for cell, seen in row:
            while busy.get(at, 0) > r:
                at += 1
            end = at + 1
            while end < at + _span(cell, "colspan") and busy.get(end, 0) <= r:
                end += 1
            down = _span(cell, "rowspan")
            if down != 1:
                busy |= dict.fromkeys(range(at, end), r + down if down else len(rows))
            lines = render(cell, depth, seen).split("\n")
            if len(lines) > 1 and len(row) > 1 and _runs_on(cell):
                lines = [" ".join(x for line in lines for x in line.split())]
            placed.append((at, end, lines))
            at = end
        out.append(placed)
    # columns in which no cell begins belong to those before them
    number = {c: i for i, c in enumerate(sorted({a for row in out for a, _, _ in row}))}
    starts = sorted(number)
    return [[(number[a], bisect.bisect_left(starts, b), lines) for a, b, lines in row] for row in out]


SEPARATOR = " | "
WIDEST = 200  # characters of a cell that its column is widened to at most; wider cells stick out


def _aligned(rows: list[list[tuple[int, int, list[str]]]]) -> list[str]:
    """Cells as blocks of lines beside each other, padded to their columns."""
    n = max(b for row in rows for _, b, _ in row)
    width, gap = [0] * n, len(SEPARATOR)
    fits = lambda lines: max((len(x) for x in lines if len(x) <= WIDEST), default=0)
    for row in rows:
        for a, b, lines in row:
            if b == a + 1 and b < n:
                width[a] = max(width[a], fits(lines))
    for row in rows:
        for a, b, lines in row:
            if b > a + 1 and b < n:
                width[b - 1] += max(0, fits(lines) - sum(width[a:b]) - gap * (b - a - 1))
    out = []
    for row in rows:
        for k in range(max(len(lines) for _, _, lines in row)):
            line, at = [], 0
            for a, b, lines in row:
                line += [" " * width[i] for i in range(at, a)]
                line.append((lines[k] if k < len(lines) else "").ljust(sum(width[a:b]) + gap * (b - a - 1)))
                at = b
            out.append(SEPARATOR.join(line).rstrip())
    return out


MAX_DEPTH = 200  # nested tables beyond that are laid out as plain blocks


def render(root: Node, depth: int = 0, seen: bool = True) -> str:
    """All visible text below a node; ``seen`` tells whether text right around it is."""
    out = _Lines()
    lists: list[list] = []  # kind and next number
    work: list[tuple] = [("open", root, seen)]
    pre = 0
    while work:
        what, node, seen = work.pop()
        if what == "close":
            tag = node.tag
            if tag in BLOCK:
                out.end(tag in SPACED and not (lists and tag in ("ul", "ol", "p") and len(lists) > 1))
            if tag == "pre":
                pre -= 1
            elif tag in ("ul", "ol", "menu", "dir"):
                lists.pop()
                out.indent -= 2
            elif tag in ("blockquote", "dd"):
                out.indent -= 2
            elif tag == "li":
                out.marker = ""
            continue
        if isinstance(node, str):
            if not seen:
                continue
            if pre:
                out.verbatim(_html.unescape(node))
            else:
                out.text(_html.unescape(node))
            continue
        tag = node.tag
        if node is not root and not visible(node):
            continue
        seen = shown(node, seen)
        if tag == "br":
            if out.line:
                out.end()
            else:
                out.blank = True
            continue
        if tag == "hr":
            out.end(True)
            continue
        if tag == "img":
            out.text(node.attrs.get("alt", "") if seen else "")
            continue
        if tag == "input":
            if seen and node.attrs.get("type", "text").lower() in ("submit", "button", "reset"):
                out.text(node.attrs.get("value", ""))
            continue
        if tag == "wbr":
            continue
        if tag in BLOCK:
            out.end(tag in SPACED and not (len(lists) > 0 and tag in ("ul", "ol", "p")))
        if tag == "table" and node is not root and depth < MAX_DEPTH:
            rows, stray, caption = _table_parts(node, seen)
            if rows:
                for c, there in stray:  # what stands in a table outside its cells comes before it
                    holder = Node("div")
                    holder.children = [c]
                    if text := render(holder, depth + 1, there):
                        out.verbatim(text)
                        out.end()
                for c, there in caption:
                    out.verbatim(render(c, depth + 1, there))
                    out.end()
                for line in _aligned(_grid(rows, depth + 1)):
                    if line:
                        out.verbatim(" " * out.indent + line)
                        out.end()
                    elif out.lines and out.lines[-1]:
                        out.lines.append("")
                out.end(True)
                continue
        if tag == "pre":
            pre += 1
        elif tag in ("ul", "ol", "menu", "dir"):
            start = node.attrs.get("start", "1")
            lists.append([tag, int(start) if start.lstrip("-").isdigit() and len(start) < 9 else 1])
            out.indent += 2
        elif tag in ("blockquote", "dd"):
            out.indent += 2
        elif tag == "li":
            if lists and lists[-1][0] == "ol":
                out.marker = f"{lists[-1][1]}. "
                lists[-1][1] += 1
            else:
                out.marker = "- "
            if not lists:
                out.indent = max(out.indent, 2)
            out.indent = max(out.indent, len(out.marker)) if len(lists) <= 1 else out.indent
        work.append(("close", node, seen))
        work.extend(("open", c, seen) for c in reversed(node.children))
    return out.done()


def page_text(page: str | None) -> str:
    return render(build_tree(page)) if page else ""


def extract_text(pages: DataFrame) -> DataFrame:
    """(page_id, text) of (page_id, html)."""

    def scan(batches):
        for batch in batches:
            for part in slices(batch, 64):
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([page_text(x) for x in part.column(1).to_pylist()], pa.string())], ["page_id", "text"])

    return arrow(pages.select(F.col("page_id").cast("bigint"), "html"), scan, "page_id bigint, text string")


def op4_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_text(table(spark, sf_dir, "pages")).withColumn("n_chars", F.length("text").cast("bigint"))
