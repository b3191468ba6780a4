"""HTML extraction by layout-aware rendering.

A tolerant tree builder (void elements, implied end tags, optional html/body, raw-text elements) makes a tree; a
renderer walks it with visibility rules and emits all visible text. Blocks are set apart by line breaks or blank
lines, list items keep their markers and indentation, and the cells of a table are padded to aligned columns.

Edge cases. Null or empty html: empty text. Text without tags: itself, with white space collapsed. Unclosed and
misnested tags: closed as the tree builder implies. A tag that the page's end cuts off: dropped, as browsers do. Depth is not limited by
recursion: both passes use stacks. Very long or hostile pages: time and memory in proportion to the page (the tokeniser never looks back, open
elements are found by their tag, and a table line is padded to at most LINE characters). Repeated rows: one result each. Empty table: empty result.
"""

from __future__ import annotations

import bisect
import html as _html
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

# Element sets of the HTML standard that the builder and the renderer need.
VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"}
RAW = {"script", "style", "textarea", "title", "xmp", "iframe", "noembed", "noframes"}
HIDDEN = {"script", "style", "template", "head", "title", "noscript", "iframe", "noembed", "noframes", "datalist", "object", "canvas", "audio", "video", "area", "param", "rp", "annotation", "annotation-xml"}
PARAGRAPH = {"p", "blockquote", "ul", "ol", "dl", "table", "pre", "h1", "h2", "h3", "h4", "h5", "h6", "article", "section", "figure", "fieldset", "menu"}
BLOCK = PARAGRAPH | {"address", "aside", "body", "caption", "center", "dd", "details", "div", "dt", "figcaption", "footer", "form", "header", "hgroup", "hr", "html", "legend", "li", "main", "nav", "optgroup", "option", "search", "summary", "tbody", "td", "tfoot", "th", "thead", "tr"}
CLOSES_P = BLOCK - {"html", "body", "td", "th", "tr", "tbody", "thead", "tfoot", "caption", "option", "optgroup", "legend"}
# What a start tag ends by implication, and the elements at which the search stops.
IMPLIED = {
    "li": ({"li"}, {"ul", "ol", "menu", "table", "td", "th"}),
    "dt": ({"dt", "dd"}, {"dl", "table", "td", "th"}),
    "dd": ({"dt", "dd"}, {"dl", "table", "td", "th"}),
    "td": ({"td", "th"}, {"table", "tr"}),
    "th": ({"td", "th"}, {"table", "tr"}),
    "tr": ({"tr", "td", "th", "caption"}, {"table"}),
    "tbody": ({"tr", "td", "th", "caption", "tbody", "thead", "tfoot", "colgroup"}, {"table"}),
    "thead": ({"tr", "td", "th", "caption", "tbody", "thead", "tfoot", "colgroup"}, {"table"}),
    "tfoot": ({"tr", "td", "th", "caption", "tbody", "thead", "tfoot", "colgroup"}, {"table"}),
    "option": ({"option"}, {"select", "datalist"}),
    "optgroup": ({"option", "optgroup"}, {"select"}),
    "rt": ({"rt", "rp"}, {"ruby"}),
    "rp": ({"rt", "rp"}, {"ruby"}),
    "body": ({"head"}, set()),
}
SCOPE = {"table", "td", "th", "caption", "html", "body"}

CROSSING = {"table", "tr", "tbody", "thead", "tfoot", "body", "html", "td", "th"}  # end tags that reach beyond the scope
LINE, COLUMN = 400, 120  # characters: most padding of a table line, widest cell that others are aligned to
DEEP = 16  # tables within so many others are rendered as plain blocks: each level copies the text of its cells

_MARKUP = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?/][^A-Za-z>][^>]*+(?:>|\Z)|<[!?][^>]*+(?:>|\Z)|</>", re.S)
_NAME = r"[\s/]++|[^\s/>=][^\s/>=]*+"
_VALUE = r"""\s*+=\s*+(?:"[^"]*+(?:"|\Z)|'[^']*+(?:'|\Z)|[^\s>"'][^\s>]*+)?+"""
_TAG = re.compile(rf"<(/?)([A-Za-z][^\s/>]*+)((?:(?:{_NAME})(?:{_VALUE})?+|=)*+)(>|\Z)")
_ATTR = re.compile(r"([^\s=/>]++)(?:\s*+=\s*+(?:\"([^\"]*+)\"?|'([^']*+)'?|([^\s>]++)))?+")
_UNSEEN = re.compile(r"display\s*:\s*none|visibility\s*:\s*(?:hidden|collapse)", re.I)
_SPACE = re.compile(r"[ \t\r\n\f]+")


class Node:
    __slots__ = ("tag", "attrs", "kids")

    def __init__(self, tag: str, attrs: str = ""):
        self.tag, self.attrs, self.kids = tag, attrs, []


def attributes(raw: str) -> dict[str, str]:
    out: dict[str, str] = {}
    for name, a, b, c in _ATTR.findall(raw):
        out.setdefault(name.lower(), _html.unescape(a or b or c))
    return out


class _Open:
    """The stack of open elements, with the places of each tag: the nearest one is found without a search."""

    def __init__(self, root: Node):
        self.stack = [root]
        self.places: dict[str, list[int]] = {}

    def push(self, node: Node) -> None:
        self.places.setdefault(node.tag, []).append(len(self.stack))
        self.stack.append(node)

    def nearest(self, names) -> int:
        """Place of the innermost open element of the names; 0 if there is none."""
        return max((at[-1] for n in names if (at := self.places.get(n))), default=0)

    def cut(self, at: int) -> None:
        while len(self.stack) > at:
            self.places[self.stack.pop().tag].pop()

    def close_to(self, names: set[str], stop: set[str]) -> None:
        """End the innermost element of the names, and the outer ones of them up to the next stop element (a row also ends the cells of its section)."""
        at = self.nearest(names)
        if not at or self.nearest(stop) > at:
            return
        border = max((p[k - 1] for n in stop if (p := self.places.get(n)) and (k := bisect.bisect_left(p, at))), default=0)
        self.cut(min(p[k] for n in names if (p := self.places.get(n)) and (k := bisect.bisect_right(p, border)) < len(p)))


def build(page: str) -> Node:
    """Text of one page -> tree."""
    root = Node("#root")
    opened, at, end = _Open(root), 0, len(page)
    stack = opened.stack
    while at < end:
        lt = page.find("<", at)
        if lt < 0:
            stack[-1].kids.append(page[at:])
            break
        if lt > at:
            stack[-1].kids.append(page[at:lt])
        m = _TAG.match(page, lt)
        if not m:
            m = _MARKUP.match(page, lt)
            if m and m[0].startswith("<![CDATA["):
                stack[-1].kids.append(_html.escape(m[0][9:].removesuffix("]]>")))
            elif not m:
                stack[-1].kids.append("<")
            at = m.end() if m else lt + 1
            continue
        at = m.end()
        if not m[4]:
            break
        tag, attrs = m[2].lower(), m[3]
        if m[1]:
            here = opened.nearest((tag,))
            if here and (tag in CROSSING or opened.nearest(SCOPE) <= here):
                opened.cut(here)
            continue
        if tag in IMPLIED:
            opened.close_to(*IMPLIED[tag])
        if tag in CLOSES_P:
            opened.close_to({"p"}, SCOPE | {"button", "li", "dd", "dt", "blockquote", "div"})
        if tag in ("td", "th") and stack[-1].tag in ("table", "tbody", "thead", "tfoot"):
            row = Node("tr")
            stack[-1].kids.append(row)
            opened.push(row)
        node = Node(tag, attrs)
        stack[-1].kids.append(node)
        if tag in VOID or attrs.endswith("/") and tag not in BLOCK and tag not in RAW:
            continue
        if tag in RAW:
            stop = re.compile(rf"</{re.escape(tag)}[\s/>]", re.I).search(page, at)
            node.kids.append(page[at : stop.start() if stop else end])
            at = page.find(">", stop.start()) + 1 or end if stop else end
            continue
        opened.push(node)
    return root


def visible(node: Node) -> bool:
    if node.tag in HIDDEN:
        return False
    if not node.attrs:
        return node.tag not in ("input", "dialog")
    a = attributes(node.attrs)
    if node.tag == "dialog" and "open" not in a:
        return False
    if "hidden" in a and a["hidden"].lower() != "until-found" or _UNSEEN.search(a.get("style", "")):
        return False
    return node.tag != "input" or a.get("type", "text").lower() in ("submit", "button", "reset")


class _Out:
    """Lines being written: inline text collapses, breaks are merged to the largest asked for."""

    def __init__(self):
        self.parts: list[str] = []
        self.breaks, self.space, self.any, self.lead = 0, False, False, ""
        self.lines = ""  # line breaks of preformatted text that wait for what follows

    def text(self, s: str) -> None:
        s = _SPACE.sub(" ", s)
        if s == " " or not s:
            self.space |= bool(s)
            return
        head, body, tail = s[0] == " ", s.strip(" "), s[-1] == " "
        if self.breaks and self.any:
            self.parts.append("\n" * self.breaks)
        elif (head or self.space) and self.any and not self.lead:
            self.parts.append(" ")
        self.parts.append(self.lead + body)
        self.breaks, self.space, self.any, self.lead = 0, tail, True, ""

    def pre(self, s: str) -> None:
        """Preformatted text, with its line breaks; those at its end are dropped by end_pre()."""
        body = s.rstrip("\n")
        if body:
            if self.breaks and self.any:
                self.parts.append("\n" * self.breaks)
            self.parts.append(self.lead + self.lines + body)
            self.breaks, self.space, self.any, self.lead, self.lines = 0, False, True, "", ""
        self.lines += s[len(body) :]

    def end_pre(self) -> None:
        self.lines = ""

    def gap(self, n: int) -> None:
        self.breaks, self.space = max(self.breaks, n), False

    def value(self) -> str:
        return "".join(self.parts)


def _table(rows: list[list[tuple[int, str]]]) -> str:
    """Rows of (column, text) with columns of equal width; a cell with several lines takes several. Columns without text take no room."""
    width: dict[int, int] = {}
    split = [[(i, c.split("\n")) for i, c in r if c] for r in rows]
    for r in split:
        for i, c in r:
            width[i] = max(width.get(i, 0), max((len(x) for x in c if len(x) <= COLUMN), default=1))
    left, at = {}, 0
    for i in sorted(width):
        left[i] = at
        at += width[i] + 2
    out = []
    for r in split:
        for k in range(max((len(c) for _, c in r), default=0)):
            line, size = [], 0
            for i, c in r:
                if k < len(c) and c[k]:
                    pad = max(min(left[i], LINE) - size, 2 if size else 0)
                    line += [" " * pad, c[k]]
                    size += pad + len(c[k])
            out.append("".join(line).rstrip())
    return "\n".join(out)


class _Table:
    """Rows of cells (column, text) with their spans over rows and columns."""

    def __init__(self, level: int):
        self.level, self.rows, self.column = level, [], 0
        self.down: dict[int, tuple[int, int]] = {}  # column -> (last row that a cell from above takes, its columns)

    def row(self) -> None:
        self.rows.append([])
        self.column = 0

    def cell(self, text: str, attrs: dict[str, str]) -> None:
        if not self.rows:
            self.row()
        now = len(self.rows) - 1
        while (held := self.down.get(self.column)) and held[0] >= now:
            self.column += held[1]
        span = [int(v) if (v := attrs.get(n, "1")).isascii() and v.isdigit() and len(v) < 9 else 1 for n in ("colspan", "rowspan")]
        cols, rows = max(1, min(span[0], 1000)), span[1] or 65534
        self.rows[-1].append((self.column, text))
        if rows > 1:
            self.down[self.column] = (now + min(rows, 65534) - 1, cols)
        self.column += cols

    def line(self, text: str) -> None:
        """Text that is no cell: a line of its own."""
        self.row()
        self.rows[-1].append((0, text))
        self.row()


def _svg_texts(node: Node) -> list:
    """The text elements of a drawing, in order; the rest of it is no text."""
    out, todo = [], list(reversed(node.kids))
    while todo:
        x = todo.pop()
        if isinstance(x, str):
            continue
        if x.tag == "text":
            out.append(x)
        elif visible(x) and x.tag != "defs":
            todo += reversed(x.kids)
    return out


def render(root: Node) -> str:
    """Tree -> visible text. A stack of steps stands for recursion; tables and cells render into outputs of their own."""
    outs: list = [_Out()]
    tables: list[_Table] = []
    lists: list[list] = []
    steps: list = [("in", root)]
    pre = deep = 0
    while steps:
        kind, x = steps.pop()
        out = outs[-1]
        if kind == "in":
            if isinstance(x, str):
                s = _html.unescape(x)
                if tables and tables[-1].level == len(outs):  # loose text between cells
                    if s.strip():
                        tables[-1].line(_SPACE.sub(" ", s).strip())
                elif pre:
                    out.pre(s)
                else:
                    out.text(s)
                continue
            if not visible(x):
                continue
            tag = x.tag
            if tag == "br":
                if pre:
                    out.lines += "\n"
                elif out.any:
                    out.breaks = out.breaks + 1 if out.breaks < 2 else out.breaks
                    out.space = False
                continue
            if tag == "img":
                if alt := attributes(x.attrs).get("alt", "").strip():
                    out.text(f" {alt} ")
                continue
            if tag == "input":
                out.text(f" {attributes(x.attrs).get('value', '')} ")
                continue
            steps.append(("out", x))
            if tag == "table" and not deep and len(tables) < DEEP:
                out.gap(2)
                tables.append(_Table(len(outs)))
            elif tag == "tr" and tables and not deep:
                tables[-1].row()
            elif tag == "svg":
                out.space = True
                steps.extend(("in", k) for k in reversed(_svg_texts(x)))
                continue
            elif tag in ("td", "th", "caption") and tables and not deep:
                outs.append(_Out())
            else:
                deep += tag == "table"
                if tag in BLOCK:
                    out.gap(2 if tag in PARAGRAPH and not (lists and tag in ("ul", "ol", "menu")) else 1)
                if tag in ("ul", "ol", "menu"):
                    start = attributes(x.attrs).get("start", "1") if tag == "ol" else "1"
                    lists.append([tag, int(start) if start.lstrip("-").isdigit() else 1])
                elif tag == "li":
                    mark = "- "
                    if lists and lists[-1][0] == "ol":
                        mark = f"{lists[-1][1]}. "
                        lists[-1][1] += 1
                    out.lead = "  " * min(max(len(lists) - 1, 0), DEEP) + mark
                elif tag == "dd":
                    out.lead = "  "
                elif tag == "pre":
                    pre += 1
                    if x.kids and isinstance(x.kids[0], str):  # the line break after the start tag is none of the text
                        x.kids[0] = x.kids[0].removeprefix("\r").removeprefix("\n")
            steps.extend(("in", k) for k in reversed(x.kids))
            continue
        tag = x.tag
        if tag == "table" and not deep:
            t = tables.pop()
            if grid := [r for r in t.rows if any(c for _, c in r)]:
                out.pre(_table(grid))
                out.end_pre()
            out.gap(2)
        elif tag in ("td", "th", "caption") and tables and not deep and len(outs) > tables[-1].level:
            cell = outs.pop().value()
            if tag == "caption":
                tables[-1].line(cell)
            else:
                tables[-1].cell(cell, attributes(x.attrs) if x.attrs else {})
        elif tag == "svg":
            out.space = True
        elif tag == "tr" and tables and not deep:
            pass
        else:
            deep -= tag == "table"
            if tag in ("ul", "ol", "menu") and lists:
                lists.pop()
            elif tag == "pre":
                pre -= 1
                out.end_pre()
            elif tag in ("li", "dd"):
                out.lead = ""
            if tag in BLOCK:
                out.gap(2 if tag in PARAGRAPH and not (lists and tag in ("ul", "ol", "menu")) else 1)
    return outs[0].value()


def extract(page: str | None) -> str:
    return render(build(page)) if page else ""


def _batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        texts = [extract(x.as_py()) for x in b.column(1)]
        yield pa.RecordBatch.from_arrays([b.column(0), pa.array(texts, pa.string())], ["page_id", "text"])


def extract_pages(pages: DataFrame, id_col: str = "page_id", html_col: str = "html") -> DataFrame:
    """(page_id, text): one row per input row. Pages are independent, so nothing is shuffled."""
    narrow = pages.selectExpr(f"`{id_col}` as page_id", f"`{html_col}` as html")
    kind = dict(narrow.dtypes)["page_id"]
    return narrow.mapInArrow(_batches, f"page_id {kind}, text string")
