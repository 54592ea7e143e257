"""Layout-aware text of HTML pages.

A tree builder closes what authors leave open (paragraphs, list items, rows, cells, options), drops stray end tags and
keeps tables from being closed from within a cell.  A renderer walks the tree under visibility rules (hidden elements,
inline display and visibility, closed details and dialogs, scripts and other unseen content) and lays out what is left:
collapsed white space, blank lines around blocks, bulleted and numbered lists, quotes, preformatted text, and tables
with aligned columns.
"""

from __future__ import annotations

import re
import sys
import unicodedata
from bisect import bisect_right
from collections.abc import Iterator
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tripleschema.llm.common import prepare, slices

#: Kinds of elements.
SECTIONS = frozenset("tbody thead tfoot".split())
NOT_DRAWN = frozenset("defs symbol metadata desc clippath mask pattern marker".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style xmp iframe noembed noframes".split())
RAW_TEXT = frozenset("textarea title".split())
UNSEEN = frozenset("head title script style template noscript noembed noframes iframe object canvas audio video datalist map annotation annotation-xml".split())
BLOCK = frozenset("address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol optgroup option p pre search section summary table tbody td tfoot th thead tr ul caption".split())
SPACED = frozenset("blockquote dl fieldset figure h1 h2 h3 h4 h5 h6 hr ol p pre table ul menu dir".split())
CLOSES_P = (BLOCK - {"body", "html", "option", "optgroup", "td", "th", "tr", "tbody", "thead", "tfoot", "caption", "legend"}) | {"li", "dd", "dt"}
#: What an opening tag closes first, and where the search for it stops.
IMPLIED = {
    "li": ({"li"}, {"ul", "ol", "menu", "dir"}),
    "dt": ({"dt", "dd"}, {"dl"}),
    "dd": ({"dt", "dd"}, {"dl"}),
    "option": ({"option"}, {"select", "datalist", "optgroup"}),
    "optgroup": ({"option", "optgroup"}, {"select"}),
    "tr": ({"tr", "td", "th", "caption"}, {"table", "tbody", "thead", "tfoot"}),
    "td": ({"td", "th"}, {"tr", "table"}),
    "th": ({"td", "th"}, {"tr", "table"}),
    "tbody": ({"tbody", "thead", "tfoot", "tr", "td", "th", "caption"}, {"table"}),
    "thead": ({"tbody", "thead", "tfoot", "tr", "td", "th", "caption"}, {"table"}),
    "tfoot": ({"tbody", "thead", "tfoot", "tr", "td", "th", "caption"}, {"table"}),
    "body": ({"head"}, {"html"}),
}
FENCE = frozenset({"td", "th", "table", "caption", "button", "object"})  # end tags of other elements do not reach beyond
TABLE_TAGS = frozenset("table tbody thead tfoot tr td th caption".split())
INDENT = 400  # columns; what is nested deeper is not moved further in

MARKUP = re.compile(r"""<(?:(!--(?:.*?--!?>|.*))|([!?][^>]*>)|/([a-zA-Z][^\s/>]*)[^>]*>|([a-zA-Z][^\s/>]*)((?:[^>=]++|=\s*+(?:"[^"]*+"|'[^']*+'|[^\s"'>][^\s>]*+|(?=>)))*+)>)""", re.DOTALL)
ATTRIBUTE = re.compile(r"""([^\s"'>/=]+)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>][^\s>]*)))?""")
GAPS = re.compile(r"[ \t\n\f\r]+")


class Node:
    __slots__ = ("attrs", "kids", "tag")

    def __init__(self, tag: str, attrs: dict[str, str] | None = None):
        self.tag, self.attrs, self.kids = tag, attrs or {}, []


def attributes(raw: str) -> dict[str, str]:
    out: dict[str, str] = {}
    for m in ATTRIBUTE.finditer(raw):
        out.setdefault(m[1].lower(), unescape(next((v for v in m.groups()[1:] if v is not None), "")))
    return out


# -- the tree


class Stack:
    """The open elements, with the places of each kind of element, so that no search walks a deep stack."""

    def __init__(self, root: Node):
        self.nodes, self.places, self.hosts = [root], {}, [0]  # hosts: the next element out that is no part of a table
        self.deepest = 1

    def push(self, node: Node) -> None:
        self.places.setdefault(node.tag, []).append(len(self.nodes))
        self.hosts.append(self.hosts[-1] if node.tag in TABLE_TAGS else len(self.nodes))
        self.nodes.append(node)
        self.deepest = max(self.deepest, len(self.nodes))

    def cut(self, at: int) -> None:
        for node in self.nodes[at:]:
            self.places[node.tag].pop()
        del self.nodes[at:], self.hosts[at:]

    def last(self, tags) -> int:
        """Place of the innermost open element of these kinds; 0 without one."""
        return max((found[-1] for t in tags if (found := self.places.get(t))), default=0)

    def close(self, tags, stops) -> None:
        """Close the outermost open element of ``tags`` that is not beyond one of ``stops`` (seen from inside)."""
        fence, cut = self.last(stops), 0
        for t in tags:
            found = self.places.get(t)
            if found and found[-1] > fence:
                at = found[bisect_right(found, fence)]
                cut = min(cut, at) if cut else at
        if cut:
            self.cut(cut)

    def end(self, tag: str) -> None:
        """An end tag closes its element unless a fence is in between."""
        table, block = tag in TABLE_TAGS, tag in ("form", "div")
        fence = self.last(t for t in FENCE if t != tag and not (table and t in ("td", "th", "caption", "button", "object")) and not (t == "button" and block))
        at = self.last((tag,))
        if at > fence:
            self.cut(at)
        elif tag == "p" and not fence:
            self.nodes[-1].kids.append(Node("p"))


def parse(html: str) -> Node:
    """The tree of a page; any text gives a tree."""
    return _parsed(html)[0]


def _parsed(html: str) -> tuple[Node, int]:
    """The tree and its depth."""
    root = Node("html")
    stack = Stack(root)
    at, n = 0, len(html)

    def text(raw: str) -> None:
        if raw:
            top = stack.nodes[-1]
            if top.tag in ("table", "tbody", "thead", "tfoot", "tr") and not raw.isspace():
                top = stack.nodes[stack.hosts[-1]]
            top.kids.append(unescape(raw) if "&" in raw else raw)

    while at < n:
        start = html.find("<", at)
        if start < 0:
            text(html[at:])
            break
        m = MARKUP.match(html, start)
        if not m:
            follows = html[start + 1 : start + 2]
            if follows.isalpha() or follows == "/":  # a tag that never ends
                text(html[at:start])
                break
            text(html[at : start + 1])
            at = start + 1
            continue
        if start > at:
            text(html[at:start])
        at = m.end()
        if m[3]:
            tag = m[3].lower()
            if tag == "br":
                stack.nodes[-1].kids.append(Node("br"))
            else:
                stack.end(tag)
            continue
        if not m[4]:
            continue
        tag = m[4].lower()
        node = Node(tag, attributes(m[5]) if m[5] and not m[5].isspace() else None)
        if tag == "html" or (tag == "body" and stack.last(("body",))):
            continue
        if tag in CLOSES_P:
            stack.close(("p",), FENCE)
        if tag in IMPLIED:
            stack.close(*IMPLIED[tag])
        if tag[0] == "h" and len(tag) == 2 and stack.nodes[-1].tag in ("h1", "h2", "h3", "h4", "h5", "h6") and tag[1].isdigit():
            stack.cut(len(stack.nodes) - 1)
        if tag in ("td", "th") and stack.nodes[-1].tag in ("table", "tbody", "thead", "tfoot"):
            row = Node("tr")
            stack.nodes[-1].kids.append(row)
            stack.push(row)
        if stack.nodes[-1].tag == "head" and tag not in ("title", "meta", "link", "base", "script", "style", "noscript", "template"):
            stack.cut(len(stack.nodes) - 1)
        top = stack.nodes[-1]
        top.kids.append(node)
        if tag in VOID or (m[5].endswith("/") and (tag in ("svg", "path", "math") or stack.last(("svg", "math")))):
            continue
        if tag == "form" and (top.tag in SECTIONS or top.tag in ("table", "tr")):  # holds nothing there
            continue
        if tag in RAW or tag in RAW_TEXT:
            end = re.compile(rf"</{tag}(?=[\s/>])", re.IGNORECASE).search(html, at)
            body = html[at : end.start()] if end else html[at:]
            node.kids.append(unescape(body) if tag in RAW_TEXT else body)
            if not end:
                break
            stop = html.find(">", end.end())
            at = stop + 1 if stop >= 0 else n
            continue
        stack.push(node)
    return root, stack.deepest


# -- visibility


def style(node: Node) -> dict[str, str]:
    raw = node.attrs.get("style")
    if not raw:
        return {}
    return {k.strip().lower(): v.replace("!important", "").strip().lower() for k, _, v in (p.partition(":") for p in raw.split(";"))}


def removed(node: Node) -> bool:
    """Whether the element takes no part in the layout."""
    if node.tag in UNSEEN or (not node.attrs and node.tag != "dialog"):
        return node.tag in UNSEEN or node.tag == "dialog"
    return ("hidden" in node.attrs and node.attrs["hidden"].lower() != "until-found") or (node.tag == "dialog" and "open" not in node.attrs) or style(node).get("display") == "none"


# -- layout


def width(text: str) -> int:
    return len(text) if text.isascii() else sum(0 if unicodedata.combining(c) else 2 if unicodedata.east_asian_width(c) in "WF" else 1 for c in text)


class Canvas:
    """Lines of one block container."""

    def __init__(self):
        self.lines: list[str] = []
        self.now: list[str] = []  # pieces of the line being written
        self.space = False  # white space waits for the next word
        self.blank = False  # a blank line waits for the next line
        self.indent = ""
        self.marker = ""  # stands at the end of the indent of the next line

    def word(self, text: str, preformatted: bool) -> None:
        if preformatted:
            first, *rest = text.split("\n")
            self.now.append(first)
            for line in rest:
                self.line(True)
                self.now.append(line)
            return
        if not text:
            return
        parts = GAPS.split(text) if text.strip(" \t\n\f\r") else None
        if parts is None:
            self.space = self.space or bool(self.now)
            return
        if (self.space or not parts[0]) and self.now:
            self.now.append(" ")
        self.now.append(" ".join(p for p in parts if p).replace("\xa0", " "))
        self.space = not parts[-1]

    def line(self, even_empty: bool = False) -> None:
        """End the line; an empty one is kept only if asked for."""
        text = "".join(self.now).rstrip()
        if text or even_empty:
            if self.blank and self.lines and self.lines[-1]:
                self.lines.append("")
            self.blank = False
            lead = self.indent[: len(self.indent) - len(self.marker)] + self.marker if self.marker else self.indent
            self.lines.append((lead + text).rstrip())
            self.marker = ""
        self.now, self.space = [], False

    def pad(self) -> None:
        """A blank line before what comes next."""
        if self.marker:
            return
        self.blank = True

    def add(self, block: list[str]) -> None:
        for text in block:
            self.now = [text]
            self.line(True)


def render(html: str | None) -> str:
    """All visible text of a page in its layout; empty for null or empty pages."""
    if not html:
        return ""
    root, depth = _parsed(html)
    if sys.getrecursionlimit() < 4 * depth + 1000:  # calls of Python functions take memory, not stack
        sys.setrecursionlimit(4 * depth + 1000)
    canvas = Canvas()
    _walk(root, canvas, True, False)
    canvas.line()
    while canvas.lines and not canvas.lines[-1]:
        canvas.lines.pop()
    return "\n".join(canvas.lines)


def _walk(node: Node, canvas: Canvas, visible: bool, preformatted: bool) -> None:
    tag = node.tag
    if node.attrs:
        css = style(node)
        visible = {"hidden": False, "collapse": False, "visible": True}.get(css.get("visibility", ""), visible)
        block = tag in BLOCK if "display" not in css else css["display"] in ("block", "list-item", "flex", "grid", "flow-root") or (tag in TABLE_TAGS)
        if "white-space" in css:
            preformatted = css["white-space"] in ("pre", "pre-wrap", "break-spaces")
    else:
        block = tag in BLOCK
    if tag == "table":
        canvas.line()
        canvas.pad()
        _table(node, canvas, visible)
        canvas.pad()
        return
    if tag == "br":
        canvas.line(True)
        return
    if tag in ("input", "img"):
        if tag == "input" and visible and node.attrs.get("type", "").lower() in ("submit", "button", "reset"):
            canvas.word(node.attrs.get("value", ""), False)
        return
    if tag == "svg":
        _drawn(node, canvas, visible)
        return
    if tag == "select":
        _select(node, canvas, visible)
        return
    spaced = block and tag in SPACED
    nested = tag in ("ul", "ol", "menu", "dir") and canvas.indent != ""
    if block:
        canvas.line()
        if spaced and not nested:
            canvas.pad()
    if tag == "hr":
        return
    indent = canvas.indent
    preformatted = preformatted or tag in ("pre", "textarea")
    if tag in ("blockquote", "dd") and len(indent) < INDENT:
        canvas.indent = indent + "    "
    if tag == "q" and visible:
        canvas.word("“", True)
    if tag in ("ul", "ol", "menu", "dir"):
        _list(node, canvas, visible, preformatted)
    elif tag == "details" and "open" not in node.attrs:
        for kid in node.kids:
            if isinstance(kid, Node) and kid.tag == "summary":
                _walk(kid, canvas, visible, preformatted)
                break
    else:
        first = True
        for kid in node.kids:
            if isinstance(kid, str):
                if visible:
                    canvas.word(kid.removeprefix("\n") if first and tag == "pre" else kid, preformatted)
            elif not removed(kid):
                _walk(kid, canvas, visible, preformatted)
            first = False
    if tag == "q" and visible:
        canvas.word("”", True)
    if block:
        canvas.line()
        canvas.indent = indent
        if spaced and not nested:
            canvas.pad()


def _drawn(node: Node, canvas: Canvas, visible: bool) -> None:
    """The text elements of a drawing."""
    for kid in node.kids:
        if isinstance(kid, Node) and kid.tag not in NOT_DRAWN and not removed(kid):
            if kid.tag in ("text", "foreignobject"):
                canvas.word(" ", False)
                _walk(kid, canvas, visible, False)
                canvas.word(" ", False)
            else:
                _drawn(kid, canvas, {"hidden": False, "collapse": False, "visible": True}.get(style(kid).get("visibility", ""), visible))


def _inside(node: Node, wanted, through=None) -> Iterator[Node]:
    """The shown elements below that are ``wanted``, in order; others are searched if they are ``through`` kinds (all, if None)."""
    stack = [iter(node.kids)]
    while stack:
        for kid in stack[-1]:
            if isinstance(kid, Node) and not removed(kid):
                if wanted(kid):
                    yield kid
                elif through is None or kid.tag in through:
                    stack.append(iter(kid.kids))
                    break
        else:
            stack.pop()


def _options(node: Node) -> Iterator[Node]:
    return _inside(node, lambda kid: kid.tag == "option")


def _select(node: Node, canvas: Canvas, visible: bool) -> None:
    """A list box shows all its options, a closed menu the selected one, or else the first that is not disabled."""
    options = list(_options(node))
    if "multiple" in node.attrs or _number(node.attrs.get("size", ""), 1) > 1:
        for kid in node.kids:
            if isinstance(kid, Node) and not removed(kid):
                if kid.tag == "optgroup" and visible and kid.attrs.get("label"):
                    canvas.line()
                    canvas.word(kid.attrs["label"], False)
                    canvas.line()
                _walk(kid, canvas, visible, False)
        return
    chosen = [o for o in options if "selected" in o.attrs][-1:] or [o for o in options if "disabled" not in o.attrs][:1] or options[:1]
    for option in chosen:
        canvas.word(" ", False)
        if visible:
            canvas.word(option.attrs.get("label") or " ".join(" ".join(_cell(option, True)).split()), False)
        canvas.word(" ", False)


def _number(text: str, default: int) -> int:
    m = re.match(r"\s*([+-]?\d{1,9})", text)
    return int(m[1]) if m else default


def _list(node: Node, canvas: Canvas, visible: bool, preformatted: bool) -> None:
    items = [k for k in node.kids if isinstance(k, Node) and k.tag == "li" and not removed(k)]
    step = -1 if "reversed" in node.attrs else 1
    number = _number(node.attrs.get("start", ""), len(items) if step < 0 else 1)
    indent = canvas.indent
    for kid in node.kids:
        if isinstance(kid, str):
            if visible:
                canvas.word(kid, preformatted)
        elif kid.tag == "li" and not removed(kid):
            canvas.line()
            if node.tag == "ol":
                number = _number(kid.attrs.get("value", ""), number)
            mark = f"{number}. " if node.tag == "ol" else "- "
            number += step
            canvas.indent = indent + " " * len(mark) if len(indent) < INDENT else indent
            shown = visible and any(not isinstance(k, str) or not k.isspace() for k in kid.kids)
            canvas.marker = mark if shown else ""
            _walk(kid, canvas, visible, preformatted)
            canvas.line()
            canvas.marker = ""
            canvas.indent = indent
        elif not removed(kid):
            _walk(kid, canvas, visible, preformatted)


def _rows(node: Node) -> Iterator[Node]:
    return _inside(node, lambda kid: kid.tag == "tr", SECTIONS)


def _misplaced(node: Node) -> Iterator[Node]:
    """Captions, and what stands between rows, which is shown before the table."""
    return _inside(node, lambda kid: kid.tag not in SECTIONS and kid.tag not in ("tr", "col", "colgroup"), SECTIONS)


def _cell(node: Node, visible: bool) -> list[str]:
    inner = Canvas()
    _walk(node, inner, visible, False)
    inner.line()
    while inner.lines and not inner.lines[-1]:
        inner.lines.pop()
    return inner.lines


def _table(node: Node, canvas: Canvas, visible: bool) -> None:
    """Caption, then rows with columns padded to their widest cell; spanned columns share the room, rowspans leave room."""
    visible = {"hidden": False, "collapse": False, "visible": True}.get(style(node).get("visibility", ""), visible)
    for kid in _misplaced(node):
        _walk(kid, canvas, visible, False)
        canvas.line()
    grid: list[list[tuple[int, int, list[str]]]] = []  # rows of (column, columns, lines)
    below: dict[int, int] = {}  # column -> rows that a cell above still takes
    for row in _rows(node):
        shown = {"hidden": False, "collapse": False, "visible": True}.get(style(row).get("visibility", ""), visible)
        column, cells, down = 0, [], {}
        for kid in row.kids:
            if not isinstance(kid, Node) or removed(kid):
                continue
            while below.get(column, 0):
                column += 1
            span = min(1000, max(1, _number(kid.attrs.get("colspan", ""), 1)))
            cells.append((column, span, _cell(kid, shown)))
            tall = min(65534, _number(kid.attrs.get("rowspan", ""), 1))
            if tall != 1:
                down.update(dict.fromkeys(range(column, column + span), tall - 1 if tall > 0 else 1 << 30))
            column += span
        below = {c: k - 1 for c, k in below.items() if k > 1} | down
        grid.append(cells)
    wide: dict[int, int] = {}
    for cells in grid:
        for column, span, lines in cells:
            if span == 1:
                wide[column] = max([wide.get(column, 0), *map(width, lines)])
    for cells in grid:
        for column, span, lines in cells:
            if span > 1:
                lack = max([0, *map(width, lines)]) - sum(wide.get(c, 0) for c in range(column, column + span)) - 2 * (span - 1)
                if lack > 0:
                    wide[column + span - 1] = wide.get(column + span - 1, 0) + lack
    left, total = {}, 0
    for c in range(max(wide, default=-1) + 1):
        left[c] = total
        total += wide.get(c, 0) + 2 if wide.get(c, 0) else 0
    for cells in grid:
        for i in range(max([0, *(len(lines) for *_, lines in cells)])):
            text, used = [], 0
            for column, _, lines in cells:
                if i < len(lines) and lines[i]:
                    at = left.get(column, total)
                    text.append(" " * max(at - used, 1 if used else at) + lines[i])
                    used = max(at, used + (1 if used else 0)) + width(lines[i])
            canvas.now = ["".join(text)]
            canvas.line(True)


# -- the operator


def _batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for part in slices(batches):
        yield pa.RecordBatch.from_arrays([part.column(0), pa.array([render(h) for h in part.column(1).to_pylist()], pa.string())], ["page_id", "text"])


def extracted(pages: DataFrame, id_col: str = "page_id", html_col: str = "html") -> DataFrame:
    """``page_id, text`` of each page, one narrow pass over whole pages.

    Null and empty pages give an empty text, null and repeated ids keep their rows, other columns are not read, and an
    empty table gives no rows.  Any input gives a tree of any depth; beyond 400 columns
    nothing is moved further in."""
    prepare(pages.sparkSession)
    return pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(html_col).cast("string").alias("html")).mapInArrow(_batches, "page_id long, text string")
