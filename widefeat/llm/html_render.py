"""Operator 6: HTML to text as a page lays it out.

A tokenizer (tags, comments, raw text, character references) feeds a tree builder that opens and closes implied
tags; a renderer walks the tree: invisible elements are left out, blocks stand on lines of their own with blank lines
around paragraphs and headings, list items carry bullets or numbers, preformatted text keeps its blanks, and the
cells of a table are padded to common column widths.

Edge cases: null, empty and tag-less input give null, "" and the plain text; unclosed tags, stray end tags, broken
attributes and content of tables outside cells are repaired, never fatal; nesting of any depth keeps its text, lists and
tables within more than `DEEPEST` others are laid out as blocks; repeated rows are rendered each.
"""

from __future__ import annotations

import html
import re
import unicodedata
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ship, text_slices

# Element classes of the HTML standard.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style xmp iframe noembed noframes plaintext".split())
ESCAPABLE_RAW = frozenset("title textarea".split())
INVISIBLE = frozenset("head script style template noscript iframe noembed noframes object audio video canvas datalist title meta link base param source track area annotation annotation-xml".split())
BLOCK = frozenset("address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol p pre search section summary table caption tbody thead tfoot tr ul option optgroup".split())
SPACED = frozenset("p h1 h2 h3 h4 h5 h6 blockquote pre ul ol dl table figure hr".split())
CLOSES_P = BLOCK - frozenset("body html tbody thead tfoot tr caption legend option optgroup".split())
HEAD_ONLY = frozenset("base link meta script style template title noscript".split())
DEEPEST = 200
TABLE_PARTS = frozenset("table tbody thead tfoot tr colgroup".split())
IN_TABLE = frozenset("caption colgroup col tbody thead tfoot tr td th script style template".split())
ROW_PARTS = frozenset("tbody thead tfoot tr td th".split())
SVG_TEXT = frozenset("text foreignobject".split())
SVG_HIDDEN = frozenset("defs desc metadata symbol clippath mask".split())

# Start tags that end an open element of the same group, unless a container lies between.
IMPLIED_END = {
    "li": ({"li"}, {"ul", "ol", "menu", "dir"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}),
    "option": ({"option"}, {"select", "datalist"}), "optgroup": ({"option", "optgroup"}, {"select"}),
    "td": ({"td", "th"}, {"table"}), "th": ({"td", "th"}, {"table"}), "tr": ({"td", "th", "tr", "caption"}, {"table"}),
    "tbody": ({"td", "th", "tr", "tbody", "thead", "tfoot", "caption"}, {"table"}), "thead": ({"td", "th", "tr", "tbody", "thead", "tfoot", "caption"}, {"table"}),
    "tfoot": ({"td", "th", "tr", "tbody", "thead", "tfoot", "caption"}, {"table"}), "caption": ({"caption"}, {"table"}),
    "rt": ({"rt", "rp"}, {"ruby"}), "rp": ({"rt", "rp"}, {"ruby"}),
}

TAG_NAME = re.compile(r"<(/?)([a-zA-Z][^\s/>]*)")
TAG_STOP = re.compile(r"[>\"']")
ATTRIBUTE = re.compile(r"([^\s=/>\"']+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?")
HIDDEN_STYLE = re.compile(r"(?:^|;)\s*(?:display\s*:\s*none|visibility\s*:\s*(?:hidden|collapse))\b", re.I)
BLANKS = re.compile(r"[ \t\n\r\f]+")


@dataclass(eq=False)
class Node:
    name: str
    attributes: dict[str, str] = field(default_factory=dict)
    children: list[Node | str] = field(default_factory=list)


def tokens(source: str) -> Iterator[tuple[str, str, str]]:
    """(kind, name or text, attributes): kinds are text, open, close."""
    at, n = 0, len(source)
    last, doomed = {c: source.rfind(c) for c in ">\"'"}, set()

    def tag_end(at: int) -> int:
        """Where the tag's > stands outside quotes, else the first >; a quote that led nowhere isn't followed again."""
        first, tried = at, []
        while m := TAG_STOP.search(source, at):
            if m[0] == ">":
                return m.start()
            if m.start() in doomed or last[m[0]] <= m.start():
                break
            tried.append(m.start())
            at = source.find(m[0], m.end()) + 1
        doomed.update(tried)
        return source.find(">", first)

    while at < n:
        start = source.find("<", at)
        if start < 0:
            yield "text", source[at:], ""
            return
        if start > at:
            yield "text", source[at:start], ""
        if source.startswith("<!--", start):
            end = source.find("-->", start + 4)
            at = n if end < 0 else end + 3
            continue
        if source[start + 1 : start + 2] in ("!", "?"):
            end = source.find(">", start)
            at = n if end < 0 else end + 1
            continue
        tag = TAG_NAME.match(source, start) if start < last[">"] else None
        if not tag:
            yield "text", "<", ""
            at = start + 1
            continue
        name, stop = tag[2].lower(), tag_end(tag.end())
        at = stop + 1
        yield "close" if tag[1] else "open", name, source[tag.end() : stop]
        if not tag[1] and name in RAW | ESCAPABLE_RAW:
            end = re.compile(rf"</{re.escape(name)}(?=[\s/>])", re.I).search(source, at)
            stop = end.start() if end else n
            yield ("text" if name in ESCAPABLE_RAW else "raw"), source[at:stop], ""
            at = stop


def attributes(text: str) -> dict[str, str]:
    out: dict[str, str] = {}
    for m in ATTRIBUTE.finditer(text):
        out.setdefault(m[1].lower(), html.unescape(m[2] or m[3] or m[4] or ""))
    return out


def build_tree(source: str) -> Node:
    """The document's tree; html, head, body, tbody and tr come into being where they are implied.

    What stands in a table outside cells and captions moves before the table, as in a browser. Where elements of a name
    are open is kept by name, so no step walks the stack and any depth is kept.
    """
    root, body = Node("html"), Node("body")
    stack = [root]
    places: dict[str, list[int]] = {}

    def top(names: Iterable[str]) -> int:
        return max((places[x][-1] for x in names if places.get(x)), default=0)

    def opened(node: Node) -> None:
        places.setdefault(node.name, []).append(len(stack))
        stack.append(node)

    def cut(at: int) -> None:
        while len(stack) > at:
            places[stack.pop().name].pop()

    def in_body() -> None:
        if not started():
            cut(1)
            root.children.append(body)
            opened(body)

    def started() -> bool:
        return bool(root.children) and root.children[-1] is body

    def misplaced() -> bool:
        return stack[-1].name in TABLE_PARTS and bool(places.get("table"))

    def add(child: Node | str, move: bool) -> None:
        if move:
            beside = stack[places["table"][-1] - 1].children
            beside.insert(len(beside) - 1, child)  # an open table is its parent's last child
        else:
            stack[-1].children.append(child)

    def push(name: str, found: dict[str, str], move: bool = False) -> None:
        node = Node(name, found)
        add(node, move)
        if name not in VOID:
            opened(node)

    def end(names: set[str], barrier: set[str]) -> None:
        lowest = top(names)
        if lowest > max(top(barrier), top(("body",))):
            while lowest > 1 and stack[lowest - 1].name in names:
                lowest -= 1
            cut(lowest)

    for kind, text, rest in tokens(source):
        if kind in ("text", "raw"):
            if text.strip() and stack[-1] in (root,):
                in_body()
            if stack[-1] is not root:
                add(html.unescape(text) if kind == "text" else text, bool(text.strip()) and misplaced())
        elif kind == "close":
            if text in ("html", "body"):
                continue
            if text == "br":
                push("br", {}, misplaced())
                continue
            at = top((text,))
            if at and (text in ("tr", "table", "tbody", "thead", "tfoot") or at >= top(("td", "th", "table", "body"))):
                cut(at)
        elif text == "html":
            root.attributes |= attributes(rest)
        elif text == "head":
            if stack == [root] and not started():
                push("head", {})
        elif text == "body":
            in_body()
            body.attributes |= attributes(rest)
        else:
            if not started() and text not in HEAD_ONLY:
                in_body()
            if text in CLOSES_P:
                end({"p"}, {"table", "td", "th", "button", "object"})
            if text[0] == "h" and text[1:] in "123456" and stack[-1].name[0] == "h" and stack[-1].name[1:].isdigit():
                cut(len(stack) - 1)
            if text in IMPLIED_END:
                end(*IMPLIED_END[text])
            if text in ROW_PARTS and places.get("table"):
                part = top(("table", "tbody", "thead", "tfoot", "tr"))
                if part > top(("td", "th")):
                    cut(part + 1)  # wrappers moved before the table end at its next row or cell
            if text == "table" and misplaced():
                cut(places["table"][-1])
            if text in ("td", "th") and stack[-1].name in ("table", "tbody", "thead", "tfoot"):
                push("tr", {})
            if text == "form" and misplaced():
                add(Node(text, attributes(rest)), False)  # holds nothing here: the cells after it are the row's
            else:
                push(text, attributes(rest), text not in IN_TABLE and misplaced())
    return root


def visible(node: Node) -> bool:
    a = node.attributes
    if node.name in INVISIBLE or "hidden" in a or a.get("aria-hidden", "").strip().lower() == "true":
        return False
    if node.name == "input" and a.get("type", "").lower() != "submit":
        return False
    return not (node.name == "dialog" and "open" not in a) and not HIDDEN_STYLE.search(a.get("style", ""))


def width(text: str) -> int:
    """Columns that a text takes; wide East Asian characters take two, combining marks none."""
    return len(text) if text.isascii() else sum(0 if unicodedata.combining(c) else 2 if unicodedata.east_asian_width(c) in "WF" else 1 for c in text)


class Writer:
    """Lines of text with collapsed blanks and at most one empty line between blocks."""

    def __init__(self) -> None:
        self.lines: list[str] = []
        self.line = ""
        self.gap = False

    def text(self, text: str) -> None:
        text = BLANKS.sub(" ", text)
        if not self.line or self.line.endswith(" "):
            text = text.lstrip(" ")
        if text:
            self._gap()
            self.line += text

    def _gap(self) -> None:
        if self.gap and self.lines and self.lines[-1]:
            self.lines.append("")
        self.gap = False

    def literal(self, text: str) -> None:
        self._gap()
        first, *more = text.split("\n")
        self.line += first
        for x in more:
            self.lines.append(self.line)
            self.line = x

    def newline(self) -> None:
        self.lines.append(self.line.rstrip(" "))
        self.line = ""

    def block(self, spaced: bool) -> None:
        if self.line.strip(" "):
            self.newline()
        self.line = ""
        self.gap |= spaced

    def value(self) -> str:
        self.block(False)
        return "\n".join(self.lines).strip("\n")


def render_children(node: Node, out: Writer, depth: int) -> Iterator[Iterator]:
    item = 1
    if node.name == "ol" and re.fullmatch(r"\s*-?\d{1,9}\s*", node.attributes.get("start", "")):
        item = int(node.attributes["start"])
    for child in node.children:
        if isinstance(child, str):
            if node.name not in ("table", "tbody", "thead", "tfoot", "tr", "ul", "ol") or child.strip():
                out.text(child)
        elif child.name == "li" and visible(child):
            mark = f"{item}. " if node.name == "ol" else "- "
            item += node.name == "ol"
            yield render_item(child, out, depth, mark)
        else:
            yield render(child, out, depth)


def render_item(node: Node, out: Writer, depth: int, mark: str) -> Iterator[Iterator]:
    if depth >= DEEPEST:
        out.block(False)
        out.text(mark)
        yield render_children(node, out, depth)
        out.block(False)
        return
    inner = Writer()
    yield render_children(node, inner, depth + 1)
    out.block(False)
    first, *more = inner.value().split("\n")
    out.literal("\n".join([f"{mark}{first}".rstrip(), *(f"{' ' * len(mark)}{x}" if x else "" for x in more)]))
    out.block(False)


def table_rows(node: Node) -> Iterator[Node]:
    for child in node.children:
        if isinstance(child, Node) and visible(child):
            if child.name == "tr":
                yield child
            elif child.name in ("tbody", "thead", "tfoot"):
                yield from table_rows(child)


def render_table(node: Node, out: Writer, depth: int) -> Iterator[Iterator]:
    for child in node.children:
        if isinstance(child, Node) and child.name not in ("tr", "tbody", "thead", "tfoot", "colgroup", "col"):
            yield render(child, out, depth)  # captions
            out.block(False)
    grid: list[list[list[str]]] = []
    held: dict[int, int] = {}
    for row in table_rows(node):
        cells: list[list[str]] = []
        for cell in row.children:
            if not isinstance(cell, Node) or cell.name not in ("td", "th") or not visible(cell):
                continue
            if depth >= DEEPEST:
                out.block(False)
                yield render_children(cell, out, depth)
                out.block(False)
                continue
            while held.get(len(cells), 0):
                held[len(cells)] -= 1
                cells.append([""])
            inner = Writer()
            yield render_children(cell, inner, depth + 1)
            spans = [int(s) if re.fullmatch(r"\d{1,3}", s := cell.attributes.get(k, "1").strip()) else 1 for k in ("colspan", "rowspan")]
            for k in range(max(1, min(spans[0], 100))):
                if spans[1] > 1:
                    held[len(cells)] = spans[1] - 1
                cells.append(inner.value().split("\n") if not k else [""])
        grid.append(cells)
    widths: dict[int, int] = {}
    for cells in grid:
        for k, lines in enumerate(cells):
            widths[k] = max(widths.get(k, 0), *map(width, lines))
    for cells in grid:
        for i in range(max(map(len, cells), default=0)):
            parts = [lines[i] if i < len(lines) else "" for lines in cells]
            out.literal("  ".join(p + " " * (widths[k] - width(p)) for k, p in enumerate(parts)).rstrip())
            out.block(False)


def render(node: Node, out: Writer, depth: int = 0) -> Iterator[Iterator]:
    """Write a node; what stands below is yielded to `drive`, so depth takes no call stack."""
    name = node.name
    if not visible(node):
        return
    if name == "br":
        out.newline()
    elif name == "img":
        out.text(node.attributes.get("alt", ""))
    elif name == "input":
        out.text(node.attributes.get("value", ""))
    elif name == "pre":
        out.block(True)
        inner: list[str] = []
        todo: list[Node | str] = [node]
        while todo:
            x = todo.pop()
            if isinstance(x, str):
                inner.append(x)
            elif x.name == "br":
                inner.append("\n")
            elif visible(x):
                todo += reversed(x.children)
        out.literal("".join(inner).removeprefix("\n").rstrip())
        out.block(True)
    else:
        block, spaced = name in BLOCK, name in SPACED and not (name in ("ul", "ol", "dl") and depth)
        if block:
            out.block(spaced)
        if name == "optgroup":
            out.text(node.attributes.get("label", ""))
            out.block(False)
        if name == "table":
            yield render_table(node, out, depth)
        elif name == "svg":
            yield render_svg(node, out, depth)
        else:
            yield render_children(node, out, depth)
        if block:
            out.block(spaced)


def render_svg(node: Node, out: Writer, depth: int) -> Iterator[Iterator]:
    todo = list(reversed(node.children))
    while todo:
        x = todo.pop()
        if isinstance(x, Node) and x.name not in SVG_HIDDEN and visible(x):
            if x.name in SVG_TEXT:
                yield render(x, out, depth)
                out.text(" ")
            else:
                todo += reversed(x.children)


def drive(first: Iterator[Iterator]) -> None:
    stack = [first]
    while stack:
        below = next(stack[-1], None)
        if below is None:
            stack.pop()
        else:
            stack.append(below)


def html_to_text(source: str | None) -> str | None:
    """All visible text of a page, laid out."""
    if source is None:
        return None
    out = Writer()
    drive(render(build_tree(source.replace("\r\n", "\n").replace("\0", "")), out))
    return out.value()


def extract_text(pages: DataFrame, column: str = "html", into: str = "text") -> DataFrame:
    """page_id, url and the rendered text of every page."""
    ship(pages.sparkSession)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in (p for b in batches for p in text_slices(b, "html")):
            texts = pa.array([html_to_text(x) for x in part.column("html").to_pylist()], pa.string())
            yield pa.RecordBatch.from_arrays([part.column("page_id"), part.column("url"), texts], ["page_id", "url", into])

    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col(column).cast("string").alias("html"))
    return rows.mapInArrow(run, f"page_id long, url string, {into} string")
