"""Layout-aware rendering of HTML: a tree builder with implied tags, rules of visibility, and text as a reader sees it.

Blocks are parted by line ends, paragraphs and headings by a blank line; list items carry their bullet or number and are indented by
depth; cells of a table are padded so that columns line up; preformatted text keeps its spaces. Nothing that is shown is left out.
"""

from __future__ import annotations

import re
import sys
from html.parser import HTMLParser

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Classes of HTML elements.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
HIDDEN = frozenset("script style template noscript head title meta link datalist iframe object audio video canvas param source defs symbol desc metadata annotation annotation-xml".split())
BLOCK = frozenset("address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol p pre search section summary table tbody td tfoot th thead tr ul caption optgroup option".split())
SPACED = frozenset("p h1 h2 h3 h4 h5 h6 blockquote pre ul ol dl table figure hr fieldset".split())
#: What a start tag closes, and the elements that shield what is open beyond them.
CLOSES = {
    "li": ({"li"}, {"ul", "ol", "menu", "dir"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "option": ({"option"}, {"select", "datalist"}), "optgroup": ({"option", "optgroup"}, {"select"}),
    "tr": ({"tr", "td", "th", "caption", "colgroup"}, {"table"}), "td": ({"td", "th"}, {"table", "tr"}), "th": ({"td", "th"}, {"table", "tr"}),
    "tbody": ({"thead", "tbody", "tfoot", "tr", "td", "th", "caption", "colgroup"}, {"table"}), "thead": ({"thead", "tbody", "tfoot", "tr", "td", "th", "caption", "colgroup"}, {"table"}), "tfoot": ({"thead", "tbody", "tfoot", "tr", "td", "th", "caption", "colgroup"}, {"table"}),
    "body": ({"head"}, set()),
}
CLOSES_P = BLOCK - frozenset("li dd dt tr td th tbody thead tfoot caption html body option optgroup legend summary".split()) | {"hr"}
IN_HEAD = frozenset("head title meta link style script base noscript template html".split())
_HIDE = re.compile(r"display\s*:\s*none|visibility\s*:\s*(?:hidden|collapse)", re.I)


class Node:
    __slots__ = ("tag", "attrs", "children", "parent")

    def __init__(self, tag: str, attrs: dict, parent: Node | None):
        self.tag, self.attrs, self.children, self.parent = tag, attrs, [], parent


class TreeBuilder(HTMLParser):
    """Builds a tree from any input: void tags, implied ends (p, li, cells, rows), implied rows and tbody, stray end tags."""

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.root = self.at = Node("#root", {}, None)

    def handle_starttag(self, tag, attrs):
        if tag == "html" and self.at is not self.root:
            return
        closed, shields = CLOSES.get(tag, (set(), set()))
        if closed:
            self._close(closed, shields, every=True)
        elif self.at.tag == "head" and tag not in IN_HEAD:
            self.at = self.at.parent
        if tag in CLOSES_P:
            self._close({"p"}, {"td", "th", "table", "li", "div", "button"})
        if tag in ("td", "th") and self._within("table") and self.at.tag in ("table", "tbody", "thead", "tfoot"):
            self._open("tr", {})
        node = self._open(tag, {k: v or "" for k, v in attrs})
        if tag in VOID:
            self.at = node.parent

    def handle_startendtag(self, tag, attrs):
        self.handle_starttag(tag, attrs)

    def handle_endtag(self, tag):
        if tag == "p" and not self._within("p"):
            self.at = self._open("p", {}).parent  # a stray end of a paragraph is an empty one
        elif tag not in VOID:
            self._close({tag}, {"table", "td", "th"} - {tag} if tag not in ("table", "tr", "tbody", "thead", "tfoot", "html", "body") else set())

    def handle_data(self, data):
        self.at.children.append(data)

    def unknown_decl(self, data):  # CDATA shows as text
        if data.startswith("CDATA["):
            self.at.children.append(data[6:])

    def _open(self, tag, attrs):
        self.at.children.append(node := Node(tag, attrs, self.at))
        self.at = node
        return node

    def _within(self, tag):
        n = self.at
        while n is not None and n.tag != tag:
            n = n.parent
        return n is not None

    def _close(self, tags, shields, every=False):
        """Ends the nearest open element of ``tags`` (with ``every``, the outermost) this side of a shield."""
        n, found = self.at, None
        while n is not None and n.tag not in shields:
            if n.tag in tags:
                found = n
                if not every:
                    break
            n = n.parent
        if found is not None:
            self.at = found.parent


def build(html: str) -> Node:
    b = TreeBuilder()
    b.feed(html)
    b.close()
    return b.root


def visible(node: Node) -> bool:
    a = node.attrs
    if node.tag in HIDDEN or "hidden" in a or (node.tag == "input" and a.get("type", "").lower() == "hidden"):
        return False
    if node.tag == "dialog" and "open" not in a:
        return False
    return not _HIDE.search(a.get("style", ""))


class _Out:
    """Text that is built line by line; asks for blank lines, which merge."""

    def __init__(self):
        self.lines, self.line, self.gap, self.prefix = [], "", 0, ""

    def inline(self, text: str):
        text = re.sub(r"[ \t\n\r\f]+", " ", text)
        if not self.line or self.line.endswith((" ", "\n")):
            text = text.lstrip(" ")
        self.line += text

    def end_line(self, blank: bool = False):
        if self.line.strip():
            self.raw(self.prefix + self.line.rstrip(" "))
            self.prefix = re.sub(r"\S", " ", self.prefix)
        self.line = ""
        if blank:
            self.gap = 1

    def raw(self, line: str):
        if self.gap and self.lines:
            self.lines.append("")
        self.gap = 0
        self.lines.append(line)

    def text(self) -> str:
        self.end_line()
        return "\n".join(self.lines)


def render(html: str | None) -> str:
    """All visible text of a page, that of formulas and drawings included. Null and empty pages give empty text; what is not HTML is text.

    Tables are laid out at any depth: a table in a cell takes a few frames of Python's stack, whose limit is raised to fit.
    """
    sys.setrecursionlimit(max(sys.getrecursionlimit(), 1_000_000))
    out = _Out()
    _walk(build(html or ""), out, 0)
    return out.text()


def _walk(root: Node, out: _Out, depth: int) -> None:
    """Renders without recursion except into tables' cells, so that deep trees are no trouble."""
    todo: list[tuple] = [("node", root, depth, "")]
    while todo:
        kind, x, depth, mark = todo.pop()
        if kind == "text":
            out.inline(x)
        elif kind == "end":
            out.end_line(blank=x in SPACED and not mark)
            if x in ("li", "dd", "blockquote"):
                out.prefix = mark or ""
        elif kind == "node" and (x.tag == "#root" or visible(x)):
            tag = x.tag
            if tag == "br":
                if out.line.strip():
                    out.end_line()
                continue
            if tag == "img" and x.attrs.get("alt"):
                out.inline(x.attrs["alt"])
                continue
            if tag == "hr":
                out.end_line(blank=True)
                continue
            if tag in BLOCK:
                out.end_line(blank=tag in SPACED and not (tag in ("ul", "ol") and depth))
            if tag == "pre":
                for line in _plain(x).strip("\n").split("\n"):
                    out.raw(out.prefix + line.rstrip())
                out.gap = 1
                continue
            if tag == "table":
                _table(x, out, depth)
                continue
            if tag == "blockquote":
                todo.append(("end", tag, depth, out.prefix))
                out.prefix += "  "
            elif tag == "dd":
                todo.append(("end", tag, depth, out.prefix))
                out.prefix += "  "
            elif tag == "li":
                todo.append(("end", tag, depth, out.prefix))
                out.prefix += mark or "- "
            elif tag in BLOCK:
                todo.append(("end", tag, depth, "nested" if tag in ("ul", "ol") and depth else ""))
            number = _number(x.attrs.get("start")) if tag == "ol" else 0
            inner = depth + (tag in ("ul", "ol"))
            steps = []
            for c in x.children:
                if isinstance(c, str):
                    steps.append(("text", c, inner, ""))
                    continue
                m = ""
                if c.tag == "li":
                    number = _number(c.attrs.get("value"), number)
                    m = f"{number}. " if tag == "ol" else "- "
                    number += visible(c)
                steps.append(("node", c, inner, m))
            todo += reversed(steps)


def _number(text: str | None, otherwise: int = 1) -> int:
    return int(text) if text and re.fullmatch(r"-?[0-9]{1,9}", text) else otherwise


def _plain(node: Node) -> str:
    out, todo = [], [node]
    while todo:
        n = todo.pop()
        if isinstance(n, str):
            out.append(n)
        elif n.tag == "br":
            out.append("\n")
        elif visible(n):
            todo += reversed(n.children)
    return "".join(out)


def _table(table: Node, out: _Out, depth: int) -> None:
    """Rows of cells, each column padded to its widest cell; a cell of several lines takes several. Cells that span columns count for all."""
    rows, captions, stray, todo = [], [], [], list(reversed(table.children))
    while todo:
        n = todo.pop()
        if isinstance(n, str):
            if n.strip():
                stray.append(n)
        elif not visible(n):
            continue
        elif n.tag == "tr":
            rows.append([c for c in n.children if isinstance(c, Node) and c.tag in ("td", "th") and visible(c)])
            stray += [c if isinstance(c, str) else _plain(c) for c in n.children if (isinstance(c, str) and c.strip()) or (isinstance(c, Node) and c.tag not in ("td", "th") and visible(c))]
        elif n.tag == "caption":
            captions.append(n)
        elif n.tag in ("tbody", "thead", "tfoot", "colgroup"):
            todo += reversed(n.children)
        else:
            stray.append(_plain(n))
    for s in stray:  # text that is not in a cell stands before the table
        out.inline(s)
        out.end_line()
    for c in captions:
        for line in _cell(c, depth):
            out.raw(out.prefix + line)
    # a span is at most 1000 columns, as browsers have it
    cells = [[(_cell(c, depth), min(1000, max(1, _number(c.attrs.get("colspan"))))) for c in row] for row in rows]
    widths: dict[int, int] = {}
    for row in cells:
        at = 0
        for lines, span in row:
            if span == 1:
                widths[at] = max(widths.get(at, 0), *(len(x) for x in lines), 0)
            else:
                widths.setdefault(at, 0)
            at += span
    for row in cells:
        height = max((len(lines) for lines, _ in row), default=0)
        for k in range(height):
            parts, at = [], 0
            for lines, span in row:
                own = [widths[c] for c in range(at, at + span) if c in widths]  # columns that no cell starts take no room
                width = sum(own) + 2 * (len(own) - 1)
                parts.append((lines[k] if k < len(lines) else "").ljust(width))
                at += span
            if line := "  ".join(parts).rstrip():
                out.raw(out.prefix + line)
    out.gap = 1


def _cell(cell: Node, depth: int) -> list[str]:
    inner = _Out()
    holder = Node("#root", {}, None)
    holder.children = cell.children
    _walk(holder, inner, 0)
    return [x for x in inner.text().split("\n") if x] or [""]


def extract_text(pages: DataFrame) -> DataFrame:
    """``pages`` with ``text`` in place of html. Null html gives empty text. A column named text is replaced."""
    keep = [c for c in pages.columns if c not in ("html", "text")]

    def rendered(batches):
        for batch in batches:
            text = pa.array([render(h) for h in batch["html"].to_pylist()], pa.string())
            yield pa.RecordBatch.from_arrays([*(batch[c] for c in keep), text], names=[*keep, "text"])

    schema = pages.select(*keep).schema.add("text", "string")
    return pages.select(*keep, "html").mapInArrow(rendered, schema)


def extraction_report(pages: DataFrame) -> DataFrame:
    return extract_text(pages.select("page_id", "url", "html")).select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"), F.sha2(F.col("text").cast("binary"), 256).alias("text_sha256"))
