"""Visible text of HTML pages, laid out: a tolerant tree builder, visibility rules, and a block renderer.

The builder supplies tags that authors leave out (paragraph, list, table and document parts end and begin where the
standard implies it), the renderer walks the tree and keeps paragraphs apart, numbers and indents lists,
and pads table cells to columns.  Nothing visible is dropped as boilerplate.
"""

from __future__ import annotations

import re
import sys
from collections import Counter
from collections.abc import Iterator
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Calls of Python code take no room on the machine's stack, so trees of any depth that a page can hold may be walked.
FRAMES = 1 << 28

_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_RAW = frozenset("script style xmp iframe noembed noframes textarea title".split())
_UNSEEN = frozenset("head script style template noscript iframe noembed noframes title object audio video canvas datalist".split())
#: Parts of drawings and formulas that are not drawn.
_METADATA = frozenset("annotation annotation-xml defs desc metadata symbol".split())
_BLOCK = frozenset(
    "address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html "
    "legend li main menu nav ol optgroup option p pre search section summary table ul".split()
)
#: Blocks with a blank line around them.
_SPACED = frozenset("blockquote dl fieldset figure h1 h2 h3 h4 h5 h6 ol p pre table ul".split())
_ENDS_P = frozenset(
    "address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre search section summary table ul li dd dt".split()
)
_HEAD_PARTS = frozenset("base link meta title style script template noscript head".split())
_HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
_SECTIONS = frozenset("thead tbody tfoot".split())
#: A start tag ends open elements of the first set, looking no further than the second.
_IMPLIED = {
    "li": (frozenset(["li"]), frozenset("ul ol menu dir table td th".split())),
    "dt": (frozenset("dt dd".split()), frozenset("dl table td th".split())),
    "dd": (frozenset("dt dd".split()), frozenset("dl table td th".split())),
    "option": (frozenset(["option"]), frozenset("select datalist optgroup".split())),
    "optgroup": (frozenset("option optgroup".split()), frozenset(["select"])),
    "tr": (frozenset(["tr"]), frozenset(["table"])),
    "td": (frozenset("td th".split()), frozenset("tr table".split())),
    "th": (frozenset("td th".split()), frozenset("tr table".split())),
    "thead": (_SECTIONS, frozenset(["table"])),
    "tbody": (_SECTIONS, frozenset(["table"])),
    "tfoot": (_SECTIONS, frozenset(["table"])),
    "caption": (frozenset("caption colgroup".split()), frozenset(["table"])),
}
_SCOPE = frozenset("html table td th caption template".split())

_TOKEN = re.compile(r"<!--(?:.*?-->|>|->|.*\Z)|<!\[CDATA\[.*?\]\]>|<(?P<end>/?)(?P<name>[a-zA-Z][^\s/>]*)|<[!?/][^>]*>", re.S)
#: The rest of a tag with quoted values in it; without one in reach, a tag ends at the next angle.
_TAG_END = re.compile(r"(?:[^>\"']+|\"[^\"]*\"|'[^']*')*+>")
_REACH = 64 << 10
#: The standard's limits on how many columns and rows a cell spans (fixed values).
_SPANS = {"colspan": 1000, "rowspan": 65534}
_ATTR = re.compile(r"([^\s=>/\"']+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?")
_RULE = re.compile(r"([^{}]+)\{([^{}]*)\}")
_HIDING = re.compile(r"(?:^|;)\s*(?:display\s*:\s*none|visibility\s*:\s*(?:hidden|collapse))\b", re.I)
_BLANKS = re.compile(r"[ \t\n\r\f]+")


class Node:
    __slots__ = ("attrs", "children", "depth", "name")

    def __init__(self, name: str, attrs: dict[str, str], depth: int):
        self.name, self.attrs, self.depth = name, attrs, depth
        self.children: list[Node | str] = []


class Builder:
    """A tree from any string; rules of hiding in style sheets are collected on the way."""

    def __init__(self, html: str):
        self.root = Node("html", {}, 0)
        self.body: Node | None = None
        self.stack = [self.root]
        self.hidden: set[str] = set()
        self.open: Counter[str] = Counter()
        at, n = 0, len(html)
        while at < n:
            m = _TOKEN.search(html, at)
            if m is None:
                self.text(html[at:])
                break
            if m.start() > at:
                self.text(html[at : m.start()])
            at = m.end()
            name = m["name"]
            if name is not None:
                tail = _TAG_END.match(html, at, min(n, at + _REACH))
                stop = tail.end() if tail else html.find(">", at) + 1
                if not stop:
                    break  # a tag that never ends swallows the rest, as in browsers
                inside, at = html[at : stop - 1], stop
            if name is None:
                if m[0].startswith("<![CDATA["):
                    self.text(m[0][9:-3], raw=True)
                continue
            name = name.lower()
            if m["end"]:
                self.end(name)
                continue
            attrs = {a[1].lower(): unescape(a[2] or a[3] or a[4] or "") for a in reversed(list(_ATTR.finditer(inside)))} if inside else {}
            self.start(name, attrs)
            if name in _RAW:
                close = re.compile(rf"</{re.escape(name)}(?=[\s/>])", re.I).search(html, at)
                inner = html[at : close.start() if close else n]
                if name == "style":
                    self.rules(inner)
                elif name in ("textarea", "title"):
                    self.text(inner)
                elif name == "xmp":
                    self.text(inner, raw=True)
                at = close.start() if close else n
                if not close:
                    self.end(name)

    def rules(self, sheet: str) -> None:
        for selectors, body in _RULE.findall(re.sub(r"/\*.*?\*/", "", sheet, flags=re.S)):
            if _HIDING.search(body):
                self.hidden.update(s for s in (x.strip() for x in selectors.split(",")) if re.fullmatch(r"[.#]?[\w-]+", s))

    def text(self, data: str, raw: bool = False) -> None:
        data = data if raw or "&" not in data else unescape(data)
        top = self.stack[-1]
        if not data.strip(" \t\n\r\f"):
            if top.name in ("html", "table", "tr", *_SECTIONS):
                return
        elif top.name == "html" or (top.name == "head" and top is not self.body):
            self.into_body()
        self.stack[-1].children.append(data)

    def into_body(self) -> None:
        """Text or flow content outside a body opens one, or goes back into the one there was."""
        while len(self.stack) > 1 and self.stack[-1].name in ("head", "html"):
            self.cut(len(self.stack) - 1)
        if self.stack[-1].name == "html":
            if self.body is None:
                self.body = self.push("body", {})
            else:
                self.stack.append(self.body)
                self.open["body"] += 1

    def cut(self, i: int) -> None:
        """End the open elements from the i-th on."""
        self.open.subtract(node.name for node in self.stack[i:])
        del self.stack[i:]

    def push(self, name: str, attrs: dict[str, str]) -> Node:
        top = self.stack[-1]
        node = Node(name, attrs, top.depth + 1)
        top.children.append(node)
        self.stack.append(node)
        self.open[name] += 1
        return node

    def close(self, names: frozenset[str], until: frozenset[str]) -> None:
        if not any(self.open[name] > 0 for name in names):
            return
        for i in range(len(self.stack) - 1, 0, -1):
            if self.stack[i].name in names:
                self.cut(i)
                return
            if self.stack[i].name in until:
                return

    def start(self, name: str, attrs: dict[str, str]) -> None:
        if name == "html":
            self.root.attrs = {**attrs, **self.root.attrs}
            return
        if name == "body":
            if self.body is None:
                self.cut(1)
                self.body = self.push("body", attrs)
            return
        if name == "head":
            if self.body is None and self.stack[-1].name == "html":
                self.push("head", attrs)
            return
        if name not in _HEAD_PARTS and self.stack[-1].name in ("html", "head"):
            self.into_body()
        elif name in _HEAD_PARTS and self.stack[-1].name == "html" and self.body is not None:
            self.into_body()
        if name in _IMPLIED:
            self.close(*_IMPLIED[name])
        if name in _ENDS_P:
            self.close(frozenset(["p"]), _SCOPE | frozenset(["button"]))
        if name in _HEADINGS and self.stack[-1].name in _HEADINGS:
            self.cut(len(self.stack) - 1)
        if name in ("td", "th") and self.stack[-1].name in ("table", *_SECTIONS):
            self.push("tr", {})
        if name in _VOID:
            self.stack[-1].children.append(Node(name, attrs, self.stack[-1].depth + 1))
        else:
            self.push(name, attrs)

    def end(self, name: str) -> None:
        if name in ("html", "body"):
            return
        if name == "br":
            self.start("br", {})
            return
        barrier = frozenset(["table"]) if name in ("tr", "td", "th", *_SECTIONS) else frozenset() if name == "table" else _SCOPE - {name}
        alike = _HEADINGS if name in _HEADINGS else frozenset([name])
        for i in range(len(self.stack) - 1, 0, -1) if any(self.open[a] > 0 for a in alike) else ():
            node = self.stack[i]
            if node.name in alike:
                self.cut(i)
                return
            if node.name in barrier:
                break
        if name == "p":  # an end without a start is an empty paragraph
            self.start("p", {})
            self.close(frozenset(["p"]), frozenset())


class Renderer:
    def __init__(self, hidden: set[str]):
        self.hidden = hidden
        self.n_tables = self.n_lists = 0

    def visible(self, node: Node) -> bool:
        if node.name in _UNSEEN or node.name in _METADATA:
            return False
        attrs = node.attrs
        if not attrs:
            return node.name not in self.hidden
        if "hidden" in attrs or (node.name == "input" and attrs.get("type", "").lower() == "hidden"):
            return False
        if "style" in attrs and _HIDING.search(attrs["style"]):
            return False
        if self.hidden:
            marks = {node.name, *(f".{c}" for c in attrs.get("class", "").split())}
            if "id" in attrs:
                marks.add(f"#{attrs['id']}")
            return not marks & self.hidden
        return True

    def lines(self, node: Node, pre: bool = False) -> list[str]:
        """The lines of a block; '' is one blank line between paragraphs."""
        out: list[str] = []
        inline: list[str] = []

        def flush() -> None:
            if not inline:
                return
            joined = "".join(inline)
            inline.clear()
            if pre:
                out.extend(x.rstrip() for x in joined.strip("\n").split("\n"))
                return
            for line in joined.split("\v"):
                line = _BLANKS.sub(" ", line).strip(" ")
                if line or "\v" in joined:
                    out.append(line)
            while out and not out[-1]:
                out.pop()

        def gap() -> None:
            if out and out[-1]:
                out.append("")

        def walk(children: list) -> None:
            number = 0
            for child in children:
                if isinstance(child, str):
                    inline.append(child.replace("\v", " "))
                    continue
                if not self.visible(child):
                    continue
                name = child.name
                if name == "br":
                    inline.append("\n" if pre else "\v")
                elif name == "hr":
                    flush(), gap()
                    out.extend(["---", ""])
                elif name == "input":
                    if child.attrs.get("type", "text").lower() in ("text", "submit", "button", "reset") and child.attrs.get("value"):
                        inline.append(child.attrs["value"])
                elif name == "select":
                    shown, boxed = self.choices(child)
                    if boxed:
                        flush()
                        out.extend(shown)
                    else:
                        inline.extend(shown)
                elif name == "text":  # a label in a drawing
                    inline.append(" ")
                    walk(child.children)
                    inline.append(" ")
                elif name == "table":
                    flush(), gap()
                    out.extend(self.table(child))
                    gap()
                elif name in ("ul", "ol", "menu", "dir"):
                    flush()
                    inner = self.items(child)
                    if node.name != "li":
                        gap()
                    out.extend(inner)
                    if node.name != "li":
                        gap()
                elif name in _BLOCK or name in ("tr", "td", "th", "caption", *_SECTIONS):
                    flush()
                    if name in _SPACED:
                        gap()
                    inner = self.lines(child, pre or name == "pre")
                    if name == "blockquote":
                        inner = [f"> {x}".rstrip() for x in inner]
                    elif name == "dd":
                        inner = [f"    {x}".rstrip() for x in inner]
                    elif name == "li":  # outside a list
                        number += 1
                        inner = [f"- {x}" if k == 0 else f"  {x}".rstrip() for k, x in enumerate(inner)]
                    out.extend(inner)
                    if name in _SPACED:
                        gap()
                else:
                    walk(child.children)

        walk(node.children)
        flush()
        while out and not out[-1]:
            out.pop()
        while out and not out[0]:
            out.pop(0)
        return out

    def choices(self, node: Node) -> tuple[list[str], bool]:
        """What a choice shows: the selected option or else the first; a list box shows all, a line each."""
        options: list[tuple[Node, list[str]]] = []
        look = [child for child in reversed(node.children) if isinstance(child, Node)]
        while look:
            child = look.pop()
            if not self.visible(child):
                continue
            if child.name == "option":
                options.append((child, self.lines(child)))
            else:
                look.extend(c for c in reversed(child.children) if isinstance(c, Node))
        size = node.attrs.get("size", "")
        if "multiple" in node.attrs or (size.isascii() and size.isdigit() and int(size[:9]) > 1):
            return [line for _, lines in options for line in lines], True
        marked = [lines for option, lines in options if "selected" in option.attrs]
        return (marked[-1:] or [lines for _, lines in options][:1] or [[]])[0], False

    def items(self, node: Node) -> list[str]:
        self.n_lists += 1
        out: list[str] = []
        ordered = node.name == "ol"
        start = node.attrs.get("start", "1")
        number = int(start) if re.fullmatch(r"-?\d{1,9}", start) else 1
        loose = Node("li", {}, node.depth + 1)
        for child in [*node.children, None]:
            if isinstance(child, Node) and child.name == "li":
                if not self.visible(child):
                    continue
                value = child.attrs.get("value", "")
                if ordered and re.fullmatch(r"-?\d{1,9}", value):
                    number = int(value)
                mark = f"{number}. " if ordered else "- "
                number += 1
                body = self.lines(child) or [""]
                out.extend((mark + x if k == 0 else " " * len(mark) + x).rstrip() for k, x in enumerate(body))
            elif child is not None and not (isinstance(child, str) and not child.strip()):
                loose.children = [child]
                out.extend(f"  {x}".rstrip() for x in self.lines(loose))
        return out

    def table(self, node: Node) -> list[str]:
        """Cells padded to their columns; a cell's further lines go below its first."""
        self.n_tables += 1
        before: list[str] = []
        grid: list[list[list[str]]] = []
        taken: dict[int, int] = {}  # by column, the row below the cell that reaches down furthest
        rows: list[Node] = []
        look = list(reversed(node.children))
        while look:
            child = look.pop()
            if isinstance(child, str):
                if child.strip():
                    before.append(_BLANKS.sub(" ", child).strip())
            elif not self.visible(child):
                continue
            elif child.name == "tr":
                rows.append(child)
            elif child.name in _SECTIONS:
                look.extend(reversed(child.children))
            elif child.name not in ("col", "colgroup"):
                holder = Node("div", {}, child.depth)
                holder.children = [child]
                before.extend(self.lines(holder))

        for r, row in enumerate(rows):
            cells: list[list[str]] = []
            for child in row.children:
                if isinstance(child, str):
                    if child.strip():
                        cells.append([_BLANKS.sub(" ", child).strip()])
                    continue
                if not self.visible(child):
                    continue
                while taken.get(len(cells), 0) > r:
                    cells.append([])
                over, down = (max(1, min(most, int(v[:9]))) if (v := child.attrs.get(k, "1")).isascii() and v.isdigit() else 1 for k, most in _SPANS.items())
                c = len(cells)
                cells.append(self.lines(child))
                cells.extend([] for _ in range(over - 1))
                if down > 1:
                    taken.update((column, r + down) for column in range(c, c + over))
            grid.append(cells)
        width: dict[int, int] = {}
        for cells in grid:
            for c, cell in enumerate(cells):
                width[c] = max([width.get(c, 0), *map(len, cell)])
        out = before
        for cells in grid:
            for k in range(max([1, *map(len, cells)]) if cells else 0):
                line = "  ".join((cell[k] if k < len(cell) else "").ljust(width[c]) for c, cell in enumerate(cells)).rstrip()
                if line:
                    out.append(line)
        return out


def render(html: str | None) -> tuple[str, int, int]:
    """(text, number of tables, number of lists)."""
    if not html:
        return "", 0, 0
    sys.setrecursionlimit(max(sys.getrecursionlimit(), FRAMES))
    tree = Builder(html)
    renderer = Renderer(tree.hidden)
    return "\n".join(renderer.lines(tree.root)), renderer.n_tables, renderer.n_lists


def _render(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        made = [render(h.as_py()) for h in batch.column("html")]
        kinds = [pa.string(), pa.int64(), pa.int64()]
        yield pa.RecordBatch.from_arrays([batch.column("page_id"), *(pa.array([m[k] for m in made], t) for k, t in enumerate(kinds))], names=["page_id", "text", "n_tables", "n_lists"])


def page_text(pages: DataFrame) -> DataFrame:
    """(page_id, text, n_chars, n_lines, n_tables, n_lists) for each row of ``pages`` (page_id, html, ...).

    Null and empty pages give empty text and no lines.  Null ids and repeated rows give a row each.  Pages of any length and
    nesting are read whole, broken markup included (a tag ends at the first angle outside quotes within 64 KiB, else at the next angle); extra columns are not read; no pages give no rows.
    """
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("html").cast("string").alias("html"))
    out = rows.mapInArrow(_render, "page_id long, text string, n_tables long, n_lists long")
    n_lines = F.when(F.col("text") == "", F.lit(0)).otherwise(F.size(F.split("text", "\n"))).cast("long")
    return out.select("page_id", "text", F.length("text").cast("long").alias("n_chars"), n_lines.alias("n_lines"), "n_tables", "n_lists")
