"""Layout-aware text of HTML pages.

A tree builder (implied end tags, implied table parts, void and raw-text elements, unknown end tags
ignored; an open head ends at the first tag or text that may not stand in it) is followed by a renderer: everything visible in document order, one line a block, a blank
line around paragraphs, headings, lists, tables, quotes and preformatted text, ``- `` or numbers before list
items by depth, table cells padded to their columns (a cell over several rows keeps its columns free below); what stands in a table beside its cells is kept, before
the row it stands in. Buttons and other fields show their value, images and image buttons their alternative text. Hidden are the head, scripts, styles, templates, comments,
elements with ``hidden``, ``display:none`` or ``visibility:hidden`` in their style or by a style sheet's rule for
their tag, class or id (of the page's own style elements, for all media or screens), hidden inputs and those that show no text of their own
(passwords, checkboxes, radio buttons, files, colours, ranges), what SVG only defines or names, annotations of formulas, and the content of
closed details but for the summary. What is visible again inside a ``visibility:hidden`` element is shown.

Odd input: null or empty html gives empty text; broken markup never fails (an unfinished tag is text, elements
deeper than ``DEPTH`` stand beside the element at that depth, hidden where what they are written in is); other columns pass through.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import in_batches, lean

DEPTH = 256
#: Element groups of the HTML standard.
VOID = frozenset("area base br col embed hr img input link meta source track wbr".split())
RAW = frozenset("script style textarea title xmp iframe noembed noframes".split())
HIDDEN = frozenset("head script style template noscript title meta link base iframe object datalist noembed noframes desc metadata defs symbol annotation annotation-xml".split())
#: What may stand in a head; inputs that show no text; button labels where no value is given.
IN_HEAD = frozenset("html head base basefont bgsound link meta title noscript noframes style script template".split())
NO_TEXT = frozenset("hidden password checkbox radio file color range image".split())
LABELS = {"submit": "Submit", "reset": "Reset"}
SPACED = frozenset("p h1 h2 h3 h4 h5 h6 ul ol dl table blockquote pre figure hr".split())
BLOCK = SPACED | frozenset("html body div section article header footer nav main aside address form fieldset li dt dd tr figcaption details summary legend option center caption".split())
CLOSES_P = SPACED | frozenset("div section article header footer nav main aside address form fieldset details figcaption center li dd dt".split())
#: A start tag in the key closes the nearest open element of the first group, unless one of the second stands between.
IMPLIED = {
    "li": ({"li"}, {"ul", "ol", "menu"}),
    "dt": ({"dt", "dd"}, {"dl"}),
    "dd": ({"dt", "dd"}, {"dl"}),
    "option": ({"option"}, {"select"}),
    "tr": ({"tr"}, {"table"}),
    "td": ({"td", "th"}, {"table", "tr"}),
    "th": ({"td", "th"}, {"table", "tr"}),
    "tbody": ({"tbody", "thead", "tfoot"}, {"table"}),
    "thead": ({"tbody", "thead", "tfoot"}, {"table"}),
    "tfoot": ({"tbody", "thead", "tfoot"}, {"table"}),
}
_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>", re.S)
_ATTR = re.compile(r"([^\s=/\"'>]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?")
_STYLE = re.compile(r"(?:^|[;{\s])(display|visibility)\s*:\s*([a-z-]+)", re.I)
_RULE = re.compile(r"([^{}]+)\{([^{}]*)\}")
_SIMPLE = re.compile(r"([a-zA-Z][\w-]*|\*)?([.#][\w-]+)?")
_SPACE = re.compile(r"[ \t\n\r\f​]+")


class Node:
    __slots__ = ("tag", "attrs", "children", "over")

    def __init__(self, tag: str, attrs: dict | None = None, over: Node | None = None):
        self.tag, self.attrs, self.children, self.over = tag, attrs or {}, [], over


def build(html: str) -> Node:
    root = Node("#root")
    stack = [root]

    def close_until(tags, fences) -> None:
        for i in range(len(stack) - 1, 0, -1):
            if stack[i].tag in tags:
                del stack[i:]
                return
            if stack[i].tag in fences:
                return

    def end_head() -> None:
        for i in range(len(stack) - 1, 0, -1):
            if stack[i].tag in ("template", "noscript", "body"):
                return
            if stack[i].tag == "head":
                del stack[i:]
                return

    def text(data: str) -> None:
        if data:
            if stack[-1].tag == "head" and data.strip(" \t\n\r\f"):
                end_head()
            stack[-1].children.append(unescape(data) if "&" in data else data)

    at, end = 0, len(html)
    while at < end:
        m = _TOKEN.search(html, at)
        if m is None:
            text(html[at:])
            break
        text(html[at : m.start()])
        at = m.end()
        tag = m[2]
        if tag is None:
            continue
        tag = tag.lower()
        if m[1]:
            if tag == "br":
                stack[-1].children.append(Node("br"))
            elif tag == "p" and not any(n.tag == "p" for n in stack):
                stack[-1].children.append(Node("p"))
            else:
                close_until({tag}, {"table"} if tag not in ("table", "html", "body") else set())
            continue
        attrs = {k.lower(): unescape(a or b or c) for k, a, b, c in _ATTR.findall(m[3])} if m[3].strip(" /") else {}
        if tag not in IN_HEAD:
            end_head()
        if tag in CLOSES_P:
            close_until({"p"}, {"table", "td", "th", "li", "div", "section", "article", "blockquote"})
        if tag in IMPLIED:
            close_until(*IMPLIED[tag])
        if tag in ("td", "th") and stack[-1].tag in ("table", "tbody", "thead", "tfoot"):
            row = Node("tr")
            stack[-1].children.append(row)
            stack.append(row)
        deep = len(stack) >= DEPTH
        node = Node(tag, attrs, stack[-1] if deep else None)
        (stack[DEPTH - 1] if deep else stack[-1]).children.append(node)
        if tag in VOID:
            continue
        if tag in RAW:
            stop = re.compile(rf"</{re.escape(tag)}\s*>", re.I).search(html, at)
            inside = html[at : stop.start() if stop else end]
            if tag in ("textarea", "title"):
                node.children.append(unescape(inside))
            elif tag == "style":
                node.children.append(inside)
            at = stop.end() if stop else end
            continue
        stack.append(node)
    return root


def sheet(root: Node) -> dict[str, list]:
    """Rules of the page's style elements that show or hide: last part of a selector -> (weight, order, tag, settings)."""
    rules: dict[str, list] = {}
    order, todo = 0, [root]
    while todo:
        node = todo.pop()
        if node.tag == "style" and node.children and re.search(r"all|screen", node.attrs.get("media", "all") or "all", re.I):
            css = re.sub(r"/\*.*?\*/", " ", node.children[0], flags=re.S)
            css = re.sub(r"@[^{};]*(?:;|\{(?:[^{}]*\{[^{}]*\})*[^{}]*\})", " ", css)
            for selectors, body in _RULE.findall(css):
                settings = {k.lower(): v.lower() for k, v in _STYLE.findall(body)}
                for selector in selectors.split(",") if settings else ():
                    m = _SIMPLE.fullmatch(selector.strip())
                    if m and (m[1] or m[2]):
                        order += 1
                        tag = (m[1] or "*").lower()
                        weight = (m[2] or "").startswith("#") * 100 + (m[2] or "").startswith(".") * 10 + (tag != "*")
                        rules.setdefault(m[2] or tag, []).append((weight, order, tag, settings))
        elif node.tag not in ("template", "noscript"):
            todo += [c for c in reversed(node.children) if isinstance(c, Node)]
    return rules


def settings(node: Node, rules: dict[str, list]) -> dict[str, str]:
    """What rules and the element's own style say of its display and visibility."""
    out = {"display": "none"} if "hidden" in node.attrs else {}
    if rules:
        keys = [node.tag, "*", *("." + c for c in node.attrs.get("class", "").split()), "#" + node.attrs.get("id", "")]
        for _, _, tag, found in sorted((r for k in keys for r in rules.get(k, ())), key=lambda r: r[:2]):
            if tag in ("*", node.tag):
                out.update(found)
    if "style" in node.attrs:
        out.update((k.lower(), v.lower()) for k, v in _STYLE.findall(node.attrs["style"]))
    return out


def settle(root: Node) -> Node:
    """The tree without what is not seen: elements that are not displayed go, invisible ones lose all but visible parts."""
    rules, gone = sheet(root), set()

    def kept(node: Node, unseen: bool) -> bool:
        if node.tag in HIDDEN or (node.over is not None and id(node.over) in gone):
            gone.add(id(node))
            return False
        if node.attrs or rules:
            told = settings(node, rules)
            if told.get("display") == "none" or node.tag == "input" and node.attrs.get("type", "").strip().lower() == "hidden":
                gone.add(id(node))
                return False
            unseen = told["visibility"] in ("hidden", "collapse") if told.get("visibility", "inherit") != "inherit" else unseen
        if node.children:
            node.children = [c for c in node.children if (not unseen if isinstance(c, str) else kept(c, unseen))]
        return bool(node.children) or not unseen

    root.children = [c for c in root.children if isinstance(c, str) or kept(c, False)]
    return root


def shown(node: Node) -> str:
    """What an input shows."""
    kind = node.attrs.get("type", "").strip().lower()
    if kind in NO_TEXT:
        return node.attrs.get("alt", "") if kind == "image" else ""
    return node.attrs.get("value") or LABELS.get(kind, "") or node.attrs.get("placeholder", "")


class Page:
    """Lines as they come; a blank line is put between spaced blocks once text follows."""

    def __init__(self):
        self.lines: list[str] = []
        self.line = ""
        self.indent: list[str] = []
        self.mark = ""
        self.gap = False

    def inline(self, data: str) -> None:
        data = _SPACE.sub(" ", data)
        if self.line.endswith(" ") or not self.line:
            data = data.lstrip(" ")
        self.line += data

    def flush(self) -> None:
        line = self.line.rstrip(" ")
        self.line = ""
        if line:
            self.put(line)

    def put(self, line: str) -> None:
        if self.gap and self.lines:
            self.lines.append("")
        self.gap = False
        self.lines.append(("".join(self.indent)[: len("".join(self.indent)) - len(self.mark)] + self.mark if self.mark else "".join(self.indent)) + line)
        self.mark = ""

    def text(self) -> str:
        self.flush()
        return "\n".join(self.lines)


def render(node, page: Page) -> None:
    if isinstance(node, str):
        page.inline(node)
        return
    tag = node.tag
    if tag == "br":
        line = page.line
        page.flush()
        if not line.strip():
            page.gap = page.gap or bool(page.lines)
        return
    if tag == "img":
        if node.attrs.get("alt"):
            page.inline(node.attrs["alt"])
        return
    if tag == "input":
        page.inline(f" {shown(node)} ")
        return
    if tag == "text":
        page.inline(" ")
        children(node, page)
        page.inline(" ")
        return
    block = tag in BLOCK
    if block:
        page.flush()
        page.gap = page.gap or tag in SPACED and not page.mark
    if tag == "table":
        table(node, page)
    elif tag == "pre":
        raw = "".join(strings(node)).strip("\n")
        for line in raw.split("\n"):
            page.put(line.rstrip())
    elif tag in ("ul", "ol", "menu"):
        items(node, page)
    elif tag == "blockquote":
        page.indent.append("> ")
        children(node, page)
        page.flush()
        page.indent.pop()
    elif tag == "dd":
        page.indent.append("  ")
        children(node, page)
        page.flush()
        page.indent.pop()
    elif tag == "details" and "open" not in node.attrs:
        for child in node.children:
            if isinstance(child, Node) and child.tag == "summary":
                render(child, page)
    elif tag == "hr":
        pass
    else:
        children(node, page)
    if block:
        page.flush()
        page.gap = page.gap or tag in SPACED


def children(node: Node, page: Page) -> None:
    for child in node.children:
        render(child, page)


def strings(node: Node):
    for child in node.children:
        if isinstance(child, str):
            yield child
        elif child.tag == "br":
            yield "\n"
        elif child.tag == "input":
            yield f" {shown(child)} "
        else:
            yield from strings(child)


def items(node: Node, page: Page) -> None:
    start = node.attrs.get("start", "")
    number = int(start) if re.fullmatch(r"-?\d{1,9}", start) else 1
    nested = bool(page.indent)
    for child in node.children:
        if isinstance(child, Node) and child.tag == "li":
            page.flush()
            mark = f"{number}. " if node.tag == "ol" else "- "
            number += 1
            page.indent.append(" " * len(mark))
            page.mark = mark
            if nested:
                page.gap = False
            children(child, page)
            page.flush()
            if page.mark == mark:
                page.put("")
            page.indent.pop()
            page.mark = ""
            page.gap = False
        elif isinstance(child, Node) or child.strip():
            render(child, page)


ROWS = ("tr", "tbody", "thead", "tfoot")


def holds(node: Node, *tags: str) -> bool:
    """Whether an element, no table or caption, has children of these tags."""
    return node.tag not in ("table", "caption") and any(isinstance(c, Node) and c.tag in tags for c in node.children)


def cells(node: Node):
    """Rows of a table, lists of (lines, columns, rows); what stands in a row or group beside them comes before its row, as a node."""
    for child in node.children:
        if not isinstance(child, Node):
            if child.strip() and node.tag != "table":
                yield child
        elif child.tag == "tr":
            row = []
            yield from beside(child, row)
            if row:
                yield row
        elif child.tag in ("tbody", "thead", "tfoot"):
            yield from cells(child)
        elif node.tag != "table" or holds(child, *ROWS, "td", "th"):
            yield from within(child)


def beside(node: Node, row: list):
    """Puts the cells of a row, also those in an element between, into ``row``; yields the rest."""
    for cell in node.children:
        if not isinstance(cell, Node):
            if cell.strip():
                yield cell
        elif cell.tag in ("td", "th"):
            inner = Page()
            children(cell, inner)
            wide, down = (cell.attrs.get(k, "1").strip() for k in ("colspan", "rowspan"))
            row.append((inner.text().split("\n"), min(1000, int(wide)) if wide.isdecimal() and int(wide) else 1, min(65534, int(down)) or 65534 if down.isdecimal() else 1))
        elif holds(cell, "td", "th"):
            yield from beside(cell, row)
        else:
            yield cell


def within(node: Node):
    """Rows in an element that stands between a group and its rows, such as a form; the element itself where it has none."""
    if holds(node, *ROWS):
        group = Node("tbody")
        group.children = node.children
        yield from cells(group)
    elif holds(node, "td", "th"):
        row: list = []
        yield from beside(node, row)
        yield row
    else:
        yield node


def table(node: Node, page: Page) -> None:
    for child in node.children:
        if isinstance(child, Node) and child.tag == "caption":
            render(child, page)
    parts = list(cells(node))
    rows = [r for r in parts if isinstance(r, list)]
    if not parts:
        rest = [c for c in node.children if isinstance(c, str) or c.tag not in ("tr", "tbody", "thead", "tfoot", "caption", "colgroup")]
        for child in rest:
            render(child, page)
        return
    widths: dict[int, int] = {}
    taken: dict[int, int] = {}
    placed: list[list] = []
    for row in rows:
        column, spots = 0, []
        for lines, span, down in row:
            while taken.get(column):
                column += 1
            spots.append((column, lines, span))
            if span == 1:
                widths[column] = max(widths.get(column, 0), *(len(x) for x in lines))
            for c in range(column, column + span):
                taken[c] = max(taken.get(c, 0), down)
            column += span
        taken = {c: n - 1 for c, n in taken.items() if n > 1}
        placed.append(spots)
    upto = iter(placed)
    for row in parts:
        if not isinstance(row, list):
            render(row, page)
            continue
        page.flush()
        spots = next(upto)
        for k in range(max((len(lines) for _, lines, _ in spots), default=0)):
            out, at = "", 0
            for column, lines, span in spots:
                out += "".join(" " * (widths.get(c, 0) + 2) for c in range(at, column))
                out += (lines[k] if k < len(lines) else "").ljust(sum(widths.get(c, 0) for c in range(column, column + span)) + 2 * (span - 1)) + "  "
                at = column + span
            if out.strip():
                page.put(out.rstrip())
    page.flush()
    for child in node.children:
        if isinstance(child, str) and child.strip() or isinstance(child, Node) and child.tag not in (*ROWS, "caption", "colgroup") and not holds(child, *ROWS, "td", "th"):
            render(child, page)


def html_text(html: str | None) -> str:
    page = Page()
    children(settle(build(html or "")), page)
    return page.text()


def extract(pages: DataFrame, html_col: str = "html", column: str = "text") -> DataFrame:
    """The rows with the visible text of their html; a column that has the result's name is replaced."""

    @F.arrow_udf("string")
    @lean()
    def rendered(arrays: Iterator[pa.Array]) -> Iterator[pa.Array]:
        import sys

        sys.setrecursionlimit(max(sys.getrecursionlimit(), 10 * DEPTH))
        for array in arrays:
            yield pa.array([html_text(x) for x in array.to_pylist()], pa.string())

    return in_batches(pages).withColumn(column, rendered(F.col(html_col).cast("string")))


def op6_html_extraction(spark, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "html")
    return extract(pages).select("page_id", "text", F.length("text").cast("long").alias("n_chars"), F.size(F.split("text", "\n\n")).cast("long").alias("n_blocks"))
