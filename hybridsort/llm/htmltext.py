"""Visible text of HTML pages, laid out: a forgiving tree builder and a renderer.

The builder supplies the tags that authors may leave out (html, head and body, ends of paragraphs, list
items, definition terms, options, rows, cells and table sections), ignores stray end tags, and takes
script, style and the like as raw text. The renderer drops what is not shown (head, script, style,
template, the hidden attribute, display:none, visibility:hidden unless made visible again below,
closed dialogs, what closed details hold besides their summary, hidden inputs, what svg and math only
describe), gives all options of a select, collapses white space except in preformatted text, sets blocks apart
by line breaks or blank lines, marks list items by nesting, and pads table cells so that columns line
up, also beside cells that span rows or columns.

Markup is read in one pass: a quotation mark that is never closed is an ordinary character, and where
quotes swallow the end of a tag, the rest of the page is read without regard to quotes.

Defined results: null html gives null text; empty html gives empty text; an unclosed comment or raw
element reaches to the end; markup nested more than ``DEEPEST`` levels is flattened into its
ancestor; repeated rows are rendered each; an empty table gives no rows; a very long page takes time in
proportion; columns named as the result are replaced, others may have any names.
"""

from __future__ import annotations

import re
import unicodedata
from collections.abc import Iterator
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import column, light_batches, tidy, without

DEEPEST = 400
# Element names with a role of their own in HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style template noscript iframe noembed noframes textarea title xmp".split())
HEAD = frozenset("base link meta title style script template noscript".split())
UNSEEN = frozenset("head script style template noscript iframe noembed noframes title object canvas audio video datalist".split())
#: Parts of svg and math that are not drawn.
NOT_DRAWN = frozenset("desc defs metadata symbol clippath mask annotation annotation-xml".split())
SPACED = frozenset("p h1 h2 h3 h4 h5 h6 ul ol dl table blockquote pre figure hr menu".split())
BLOCK = SPACED | frozenset("html body div article section header footer nav aside main address form fieldset legend li dt dd tr caption thead tbody tfoot figcaption details summary center dialog hgroup search option optgroup".split())
#: Start tags that end an open paragraph.
ENDS_P = SPACED | frozenset("address article aside center details dialog div dd dl dt fieldset figcaption footer form header hgroup li main nav search section summary".split())
#: For a start tag: the open elements that it ends, and those that such a search doesn't go beyond.
ENDS = {
    "li": ({"li"}, {"ul", "ol", "menu"}),
    "dt": ({"dt", "dd"}, {"dl"}),
    "dd": ({"dt", "dd"}, {"dl"}),
    "option": ({"option"}, {"select", "optgroup", "datalist"}),
    "td": ({"td", "th"}, {"tr", "table"}),
    "th": ({"td", "th"}, {"tr", "table"}),
    "tr": ({"tr"}, {"table"}),
    "thead": ({"thead", "tbody", "tfoot"}, {"table"}),
    "tbody": ({"thead", "tbody", "tfoot"}, {"table"}),
    "tfoot": ({"thead", "tbody", "tfoot"}, {"table"}),
}
#: Elements that a stray end tag inside them doesn't reach out of.
WALLS = frozenset("table td th caption button".split())

NAME = re.compile(r"/?[a-zA-Z][^\s/>]*")
STOP = re.compile("[>\"']")
#: The greatest spans that HTML knows.
MOST_COLUMNS, MOST_ROWS = 1000, 65534
ATTRIBUTE = re.compile(r"([^\s=/>\"']+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?")
BLANKS = re.compile(r"[ \t\n\r\f]+")


class Node:
    __slots__ = ("tag", "attributes", "children")

    def __init__(self, tag: str, attributes: str = ""):
        self.tag, self.attributes, self.children = tag, attributes, []

    def attribute(self, name: str) -> str | None:
        for m in ATTRIBUTE.finditer(self.attributes):
            if m[1].lower() == name:
                return unescape(next((v for v in m.groups()[1:] if v is not None), ""))
        return None


def tokens(html: str) -> Iterator[tuple[int, int, str | None, bool, str]]:
    """Where each piece of markup begins and ends, its tag in lower case (None for comments), whether it is an end tag, and its attributes."""
    at, n, quoted = 0, len(html), True
    last = {q: html.rfind(q) for q in ">\"'"}
    while (begin := html.find("<", at)) >= 0:
        if html.startswith("<!--", begin):
            end = html.find("-->", begin + 4)
            at = n if end < 0 else end + 3
            yield begin, at, None, False, ""
            continue
        if html.startswith(("<!", "<?"), begin):
            end = html.find(">", begin)
            at = n if end < 0 else end + 1
            yield begin, at, None, False, ""
            continue
        name = NAME.match(html, begin + 1)
        if name is None or begin > last[">"]:
            at = begin + 1
            continue
        end = name.end()
        while quoted:
            stop = STOP.search(html, end)
            if stop is None:
                quoted = False
            elif stop[0] == ">":
                end = stop.start()
                break
            else:
                close = html.find(stop[0], stop.end()) if stop.start() < last[stop[0]] else stop.start()
                end = close + 1
        if not quoted:
            end = html.find(">", name.end())
            if end < 0:
                at = begin + 1
                continue
        at = end + 1
        tag = name[0].lower()
        moved = yield begin, at, tag.lstrip("/"), tag[0] == "/", html[name.end() : end]
        if moved is not None:
            at = moved


def build(html: str) -> Node:
    """The document's element tree; text children are strings."""
    root = Node("html")
    body = Node("body")
    root.children.append(body)
    head: Node | None = None
    stack = [root, body]

    def close(tags: set, walls: set) -> None:
        for k in range(len(stack) - 1, 1, -1):
            if stack[k].tag in tags:
                del stack[k:]
                return
            if stack[k].tag in walls:
                return

    at, n, found, moved = 0, len(html), tokens(html), None
    while True:
        try:
            begin, past, tag, is_end, attributes = found.send(moved)
        except StopIteration:
            if at < n:
                stack[-1].children.append(unescape(html[at:]))
            break
        moved = None
        if begin > at:
            stack[-1].children.append(unescape(html[at:begin]))
        at = past
        if tag is None:
            continue
        if is_end:
            if tag in ("html", "body"):
                continue
            if tag == "head":
                stack = [root, body]
                head = None
                continue
            for k in range(len(stack) - 1, 1, -1):
                if stack[k].tag == tag:
                    del stack[k:]
                    break
                if stack[k].tag in WALLS and tag not in ("table", "tr", "tbody", "thead", "tfoot"):
                    break
            else:
                if tag == "p":
                    stack[-1].children.append(Node("p"))
            continue
        if tag in ("html", "body"):
            if tag == "body":
                stack = [root, body]
                head = None
                body.attributes += attributes
            continue
        if tag == "head":
            head = Node("head")
            root.children.insert(0, head)
            stack = [root, head]
            continue
        if head is not None and len(stack) == 2 and tag not in HEAD:
            stack, head = [root, body], None
        if tag in ENDS_P:
            close({"p"}, WALLS | {"li", "dd", "dt"} if tag not in ("li", "dd", "dt") else WALLS)
        if tag in ENDS:
            close(*ENDS[tag])
            if tag in ("td", "th") and stack[-1].tag in ("table", "thead", "tbody", "tfoot"):
                row = Node("tr")
                stack[-1].children.append(row)
                stack.append(row)
        node = Node(tag, attributes)
        stack[-1].children.append(node)
        if tag in RAW:
            end = re.compile(rf"</{re.escape(tag)}[\s/>]", re.I).search(html, at)
            if tag == "textarea":
                node.children.append(unescape(html[at : end.start() if end else n]))
            at = html.find(">", end.start()) + 1 if end else n
            at = moved = at or n
        elif tag not in VOID and not attributes.rstrip().endswith("/") and len(stack) < DEEPEST:
            stack.append(node)
    return root


def _hidden(node: Node) -> bool:
    if node.tag in UNSEEN or node.tag in NOT_DRAWN:
        return True
    if node.tag == "dialog" and node.attribute("open") is None:
        return True
    if not node.attributes:
        return False
    low = node.attributes.lower()
    if "hidden" in low and node.attribute("hidden") is not None:
        return True
    return "display" in low and re.search(r"display\s*:\s*none", (node.attribute("style") or "").lower()) is not None


def _visibility(node: Node, visible: bool) -> bool:
    if "visibility" in node.attributes.lower():
        found = re.search(r"visibility\s*:\s*(\w+)", (node.attribute("style") or "").lower())
        if found:
            return found[1] not in ("hidden", "collapse")
    return visible


def width(text: str) -> int:
    """Columns that text takes on a terminal."""
    if text.isascii():
        return len(text)
    return sum(0 if unicodedata.combining(c) else 2 if unicodedata.east_asian_width(c) in "WF" else 1 for c in text)


class _Page:
    """Lines in the making: a gap before the next text is owed as blanks, line breaks or a blank line."""

    def __init__(self):
        self.parts: list[str] = []
        self.breaks = 0
        self.blank = False
        self.started = False

    def gap(self, breaks: int) -> None:
        self.breaks = max(self.breaks, breaks)
        self.blank = False

    def _settle(self) -> None:
        if self.breaks and self.started:
            self.parts.append("\n" * self.breaks)
        elif self.blank and self.started and not self.breaks:
            self.parts.append(" ")
        self.breaks, self.blank, self.started = 0, False, True

    def text(self, text: str) -> None:
        words = BLANKS.sub(" ", text)
        if words == " " or not words:
            self.blank = self.blank or (bool(words) and not self.breaks)
            return
        if words[0] == " " and not self.breaks:
            self.blank = True
        self._settle()
        self.parts.append(words.strip(" "))
        self.blank = words[-1] == " "

    def exact(self, text: str) -> None:
        if text:
            self._settle()
            self.parts.append(text)


def _render(node: Node, page: _Page, visible: bool = True, exact: bool = False, lists: tuple = ()) -> None:
    number = 1
    if node.tag == "ol" and (start := node.attribute("start")) and start.lstrip("-").isdigit():
        number = int(start)
    closed = node.tag == "details" and node.attribute("open") is None
    summary = next((c for c in node.children if not isinstance(c, str) and c.tag == "summary"), None) if closed else None
    for child in node.children:
        if isinstance(child, str):
            if visible and not closed:
                (page.exact if exact else page.text)(child)
            continue
        if _hidden(child) or (closed and child is not summary):
            continue
        shown = _visibility(child, visible)
        tag = child.tag
        if tag == "br":
            page.breaks += 1
            page.blank = False
        elif tag == "hr":
            page.gap(2)
            if shown:
                page.exact("---")
            page.gap(2)
        elif tag == "input":
            if shown and (child.attribute("type") or "text").lower() in ("submit", "button", "reset", "text", "search") and (value := child.attribute("value")):
                page.text(value)
        elif tag == "table":
            page.gap(2)
            page.exact(_table(child, shown))
            page.gap(2)
        elif tag == "li":
            page.gap(1)
            mark = f"{number}. " if node.tag == "ol" else "- "
            number += 1
            inner = _block(child, shown, exact, lists)
            if inner:
                page.exact(mark + inner.replace("\n", "\n" + " " * len(mark)))
            page.gap(1)
        elif tag == "dd":
            page.gap(1)
            inner = _block(child, shown, exact, lists)
            if inner:
                page.exact("    " + inner.replace("\n", "\n    "))
            page.gap(1)
        elif tag in BLOCK:
            nested = tag in ("ul", "ol", "menu", "dl") and lists
            space = 1 if nested or tag not in SPACED else 2
            page.gap(space)
            _render(child, page, shown, exact or tag == "pre", (*lists, tag) if tag in ("ul", "ol", "menu", "dl") else lists)
            page.gap(space)
        else:
            _render(child, page, shown, exact or tag == "textarea", lists)


def _block(node: Node, visible: bool, exact: bool, lists: tuple) -> str:
    page = _Page()
    _render(node, page, visible, exact, lists)
    return "".join(page.parts)


def _parts(node: Node, visible: bool) -> Iterator[tuple[Node | str, bool]]:
    """The rows below a table, and all else that stands between them, in order; sections and forms are looked into."""
    for child in node.children:
        if isinstance(child, str):
            if visible:
                yield child, True
        elif not _hidden(child) and child.tag not in ("col", "colgroup"):
            shown = _visibility(child, visible)
            if child.tag in ("thead", "tbody", "tfoot", "form"):
                yield from _parts(child, shown)
            else:
                yield child, shown


def _span(cell: Node, name: str, most: int) -> int:
    value = (cell.attribute(name) or "1").strip()
    return min(int(value), most) if value.isascii() and value.isdigit() else 1


def _table(table: Node, visible: bool) -> str:
    """Rows of cells, each column as wide as its widest line; cells of several lines make rows of several lines.

    None stands where a cell of the same row or of one above reaches.
    """
    grid: list[list[list[str] | None]] = []
    loose = _Page()
    reach: dict[int, int] = {}  # columns that cells above take, and for how many rows more
    for part, shown in _parts(table, visible):
        if isinstance(part, str):
            loose.text(part)
            continue
        if part.tag != "tr":
            holder = Node("div")
            holder.children.append(part)
            _render(holder, loose, shown)
            loose.gap(1)
            continue
        cells: list[list[str] | None] = []
        held, reach = reach, {k: n - 1 for k, n in reach.items() if n > 1}
        for cell in part.children:
            if isinstance(cell, str):
                if shown and cell.strip():
                    loose.text(cell)
                continue
            if _hidden(cell):
                continue
            while len(cells) in held:
                cells.append(None)
            inner = _block(cell, _visibility(cell, shown), False, ())
            columns, rows = max(1, _span(cell, "colspan", MOST_COLUMNS)), _span(cell, "rowspan", MOST_ROWS) or MOST_ROWS
            if rows > 1:
                reach.update((k, rows - 1) for k in range(len(cells), len(cells) + columns))
            cells.append(inner.split("\n") if inner else [""])
            cells += [None] * (columns - 1)
        while cells and cells[-1] is None:
            cells.pop()
        if any(any(c) for c in cells if c):
            grid.append(cells)
    wide: list[int] = []
    for cells in grid:
        for k, lines in enumerate(cells):
            size = max(map(width, lines or [""]))
            if k == len(wide):
                wide.append(size)
            elif size > wide[k]:
                wide[k] = size
    out = []
    for cells in grid:
        for line in range(max(len(c or "") for c in cells)):
            parts = [(c[line] if c and line < len(c) else "") for c in cells]
            out.append(" | ".join(p + " " * (wide[k] - width(p)) for k, p in enumerate(parts)).rstrip())
    text = "".join(loose.parts)
    return "\n".join([*([text] if text else []), *out])


def extract(html: str | None) -> str | None:
    if html is None:
        return None
    lines = _block(build(html), True, False, ()).split("\n")
    return "\n".join(line.rstrip() for line in lines).strip("\n")


def render(pages: DataFrame, html: str = "html", to: str = "text") -> DataFrame:
    """pages with the visible text of ``html`` in the column ``to``, in place of html."""
    rest = without(pages, to)
    kept = [c for c in rest.columns if c != html]
    kinds = "".join(f"`{c}` {rest.schema[c].dataType.simpleString()}, " for c in kept)

    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in light_batches(batches, html):
            texts = pa.array([extract(x.as_py()) for x in column(batch, html)], pa.string())
            yield pa.RecordBatch.from_arrays([*[column(batch, c) for c in kept], texts], names=[*kept, to])

    return rest.select(*[f"`{c}`" for c in [*kept, html]]).mapInArrow(run, f"{kinds}`{to}` string")
