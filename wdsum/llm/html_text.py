"""Visible text of web pages, laid out: blocks, lists and aligned table cells.

A forgiving tree builder (implied end tags, void and raw-text elements, stray
end tags) makes a tree of elements; visibility rules drop what a reader
wouldn't see; the rest is rendered as text. Paragraph-like blocks stand apart by
an empty line, other blocks by a line; list items have markers and nested lists
are indented; the cells of a table's column start at one place.
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# fixed values of the markup language, by element name
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style title textarea noscript iframe noembed noframes xmp".split())
UNSEEN = frozenset("head script style template noscript iframe noembed noframes title datalist object audio video canvas meta link base param source track area map".split())
APART = frozenset("p h1 h2 h3 h4 h5 h6 blockquote dl figure fieldset hr".split())
LINES = frozenset("address article aside body center dd details dialog div dt figcaption footer form header hgroup html legend li main nav option optgroup section summary caption td th tr tbody thead tfoot".split())
#: within drawings and formulas: not drawn, drawn apart, and elements of the page that end them
UNDRAWN = frozenset("defs desc metadata symbol clippath mask pattern marker annotation annotation-xml".split())
DRAWN_APART = frozenset("text mfrac msup msub msubsup munder mover munderover mroot mmultiscripts mtable mtr mlabeledtr mtd".split())
ENDS_DRAWING = frozenset("b big blockquote body center code dd div dl dt em embed h1 h2 h3 h4 h5 h6 head hr i img li listing menu nobr ol p pre ruby s small span strong strike sub sup table tt u ul var".split())
HOLDS_PAGE = frozenset("foreignobject desc mi mo mn ms mtext annotation-xml".split())
#: what the parts of a table stand in
SECTIONS = frozenset(("thead", "tbody", "tfoot"))
WITHIN = {"td": SECTIONS | {"table", "tr"}, "th": SECTIONS | {"table", "tr"}, "tr": SECTIONS | {"table"}, "tbody": {"table"}, "thead": {"table"}, "tfoot": {"table"}}
CLOSES_P = APART | frozenset("address article aside center details dialog div figcaption footer form header hgroup main menu nav ol pre section summary table ul dir".split())
#: a start tag ends an open element of these names, up to the barrier
ENDS = {
    "li": ({"li"}, {"ul", "ol", "menu", "dir"}),
    "dt": ({"dt", "dd"}, {"dl"}),
    "dd": ({"dt", "dd"}, {"dl"}),
    "tr": ({"tr", "td", "th", "caption", "colgroup"}, {"table"}),
    "td": ({"td", "th", "caption", "colgroup"}, {"tr", "table"}),
    "th": ({"td", "th", "caption", "colgroup"}, {"tr", "table"}),
    "tbody": ({"thead", "tbody", "tfoot", "tr", "td", "th", "caption", "colgroup"}, {"table"}),
    "thead": ({"thead", "tbody", "tfoot", "tr", "td", "th", "caption", "colgroup"}, {"table"}),
    "tfoot": ({"thead", "tbody", "tfoot", "tr", "td", "th", "caption", "colgroup"}, {"table"}),
    "option": ({"option"}, {"select", "datalist"}),
    "optgroup": ({"option", "optgroup"}, {"select"}),
}
BARRIER = frozenset("table td th caption html template button".split())
#: elements nested deeper than this become siblings, as in browsers
DEPTH = 200

_TAG = re.compile(r"<(?:(!--)|([!?])|(/?)([a-zA-Z][^\s/>]*))")
#: what may end a tag, or hide its end: ">", or "=" with a quote or an unquoted value behind it
_ENDING = re.compile(r">|=\s*(?:([\"'])|[^\s>]*)")
_ATTRIBUTE = re.compile(r"([^\s=/\"'>]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
_RAW_END = {x: re.compile(rf"</{x}(?=[\s/>])", re.I) for x in RAW}
_SPACES = re.compile(r"[ \t\n\r\f\v]+")


class Element:
    __slots__ = ("tag", "attributes", "children")

    def __init__(self, tag: str, attributes: str = ""):
        self.tag, self.attributes, self.children = tag, attributes, []

    def get(self, name: str) -> str | None:
        for m in _ATTRIBUTE.finditer(self.attributes):
            if m[1].lower() == name:
                return html.unescape(m[2] or m[3] or m[4] or "")
        return None


def past(page: str, mark: str, at: int) -> int:
    """The place after the next ``mark``, or the page's end."""
    found = page.find(mark, at)
    return len(page) if found < 0 else found + len(mark)


def tag_end(page: str, at: int) -> int:
    """The place after the ``>`` that ends a tag whose attributes begin at ``at``; -1 if nothing ends it.

    A ``>`` in a quoted value ends nothing. A quote that is never closed hides
    nothing: its tag ends at the next ``>``. No place is looked at more than
    twice in all the tags of a page, since a quote that isn't closed has no other
    of its kind behind it.
    """
    while (m := _ENDING.search(page, at)) is not None:
        at = m.end()
        if m[0] == ">":
            return at
        if m[1] and (close := page.find(m[1], at)) >= 0:
            at = close + 1
    return -1


def tags(page: str) -> Iterator[tuple[int, int, str, str, str]]:
    """(begin, end, slash, name, attributes) of comments, declarations (without a name) and tags in order.

    The caller sends a place to go on at, or None. A tag that nothing ends takes
    the rest of the page.
    """
    at = 0
    while (m := _TAG.search(page, at)) is not None:
        if m[4] is None:
            at = past(page, "-->" if m[1] else ">", m.end())
            found = (m.start(), at, "", "", "")
        else:
            at = tag_end(page, m.end())
            at = len(page) if at < 0 else at
            found = (m.start(), at, m[3], m[4], page[m.end() : at - 1]) if page[at - 1] == ">" else (m.start(), at, "", "", "")
        at = (yield found) or at


def parse(page: str) -> Element:
    """The page's tree, under an element without a name."""
    root = Element("")
    opened = [root]
    at, end = 0, len(page)
    draws = re.search("<(?:svg|math)", page, re.I) is not None

    def text(s: str) -> None:
        if s:
            opened[-1].children.append(html.unescape(s) if "&" in s else s)

    def close(names: set[str] | frozenset[str], barrier: set[str] | frozenset[str]) -> None:
        """Ends the outermost open element of these names above the barrier."""
        found = 0
        for k in range(len(opened) - 1, 0, -1):
            if opened[k].tag in names:
                found = k
            elif opened[k].tag in barrier:
                break
        if found:
            del opened[found:]

    marks, skip = tags(page), None
    while True:
        try:
            begin, stop_at, slash, name, attributes = marks.send(skip)
        except StopIteration:
            text(page[at:])
            break
        text(page[at:begin])
        at, skip = stop_at, None
        if not name:
            continue
        tag = name.lower()
        if slash:
            if tag == "br":
                opened[-1].children.append(Element("br"))
            elif tag == "p" and not any(e.tag == "p" for e in opened):
                opened[-1].children.append(Element("p"))
            else:
                for k in range(len(opened) - 1, 0, -1):
                    if opened[k].tag == tag:
                        del opened[k:]
                        break
                    if opened[k].tag in BARRIER and tag not in ("table", "tr", "tbody", "thead", "tfoot", "body", "html"):
                        break
            continue
        if tag in CLOSES_P:
            close({"p"}, BARRIER)
        if tag in ENDS:
            close(*ENDS[tag])
        if tag in WITHIN:
            # other elements between a table and its parts end, as in browsers; a cell without a row opens one
            k = len(opened) - 1
            while k and opened[k].tag not in WITHIN[tag] and opened[k].tag not in ("td", "th", "caption", "template", "button"):
                k -= 1
            if opened[k].tag in WITHIN[tag]:
                del opened[k + 1 :]
                if tag in ("td", "th") and opened[k].tag != "tr" and len(opened) < DEPTH:
                    opened.append(Element("tr"))
                    opened[k].children.append(opened[-1])
        if draws and tag in ENDS_DRAWING:
            close({"svg", "math"}, BARRIER | HOLDS_PAGE)
        shut = draws and attributes.endswith("/") and (tag in ("svg", "math") or any(e.tag in ("svg", "math") for e in opened))
        element = Element(tag, attributes)
        opened[-1].children.append(element)
        if shut:
            continue
        if tag in RAW:
            stop = _RAW_END[tag].search(page, at)
            inside = page[at : stop.start() if stop else end]
            if tag == "textarea":
                element.children.append(html.unescape(inside))
            elif tag == "xmp":
                element.children.append(inside)
            at = skip = past(page, ">", stop.end()) if stop else end
        elif tag not in VOID and len(opened) < DEPTH:
            opened.append(element)
    return root


def unseen(e: Element) -> bool:
    if e.tag in UNSEEN:
        return True
    a = e.attributes
    if not a:
        return e.tag == "dialog"
    low = a.lower()
    if "hidden" in low and (e.get("hidden") is not None or e.tag == "input" and (e.get("type") or "").lower() == "hidden"):
        return True
    if "style" in low:
        style = re.sub(r"\s+", "", (e.get("style") or "").lower())
        if "display:none" in style or "visibility:hidden" in style or "visibility:collapse" in style:
            return True
    return e.tag == "dialog" and e.get("open") is None


class Flow:
    """Lines being filled: inline text joins the open line, gaps wait for the next text."""

    def __init__(self):
        self.lines: list[str] = []
        self.open: list[str] = []
        self.space = False  # a collapsed space is due
        self.due = 0  # 1: a new line, 2: an empty line before what comes

    def _begin(self) -> None:
        if self.due == 2 and self.lines:
            self.lines.append("")
        self.due = 0

    def text(self, s: str) -> None:
        parts = _SPACES.split(s)
        if len(parts) == 1:
            if s:
                self._word(s)
            return
        body = " ".join(p for p in parts if p)
        self.space |= not parts[0]
        if body:
            self._word(body)
            self.space = not parts[-1]

    def _word(self, s: str) -> None:
        if not self.open:
            self._begin()
        elif self.space:
            self.open.append(" ")
        self.space = False
        self.open.append(s)

    def end_line(self) -> None:
        if self.open:
            self.lines.append("".join(self.open))
            self.open = []
        self.space = False

    def line_break(self) -> None:
        if self.open:
            self.end_line()
        else:
            self._begin()
            self.lines.append("")

    def gap(self, size: int) -> None:
        self.end_line()
        self.due = max(self.due, size)

    def block(self, lines: list[str], size: int) -> None:
        if lines:
            self.gap(size)
            self._begin()
            self.lines += lines
            self.due = size

    def done(self) -> list[str]:
        self.end_line()
        a, b = 0, len(self.lines)
        while a < b and not self.lines[a]:
            a += 1
        while b > a and not self.lines[b - 1]:
            b -= 1
        return self.lines[a:b]


def inside(e: Element) -> list[str]:
    flow = Flow()
    fill(e, flow)
    return flow.done()


def fill(e: Element, flow: Flow, listed: bool = False) -> None:
    for c in e.children:
        if isinstance(c, str):
            flow.text(c)
            continue
        tag = c.tag
        if unseen(c):
            continue
        if tag == "br":
            flow.line_break()
        elif tag in ("ul", "ol", "menu", "dir"):
            flow.block(item_lines(c), 1 if listed else 2)
        elif tag == "table":
            flow.block(table_lines(c), 2)
        elif tag in ("pre", "textarea", "xmp"):
            flow.block(kept_lines(c), 2)
        elif tag in ("blockquote", "dd"):
            flow.block(["  " + x if x else x for x in inside(c)], 2 if tag == "blockquote" else 1)
        elif tag in ("svg", "math"):
            draw(c, flow)
        elif tag == "q":
            flow.text("“")
            fill(c, flow, listed)
            flow.text("”")
        elif tag in APART or tag in LINES:
            size = 2 if tag in APART else 1
            flow.gap(size)
            fill(c, flow)
            flow.gap(size)
        else:
            fill(c, flow, listed)


def draw(e: Element, flow: Flow) -> None:
    """Text of a drawing or formula, in one line; what it positions stands apart by a space."""
    for c in e.children:
        if isinstance(c, str):
            flow.text(c)
        elif c.tag == "foreignobject" and not unseen(c):
            fill(c, flow)
        elif c.tag not in UNDRAWN and not unseen(c):
            apart = c.tag in DRAWN_APART or e.tag in DRAWN_APART and e.tag != "text"
            flow.text(" " if apart else "")
            draw(c, flow)
            flow.text(" " if apart else "")


def kept_lines(e: Element) -> list[str]:
    """Preformatted text with its white space."""
    out: list[str] = []

    def take(x: Element) -> None:
        for c in x.children:
            if isinstance(c, str):
                out.append(c)
            elif c.tag == "br":
                out.append("\n")
            elif c.tag in ("svg", "math") and not unseen(c):
                out.append(" ".join(inside_one(c)))
            elif not unseen(c):
                take(c)

    take(e)
    lines = "".join(out).replace("\r\n", "\n").replace("\r", "\n").expandtabs(8).removeprefix("\n").rstrip().split("\n")
    return [x.rstrip() for x in lines] if any(lines) else []


def number(text: str | None, default: int, least: int = -(10**6), most: int = 10**6) -> int:
    try:
        return min(max(int(text or ""), least), most)
    except ValueError:
        return default


def item_lines(e: Element) -> list[str]:
    out: list[str] = []
    ordered = e.tag == "ol"
    items = [c for c in e.children if isinstance(c, Element) and not unseen(c)]
    step = -1 if ordered and e.get("reversed") is not None else 1
    at = number(e.get("start"), 1 if step == 1 else sum(c.tag == "li" for c in items)) if ordered else 0
    loose = [c for c in e.children if isinstance(c, str) and c.strip()]
    if loose:  # text straight in a list is seen all the same
        out += [" ".join(" ".join(loose).split())]
    for c in items:
        flow = Flow()
        if c.tag == "li":
            fill(c, flow, listed=True)
            if ordered:
                at = number(c.get("value"), at)
            mark = f"{at}. " if ordered else "- "
            at += step
        else:  # a nested list or anything else without an item of its own
            holder = Element("")
            holder.children.append(c)
            fill(holder, flow, listed=True)
            mark = "  "
        lines = flow.done()
        if lines:
            out += [mark + lines[0], *(" " * len(mark) + x if x else x for x in lines[1:])]
    return out


def rows_of(e: Element) -> Iterator[Element]:
    """Rows in the order shown: heads first, feet last."""
    direct = [c for c in e.children if isinstance(c, Element) and not unseen(c)]
    for kinds in (("thead",), ("tr", "tbody"), ("tfoot",)):
        for c in direct:
            if c.tag in kinds:
                yield from [c] if c.tag == "tr" else rows_of(c)


def table_lines(e: Element) -> list[str]:
    out: list[str] = []
    stray = Element("")

    def part(x: Element) -> None:
        for c in x.children:
            if isinstance(c, str):
                if c.strip():
                    stray.children.append(c)
            elif c.tag in SECTIONS or c.tag == "colgroup":
                if not unseen(c):
                    part(c)
            elif c.tag == "caption" and x is e:
                if not unseen(c):
                    out.extend(inside(c))
            elif c.tag != "tr" or x.tag == "colgroup":
                stray.children.append(c)

    part(e)
    before = inside(stray)  # what stands between rows is shown before the table
    grid: list[dict[int, list[str]]] = []
    spans: dict[int, int] = {}  # columns taken from rows above: rows left
    widths: dict[int, int] = {}
    wide: list[tuple[int, int, int]] = []  # (first column, columns, width) of cells over several
    for row in rows_of(e):
        cells: dict[int, list[str]] = {}
        taken = {k for k, n in spans.items() if n > 0}
        spans = {k: n - 1 for k, n in spans.items() if n > 1}
        at = 0
        for c in row.children:
            if isinstance(c, str):
                if c.strip():
                    before.append(" ".join(c.split()))
                continue
            if unseen(c):
                continue
            if c.tag not in ("td", "th"):
                before += inside_one(c)
                continue
            while at in taken:
                at += 1
            lines = inside(c)
            across = number(c.get("colspan"), 1, 1, 1000)
            down = number(c.get("rowspan"), 1, 1, 65534)
            if down > 1:
                spans.update((k, down - 1) for k in range(at, at + across))
            cells[at] = lines
            width = max(map(len, lines), default=0)
            if across == 1:
                widths[at] = max(widths.get(at, 0), width)
            else:
                widths.setdefault(at, 0)
                wide.append((at, across, width))
            at += across
        grid.append(cells)
    columns = sorted(widths)
    for first, across, width in wide:
        inner = [k for k in columns if first <= k < first + across]
        have = sum(widths[k] for k in inner) + 2 * (len(inner) - 1)
        if inner and width > have:
            widths[inner[-1]] += width - have
    start, x = {}, 0
    for k in columns:
        start[k] = x
        x += widths[k] + 2 if widths[k] else 0
    for cells in grid:
        for i in range(max((len(c) for c in cells.values()), default=0)):
            line = ""
            for k in sorted(cells):
                if i < len(cells[k]) and cells[k][i]:
                    line = line.ljust(start[k]) + cells[k][i]
            out.append(line)
    return before + out


def inside_one(e: Element) -> list[str]:
    holder = Element("")
    holder.children.append(e)
    return inside(holder)


def visible_text(page: str | None) -> str:
    """All visible text of a page; a null page has none."""
    return "\n".join(inside(parse(page))) if page else ""


def extract(pages: DataFrame, id_col: str = "page_id", html_col: str = "html") -> DataFrame:
    """(page_id, text, n_chars, n_lines) of every page.

    Null and empty pages have an empty text; broken markup never fails; repeated
    rows are rendered each; other columns are ignored.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 500):
                part = b.slice(at, 500)
                texts = [visible_text(x) for x in part.column(1).to_pylist()]
                yield pa.record_batch([part.column(0), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64()), pa.array([t.count("\n") + 1 if t else 0 for t in texts], pa.int64())], names=["page_id", "text", "n_chars", "n_lines"])

    return pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(html_col).cast("string").alias("html")).mapInArrow(run, "page_id long, text string, n_chars long, n_lines long")
