"""Layout-aware text of HTML pages.

`Builder` turns tags into the elements of a tree, with the tags that HTML lets authors leave out, and
reports their starts, ends and texts in order. `Renderer` lays the visible ones out: blocks on lines of
their own, with blank lines where margins would be, lists with marks and indents, preformatted text as
it stands, and table cells in columns padded to the widest cell.
"""

from __future__ import annotations

import html
import re
import unicodedata
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

_TAG = re.compile(r"<!--(?:>|->|.*?(?:--!?>|\Z))|<(/?)([a-zA-Z][^\s/>]*+)((?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+)>|<(/?)([a-zA-Z][^\s/>]*+)([^>]*+)>|<[!?/][^>]*+(?:>|\Z)", re.S)
_ATTRIBUTE = re.compile(r"([^\s=/>\"']+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?", re.S)
_BLANKS = re.compile(r"[ \t\n\r\f]+")
_HIDDEN_STYLE = re.compile(r"(?:^|;)\s*(?:display\s*:\s*none|visibility\s*:\s*(?:hidden|collapse))\s*(?:!important\s*)?(?:;|$)", re.I)

# Fixed values of the HTML standard.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style xmp iframe noembed noframes".split())
ESCAPABLE = frozenset("textarea title".split())
UNSEEN = frozenset("head script style template noscript iframe noembed noframes object audio video canvas svg math datalist param source track title".split())
CLOSES_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section summary table ul xmp".split())
HEAD_ONLY = frozenset("base link meta title style script template noscript".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
#: Start tag: the open elements it ends, and those that bound the search.
ENDS = {
    "li": (("li",), ("ul", "ol", "menu", "dir")),
    "dt": (("dt", "dd"), ("dl",)),
    "dd": (("dt", "dd"), ("dl",)),
    "tr": (("tr", "td", "th", "caption"), ("table",)),
    "td": (("td", "th", "caption"), ("tr", "table")),
    "th": (("td", "th", "caption"), ("tr", "table")),
    "tbody": (("tbody", "thead", "tfoot", "tr", "td", "th", "caption"), ("table",)),
    "thead": (("tbody", "thead", "tfoot", "tr", "td", "th", "caption"), ("table",)),
    "tfoot": (("tbody", "thead", "tfoot", "tr", "td", "th", "caption"), ("table",)),
    "option": (("option",), ("select", "datalist")),
    "optgroup": (("option", "optgroup"), ("select",)),
    "rt": (("rt", "rp"), ("ruby",)),
    "rp": (("rt", "rp"), ("ruby",)),
}
BOUNDS = frozenset("table td th caption html template button object body".split())
#: Blank lines (1) or only a line of their own (0) around a block.
BLOCKS = dict.fromkeys("address article aside body caption center dd details dialog div dt fieldset figcaption figure footer form header hgroup html legend li main nav section summary option optgroup tr".split(), 0) | dict.fromkeys("blockquote dir dl h1 h2 h3 h4 h5 h6 hr menu ol p pre table ul xmp".split(), 1)
LISTS = frozenset("ul ol menu dir".split())


def attributes(text: str) -> dict[str, str]:
    return {k.lower(): html.unescape(a or b or c or "") for k, a, b, c in reversed(_ATTRIBUTE.findall(text))} if text else {}


class Builder:
    """Open elements, and what start and end tags do to them."""

    def __init__(self, out: Renderer):
        self.out, self.open = out, []

    def feed(self, text: str) -> None:
        at, n = 0, len(text)
        while at < n:
            m = _TAG.search(text, at)
            end = m.start() if m else n
            if end > at:
                self.text(text[at:end])
            if not m:
                break
            at = m.end()
            name = m[2] or m[5]
            if not name:
                continue
            name = name.lower()
            if m[1] or m[4]:
                self.end(name)
                continue
            attrs = attributes(m[3] or m[6] or "")
            self.start(name, attrs)
            if name in RAW or name in ESCAPABLE:
                close = re.compile(rf"</{re.escape(name)}(?=[\s/>])[^>]*>?", re.I).search(text, at)
                inner = text[at : close.start() if close else n]
                at = close.end() if close else n
                if name in ESCAPABLE:
                    self.out.text(html.unescape(inner))
                elif name == "xmp":
                    self.out.text(inner)
                self.end(name)
        while self.open:
            self.pop()

    def pop(self) -> None:
        self.out.end(self.open.pop())

    def text(self, data: str) -> None:
        if "&" in data:
            data = html.unescape(data)
        if self.open and self.open[-1] == "head" and data.strip(" \t\n\r\f"):
            self.pop()
        self.out.text(data)

    def start(self, name: str, attrs: dict[str, str]) -> None:
        if name in ("html", "body") and name in self.open:
            return
        if "head" in self.open and name not in HEAD_ONLY and name != "head":
            while self.open and self.open[-1] != "head":
                self.pop()
            self.pop()
        if name in CLOSES_P:
            self.close_to(("p",), BOUNDS)
            if name in HEADINGS and self.open and self.open[-1] in HEADINGS:
                self.pop()
        if name in ENDS:
            ended, bounds = ENDS[name]
            while self.close_to(ended, bounds):
                pass
        if name in ("td", "th") and self.within("table") and not self.within("tr", ("table",)):
            self.push("tr", {})
        self.push(name, attrs)
        if name in VOID:
            self.pop()

    def push(self, name: str, attrs: dict[str, str]) -> None:
        self.open.append(name)
        self.out.start(name, attrs)

    def within(self, name: str, bounds: tuple[str, ...] = ()) -> bool:
        for x in reversed(self.open):
            if x == name:
                return True
            if x in bounds:
                return False
        return False

    def close_to(self, names: tuple[str, ...], bounds) -> bool:
        """Ends the innermost open element of these, and all in it, unless a bound is nearer."""
        for i in range(len(self.open) - 1, -1, -1):
            if self.open[i] in names:
                while len(self.open) > i:
                    self.pop()
                return True
            if self.open[i] in bounds:
                return False
        return False

    def end(self, name: str) -> None:
        if name in VOID:
            if name == "br":
                self.start("br", {})
            return
        if name == "p" and not self.within("p", tuple(BOUNDS)):
            self.push("p", {})
        if name in HEADINGS:
            self.close_to(tuple(HEADINGS), BOUNDS)
            return
        bounds = ("table",) if name in ("tr", "td", "th", "tbody", "thead", "tfoot", "caption") else () if name in ("html", "body", "table") else ("td", "th", "caption", "table")
        if name in ("html", "body"):
            return  # what follows still belongs to the body
        self.close_to((name,), bounds)


class _Flow:
    """Lines of one block context: the page, or a table cell."""

    def __init__(self):
        self.lines: list[str] = []
        self.now: list[str] = []
        self.blank = 0  # blank lines due before the next line
        self.space = False
        self.mark = ""

    def break_line(self, margin: int = 0) -> None:
        if self.now:
            self.lines.append("".join(self.now).rstrip(" "))
            self.now, self.blank = [], 0
        self.space = False
        self.blank = max(self.blank, margin)

    def put(self, text: str, indent: str) -> None:
        if not self.now:
            if self.lines and self.blank:
                self.lines += [""] * self.blank
            self.blank = 0
            self.now.append(indent + self.mark)
            self.mark = ""
        elif self.space:
            self.now.append(" ")
        self.space = False
        self.now.append(text)


def _number(text: str | None, most: int) -> int:
    """A span attribute; 1 where it is missing or no number."""
    text = (text or "").strip()
    return min(int(text), most) if text.isascii() and text.isdecimal() else 1


def _placed(rows: list[list[tuple[list[str], int, int]]]) -> list[list[tuple[list[str], int]]]:
    """The cells (lines, columns) of each row, with empty ones where a cell of a row above reaches down; 0 rows: to the last."""
    out, below = [], []  # below: how many rows each column is still taken, this one included
    for i, row in enumerate(rows):
        placed, col = [], 0
        for lines, span, down in row:
            while col < len(below) and below[col]:
                placed.append(([], 1))
                col += 1
            placed.append((lines, span))
            below += [0] * (col + span - len(below))
            below[col : col + span] = [min(down or len(rows), len(rows) - i)] * span
            col += span
        out.append(placed)
        below = [max(0, x - 1) for x in below]
    return out


def width(text: str) -> int:
    """Columns of a text: wide characters take two, combining ones none."""
    return len(text) if text.isascii() else sum(0 if unicodedata.combining(c) else 1 + (unicodedata.east_asian_width(c) in "WF") for c in text)


class Renderer:
    def __init__(self):
        self.flows = [_Flow()]
        self.hidden = 0
        self.stack: list[tuple[str, bool]] = []
        self.lists: list[list] = []
        self.tables: list[list[list[tuple[list[str], int, int]]]] = []
        self.indent = 0
        self.pre = 0

    def start(self, name: str, attrs: dict[str, str]) -> None:
        unseen = name in UNSEEN or "hidden" in attrs or ("style" in attrs and bool(_HIDDEN_STYLE.search(attrs["style"])))
        unseen |= name == "dialog" and "open" not in attrs
        self.stack.append((name, unseen))
        if unseen:
            self.hidden += 1
        if self.hidden:
            return
        flow = self.flows[-1]
        if name in ("td", "th") and self.tables:
            self.flows.append(_Flow())
            if not self.tables[-1]:
                self.tables[-1].append([])
            self.tables[-1][-1].append(([], _number(attrs.get("colspan"), 1000) or 1, _number(attrs.get("rowspan"), 65534)))
            return
        if name == "tr" and self.tables:
            self.tables[-1].append([])
            return
        if name == "table":
            flow.break_line(1)
            self.tables.append([])
            return
        if name == "br":
            if flow.now:
                flow.break_line()
            elif flow.lines:
                flow.blank += 1
            return
        if name in BLOCKS:
            flow.break_line(0 if self.lists and name in LISTS else BLOCKS[name])
        if name in LISTS:
            start = attrs.get("start", "1")
            self.lists.append([name == "ol", int(start) if re.fullmatch(r"-?\d{1,9}", start) else 1])
            self.indent += 2 if len(self.lists) > 1 else 0
        elif name == "li":
            if self.lists and self.lists[-1][0]:
                value = attrs.get("value", "")
                self.lists[-1][1] = int(value) if re.fullmatch(r"-?\d{1,9}", value) else self.lists[-1][1]
                flow.mark = f"{self.lists[-1][1]}. "
                self.lists[-1][1] += 1
            else:
                flow.mark = "- "
        elif name in ("blockquote", "dd"):
            self.indent += 2
        elif name in ("pre", "xmp", "textarea"):
            self.pre += 1
        elif name == "img" and attrs.get("alt", "").strip():
            self.text(attrs["alt"])

    def end(self, name: str) -> None:
        _, unseen = self.stack.pop()
        if self.hidden:
            self.hidden -= unseen
            return
        flow = self.flows[-1]
        if name in ("td", "th") and self.tables:
            flow.break_line()
            self.flows.pop()
            self.tables[-1][-1][-1][0].extend(flow.lines)
            return
        if name == "tr" and self.tables:
            return
        if name == "table":
            self._lay_out(self.tables.pop())
            return
        if name in BLOCKS:
            flow.break_line(0 if len(self.lists) > 1 and name in LISTS else BLOCKS[name])
        if name in LISTS:
            self.indent -= 2 if len(self.lists) > 1 else 0
            self.lists.pop()
        elif name == "li":
            flow.mark = ""
        elif name in ("blockquote", "dd"):
            self.indent -= 2
        elif name in ("pre", "xmp", "textarea"):
            self.pre -= 1

    def text(self, data: str) -> None:
        if self.hidden:
            return
        flow, indent = self.flows[-1], " " * self.indent
        if self.pre:
            lines = data.replace("\r\n", "\n").split("\n")
            if not flow.now and lines and lines[0] == "":
                lines = lines[1:]
            for i, line in enumerate(lines):
                if i:
                    flow.break_line()
                    if not lines[i - 1]:
                        flow.blank += 1
                if line:
                    flow.put(line, indent)
            return
        words = [x for x in _BLANKS.split(data) if x]
        if not words:
            flow.space |= bool(data) and bool(flow.now)
            return
        flow.space |= data[0] in " \t\n\r\f"
        flow.put(" ".join(words), indent)
        flow.space = data[-1] in " \t\n\r\f"

    def _lay_out(self, cells: list[list[tuple[list[str], int, int]]]) -> None:
        flow, widths, rows = self.flows[-1], [], _placed(cells)
        for row in rows:
            col = 0
            for lines, span in row:
                widths += [0] * (col + span - len(widths))
                if span == 1:
                    widths[col] = max(widths[col], max(map(width, lines), default=0))
                col += span
        for row in rows:  # a cell over several columns that is wider than they are widens the last
            col = 0
            for lines, span in row:
                if span > 1:
                    room = sum(widths[col : col + span]) + 2 * (span - 1)
                    widths[col + span - 1] += max(0, max(map(width, lines), default=0) - room)
                col += span
        flow.break_line()
        for row in rows:
            for k in range(max((len(lines) for lines, _ in row), default=0)):
                parts, col = [], 0
                for lines, span in row:
                    cell = lines[k] if k < len(lines) else ""
                    room = sum(widths[col : col + span]) + 2 * (span - 1)
                    parts.append(cell + " " * max(0, room - width(cell)))
                    col += span
                line = "  ".join(parts).rstrip(" ")
                if line:
                    flow.put(line, " " * self.indent)
                    flow.break_line()
        flow.break_line(1)

    def result(self) -> str:
        self.flows[0].break_line()
        return "\n".join(self.flows[0].lines)


def extract(page: str | None) -> str:
    """The visible text of one page; a null page has none."""
    out = Renderer()
    Builder(out).feed(page or "")
    return out.result()


def extract_pages(pages: DataFrame, id_col: str = "page_id", html_col: str = "html") -> DataFrame:
    """(id, text) of every row.

    All visible text is kept, also navigation and footers; scripts, styles, comments, the head and
    elements hidden by attribute or inline style are not. Null, empty and broken pages give what text
    they have. Rows are independent: repeated rows give repeated results, null ids stay null, an
    empty table gives no rows. Other columns are ignored.
    """

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 500):
                part = batch.slice(lo, 500)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([extract(x) for x in part.column(1).to_pylist()], pa.string())], ["page_id", "text"])

    return pages.select(F.col(f"`{id_col}`").cast("long").alias("i"), F.col(f"`{html_col}`").cast("string").alias("h")).mapInArrow(work, "page_id long, text string").withColumnRenamed("page_id", id_col)
