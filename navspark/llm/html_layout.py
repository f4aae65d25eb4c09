"""Layout-aware HTML to text.

A tokenizer and a tree builder with implied tags make a tree of elements; visibility rules
prune it (``display`` drops a subtree, ``visibility`` is inherited and may be set again below); a
renderer emits all visible text with block spacing, list marks and aligned table cells. Trees
are walked with explicit stacks, so nesting depth is no limit, and the time is linear in the
page, whatever its markup.

Defined results: null or empty html gives an empty text; broken markup never fails; a quoted
value that is never closed ends its tag at the next >; a page that ends inside a tag or comment
ends before it; list marks are indented by at most 40 levels; repeated rows are rendered each;
null ids are carried; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import re
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: Elements whose content is no text of the page.
UNSEEN = frozenset("script style template noscript head title iframe object svg math canvas audio video datalist select".split())
RAW = frozenset("script style textarea title xmp iframe noembed noframes".split())
#: Blocks set off by an empty line, and blocks that only begin on a line of their own.
SPACED = frozenset("p h1 h2 h3 h4 h5 h6 ul ol dl table blockquote pre figure form fieldset hr article section main header footer nav aside".split())
BLOCKS = SPACED | frozenset("div li dt dd tr td th caption thead tbody tfoot address figcaption details summary html body center option legend".split())
#: A start tag (key) ends open elements (first), looked for up to a boundary (second).
_P = frozenset(["p"])
_CELLS = frozenset(["td", "th"])
_TABLE = frozenset(["table"])
IMPLIED = {
    "li": (frozenset(["li"]), frozenset(["ul", "ol"])),
    "dt": (frozenset(["dt", "dd"]), frozenset(["dl"])),
    "dd": (frozenset(["dt", "dd"]), frozenset(["dl"])),
    "td": (_CELLS, frozenset(["tr", "table"])),
    "th": (_CELLS, frozenset(["tr", "table"])),
    "tr": (frozenset(["tr", "caption"]), _TABLE),
    "thead": (frozenset(["thead", "tbody", "tfoot", "caption"]), _TABLE),
    "tbody": (frozenset(["thead", "tbody", "tfoot", "caption"]), _TABLE),
    "tfoot": (frozenset(["thead", "tbody", "tfoot", "caption"]), _TABLE),
    "option": (frozenset(["option"]), frozenset(["select", "datalist"])),
    "body": (frozenset(["head"]), frozenset()),
}
_CLOSES_P = frozenset("address article aside blockquote center details div dl fieldset figure footer form h1 h2 h3 h4 h5 h6 header hr main nav ol p pre section table ul li".split())
_P_BOUNDS = frozenset(["td", "th", "table", "body", "html", "button", "object", "caption"])
_CLOSE_BOUNDS = {"li": frozenset(["ul", "ol"]), "p": _P_BOUNDS, "td": _TABLE, "th": _TABLE, "tr": _TABLE}

_NAME = re.compile(r"<(/?)([a-zA-Z][^\s/>]*)")
_STOP = re.compile(r">|=\s*([\"'])")
_ATTR = re.compile(r"([^\s=/>\"']+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?")
_SPACES = re.compile(r"[ \t\n\r\f\v]+")
_INDENT = 40
_BLANKS = 1000


class Node:
    __slots__ = ("tag", "attrs", "kids")

    def __init__(self, tag: str, attrs: str = ""):
        self.tag, self.attrs = tag, attrs
        self.kids: list[Node | str] = []

    def get(self, name: str) -> str | None:
        if not self.attrs or name not in self.attrs.lower():
            return None
        for m in _ATTR.finditer(self.attrs):
            if m[1].lower() == name:
                return unescape(next((g for g in m.groups()[1:] if g is not None), ""))
        return None

    def style(self, name: str) -> str | None:
        """Value of a property in the style attribute; the last one counts, an important one first."""
        got, strong = None, False
        for part in (self.get("style") or "").split(";"):
            key, colon, value = part.partition(":")
            if colon and key.strip().lower() == name:
                value = value.strip().lower()
                must = value.endswith("!important")
                if must or not strong:
                    got, strong = value.removesuffix("!important").strip(), must
        return got

    def gone(self) -> bool:
        """Whether the element and all below it take no part in the page."""
        if self.tag in UNSEEN:
            return True
        if self.tag == "dialog" and self.get("open") is None:
            return True
        display = self.style("display") if self.attrs else None
        return display == "none" if display else bool(self.attrs) and self.get("hidden") is not None

    def shown(self, above: bool) -> bool:
        """Whether its own text is visible, given that of the element above."""
        value = self.style("visibility") if self.attrs else None
        return above if value in (None, "", "inherit") else value not in ("hidden", "collapse")


def parse(html: str) -> Node:
    """Tree of the document. End tags without a start are dropped; what is open at the end closes.

    Each step is constant in what is open: for every tag the places of its open elements are known,
    so nothing walks the stack, and what was once searched for in vain is not searched for again.
    """
    root = Node("#root")
    stack = [root]
    places: dict[str, list[int]] = {}
    missing: set[str] = set()

    def find(what: str, start: int) -> int:
        if what in missing:
            return -1
        i = html.find(what, start)
        if i < 0:
            missing.add(what)
        return i

    def close(names, bounds) -> None:
        at = max((places[t][-1] for t in names if places.get(t)), default=0)
        if at > max((places[t][-1] for t in bounds if places.get(t)), default=0):
            for node in reversed(stack[at:]):
                places[node.tag].pop()
            del stack[at:]

    def text(s: str) -> None:
        if s:
            stack[-1].kids.append(unescape(s) if "&" in s else s)

    at, done = 0, len(html)
    while at < done:
        begin = find("<", at)
        if begin < 0:
            text(html[at:])
            break
        text(html[at:begin])
        m = _NAME.match(html, begin)
        if not m:
            if html.startswith("<!--", begin):
                end = find("-->", begin + 4)
                at = end + 3 if end >= 0 else done
            elif html[begin + 1 : begin + 2] in ("!", "?", "/"):
                end = find(">", begin)
                at = end + 1 if end >= 0 else done
            else:
                text("<")
                at = begin + 1
            continue
        # The tag ends at a > outside quoted values; a quote that is never closed quotes nothing.
        pos = m.end()
        while (stop := _STOP.search(html, pos) if ">" not in missing else None) and stop[1]:
            end = find(stop[1], stop.end())
            pos = end + 1 if end >= 0 else stop.end()
        if not stop:
            missing.add(">")
            break  # the page ends inside a tag
        at = stop.end()
        tag = m[2].lower()
        if m[1]:
            close((tag,), _CLOSE_BOUNDS.get(tag, ()))
            continue
        if tag in _CLOSES_P:
            close(_P, _P_BOUNDS)
        if tag in IMPLIED:
            close(*IMPLIED[tag])
        if tag == "tr":
            close(("tr",), _TABLE)
        node = Node(tag, html[m.end() : stop.start()])
        stack[-1].kids.append(node)
        if tag in RAW:
            end = re.compile(f"</{tag}[\\s/>]", re.I).search(html, at)
            body = html[at : end.start()] if end else html[at:]
            if tag == "textarea":
                node.kids.append(unescape(body))
            close_at = find(">", end.start()) if end else -1
            at = close_at + 1 if close_at >= 0 else done
        elif tag not in VOID:
            places.setdefault(tag, []).append(len(stack))
            stack.append(node)
    return root


class _Page:
    """Lines of text with pending block breaks and collapsed spaces."""

    def __init__(self):
        self.parts: list[str] = []
        self.breaks = 0
        self.space = False
        self.fresh = True  # nothing on the line yet
        self.mark = ""

    def block(self, lines: int) -> None:
        if self.parts:
            self.breaks = max(self.breaks, lines)
        self.space = False

    def line(self) -> None:
        if self.parts:
            self.breaks = max(self.breaks + 1 if self.breaks else 1, 1)
        self.space = False

    def _flush(self) -> None:
        if self.breaks:
            self.parts.append("\n" * min(self.breaks, 2))
            self.breaks, self.fresh = 0, True
        if self.mark:
            self.parts.append(self.mark)
            self.mark, self.fresh = "", True

    def inline(self, s: str) -> None:
        words = _SPACES.sub(" ", s)
        if words == " " or not words:
            self.space = self.space or bool(words)
            return
        body = words.strip(" ")
        lead = (self.space or words[0] == " ") and not self.breaks and not self.fresh and not self.mark
        if not self.parts:
            lead = False
        self._flush()
        self.parts.append(" " + body if lead else body)
        self.fresh, self.space = False, words[-1] == " "

    def exact(self, s: str) -> None:
        if s:
            self._flush()
            self.parts.append(s)
            self.fresh = self.space = False

    def text(self) -> str:
        return "".join(self.parts)


def _number(value: str | None, least: int, most: int) -> int:
    value = (value or "").strip()
    return max(least, min(int(value), most)) if value.isascii() and value.isdecimal() and len(value) < 10 else least


def _table_lines(table: Node, shown: bool) -> list[str]:
    """A table's rows with aligned cells, and other text inside it, in the order of the page.

    Nested tables stay inside their cell. A cell's spans leave blank cells, in all at most
    ``_BLANKS`` and four for each cell that there is.
    """
    items: list[str | list[str]] = []
    stray: list[str] = []
    below: dict[int, int] = {}  # column: last row that a cell above spans
    row_no, blanks = 0, _BLANKS
    stack: list[tuple[Node | str, bool]] = [(x, shown) for x in reversed(table.kids)]

    def loose(x: Node | str, shown: bool) -> str:
        return _SPACES.sub(" ", _flow(x, shown, True)).strip(" ")

    while stack:
        x, shown = stack.pop()
        if isinstance(x, Node):
            if x.gone():
                continue
            shown = x.shown(shown)
        if isinstance(x, Node) and x.tag in ("td", "th"):
            stray.append(loose(x, shown))
            continue
        if stray:
            items.append(stray)
            stray = []
        if isinstance(x, Node) and x.tag in ("thead", "tbody", "tfoot"):
            stack.extend((k, shown) for k in reversed(x.kids))
        elif isinstance(x, Node) and x.tag == "tr":
            row: list[str] = []
            row_no += 1
            for c in x.kids:
                if isinstance(c, Node) and c.gone():
                    continue
                one = loose(c, c.shown(shown) if isinstance(c, Node) else shown)
                if not one and not isinstance(c, Node):
                    continue
                while below.get(len(row), 0) >= row_no and blanks > 0:
                    row.append("")
                    blanks -= 1
                at, wide, high = len(row), 1, 1
                if isinstance(c, Node):
                    wide, high = _number(c.get("colspan"), 1, 100), _number(c.get("rowspan"), 1, 65_534)
                blanks += 4
                wide = min(wide, 1 + max(0, blanks))
                blanks -= wide - 1
                row += [one] + [""] * (wide - 1)
                if high > 1:
                    below |= dict.fromkeys(range(at, at + wide), row_no + high - 1)
            if any(row):
                items.append(row)
        elif one := loose(x, shown):
            items.append(one)
    if stray:
        items.append(stray)
    return _aligned(items)


def _aligned(items: list[str | list[str]]) -> list[str]:
    widths: list[int] = []
    for row in items:
        if isinstance(row, list):
            widths += [0] * (len(row) - len(widths))
            for i, c in enumerate(row):
                widths[i] = max(widths[i], min(len(c), 60))
    out = []
    for row in items:
        if isinstance(row, str):
            out.append(row)
        elif any(row):
            out.append(row[0] if len(widths) == 1 else " | ".join([*(c.ljust(widths[i]) for i, c in enumerate(row[:-1])), row[-1]]).rstrip())
    return out


def _flow(top: Node | str, shown: bool, flat: bool) -> str:
    """Text of a subtree. ``flat``: inside a cell, where a table is a run of blocks like any other
    (so tables nested ever deeper need no recursion) and the caller joins the lines."""
    page = _Page()
    lists: list[list] = []  # kind and next number of the open lists
    pre = 0
    stack: list[tuple[Node | str, bool, bool]] = [(top, shown, False)]
    while stack:
        x, shown, leaving = stack.pop()
        if isinstance(x, str):
            if shown:
                page.exact(x) if pre else page.inline(x)
            continue
        tag = x.tag
        if leaving:
            if tag in ("ul", "ol"):
                lists.pop()
            elif tag == "pre":
                pre -= 1
            page.block(2 if tag in SPACED and not (tag in ("ul", "ol") and lists) else 1)
            if tag == "li":
                page.mark = ""
            continue
        if x.gone():
            continue
        shown = x.shown(shown)
        if tag == "br":
            page.line()
            continue
        if tag == "img":
            if shown:
                page.inline(x.get("alt") or "")
            continue
        if tag == "input":
            kind = (x.get("type") or "text").lower()
            if shown and kind in ("submit", "button", "reset", "text", "search"):
                page.inline(x.get("value") or "")
            continue
        if tag == "table" and not flat:
            page.block(2)
            for line in _table_lines(x, shown):
                page.block(1)
                page.exact(line)
            page.block(2)
            continue
        if tag in BLOCKS:
            page.block(2 if tag in SPACED and not (tag in ("ul", "ol") and lists) else 1)
            if tag in ("ul", "ol"):
                lists.append([tag, _number(x.get("start"), 0, 10**9) if tag == "ol" and x.get("start") else 1])
            elif tag == "li":
                indent = "  " * min(len(lists) - 1, _INDENT)
                if lists and lists[-1][0] == "ol":
                    page.mark = f"{indent}{lists[-1][1]}. "
                    lists[-1][1] += 1
                else:
                    page.mark = indent + "- "
            elif tag == "dd":
                page.mark = "  "
            elif tag == "pre":
                pre += 1
            stack.append((x, shown, True))
        stack.extend((k, shown, False) for k in reversed(x.kids))
    return page.text()


def render(html: str | None) -> str:
    return _flow(parse(html or ""), True, False)


def rendered(pages: DataFrame) -> DataFrame:
    """page_id and text of each row."""

    def run(batches):
        for b in batches:
            out = [render(h.as_py()) for h in b.column("html")]
            yield pa.RecordBatch.from_arrays([b.column("page_id"), pa.array(out, pa.string())], ["page_id", "text"])

    return pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("html").cast("string").alias("html")).mapInArrow(run, "page_id long, text string")


def op5_result(pages: DataFrame) -> DataFrame:
    got = rendered(pages)
    return got.select("page_id", "text", F.char_length("text").cast("long").alias("n_chars"), F.when(F.col("text") == "", 0).otherwise(F.size(F.split("text", "\n"))).cast("long").alias("n_lines"))
