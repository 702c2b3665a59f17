"""HTML extraction by layout-aware rendering: a tree with implied tags, visibility rules, and a renderer of blocks.

All visible text is kept: paragraphs and headings are set apart by an empty line, other blocks start a new line, list
items carry a bullet or their number and are indented by depth, cells of a table are padded to the width of their
column.  Invisible: elements that browsers never show (head, script, style, template, ...), the ``hidden`` attribute,
inline ``display:none`` or ``visibility:hidden``, hidden inputs, and selectors of one class, id or tag which a style
sheet of the page sets to ``display:none``.  Closed ``details`` and ``aria-hidden`` text count as visible.

A null or empty page has an empty text.  Broken markup never fails: unclosed elements end with the page, stray end
tags are dropped, a ``<`` that opens no tag is text.  Pages are rendered one by one in the scan; repeats, ties and
skew do not matter; extra columns are not read.
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from walkengine.llm.common import only, read_table

#: Element names by their part in the layout.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp iframe noembed noframes".split())
UNSEEN = frozenset("head script style title meta link base template noscript iframe noembed noframes object audio video canvas datalist metadata desc defs annotation annotation-xml".split())
BLOCK = frozenset(
    "html body address article aside blockquote center dd details dialog dir div dl dt fieldset figcaption figure footer form "
    "h1 h2 h3 h4 h5 h6 header hgroup hr legend li main menu nav ol p pre search section summary table ul option optgroup".split()
)
SPACED = frozenset("p h1 h2 h3 h4 h5 h6 ul ol dl table pre blockquote figure".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
#: An opening tag ends these open elements, unless one of the second names stands between.
_CLOSES_P = frozenset(BLOCK - {"html", "body", "option", "optgroup", "legend"})
IMPLIED_END = {
    "li": ({"li"}, {"ul", "ol", "menu", "dir"}),
    "dt": ({"dt", "dd"}, {"dl"}),
    "dd": ({"dt", "dd"}, {"dl"}),
    "option": ({"option"}, {"select", "datalist"}),
    "optgroup": ({"option", "optgroup"}, {"select"}),
    "tr": ({"tr", "td", "th", "caption", "colgroup"}, {"table"}),
    "td": ({"td", "th"}, {"table", "tr"}),
    "th": ({"td", "th"}, {"table", "tr"}),
    "thead": ({"thead", "tbody", "tfoot", "tr", "td", "th", "caption", "colgroup"}, {"table"}),
    "tbody": ({"thead", "tbody", "tfoot", "tr", "td", "th", "caption", "colgroup"}, {"table"}),
    "tfoot": ({"thead", "tbody", "tfoot", "tr", "td", "th", "caption", "colgroup"}, {"table"}),
    "body": ({"head"}, set()),
}
#: Elements that an end tag of something outside can't cross.
_BARRIER = frozenset({"table", "td", "th", "caption", "template", "object"})
_END_BARRIER = {"table": frozenset()} | dict.fromkeys("td th tr thead tbody tfoot caption".split(), frozenset({"table"}))

_TAG = re.compile(
    r"<!--(?:.*?--!?>|.*)|<!\[CDATA\[.*?(?:\]\]>|$)|<[!?][^>]*>?"
    r"|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+)>"
    r"|<(/?)([a-zA-Z][^\s/>]*)([^>]*)(?:>|$)",
    re.S,
)
_ATTRIBUTE = re.compile(r"([^\s=/\"'>]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?")
_SHEET_RULE = re.compile(r"([^{}]+)\{[^{}]*display\s*:\s*none[^{}]*\}", re.I)
_MEDIA = re.compile(r"@media([^{}]*)\{((?:[^{}]*\{[^{}]*\})*)[^{}]*\}", re.I)
_NUMBER = re.compile(r"\s*([+-]?[0-9]{1,9})(?![0-9])")
_HIDDEN_STYLE = re.compile(r"display\s*:\s*none|visibility\s*:\s*(?:hidden|collapse)", re.I)
_GAP = re.compile(r"[ \t\n\r\f]+")


class Node:
    __slots__ = ("name", "attributes", "children")

    def __init__(self, name: str, attributes: dict[str, str]):
        self.name, self.attributes = name, attributes
        self.children: list[Node | str] = []


def _attributes(text: str) -> dict[str, str]:
    if not text or text.isspace():
        return {}
    found: dict[str, str] = {}
    for name, a, b, c in _ATTRIBUTE.findall(text):
        found.setdefault(name.lower(), html.unescape(a or b or c))
    return found


def parse(page: str) -> tuple[Node, list[str]]:
    """(tree, style sheets).  End tags that the page omits are implied."""
    root = Node("#root", {})
    stack, sheets, at = [root], [], 0

    def close(names, barrier) -> None:
        for depth in range(len(stack) - 1, 0, -1):
            name = stack[depth].name
            if name in names:
                del stack[depth:]
                return
            if name in barrier:
                return

    while True:
        match = _TAG.search(page, at)
        end = match.start() if match else len(page)
        if end > at:
            stack[-1].children.append(html.unescape(page[at:end]))
        if not match:
            return root, sheets
        at = match.end()
        slash, name, rest = match.group(1, 2, 3) if match.group(2) else match.group(4, 5, 6)
        if not name:
            if page.startswith("<![CDATA[", match.start()):
                stack[-1].children.append(match.group()[9:].removesuffix("]]>"))
            continue
        name = name.lower()
        if slash:
            if name == "p" and not any(n.name == "p" for n in stack):
                stack[-1].children.append(Node("p", {}))
            elif name in HEADINGS:
                close(HEADINGS, _BARRIER)
            elif name not in VOID:
                close({name}, _END_BARRIER.get(name, _BARRIER))
            continue
        if name in _CLOSES_P:
            close({"p"}, _BARRIER | {"button", "li", "div", "section", "article", "blockquote"})
        if name in IMPLIED_END:
            names, barrier = IMPLIED_END[name]
            if len(names) == 1:
                close(names, barrier)
            else:
                while any(n.name in names for n in _until(stack, barrier)):
                    close(names, barrier)
        node = Node(name, _attributes(rest))
        stack[-1].children.append(node)
        if name in RAW:
            stop = re.compile(rf"</{name}[\s/>]", re.I).search(page, at)
            body = page[at : stop.start()] if stop else page[at:]
            at = page.find(">", stop.start()) + 1 or len(page) if stop else len(page)
            if name == "style":
                sheets.append(body)
            elif name not in UNSEEN:
                node.children.append(html.unescape(body))
        elif name not in VOID:
            stack.append(node)


def _until(stack: list[Node], barrier) -> Iterator[Node]:
    for node in reversed(stack):
        if node.name in barrier:
            return
        yield node


def _number(text: str, default: int) -> int:
    """The number that an attribute begins with; the default where it begins with none or with more than nine digits."""
    found = _NUMBER.match(text)
    return int(found[1]) if found else default


def hidden_selectors(sheets: list[str]) -> set[str]:
    """Selectors of one class, id or tag that a sheet never shows on a screen.  Rules under a media query with a condition
    or for another medium are passed over, since they hold for some readers alone."""
    found = set()
    for sheet in sheets:
        sheet = _MEDIA.sub(lambda m: m[2] if m[1].strip().lower() in ("", "all", "screen", "only screen") else "", sheet)
        for names in _SHEET_RULE.findall(sheet):
            found |= {s.strip() for s in names.split(",") if re.fullmatch(r"[.#]?[\w-]+", s.strip())}
    return found


def _visible(node: Node, unseen: set[str]) -> bool:
    name, own = node.name, node.attributes
    if name in UNSEEN:
        return False
    if not own and not unseen:
        return True
    if "hidden" in own or (name == "input" and own.get("type", "").lower() == "hidden"):
        return False
    if "style" in own and _HIDDEN_STYLE.search(own["style"]):
        return False
    if name == "dialog" and "open" not in own:
        return False
    keys = [name, *("." + c for c in own.get("class", "").split()), "#" + own.get("id", "")]
    return unseen.isdisjoint(keys)


class _Page:
    """Lines of text under way.  ``line`` gathers inline text; an empty line is asked for, never doubled."""

    def __init__(self, unseen: set[str]):
        self.unseen, self.lines, self.line, self.indent, self.lead = unseen, [], [], "", ""
        self.blank = False

    def put(self, text: str, keep: bool) -> None:
        if keep:
            first, *more = text.split("\n")
            self.line.append(first)
            for x in more:
                self.flush(keep=True)
                self.line.append(x)
        else:
            self.line.append(text)

    def flush(self, keep: bool = False) -> None:
        text = "".join(self.line)
        self.line.clear()
        text = text.rstrip() if keep else _GAP.sub(" ", text).strip(" ")
        if not text and not (keep and self.lines):
            return
        if self.blank and self.lines and self.lines[-1]:
            self.lines.append("")
        self.blank = False
        self.lines.append((self.lead or self.indent) + text if text else "")
        self.lead = ""

    def gap(self) -> None:
        self.flush()
        self.blank = True


def _render(root: Node, unseen: set[str], tables: dict[int, list[str]]) -> list[str]:
    """Walks the tree with a stack of its own, so depth is bounded by memory alone; ``tables`` has the lines of the
    tables below, which are laid out before."""
    page = _Page(unseen)
    work: list[tuple] = [("open", root, False, [])]
    while work:
        step, node, keep, lists = work.pop()
        if step == "close":
            node(page)
            continue
        if isinstance(node, str):
            page.put(node, keep)
            continue
        name = node.name
        if name == "br":
            page.flush(keep)
            continue
        if name == "hr":
            page.gap()
            continue
        if not _visible(node, unseen):
            continue
        if name == "table":
            page.gap()
            for line in tables[id(node)]:
                page.lines += [""] * bool(page.blank and page.lines and page.lines[-1])
                page.blank = False
                page.lines.append((page.lead or page.indent) + line)
                page.lead = ""
            page.gap()
            continue
        if name in BLOCK:
            spaced = name in SPACED and not (name in ("ul", "ol") and lists)
            page.gap() if spaced else page.flush(keep)
            ended = _Page.gap if spaced else _Page.flush
            if name in ("ul", "ol", "menu", "dir"):
                lists = [*lists, [name == "ol", _number(node.attributes.get("start", "1"), 1) - 1]]
            elif name == "li":
                counter = lists[-1] if lists else [False, 0]
                counter[1] += 1
                old, depth = page.indent, "  " * max(0, len(lists) - 1)
                mark = f"{counter[1]}. " if counter[0] else "- "
                page.lead, page.indent = depth + mark, depth + " " * len(mark)

                def ended(page, old=old):
                    page.flush()
                    page.indent, page.lead = old, ""

            elif name == "blockquote":
                old = page.indent
                page.indent += "  "

                def ended(page, old=old):
                    page.gap()
                    page.indent = old

            work.append(("close", ended, False, lists))
        keep = keep or name in ("pre", "textarea", "xmp")
        work.extend(("open", child, keep, lists) for child in reversed(node.children))
    page.flush()
    return page.lines


def _rows(table: Node, unseen: set[str]) -> Iterator[tuple[str, list[Node]]]:
    """Captions and rows in order; cells without a row are a row of their own."""
    loose: list[Node] = []
    open_parts = [iter(table.children)]
    while open_parts:
        child = next(open_parts[-1], None)
        if child is None:
            open_parts.pop()
            if loose:
                yield "row", loose
                loose = []
        elif isinstance(child, str):
            if child.strip():
                loose.append(child)
        elif not _visible(child, unseen):
            continue
        elif child.name in ("td", "th"):
            loose.append(child)
        else:
            if loose:
                yield "row", loose
                loose = []
            if child.name == "tr":
                yield "row", [c for c in child.children if not isinstance(c, str) or c.strip()]
            elif child.name in ("thead", "tbody", "tfoot"):
                open_parts.append(iter(child.children))
            elif child.name not in ("colgroup", "col"):
                yield "caption", [child]


def _laid_out(root: Node, unseen: set[str]) -> dict[int, list[str]]:
    """The lines of every table, inner ones first."""
    found, work = [], [root]
    while work:
        node = work.pop()
        if node.name == "table":
            found.append(node)
        work.extend(c for c in node.children if not isinstance(c, str))
    tables: dict[int, list[str]] = {}
    for node in reversed(found):  # a table is found before the tables in it
        tables[id(node)] = _table(node, unseen, tables)
    return tables


def _table(table: Node, unseen: set[str], tables: dict[int, list[str]]) -> list[str]:
    grid: list[tuple[str, list[str]]] = []
    for kind, cells in _rows(table, unseen):
        texts = []
        for cell in cells:
            if isinstance(cell, str):
                texts.append(_GAP.sub(" ", cell).strip())
            elif _visible(cell, unseen):
                inner = Node("#cell", {})
                inner.children = cell.children
                texts.append(" ".join(x.strip() for x in _render(inner, unseen, tables) if x))
                texts += [""] * (min(_number(cell.attributes.get("colspan", "1"), 1), 1000) - 1)
        if any(texts):
            grid.append((kind, texts))
    width: list[int] = []
    for kind, texts in grid:
        if kind == "row":
            width += [0] * (len(texts) - len(width))
            for i, t in enumerate(texts):
                width[i] = max(width[i], len(t))
    out = []
    for kind, texts in grid:
        cells = [t.ljust(width[i]) for i, t in enumerate(texts)] if kind == "row" else texts
        out.append(" | ".join(cells).rstrip(" ").rstrip("|").rstrip(" ") if kind == "row" else texts[0])
    return out


def render(page: str | None) -> str:
    """The visible text of a page."""
    root, sheets = parse(page or "")
    unseen = hidden_selectors(sheets)
    return "\n".join(_render(root, unseen, _laid_out(root, unseen))).strip("\n")


def extract(pages: DataFrame, key: str = "page_id", markup: str = "html") -> DataFrame:
    """key, text, n_lines, n_chars of every page."""
    kind = pages.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [render(x) for x in batch[markup].to_pylist()]
            columns = [batch[key], pa.array(texts, pa.string()), pa.array([t.count("\n") + bool(t) for t in texts], pa.int64())]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(map(len, texts), pa.int64())], names=[key, "text", "n_lines", "n_chars"])

    return only(pages, key, markup).mapInArrow(run, f"{key} {kind}, text string, n_lines long, n_chars long")


def op7_html_extract(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(read_table(spark, sf_dir, "pages"))


QUERIES = {"op7_html_extract": op7_html_extract}
ORACLES: dict[str, str] = {}
