"""HTML extraction by layout-aware rendering.

A tokenizer and a tree builder with implied tags make an element tree from any input; visibility
rules drop what a browser does not show; the renderer then writes all visible text with blank lines
around blocks, list markers, preformatted text as it is, and table cells in aligned columns.
Everything is linear in the page, without recursion, so depth and length are bounded by memory only.
"""

from __future__ import annotations

import html
import re
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame

from sigres.llm.batches import map_text

# Fixed values of the HTML standard: element names by role.
VOID = frozenset("area base br col embed hr img input link meta source track wbr".split())
HIDDEN = frozenset("head script style template noscript iframe object svg math canvas audio video datalist title".split())
RAW = frozenset("script style template noscript iframe textarea title".split())
BLOCK = frozenset(
    "address article aside blockquote body center details dialog dd div dl dt fieldset figcaption figure footer form "
    "h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol optgroup option p pre search section summary "
    "table tbody td tfoot th thead tr ul caption".split())
#: Blocks with an empty line before and after them.
SPACED = frozenset("p h1 h2 h3 h4 h5 h6 ul ol dl table blockquote pre article section figure form hr".split())
#: What a start tag ends if it is open, and the elements beyond which it does not look.
CLOSES = {
    "li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}),
    "tr": ({"tr", "td", "th", "caption"}, {"table"}), "td": ({"td", "th"}, {"tr", "table"}),
    "th": ({"td", "th"}, {"tr", "table"}), "tbody": ({"thead", "tbody", "tfoot", "tr", "td", "th", "caption"}, {"table"}),
    "thead": ({"thead", "tbody", "tfoot", "tr", "td", "th", "caption"}, {"table"}),
    "tfoot": ({"thead", "tbody", "tfoot", "tr", "td", "th", "caption"}, {"table"}),
    "option": ({"option"}, {"select", "datalist", "optgroup"}), "optgroup": ({"option", "optgroup"}, {"select"}),
    "body": ({"head"}, set()),
}
#: Start tags that end an open paragraph.
ENDS_P = frozenset(
    "address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 "
    "h5 h6 header hgroup hr main menu nav ol p pre search section table ul".split())
#: Elements that end tags of inline elements do not reach through.
SCOPE = frozenset("html body table td th caption button object template".split())

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*+>?|<(/?)([a-zA-Z][^\s/>]*+)((?:[^>\"']|\"[^\"]*+\"|'[^']*+')*+)(?:>|\Z)", re.S)
_ATTR = re.compile(r"([^\s=/\"']+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"']+)))?")
_SPACE = re.compile(r"[\x20\t\n\f\r]+")
_STYLED = re.compile(r"(?:^|;)\s*(display|visibility)\s*:\s*([a-z-]+)", re.I)
_CONDITIONAL = re.compile(r"/\*.*?(?:\*/|\Z)|@[^{};]*+(?:;|\{(?:[^{}]*+\{[^{}]*+\})*+[^{}]*+\})", re.S)
_RULE = re.compile(r"([^{}]*+)\{([^{}]*+)\}")
_SELECTOR = re.compile(r"([a-zA-Z][\w-]*)?(?:([.#])([\w-]+))?")


@dataclass(slots=True)
class Node:
    name: str
    attrs: dict[str, str] = field(default_factory=dict)
    children: list = field(default_factory=list)  # nodes and strings


def _attrs(text: str) -> dict[str, str]:
    out: dict[str, str] = {}
    if text and not text.isspace():
        for m in _ATTR.finditer(text):
            out.setdefault(m[1].lower(), html.unescape(m[2] or m[3] or m[4] or ""))
    return out


class Builder:
    """Open elements and the tree below ``root``."""

    def __init__(self) -> None:
        self.root = Node("#root")
        self.open = [self.root]
        self.names: dict[str, int] = {}

    def push(self, node: Node) -> None:
        self.open[-1].children.append(node)
        self.open.append(node)
        self.names[node.name] = self.names.get(node.name, 0) + 1

    def pop(self) -> Node:
        node = self.open.pop()
        self.names[node.name] -= 1
        return node

    def close(self, names: set[str], bounds) -> None:
        """Close the outermost of ``names`` that is open inside the nearest of ``bounds``."""
        if not any(self.names.get(n) for n in names):
            return
        cut = None
        for i in range(len(self.open) - 1, 0, -1):
            if self.open[i].name in bounds:
                break
            if self.open[i].name in names:
                cut = i
        while cut is not None and len(self.open) > cut:
            self.pop()

    def start(self, name: str, attrs: dict[str, str], empty: bool) -> None:
        if name in ENDS_P and self.names.get("p"):
            self.close({"p"}, SCOPE)
        if name in CLOSES:
            self.close(*CLOSES[name])
        top = self.open[-1].name
        if name in ("td", "th") and self.names.get("table"):
            if top in ("table", "tbody", "thead", "tfoot"):
                self.push(Node("tr"))
        elif name not in ("head", "body", "html", "title", "meta", "link", "base", "script", "style", "template", "noscript") and self.names.get("head"):
            self.close({"head"}, ())
        node = Node(name, attrs)
        if name in VOID or empty and name in ("svg", "math"):
            self.open[-1].children.append(node)
        else:
            self.push(node)

    def end(self, name: str) -> None:
        if name == "br":
            self.open[-1].children.append(Node("br"))
        if not self.names.get(name):
            if name == "p":
                self.open[-1].children.append(Node("p"))
            return
        inline = name not in BLOCK
        for i in range(len(self.open) - 1, 0, -1):
            if self.open[i].name == name:
                while len(self.open) > i:
                    self.pop()
                return
            if (inline and self.open[i].name in BLOCK or self.open[i].name in ("table", "td", "th") and name not in (
                    "table", "tr", "tbody", "thead", "tfoot", "body", "html")):
                return


def parse(page: str) -> Node:
    """The element tree of any text."""
    b, at, n = Builder(), 0, len(page)
    while at < n:
        m = _TOKEN.search(page, at)
        if m is None:
            b.open[-1].children.append(html.unescape(page[at:]))
            break
        if m.start() > at:
            b.open[-1].children.append(html.unescape(page[at:m.start()]))
        at = m.end()
        if not m[2]:
            continue
        name = m[2].lower()
        if m[1]:
            b.end(name)
            continue
        b.start(name, _attrs(m[3]), m[3].endswith("/"))
        if name in RAW and name not in VOID:
            stop = re.compile(f"</{name}[\\s/>]", re.I).search(page, at)
            raw = page[at:stop.start() if stop else n]
            b.open[-1].children.append(html.unescape(raw) if name in ("textarea", "title") else raw)
            at = stop.start() if stop else n
    return b.root


def _style(text: str) -> dict[str, str]:
    """The last value of display and of visibility in a list of declarations."""
    return {m[1].lower(): m[2].lower() for m in _STYLED.finditer(text)} if text else {}


def undisplayed(sheets: list[str]) -> set[tuple[str, str, str]]:
    """Selectors (name, sign, class or id) that style sheets give ``display: none`` last.

    Only an element name, a class, an id or a name with one of these count; conditional rules do not.
    """
    out: set[tuple[str, str, str]] = set()
    for sheet in sheets:
        if "display" not in sheet.lower():
            continue
        for m in _RULE.finditer(_CONDITIONAL.sub(" ", sheet)):
            value = _style(m[2]).get("display")
            for one in m[1].split(",") if value else ():
                s = _SELECTOR.fullmatch(one.strip())
                if s and s[0]:
                    (out.add if value == "none" else out.discard)(((s[1] or "").lower(), s[2] or "", s[3] or ""))
    return out


def displayed(node: Node, sheet: set[tuple[str, str, str]] = frozenset()) -> bool:
    """Whether a browser without scripts lays the element out: not ``hidden``, not styled away."""
    a = node.attrs
    if node.name in HIDDEN or node.name == "input" or node.name == "dialog" and "open" not in a:
        return False
    own = _style(a.get("style", "")).get("display")
    if own:
        return own != "none"
    if "hidden" in a:
        return False
    if sheet:
        marks = [("", "")] + [(".", c) for c in a.get("class", "").split()] + ([("#", a["id"])] if "id" in a else [])
        return not any((name, *mark) in sheet for name in (node.name, "") for mark in marks)
    return True


class Lines:
    """Text under construction: lines, the open line, and what is due before the next text."""

    def __init__(self) -> None:
        self.done: list[str] = []
        self.parts: list[str] = []
        self.space = self.blank = False

    def text(self, s: str) -> None:
        words = _SPACE.split(s)
        if len(words) == 1 and not words[0]:
            return
        lead, trail = not words[0], not words[-1]
        core = " ".join(w for w in words if w)
        if not core:
            self.space = True
            return
        if self.parts and (self.space or lead):
            self.parts.append(" ")
        elif not self.parts and self.blank:
            if self.done:
                self.done.append("")
        self.blank = False
        self.parts.append(core)
        self.space = trail

    def exact(self, s: str) -> None:
        """Preformatted text: every character counts."""
        first, *rest = s.replace("\r\n", "\n").split("\n")
        if self.blank and not self.parts:
            if self.done and (first or rest):
                self.done.append("")
            self.blank = False
        self.parts.append(first)
        for more in rest:
            self.line(force=True)
            self.parts.append(more)

    def line(self, force: bool = False) -> None:
        if self.parts or force:
            self.done.append("".join(self.parts))
            self.parts = []
        self.space = False

    def gap(self) -> None:
        self.line()
        self.blank = True

    def result(self) -> list[str]:
        self.line()
        return self.done


class Table:
    """Rows of cells (lists of lines) on the table's grid; ``taken`` counts the rows in which a column is still held from above."""

    def __init__(self) -> None:
        self.rows: list[list[list[str]]] = []
        self.taken: dict[int, int] = {}

    def _skip(self, row: list[list[str]]) -> None:
        while self.taken.get(len(row), 0) > 0:
            self.taken[len(row)] -= 1
            row.append([])

    def start_row(self) -> None:
        if self.rows:
            self._finish()
        self.rows.append([])

    def _finish(self) -> None:
        row = self.rows[-1]
        for at in sorted(k for k, n in self.taken.items() if n > 0 and k >= len(row)):
            row.extend([[]] * (at - len(row)))
            self._skip(row)

    def cell(self, lines: list[str], across: int, down: int) -> None:
        row = self.rows[-1]
        self._skip(row)
        for j in range(across):
            if down > 1:
                self.taken[len(row)] = down - 1
            row.append([] if j else lines)

    def whole(self) -> list[list[list[str]]]:
        if self.rows:
            self._finish()
        return self.rows


def _grid(rows: list[list[list[str]]]) -> list[str]:
    """Cells (lists of lines) in aligned columns, two spaces apart; a cell may have several lines.

    A column is as wide as its widest line of at most 80 characters; longer lines run over, as
    padding to them would make the output grow with rows times width.
    """
    if not rows:
        return []
    if max(map(len, rows)) == 1:
        return [line for row in rows for cell in row for line in cell]
    wide: list[int] = []
    for row in rows:
        for j, cell in enumerate(row):
            w = max((len(line) for line in cell if len(line) <= 80), default=0)
            if j == len(wide):
                wide.append(w)
            wide[j] = max(wide[j], w)
    out = []
    for row in rows:
        for k in range(max(1, max(map(len, row), default=1))):
            parts = [(cell[k] if k < len(cell) else "") for cell in row]
            out.append("  ".join(p.ljust(w) for p, w in zip(parts, wide)).rstrip())
    return out


def _sheets(root: Node) -> list[str]:
    """Texts of all style elements, in document order."""
    out, stack = [], [root]
    while stack:
        node = stack.pop()
        if node.name == "style":
            out.append("".join(c for c in node.children if isinstance(c, str)))
        stack += [c for c in reversed(node.children) if not isinstance(c, str)]
    return out


def render(root: Node) -> str:
    """All visible text of a tree, with an explicit stack instead of recursion."""
    out = Lines()
    sheet = undisplayed(_sheets(root))
    # entries: ("node", node, pre, shown), ("text", string, pre, shown), or ("call", function); shown is the inherited visibility
    stack: list[tuple] = [("node", root, False, True)]
    sinks: list[Lines] = [out]
    tables: list[Table] = []
    lists: list[list] = []

    def leave_block(spaced: bool):
        return lambda: sinks[-1].gap() if spaced else sinks[-1].line()

    while stack:
        kind, *rest = stack.pop()
        if kind == "call":
            rest[0]()
            continue
        item, pre, shown = rest
        sink = sinks[-1]
        if kind == "text":
            if shown:
                sink.exact(item) if pre else sink.text(item)
            continue
        name = item.name
        if not displayed(item, sheet):
            continue
        if "style" in item.attrs:
            own = _style(item.attrs["style"]).get("visibility", "inherit")
            shown = shown if own == "inherit" else own not in ("hidden", "collapse")
        if name == "br":
            sink.line(force=True)
            continue
        if name == "hr":
            sink.gap()
            continue
        if name == "img":
            if shown and item.attrs.get("alt"):
                sink.text(" " + item.attrs["alt"] + " ")
            continue
        after: list = []
        spaced = name in SPACED and not (name in ("ul", "ol") and lists)
        if name in BLOCK:
            sink.gap() if spaced else sink.line()
            after.append(leave_block(spaced))
        if name in ("ul", "ol", "menu"):
            start = item.attrs.get("start", "1")
            lists.append([name, int(start) if re.fullmatch(r"-?[0-9]{1,9}", start) else 1])
            after.append(lists.pop)
        elif name == "li":
            mark = "- "
            if lists and lists[-1][0] == "ol":
                mark = f"{lists[-1][1]}. "
                lists[-1][1] += 1
            inner = Lines()
            sinks.append(inner)

            def close_item(mark=mark, inner=inner, outer=sink) -> None:
                sinks.pop()
                for i, line in enumerate(inner.result()):
                    lead = mark if not i else (" " * len(mark) if line else "")
                    outer.exact(lead + line)
                    outer.line(force=True)
            after.append(close_item)
        elif name == "table":
            tables.append(Table())
            saved, lists = lists, []

            def close_table(outer=sink, saved=saved) -> None:
                nonlocal lists
                lists = saved
                for line in _grid(tables.pop().whole()):
                    outer.exact(line)
                    outer.line(force=True)
            after.append(close_table)
        elif name == "tr" and tables:
            tables[-1].start_row()
        elif name in ("td", "th") and tables and tables[-1].rows:
            inner = Lines()
            sinks.append(inner)

            def close_cell(table=tables[-1], inner=inner, attrs=item.attrs) -> None:
                sinks.pop()
                table.cell(inner.result(), _span(attrs, "colspan"), _span(attrs, "rowspan"))
            after.append(close_cell)
        stack += [("call", f) for f in after]
        inside = pre or name in ("pre", "textarea", "listing")
        children = item.children
        if name == "details" and "open" not in item.attrs:  # closed: its summary is all that is shown
            children = [c for c in children if not isinstance(c, str) and c.name == "summary"][:1]
        for child in reversed(children):
            stack.append(("text" if isinstance(child, str) else "node", child, inside, shown))
    lines = [x.rstrip(" ") for x in out.result()]
    text = "\n".join(lines).strip("\n")
    return re.sub(r"\n{3,}", "\n\n", text)


def _span(attrs: dict[str, str], name: str) -> int:
    """Columns or rows that a cell takes: 1 to 1000."""
    value = attrs.get(name, "1")
    return max(1, min(int(value), 1000)) if re.fullmatch(r"[0-9]{1,4}", value) else 1


def extract(page: str | None) -> str | None:
    """Visible text of a page; null stays null."""
    return None if page is None else render(parse(page.replace("\0", "")))


def extract_pages(pages: DataFrame) -> DataFrame:
    """One row per row of ``pages`` (page_id, url, html): page_id, url, text, n_chars, n_lines.

    Cells stand on the table's grid, row and column spans included.  Elements that are not displayed (by
    attribute, own style, or a style sheet's rule for one name, class or id) are left out with all below
    them; of what is only invisible, visible descendants are kept; closed details show their summary.
    Null html gives null text and zero counts; empty html gives an empty text.  Repeated rows are
    rendered each; an empty table gives an empty result; other columns are not read.
    """
    def run(part: pa.RecordBatch) -> dict:
        texts = [extract(t) for t in part.column("html").to_pylist()]
        return {"page_id": part.column("page_id"), "url": part.column("url"), "text": texts,
                "n_chars": [len(t or "") for t in texts], "n_lines": [(t.count("\n") + 1) if t else 0 for t in texts]}

    return map_text(pages.select("page_id", "url", "html"), run, "page_id long, url string, text string, n_chars long, n_lines long", text="html")
