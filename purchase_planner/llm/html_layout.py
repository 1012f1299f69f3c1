"""Layout-aware rendering of HTML to text: a tree builder with implied tags, visibility rules, and a text layout.

The tokenizer knows comments, declarations, raw-text elements and attributes; the builder closes what HTML implies (a
paragraph at the next block, list items, table parts, options) and ignores stray end tags. Hidden are head, script and the
like, `hidden`, and what inline styles or compound selectors (tag, .class, #id and their combinations) of style elements
take out by display:none; visibility:hidden hides text but not that of descendants made visible again. All other text is
emitted: blocks on lines of their own, a blank line around paragraphs, headings, lists and tables, list marks with indents,
preformatted text as it is, and table cells, with their row and column spans, padded to their column's width.

Both passes run without recursion, so depth does no harm. Work is linear in the length of a page: a tag's end is sought
once, open elements are counted by tag, and every node knows the element that a start tag would close.

Defined cases: a null or empty html gives an empty text; a tag that the page's end cuts off is dropped; repeated rows
repeat; an empty table gives an empty result; only the id and html columns are read, so other columns may have any names.
"""

from __future__ import annotations

import html as entities
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Fixed values of the HTML standard.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp iframe noembed noframes".split())
HIDDEN = frozenset("head script style title template noscript datalist noembed noframes iframe object audio video canvas svg param source track".split())
BLOCK = frozenset("address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol optgroup option p pre search section summary table tbody td tfoot th thead tr ul".split())
SPACED = frozenset("blockquote dl figure h1 h2 h3 h4 h5 h6 hr ol p pre table ul".split())
CLOSES_P = BLOCK - frozenset("body html dd dt li option optgroup td th tr tbody thead tfoot legend summary".split()) | {"li", "dd", "dt"}
#: A start tag closes these open elements, looking no further up than the scopes.
IMPLIED = {
    "li": ({"li"}, {"ul", "ol", "menu", "dir"}),
    "dt": ({"dt", "dd"}, {"dl"}),
    "dd": ({"dt", "dd"}, {"dl"}),
    "tr": ({"tr", "td", "th"}, {"table"}),
    "td": ({"td", "th"}, {"table", "tr"}),
    "th": ({"td", "th"}, {"table", "tr"}),
    "tbody": ({"tbody", "thead", "tfoot", "tr", "td", "th", "caption", "colgroup"}, {"table"}),
    "thead": ({"tbody", "thead", "tfoot", "tr", "td", "th", "caption", "colgroup"}, {"table"}),
    "tfoot": ({"tbody", "thead", "tfoot", "tr", "td", "th", "caption", "colgroup"}, {"table"}),
    "option": ({"option"}, {"select", "datalist", "optgroup"}),
    "optgroup": ({"option", "optgroup"}, {"select"}),
    "body": ({"head"}, {"html"}),
}
#: What an end tag of anything but a table's part does not reach out of.
_CELLS = ("td", "th", "table")
_TABLE_PARTS = frozenset("table body html tr td th tbody thead tfoot caption".split())
#: Largest spans that the standard allows.
MOST_COLUMNS, MOST_ROWS = 1000, 65534
_NAME = re.compile(r"</?([a-zA-Z][^\s/>]*)")
_VALUE = re.compile(r"[^>=]*(?:=\s*)?")
_ATTRIBUTE = re.compile(r"([^\s=/>\"']+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?")
_RULE = re.compile(r"([^{}]+)\{([^}]*)\}")
_GONE = re.compile(r"display\s*:\s*none", re.I)
_SEEN = re.compile(r"visibility\s*:\s*(hidden|collapse|visible)", re.I)
_COMPOUND = re.compile(r"(?P<tag>[a-zA-Z][\w-]*|\*)?(?P<marks>(?:[.#][\w-]+)*)$")
_BLANKS = re.compile(r"[ \t\n\r\f]+")


#: The ways in which a start tag closes open elements: the paragraph, and those of IMPLIED.
_WAYS = [({"p"}, {"td", "th", "table", "button", "object"}), *dict.fromkeys((frozenset(c), frozenset(u)) for c, u in IMPLIED.values())]
_WAY_OF = {tag: next(k for k, (c, u) in enumerate(_WAYS) if k and (set(c), set(u)) == ways) for tag, ways in IMPLIED.items()}
_CHANGES = {tag: [(k, tag in u) for k, (c, u) in enumerate(_WAYS) if tag in c or tag in u] for tag in set().union(*(set(c) | set(u) for c, u in _WAYS))}


@dataclass
class Node:
    tag: str
    attributes: dict[str, str]
    parent: Node | None
    children: list = field(default_factory=list)  # of Node and str
    closable: tuple = (None,) * len(_WAYS)  # for each way the topmost open element that it would close

    def __post_init__(self) -> None:
        if self.parent is not None:
            self.closable = self.parent.closable
            changes = _CHANGES.get(self.tag)
            if changes:
                now = list(self.closable)
                for k, scope in changes:
                    now[k] = None if scope else now[k] or self
                self.closable = tuple(now)


def _attributes(text: str) -> dict[str, str]:
    if not text or text == "/":
        return {}
    out: dict[str, str] = {}
    for m in _ATTRIBUTE.finditer(text):
        value = m[2] if m[2] is not None else m[3] if m[3] is not None else m[4] or ""
        out.setdefault(m[1].lower(), entities.unescape(value) if "&" in value else value)
    return out


class _Open:
    """The element that is open, and how many of each tag are: in all, and since the last cell or table."""

    def __init__(self, root: Node):
        self.node, self.total, self.inner = root, Counter(), [Counter()]

    def enter(self, node: Node) -> None:
        self.node = node
        self.total[node.tag] += 1
        if node.tag in _CELLS:
            self.inner.append(Counter())
        self.inner[-1][node.tag] += 1

    def leave(self, node: Node) -> None:
        """Close an open element and all within it."""
        last = None
        while last is not node:
            last = self.node
            self.total[last.tag] -= 1
            self.inner[-1][last.tag] -= 1
            if last.tag in _CELLS:
                self.inner.pop()
            self.node = last.parent

    def end(self, tag: str) -> bool:
        if not (self.total if tag in _TABLE_PARTS else self.inner[-1])[tag]:
            return False
        up = self.node
        while up.tag != tag:
            up = up.parent
        self.leave(up)
        return True


def _tag_end(page: str, at: int, quotes: dict[str, bool]) -> int:
    """Where the > of a tag stands, beyond quoted values; -1 if the page ends before. quotes: which are known to come no more."""
    while True:
        at = _VALUE.match(page, at).end()
        if at >= len(page):
            return -1
        c = page[at]
        if c == ">":
            return at
        if c in quotes and quotes[c]:
            close = page.find(c, at + 1)
            if close < 0:
                quotes[c] = False
            at = close + 1 if close >= 0 else at + 1
        else:
            at += 1


def parse(page: str) -> Node:
    """The tree of a page under a root without a tag."""
    root = Node("", {}, None)
    now, at, n = _Open(root), 0, len(page)
    quotes = {'"': True, "'": True}
    while at < n:
        lt = page.find("<", at)
        while lt >= 0 and not (page[lt + 1 : lt + 2] in ("!", "?") and lt + 1 < n or _NAME.match(page, lt)):
            lt = page.find("<", lt + 1)  # a bare < is text
        text = page[at : lt if lt >= 0 else n]
        if text:
            now.node.children.append(entities.unescape(text) if "&" in text else text)
        if lt < 0:
            break
        m = _NAME.match(page, lt)
        if m is None:
            close = page.find("-->", lt + 4) if page.startswith("<!--", lt) else page.find(">", lt)
            at = n if close < 0 else close + (3 if page.startswith("<!--", lt) else 1)
            continue
        close = _tag_end(page, m.end(), quotes)
        if close < 0:
            break  # an unfinished tag
        at = close + 1
        tag = m[1].lower()
        if page[lt + 1] == "/":
            if not now.end(tag) and tag == "p":
                now.node.children.append(Node("p", {}, now.node))
            continue
        if tag in CLOSES_P and now.node.closable[0] is not None:
            now.leave(now.node.closable[0])
        if tag in _WAY_OF and now.node.closable[_WAY_OF[tag]] is not None:
            now.leave(now.node.closable[_WAY_OF[tag]])
        new = Node(tag, _attributes(page[m.end() : close]), now.node)
        now.node.children.append(new)
        if tag in RAW:
            end = re.compile(rf"</{re.escape(tag)}(?=[\s/>])", re.I).search(page, at)
            stop = end.start() if end else n
            if stop > at:
                raw = page[at:stop]
                new.children.append(entities.unescape(raw) if tag in ("title", "textarea") else raw)
            after = page.find(">", end.end()) if end else -1
            at = after + 1 if after >= 0 else n
        elif tag not in VOID:
            now.enter(new)
    return root


@dataclass
class Styles:
    """Compound selectors by one of their parts: which take elements out, and which hide or show their text."""

    gone: dict[str, list] = field(default_factory=dict)
    seen: dict[str, list] = field(default_factory=dict)

    def add(self, selector: str, body: str) -> None:
        m = _COMPOUND.match(selector)
        seen = _SEEN.findall(body)
        if not selector or not m:
            return
        marks = re.findall(r"[.#][\w-]+", m["marks"])
        key = marks[-1] if marks else m["tag"].lower()
        entry = (None if m["tag"] in (None, "*") else m["tag"].lower(), frozenset(marks))
        if _GONE.search(body):
            self.gone.setdefault(key, []).append((*entry, True))
        if seen:
            self.seen.setdefault(key, []).append((*entry, seen[-1].lower() == "visible"))

    def of(self, rules: dict[str, list], node: Node) -> bool | None:
        """What the last fitting rule says, the most specific first."""
        if not rules:
            return None
        marks = {f".{c}" for c in node.attributes.get("class", "").split()} | ({f"#{node.attributes['id']}"} if "id" in node.attributes else set())
        fits = [(len(need), tag is not None, said) for key in (node.tag, "*", *sorted(marks)) for tag, need, said in rules.get(key, ()) if tag in (None, node.tag) and need <= marks]
        return max(fits, key=lambda f: f[:2])[2] if fits else None


def styles_of(root: Node) -> Styles:
    found, stack = Styles(), [root]
    while stack:
        x = stack.pop()
        if x.tag == "style":
            for selectors, body in _RULE.findall("".join(c for c in x.children if isinstance(c, str))):
                for one in selectors.split(","):
                    found.add(one.strip(), body)
        stack += [c for c in x.children if isinstance(c, Node)]
    return found


def displayed(node: Node, styles: Styles) -> bool:
    a = node.attributes
    if node.tag in HIDDEN or "hidden" in a or node.tag == "input" or node.tag == "dialog" and "open" not in a:
        return False
    if "style" in a and re.search(r"display\s*:", a["style"], re.I):
        return not _GONE.search(a["style"])
    return not styles.of(styles.gone, node)


def shown(node: Node, styles: Styles, before: bool) -> bool:
    """Whether the text of an element is visible: by its own style, by a rule, else as its parent's."""
    own = _SEEN.findall(node.attributes.get("style", ""))
    if own:
        return own[-1].lower() == "visible"
    said = styles.of(styles.seen, node)
    return before if said is None else said


class _Flow:
    """Lines under construction: collapses white space, keeps block spacing, indents."""

    def __init__(self) -> None:
        self.lines: list[str] = []
        self.line: list[str] = []
        self.space = self.blank = False
        self.indents: list[str] = []
        self.mark = ""

    def text(self, s: str, keep: bool) -> None:
        if keep:
            head, *rest = s.split("\n")
            self._put(head, True)
            for x in rest:
                self.break_(True)
                self._put(x, True)
            return
        words = _BLANKS.sub(" ", s)
        if words[:1] == " " and self.line:
            self.space = True
        body = words.strip(" ")
        if body:
            self._put((" " if self.space and self.line else "") + body, False)
            self.space = words[-1] == " "

    def _put(self, s: str, keep: bool) -> None:
        if not s:
            return
        if not self.line:
            if self.blank and self.lines:
                self.lines.append("")
            self.blank = False
            self.line.append("".join(self.indents)[: -len(self.mark) or None] + self.mark if self.mark else "".join(self.indents))
            self.mark = ""
        self.line.append(s)

    def break_(self, forced: bool = False) -> None:
        if self.line:
            self.lines.append("".join(self.line).rstrip())
        elif forced and self.lines:
            self.lines.append("")
        self.line, self.space = [], False

    def gap(self) -> None:
        self.break_()
        self.blank = True

    def done(self) -> str:
        self.break_()
        return "\n".join(self.lines).strip("\n")


def _span(node: Node, name: str, most: int) -> int:
    said = node.attributes.get(name, "1").strip()
    if not re.fullmatch(r"[0-9]{1,9}", said):
        return 1
    return most if name == "rowspan" and int(said) == 0 else max(1, min(int(said), most))


def _placed(rows: list[list[tuple[list[str], int, int]]]) -> list[list[list[str]]]:
    """Cells in the columns where they stand: what spans rows or columns leaves blanks."""
    taken: dict[int, int] = {}  # column: rows that a cell above still covers
    out = []
    for row in rows:
        line: dict[int, list[str]] = {}
        column, covers = 0, dict(taken)
        for cell, wide, high in row:
            while covers.get(column):
                column += 1
            line[column] = cell
            for k in range(column, column + wide):
                if high > 1:
                    taken[k] = high
            column += wide
        out.append([line.get(k, [""]) for k in range(max([column, *(k + 1 for k in covers)] if covers else [column]))])
        taken = {k: v - 1 for k, v in taken.items() if v > 1}
    return out


def render(page: str) -> tuple[str, int, int, int]:
    """The text of a page, and how many blocks, list items and table cells it shows."""
    root = parse(page)
    styles = styles_of(root)
    flows, lists, tables = [_Flow()], [], []
    pre, counts = 0, [0, 0, 0]
    stack: list[tuple] = [(root, False, True)]
    while stack:
        node, leaving, seen = stack.pop()
        out = flows[-1]
        if isinstance(node, str):
            if seen:
                out.text(node, pre > 0)
            continue
        tag = node.tag
        if not leaving:
            if not displayed(node, styles):
                continue
            seen = shown(node, styles, seen)
            if tag == "br":
                out.break_(True)
                continue
            counts[0] += tag in BLOCK
            if tag in SPACED and not (lists and tag in ("ul", "ol")):
                out.gap()
            elif tag in BLOCK and tag not in ("td", "th"):
                out.break_()
            if tag in ("ul", "ol", "menu", "dir"):
                start = node.attributes.get("start", "")
                lists.append(int(start) if tag == "ol" and re.fullmatch(r"-?\d{1,9}", start) else 1 if tag == "ol" else None)
            elif tag == "li":
                counts[1] += 1
                mark = "- "
                if lists and lists[-1] is not None:
                    mark = f"{lists[-1]}. "
                    lists[-1] += 1
                out.indents.append(" " * len(mark))
                out.mark = mark if seen else ""
            elif tag in ("blockquote", "dd"):
                out.indents.append("  ")
            elif tag == "pre":
                pre += 1
            elif tag == "hr":
                out.text("-" * 8, True)
                out.gap()
            elif tag == "table":
                tables.append([])
            elif tag == "tr" and tables:
                tables[-1].append([])
            elif tag in ("td", "th") and tables:
                counts[2] += 1
                if not tables[-1]:
                    tables[-1].append([])
                flows.append(_Flow())
            stack.append((node, True, seen))
            stack += [(c, False, seen) for c in reversed(node.children)]
            continue
        if tag in ("ul", "ol", "menu", "dir"):
            lists.pop()
        elif tag == "li":
            if out.mark:  # nothing followed the mark
                out.mark = ""
            out.break_()
            out.indents.pop()
        elif tag in ("blockquote", "dd"):
            out.break_()
            out.indents.pop()
        elif tag == "pre":
            pre -= 1
        elif tag in ("td", "th") and tables:
            tables[-1][-1].append((flows.pop().done().split("\n"), _span(node, "colspan", MOST_COLUMNS), _span(node, "rowspan", MOST_ROWS)))
            continue
        elif tag == "table" and tables:
            rows = _placed(tables.pop())
            widths: list[int] = []
            for row in rows:
                for k, cell in enumerate(row):
                    widest = max(map(len, cell))
                    if k == len(widths):
                        widths.append(0)
                    widths[k] = max(widths[k], widest)
            for row in rows:
                for i in range(max((len(c) for c in row), default=0)):
                    line = " | ".join((c[i] if i < len(c) else "").ljust(widths[k]) for k, c in enumerate(row)).rstrip()
                    out.break_()
                    out.text(line, True)
                out.break_()
        if tag in SPACED and not (lists and tag in ("ul", "ol")):
            out.gap()
        elif tag in BLOCK:
            out.break_()
    return flows[0].done(), *counts


def texts(pages: DataFrame, id_col: str = "page_id", html_col: str = "html") -> DataFrame:
    """The id column, text, n_chars, n_blocks, n_items and n_cells of every page."""
    rows = pages.select(F.col(id_col).alias("id"), F.col(html_col).cast("string").alias("html"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(0, batch.num_rows, 256):
                part = batch.slice(i, 256)
                made = [render(x.as_py() or "") for x in part.column(1)]
                text, blocks, items, cells = zip(*made, strict=True)
                ints = [pa.array(x, pa.int32()) for x in (blocks, items, cells)]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(text, pa.string()), pa.array([len(t) for t in text], pa.int64()), *ints], ["id", "text", "n_chars", "n_blocks", "n_items", "n_cells"])

    return rows.mapInArrow(run, f"id {rows.schema['id'].dataType.simpleString()}, text string, n_chars long, n_blocks int, n_items int, n_cells int").withColumnRenamed("id", id_col)
