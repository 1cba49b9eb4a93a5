"""HTML extraction by layout-aware rendering.

A tokenizer and tree builder with the implied end tags of HTML (p, li, dt, dd, option, table parts)
builds a tree; a renderer walks it without recursion and emits all visible text: blocks are separated by
line breaks (paragraphs and headings by a blank line), list items get bullets or numbers and
indentation, table cells are padded into aligned columns (a cell over several rows keeps its columns in all of them), pre keeps its white space. What a browser does
not show is left out: head, script, style, template, noscript, comments, hidden attributes,
display:none styles, visibility:hidden ones but for descendants that are visible again, closed details and dialogs, hidden inputs, definitions and descriptions of svg, annotations of math. Nothing is loaded or drawn, so the text that
stands in for an object, a canvas, a video or a sound is shown.

Defined results: null or empty html gives an empty text; broken mark-up is rendered as far as the
rules go and never raises; repeated rows are rendered alike; an empty table gives an empty table; other columns are ignored.
"""

import bisect
import html as entities
import re
import unicodedata

import pyarrow as pa
from pyspark.sql import DataFrame

from . import common

# Fixed values of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp iframe noembed noframes".split())
HIDDEN = frozenset("head script style template noscript iframe datalist noembed noframes title meta link annotation annotation-xml".split())
HIDDEN_IN_SVG = frozenset("desc metadata defs symbol clippath mask marker pattern".split())
SPACED = frozenset("p h1 h2 h3 h4 h5 h6 blockquote pre ul ol dl table figure hr menu".split())
BLOCK = SPACED | frozenset("html body div section article nav aside header footer main address li dt dd form fieldset legend details summary figcaption caption thead tbody tfoot tr center dir hgroup search option optgroup dialog".split())
CLOSES_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre search section table ul li dt dd".split())
IMPLIED = {
    "li": ({"li"}, {"ul", "ol", "menu", "dir"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}),
    "option": ({"option"}, {"select", "datalist", "optgroup"}), "optgroup": ({"option", "optgroup"}, {"select"}),
    "tr": ({"tr", "td", "th"}, {"table", "thead", "tbody", "tfoot"}), "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}),
    "thead": ({"thead", "tbody", "tfoot", "tr", "td", "th", "caption", "colgroup"}, {"table"}), "tbody": ({"thead", "tbody", "tfoot", "tr", "td", "th", "caption", "colgroup"}, {"table"}),
    "tfoot": ({"thead", "tbody", "tfoot", "tr", "td", "th", "caption", "colgroup"}, {"table"}), "rt": ({"rt", "rp"}, {"ruby"}), "rp": ({"rt", "rp"}, {"ruby"}),
}
SCOPE = frozenset("html table td th caption template object".split())
P_STOP = SCOPE | {"button"}
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|</([A-Za-z][^\s/>]*)[^>]*(?:>|\Z)|<([A-Za-z][^\s/>]*)((?:[^>=]++|=\s*+(?:\"[^\"]*+(?:\"|\Z)|'[^']*+(?:'|\Z)|[^\s>\"'][^\s>]*+)?+)*+)(?:>|\Z)", re.S)  # a quote opens a value only after =
ATTRIBUTE = re.compile(r"([^\s=/>\"']+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]*)))?")
UNSEEN = re.compile(r"(?:^|;)\s*display\s*:\s*none", re.I)
VISIBILITY = re.compile(r"(?:^|;)\s*visibility\s*:\s*(visible|hidden|collapse)", re.I)
MOST_COLUMNS, MOST_ROWS = 1000, 65534  # larger spans are cut to these by HTML
SPACE = re.compile(r"[ \t\n\r\f]+")


class Node:
    __slots__ = ("tag", "attrs", "kids", "parent", "in_svg")

    def __init__(self, tag, attrs=None, parent=None):
        self.tag, self.attrs, self.kids, self.parent = tag, attrs or {}, [], parent
        self.in_svg = parent is not None and (parent.in_svg or parent.tag == "svg")


class Open:
    """The open elements from the root on, with the depths at which each tag is open: finding one takes no walk."""

    def __init__(self):
        self.path, self.depths = [Node("#root")], {}

    @property
    def last(self) -> Node:
        return self.path[-1]

    def push(self, node: Node):
        self.depths.setdefault(node.tag, []).append(len(self.path))
        self.path.append(node)

    def pop(self):
        self.depths[self.path.pop().tag].pop()

    def depth(self, tags) -> int:
        return max((self.depths[t][-1] for t in tags if self.depths.get(t)), default=0)

    def close(self, tags, stop=()) -> bool:
        """Close the nearest open element in tags, unless one of stop lies as near."""
        at = self.depth(tags)
        if not at or self.depth(stop) >= at:
            return False
        while len(self.path) > at:
            self.pop()
        return True


def parse(source: str) -> Node:
    stack, pos = Open(), 0
    while pos < len(source):
        m = TOKEN.search(source, pos)
        if not m:
            stack.last.kids.append(entities.unescape(source[pos:]))
            break
        if m.start() > pos:
            stack.last.kids.append(entities.unescape(source[pos:m.start()]))
        pos = m.end()
        if source.startswith("<![CDATA[", m.start()) and stack.depth(("svg", "math")):
            end = source.find("]]>", m.start())  # elsewhere it is a comment up to the first >
            pos = end + 3 if end >= 0 else len(source)
            stack.last.kids.append(source[m.start() + 9:end if end >= 0 else len(source)])
        elif m[1]:
            tag = m[1].lower()
            if tag == "br":
                stack.last.kids.append(Node("br", parent=stack.last))
            elif tag not in VOID and not stack.close((tag,), ("html",) if tag in SCOPE and tag != "html" else () if tag in SCOPE else SCOPE) and tag == "p":
                stack.last.kids.append(Node("p", parent=stack.last))
        elif m[2]:
            tag = m[2].lower()
            attrs = {a[1].lower(): entities.unescape(a[2] or a[3] or a[4] or "") for a in ATTRIBUTE.finditer(m[3] or "")}
            if tag in ("html", "body") and stack.depth((tag,)):
                continue
            if tag in CLOSES_P:
                stack.close(("p",), P_STOP)
            if tag == "body":
                stack.close(("head",))
            elif tag in BLOCK and stack.last.tag == "head":
                stack.pop()
            if tag in IMPLIED:
                own, stop = IMPLIED[tag]
                while stack.close(own, stop):
                    pass
            elif tag in HEADINGS and stack.last.tag in HEADINGS:
                stack.pop()
            elif tag in ("a", "button"):
                stack.close((tag,), SCOPE)
            node = Node(tag, attrs, stack.last)
            stack.last.kids.append(node)
            if tag in RAW:
                end = re.compile(rf"</{tag}[\s/>]", re.I).search(source, pos)
                raw = source[pos:end.start() if end else len(source)]
                node.kids.append(entities.unescape(raw) if tag in ("textarea", "title") else raw)
                pos = (source.find(">", end.start()) + 1 or len(source)) if end else len(source)
            elif tag not in VOID and not (m[3] or "").rstrip().endswith("/") or tag not in VOID and tag in BLOCK:
                stack.push(node)
    return stack.path[0]


def is_block(node: Node) -> bool:
    return node.tag in BLOCK or node.tag == "text" and node.in_svg


def span_of(node: Node, name: str, most: int) -> int:
    """A colspan or rowspan; 1 where it is not a number. rowspan=0 reaches to the end of the table."""
    given = re.match(r"\s*\+?(\d{1,9})", node.attrs.get(name, "1"))
    n = int(given[1]) if given else 1
    return min(n, most) if n else most if name == "rowspan" else 1


def visible(node: Node) -> bool:
    """Whether a box is made for the node; its visibility is another matter, which a descendant may change."""
    if node.tag in HIDDEN or "hidden" in node.attrs or UNSEEN.search(node.attrs.get("style", "")):
        return False
    if node.tag == "dialog" and "open" not in node.attrs or node.tag in HIDDEN_IN_SVG and node.in_svg:
        return False
    if node.tag == "input":
        return node.attrs.get("type", "").lower() in ("submit", "button", "reset")
    up = node.parent
    return not (up is not None and up.tag == "details" and "open" not in up.attrs and node.tag != "summary")


class Lines:
    """Collects lines with collapsed white space and pending breaks."""

    def __init__(self):
        self.done, self.line, self.breaks, self.indent, self.mark = [], "", 0, 0, ""

    def text(self, s, pre=False):
        if pre:
            first, *rest = s.split("\n")
            self.put(first)
            for x in rest:
                self.end_line(True)
                self.put(x)
            return
        s = SPACE.sub(" ", s)
        if s.startswith(" ") and (not self.line or self.line.endswith(" ")):
            s = s[1:]
        self.put(s)

    def put(self, s):
        if s:
            if not self.line:
                self.open()
            self.line += s

    def open(self):
        if self.done and self.breaks > 1 and self.done[-1] != "":
            self.done.append("")
        self.breaks = 0

    def end_line(self, force=False):
        if self.line.strip() or self.mark and self.line:
            lead = " " * self.indent
            if self.mark:
                lead = " " * max(0, self.indent - len(self.mark)) + self.mark
                self.mark = ""
            self.done.append(lead + self.line.rstrip())
        elif force and self.done:
            self.done.append("")
        self.line = ""

    def block(self, spaced):
        self.end_line()
        self.breaks = max(self.breaks, 2 if spaced else 1)


def wide(s: str) -> int:
    """Columns that a text takes: wide East Asian characters take two, combining marks none."""
    return len(s) if s.isascii() else sum(0 if unicodedata.combining(c) else 2 if unicodedata.east_asian_width(c) in "WF" else 1 for c in s)


def render(root: Node) -> str:
    """All visible text. The walk keeps its own stack, so depth is bounded by memory, not by recursion."""
    out = Lines()
    tables = []  # open tables: (outer Lines, rows)
    counters = []  # open lists: next number or None
    cells = []
    stack = [(root, "in", True)]
    while stack:
        node, phase, seen = stack.pop()
        if isinstance(node, str):
            pre = phase == "pre"
            if seen and not (not pre and not SPACE.sub("", node) and (not out.line or out.line.endswith(" "))):
                out.text(node, pre)
            continue
        tag = node.tag
        if phase in ("in", "pre"):
            if tag != "#root" and not visible(node):
                continue
            pre = phase == "pre" or tag == "pre"
            if set_here := VISIBILITY.findall(node.attrs.get("style", "")):
                seen = set_here[-1].lower() == "visible"
            if tag == "br":
                out.end_line(True)
                continue
            if tag == "hr":
                out.block(True)
                continue
            if tag == "img":
                if seen and node.attrs.get("alt"):
                    out.text(node.attrs["alt"])
                continue
            if tag == "input":
                if seen:
                    out.text(node.attrs.get("value", ""))
                continue
            if tag == "table":
                out.block(True)
                tables.append((out, []))
                out = Lines()
            elif tag in ("td", "th") and tables:
                cells.append(out)
                out = Lines()
            elif tag == "tr" and tables:
                out.block(False)
                tables[-1][1].append([])
            elif is_block(node):
                out.block(tag in SPACED and not (tag in ("ul", "ol", "menu") and counters))
            if tag in ("ul", "ol", "menu", "dir"):
                start = node.attrs.get("start", "1")
                counters.append((int(start) if re.fullmatch(r"-?\d{1,9}", start) else 1) if tag == "ol" else None)
                out.indent += 2
            elif tag == "li":
                number = counters[-1] if counters else None
                out.mark = "" if not seen else "- " if number is None else f"{number}. "
                if number is not None:
                    counters[-1] = number + 1
            elif tag == "dd" or tag == "blockquote":
                out.indent += 2
            stack.append((node, "out", seen))
            closed = tag == "details" and "open" not in node.attrs  # shows its summary only
            for kid in reversed([k for k in node.kids if not (closed and isinstance(k, str))]):
                stack.append((kid, "pre" if pre else "in", seen))
            continue
        if tag == "table" and tables:
            out.end_line()
            loose = out.done
            out, rows = tables.pop()
            for line in loose:
                out.put(line)
                out.end_line()
            for line in aligned(rows):
                out.put(line)
                out.end_line()
            out.breaks = 2
        elif tag in ("td", "th") and cells:
            out.end_line()
            text = [x for x in out.done if x]
            out = cells.pop()
            if tables:
                if not tables[-1][1]:
                    tables[-1][1].append([])
                tables[-1][1][-1].append((text, span_of(node, "colspan", MOST_COLUMNS), span_of(node, "rowspan", MOST_ROWS)))
        else:
            if tag in ("ul", "ol", "menu", "dir"):
                counters.pop()
                out.end_line()
                out.indent -= 2
            elif tag == "dd" or tag == "blockquote":
                out.end_line()
                out.indent -= 2
            elif tag == "li":
                out.end_line()
                out.mark = ""
            if is_block(node):
                out.block(tag in SPACED and not (tag in ("ul", "ol", "menu") and counters))
    out.end_line()
    return "\n".join(out.done).strip("\n")


def placed(rows: list) -> list:
    """(column, text, columns) of the cells of each row: a cell goes to the first column that no cell of this row or from above takes."""
    grid, held = [], []  # held: (first column, end, rows left) of cells from above, by column
    for r in rows:
        cells, at, k, kept = [], 0, 0, []
        for text, span, down in r:
            while k < len(held) and held[k][0] <= at:
                at = max(at, held[k][1])
                k += 1
            cells.append((at, text, span))
            if down > 1:
                kept.append((at, at + span, down))
            at += span
        grid.append(cells)
        held = sorted((a, b, left - 1) for a, b, left in held + kept if left > 1)
    return grid


def aligned(rows: list) -> list[str]:
    """Rows of cells as lines; columns are as wide as their widest one-column cell."""
    grid = [r for r in placed(rows) if any(text for _, text, _ in r)]
    widths: dict[int, int] = {}
    for r in grid:
        for col, text, span in r:
            if span == 1:
                widths[col] = max([widths.get(col, 0), *map(wide, text)])
    columns = sorted(widths)
    begin = [0]  # where each of them begins; a gap of two follows each
    for c in columns:
        begin.append(begin[-1] + widths[c] + 2)
    lines = []
    for r in grid:
        for i in range(max(len(text) for _, text, _ in r)):
            line, taken = "", 0
            for col, text, _ in r:
                s = text[i] if i < len(text) else ""
                gap = begin[bisect.bisect_left(columns, col)] - taken
                if s and line.strip() and gap < 2:
                    gap = 2
                line += " " * max(0, gap) + s
                taken += max(0, gap) + wide(s)
            lines.append(line.rstrip())
    return lines


def visible_text(source) -> str:
    return render(parse(source)) if source else ""


def page_title(source) -> str | None:
    m = re.search(r"<title\b[^>]*>(.*?)</title", source or "", re.I | re.S)
    return SPACE.sub(" ", entities.unescape(m[1])).strip() if m else None


def extract(pages: DataFrame, *, key: str = "page_id", html: str = "html") -> DataFrame:
    """key, title, text, n_lines, n_chars of every page."""
    kind = dict(pages.dtypes)[key]

    def run(batch: pa.RecordBatch):
        sources = common.texts_of(batch, "__html")
        texts = [visible_text(x) for x in sources]
        return {key: common.column_of(batch, key), "title": [page_title(x) for x in sources], "text": texts, "n_lines": [x.count("\n") + 1 if x else 0 for x in texts], "n_chars": [len(x) for x in texts]}

    return common.arrow_map(pages.selectExpr(f"`{key}`", f"`{html}` as __html"), run, f"`{key}` {kind}, title string, text string, n_lines long, n_chars long")


def op10_html_text(spark, sf_dir):
    return extract(spark.read.parquet(f"{sf_dir}/pages.parquet"))
