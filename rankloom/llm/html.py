"""HTML to text by layout-aware rendering.

A tokenizer and a tree builder with the implied tags of HTML (a <p> ends at the
next block, <li>, <dt>, <dd>, <option>, table rows and cells end at their like,
void elements have no content) make a tree; visibility rules take hidden parts
out; the rest is laid out: blocks on lines of their own with blank lines around
paragraphs, list items with bullets or numbers and indents, table cells padded to
aligned columns, preformatted text as it is. Hidden are elements without visible
content, those with hidden, display: none or the like, and those that rules of the
page's style sheets by element, class or id hide; other selectors are not followed.

Every character is read a bounded number of times.

Edge cases: null or empty HTML gives empty text; broken or unclosed tags are
text or closed at the end; very deep nesting is followed without recursion in
building and cut off from deeper indents in layout; cells of more than 100
characters do not widen their column; rows repeat as they come.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame

#: A tag from behind its "<"; quotes count behind "=" only, and one that is never closed is a character. Nothing is read twice.
TAG = re.compile(r"""(/?)([a-zA-Z][^\s/>]*+)((?:[^>=]++|=\s*+(?:"[^"]*+"|'[^']*+')?+)*+)>""")
#: The same where an earlier tag had no end.
PLAIN_TAG = re.compile(r"(/?)([a-zA-Z][^\s/>]*+)([^>]*+)>")
ATTRIBUTE = re.compile(r"""([^\s=/"'>]+)(?:\s*=\s*("[^"]*"|'[^']*'|[^\s"'>]+))?""")
SPACES = re.compile(r"[ \t\n\r\f]+")
HIDING_STYLE = re.compile(r"(?:^|;)\s*(?:display\s*:\s*none|visibility\s*:\s*(?:hidden|collapse)|content-visibility\s*:\s*hidden)", re.I)

# Element classes of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp noembed noframes iframe".split())
INVISIBLE = frozenset("head script style template title meta link base noembed noframes iframe object audio video canvas svg math datalist param source track".split())
PARAGRAPHS = frozenset("p blockquote figure pre ul ol dl table h1 h2 h3 h4 h5 h6 fieldset hr".split())
BLOCKS = PARAGRAPHS | frozenset("address article aside body center dd details dialog dir div dt figcaption footer form frameset header hgroup html legend li main menu nav optgroup option search section summary caption tbody tfoot thead tr".split())
CELLS = frozenset(("td", "th"))
#: An opening tag ends the open elements it names, up to the nearest limit.
ENDS = {
    "li": (frozenset(("li",)), frozenset(("ul", "ol", "menu", "dir"))),
    "dt": (frozenset(("dt", "dd")), frozenset(("dl",))),
    "dd": (frozenset(("dt", "dd")), frozenset(("dl",))),
    "option": (frozenset(("option",)), frozenset(("select", "optgroup", "datalist"))),
    "optgroup": (frozenset(("option", "optgroup")), frozenset(("select",))),
    "td": (CELLS, frozenset(("tr", "table"))),
    "th": (CELLS, frozenset(("tr", "table"))),
    "tr": (frozenset(("tr", "td", "th", "caption")), frozenset(("table",))),
    "tbody": (frozenset(("tbody", "thead", "tfoot", "tr", "td", "th", "caption")), frozenset(("table",))),
}
ENDS["thead"] = ENDS["tfoot"] = ENDS["tbody"]
CLOSES_P = BLOCKS - frozenset(("option", "optgroup", "html", "body", "caption", "tbody", "tfoot", "thead", "tr"))
HEADINGS = frozenset(("h1", "h2", "h3", "h4", "h5", "h6"))
#: Depths of layout and of the tree; elements below stand beside each other. Widest cell that others are aligned to.
MOST_DEPTH, MOST_OPEN, MOST_WIDTH = 200, 512, 100


#: Rules of style sheets that are followed: element, class or id, alone or element with one of both.
SELECTOR = re.compile(r"([a-z][a-z0-9-]*)?([.#][\w-]+)?", re.I)
COMMENT = re.compile(r"/\*.*?(?:\*/|\Z)", re.S)
HINT = re.compile("hid|none|collapse", re.I)
DISPLAY = re.compile(r"(?:^|;)\s*(display|visibility|content-visibility)\s*:", re.I)


def sheet_rules(css: str, hidden: dict[str, bool]) -> None:
    """Adds to hidden what simple selectors of a style sheet hide or show; rules within others (media) are passed over."""
    css = COMMENT.sub(" ", css)
    depth, last, opened, selector = 0, 0, 0, ""
    for m in re.finditer("[{}]", css):
        if m[0] == "{":
            if depth == 0:
                selector, opened = css[last : m.start()], m.end()
            depth += 1
            continue
        depth = max(0, depth - 1)
        if depth == 0:
            body, last = css[opened : m.start()], m.end()
            if "{" not in body and "@" not in selector and DISPLAY.search(body):
                for one in selector.split(","):
                    if (one := one.strip()) and SELECTOR.fullmatch(one):
                        hidden[one.lower()] = bool(HIDING_STYLE.search(body))


class Element:
    __slots__ = ("name", "attributes", "children")

    def __init__(self, name: str, attributes: str):
        self.name, self.attributes, self.children = name, attributes, []

    def attribute(self, name: str) -> str | None:
        if not self.attributes:
            return None
        for m in ATTRIBUTE.finditer(self.attributes):
            if m[1].lower() == name:
                return (m[2] or "").strip("\"'")
        return None

    def hidden(self, sheet: dict[str, bool] | None = None) -> bool:
        if self.name in INVISIBLE:
            return True
        a = self.attributes
        by_sheet = bool(sheet) and self.hidden_by(sheet)
        if not a or not (by_sheet or HINT.search(a)):
            return by_sheet
        if self.attribute("hidden") is not None:
            return True
        if self.name == "input" and (self.attribute("type") or "").lower() == "hidden":
            return True
        style = self.attribute("style") or ""
        return bool(HIDING_STYLE.search(style)) or by_sheet and not DISPLAY.search(style)

    def hidden_by(self, sheet: dict[str, bool]) -> bool:
        """What the most special of its rules says: id before class before element."""
        keys = [self.name]
        if self.attributes:
            for mark, value in ((".", (self.attribute("class") or "").lower().split()), ("#", [(self.attribute("id") or "").lower()])):
                keys += [f"{mark}{v}" for v in value] + [f"{self.name}{mark}{v}" for v in value]
        return next((sheet[k] for k in reversed(keys) if k in sheet), False)


def build_tree(html: str) -> tuple[Element, dict[str, bool]]:
    """The tree of a page, whose children are elements and strings, and what its style sheets hide."""
    root, sheet = Element("html", ""), {}
    stack = [root]
    pos, n, tag = 0, len(html), TAG
    endless: set[str] = set()
    while pos < n:
        at = html.find("<", pos)
        if at < 0:
            stack[-1].children.append(html[pos:])
            break
        if at > pos:
            stack[-1].children.append(html[pos:at])
        mark = html[at + 1 : at + 2]
        if mark in ("!", "?"):
            comment = html.startswith("<!--", at)
            end = html.find("-->" if comment else ">", at + 4 if comment else at)
            if end < 0 and not comment:
                stack[-1].children.append(html[at:])
            pos = n if end < 0 else end + (3 if comment else 1)
            continue
        m = None
        if mark == "/" or (mark.isascii() and mark.isalpha()):
            m = tag.match(html, at + 1)
            if m is None and tag is TAG:
                # A tag that runs to the end of the page: from here on, the next ">" ends a tag, and without one all is text.
                tag = PLAIN_TAG
                m = tag.match(html, at + 1)
        if m is None:
            starts = html[at + 1 : at + 3].lstrip("/")[:1]
            following = -1 if starts.isascii() and starts.isalpha() else html.find("<", at + 1)
            following = n if following < 0 else following
            stack[-1].children.append(html[at:following])
            pos = following
            continue
        pos = m.end()
        name = m[2].lower()
        if m[1]:
            _close(stack, name)
            continue
        if name in ("html", "body"):
            if name == "body":
                _close(stack, "head")
            stack[0].attributes += " " + (m[3] or "")
            continue
        _imply(stack, name)
        element = Element(name, m[3])
        stack[-1].children.append(element)
        if name in RAW:
            end = None if name in endless else re.compile(rf"</{name}\s*+>", re.I).search(html, pos)
            if end is None:
                endless.add(name)
            else:
                element.children.append(html[pos : end.start()])
                if name == "style":
                    sheet_rules(html[pos : end.start()], sheet)
                pos = end.end()
            continue
        if name not in VOID:
            if len(stack) > MOST_OPEN:
                stack.pop()
            stack.append(element)
    return root, sheet


def _close(stack: list[Element], name: str) -> None:
    """An end tag closes its element and all within; cells and tables hold their inside."""
    for i in range(len(stack) - 1, 0, -1):
        if stack[i].name == name:
            del stack[i:]
            return
        if stack[i].name in ("td", "th", "table") and name not in ("td", "th", "tr", "tbody", "thead", "tfoot", "table"):
            return
    if name == "br":
        stack[-1].children.append(Element("br", ""))


def _imply(stack: list[Element], name: str) -> None:
    if name in CLOSES_P:
        for i in range(len(stack) - 1, 0, -1):
            if stack[i].name == "p":
                del stack[i:]
                break
            if stack[i].name in ("td", "th", "table", "caption", "button", "li", "div", "section", "article"):
                break
    if name in HEADINGS and stack[-1].name in HEADINGS:
        stack.pop()
    if stack[-1].name == "head" and name not in INVISIBLE and name != "noscript":
        stack.pop()
    if name in ENDS:
        ended, limit = ENDS[name]
        for i in range(len(stack) - 1, 0, -1):
            if stack[i].name in limit:
                break
            if stack[i].name in ended:
                del stack[i:]
                if name in ("tr", "tbody", "thead", "tfoot", "optgroup"):
                    _imply(stack, name)
                break


class Layout:
    """Lines of text with block spacing; an open line collects inline text."""

    def __init__(self, sheet: dict[str, bool] | None = None):
        self.sheet = sheet
        self.lines: list[str] = []
        self.open: list[str] = []
        self.gap = False
        self.lead = ""
        self.indent = ""

    def inline(self, text: str) -> None:
        self.open.append(text)

    def end_line(self) -> None:
        if self.open:
            text = SPACES.sub(" ", "".join(self.open)).strip(" ")
            self.open = []
            if text:
                self.put(text)

    def put(self, text: str) -> None:
        if self.gap and self.lines:
            self.lines.append("")
        self.gap = False
        self.lines.append((self.indent + self.lead if self.lead else self.indent) + text)
        if self.lead:
            self.indent += " " * len(self.lead)
            self.lead = ""

    def space(self) -> None:
        self.end_line()
        self.gap = True


def render(root: Element, sheet: dict[str, bool] | None = None) -> str:
    out = Layout(sheet)
    _lay(root, out, 0)
    out.end_line()
    return "\n".join(out.lines)


def _lay(element: Element, out: Layout, depth: int, counter: list[int] | None = None) -> None:
    for child in element.children:
        if isinstance(child, str):
            out.inline(unescape(child) if "&" in child else child)
            continue
        name = child.name
        if child.hidden(out.sheet):
            continue
        if name == "br":
            out.open.append(" ")
            text = SPACES.sub(" ", "".join(out.open)).strip(" ")
            out.open = []
            out.put(text) if text else out.lines and out.put("")
        elif name == "hr":
            out.space()
        elif name == "img":
            if alt := child.attribute("alt"):
                out.inline(f" {unescape(alt)} ")
        elif name == "input":
            if (child.attribute("type") or "text").lower() in ("button", "submit", "reset", "text", "") and (value := child.attribute("value")):
                out.inline(f" {unescape(value)} ")
        elif name == "textarea":
            out.inline(unescape("".join(c for c in child.children if isinstance(c, str))))
        elif name in ("pre", "listing"):
            out.space()
            for line in unescape(_raw_text(child, out.sheet)).strip("\n").split("\n"):
                out.put(line.rstrip("\r"))
            out.gap = True
        elif name == "table" and depth < MOST_DEPTH:
            out.space()
            _table(child, out, depth + 1)
            out.space()
        elif name == "li" and depth < MOST_DEPTH:
            out.end_line()
            before, lead = out.indent, out.lead
            if counter is not None:
                value = child.attribute("value")
                counter[0] = int(value) if value and re.fullmatch(r"-?\d{1,9}", value) else counter[0] + 1
                out.lead = f"{counter[0]}. "
            else:
                out.lead = "- "
            _lay(child, out, depth + 1)
            out.end_line()
            out.indent, out.lead = before, lead
        elif name == "details" and child.attribute("open") is None:
            summary = [c for c in child.children if isinstance(c, Element) and c.name == "summary"]
            out.end_line()
            for c in summary[:1]:
                _lay(c, out, depth + 1)
            out.end_line()
        elif name in BLOCKS and depth < MOST_DEPTH:
            wide = name in PARAGRAPHS
            nested = wide and name in ("ul", "ol") and bool(out.indent or out.lead)
            out.space() if wide and not nested else out.end_line()
            before = out.indent
            if name == "blockquote" or name == "dd":
                out.indent += "  "
            start = child.attribute("start") if name == "ol" else None
            _lay(child, out, depth + 1, [int(start) - 1 if start and re.fullmatch(r"-?\d{1,9}", start) else 0] if name == "ol" else None)
            out.space() if wide and not nested else out.end_line()
            out.indent = before
        elif depth >= MOST_DEPTH:
            out.inline(f" {unescape(_raw_text(child, out.sheet))} ")
        else:
            _lay(child, out, depth + 1, counter)


def _raw_text(element: Element, sheet: dict[str, bool] | None = None) -> str:
    """Visible text below an element, without recursion."""
    parts, todo = [], [element]
    while todo:
        x = todo.pop()
        if isinstance(x, str):
            parts.append(x)
        elif x is element or not x.hidden(sheet):
            if x.name == "br":
                parts.append("\n")
            todo.extend(reversed(x.children))
    return "".join(parts)


def _span(cell: Element, name: str, most: int) -> int:
    span = cell.attribute(name) or ""
    return min(int(span), most) if re.fullmatch(r"[1-9]\d{0,3}", span) else 1


def _table(table: Element, out: Layout, depth: int) -> None:
    """Rows of cells on a grid, each column as wide as its widest one-line cell; a cell over rows holds its columns in them."""
    rows: list[list[str]] = []
    captions: list[Element] = []
    held: dict[int, int] = {}

    def laid(cell: Element) -> str:
        inner = Layout(out.sheet)
        _lay(_as_block(cell), inner, depth + 1)
        inner.end_line()
        return "\n".join(inner.lines)

    def add_row(cells: list[Element | str]) -> None:
        row: list[str] = []
        below = {column: left - 1 for column, left in held.items() if left > 1}
        for cell in cells:
            while len(row) in held:
                row.append("")
            text, wide, high = (cell, 1, 1) if isinstance(cell, str) else (laid(cell), _span(cell, "colspan", 100), _span(cell, "rowspan", 1000))
            for column in range(len(row), len(row) + wide):
                if high > 1:
                    below[column] = max(below.get(column, 0), high - 1)
            row += [text] + [""] * (wide - 1)
        held.clear()
        held.update(below)
        rows.append(row)

    def gather(element: Element, level: int) -> None:
        loose: list[Element | str] = []
        for child in element.children:
            if isinstance(child, str):
                if child.strip():
                    rows.append([SPACES.sub(" ", unescape(child)).strip(" ")])
            elif child.hidden(out.sheet):
                continue
            elif child.name == "tr":
                texts = (SPACES.sub(" ", unescape(x)).strip(" ") if isinstance(x, str) else x for x in child.children)
                add_row([x for x in texts if (x if isinstance(x, str) else not x.hidden(out.sheet))])
            elif child.name in ("tbody", "thead", "tfoot", "colgroup") and level < 20:
                held.clear()
                gather(child, level + 1)
                held.clear()
            elif child.name in CELLS:
                loose.append(child)
            else:
                captions.append(child)
        if loose:
            add_row(loose)

    gather(table, 0)
    for caption in captions:
        _lay(_as_block(caption), out, depth + 1)
        out.end_line()
    widths: list[int] = []
    split = [[cell.split("\n") for cell in row] for row in rows]
    for row in split:
        for i, cell in enumerate(row):
            if i >= len(widths):
                widths.append(0)
            widths[i] = max(widths[i], max((len(x) for x in cell if len(x) <= MOST_WIDTH), default=0))
    for row in split:
        for k in range(max(map(len, row), default=0)):
            line = "  ".join((cell[k] if k < len(cell) else "").ljust(widths[i]) for i, cell in enumerate(row)).rstrip(" ")
            if line:
                out.put(line)


def _as_block(element: Element) -> Element:
    block = Element("div", "")
    block.children = element.children
    return block


def page_text(html: str | None) -> str:
    """All visible text of a page, laid out."""
    return render(*build_tree(html)) if html else ""


def extract_pages(pages: DataFrame) -> DataFrame:
    """op10: pages -> page_id, url, text, n_chars."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [page_text(h) for h in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return pages.select("page_id", "url", "html").mapInArrow(run, "page_id bigint, url string, text string, n_chars bigint")
