"""Layout-aware text of HTML pages.

A tree builder with implied tags (a paragraph ends where a block begins, a list item where the next begins, table parts open their missing
parents) feeds a renderer that leaves out what a browser does not show, keeps paragraphs apart by an empty line and other blocks by a line end, marks and
indents list items, keeps preformatted text and that of text areas, shows of a drop-down its chosen option and of a list box all, of a drawing its texts (one a line),
of a formula its tokens (parts of fractions and scripts apart), of an object what stands in for it, and puts the cells of a table in columns.

A table's cells take the columns that colspan and rowspan give them; a column is as wide as its widest line of up to WIDE characters, and longer lines run over. Tables of more than COLUMNS
columns, and those whose padding would be more than four times their text, are written without padding, cells of several lines on lines of their own. Tables more than DEEP deep in each other
are plain blocks, and lists and quotations are indented by at most INDENT blanks. So the text of a page is never much longer than the page, and reading and writing it take time in proportion to its length.

Defined results: a null or empty page is an empty text. Bad or unclosed tags never raise; what is open at the end is closed there, and a tag or quoted value that the page's end cuts off shows
nothing, as in a browser. Only void elements and those of drawings and formulas close themselves. Nesting of any depth is walked without recursion. Repeated rows get equal texts. Other columns
are kept unread, but for one of the name of the result, which the result replaces.
"""

from __future__ import annotations

import re
from html import unescape

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallywalk.llm._frame import struct_udf

# fixed values: the sets of element names that HTML gives these roles
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
UNSEEN = frozenset("head script style template noscript iframe title datalist audio video canvas meta link".split())
RAW = frozenset("script style textarea title iframe noscript xmp noembed noframes".split())
DRAWN = frozenset("text foreignobject".split())  # elements of a drawing whose text is shown
ASIDE = {"svg": frozenset("desc metadata clippath mask pattern marker".split()), "math": frozenset("annotation annotation-xml mphantom".split())}
APART = frozenset("mfrac msup msub msubsup munder mover munderover mmultiscripts mroot mtr mlabeledtr".split())  # elements of a formula whose children are not one word
SPACED = frozenset("p h1 h2 h3 h4 h5 h6 blockquote pre ul ol dl table figure fieldset hr".split())
BLOCK = SPACED | frozenset("html body div section article aside nav header footer main address form details summary li dt dd tr caption figcaption center legend option textarea mtr mlabeledtr thead tbody tfoot".split())
ENDS_P = SPACED | frozenset("div section article aside nav header footer main address form details li dt dd center".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
WHOLE = frozenset("table html body div article section main".split())  # their end tags close whatever is open inside
P_LIMITS = ("td", "th", "table", "li", "div", "article", "section", "button")
TABLE_PARTS = frozenset("caption colgroup thead tbody tfoot tr td th".split())

WIDE, COLUMNS, DEEP, INDENT = 60, 100, 8, 80
RAW_END = {tag: re.compile(rf"</{tag}(?=[\s/>])", re.I) for tag in RAW}

TAG = re.compile(r"""</?([a-zA-Z][^\s/>]*+)((?:[^=>]++|=\s*+(?:"[^"]*+(?:"|\Z)|'[^']*+(?:'|\Z)|[^\s>"'][^\s>]*+)?)*+)(>?)""")
VALUE_END = re.compile(r"""=\s*+[^\s>"'][^\s>]*+\Z""")
ATTRIBUTE = re.compile(r"""([^\s=/"'>]++)(?:\s*+=\s*+("[^"]*+"|'[^']*+'|[^\s>]++))?""")
HIDING = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden")
SPACES = re.compile(r"[ \t\n\r\f]+")


class Node:
    __slots__ = ("attributes", "children", "tag")

    def __init__(self, tag: str, attributes: str = ""):
        self.tag, self.attributes, self.children = tag, attributes, []

    def values(self) -> dict[str, str]:
        return {m[1].lower(): unescape((m[2] or "").strip("\"'")) for m in ATTRIBUTE.finditer(self.attributes)}

    def seen(self) -> bool:
        if self.tag in UNSEEN:
            return False
        low = self.attributes
        if "hidden" not in low.lower() and "display" not in low.lower():
            return True
        v = self.values()
        return not ("hidden" in v or HIDING.search(v.get("style", "").lower()) or self.tag == "input" and v.get("type", "").lower() == "hidden")


def words_in(node: Node) -> str:
    out, todo = [], [node]
    while todo:
        x = todo.pop()
        if isinstance(x, str):
            out.append(x)
        elif x.seen():
            todo += reversed(x.children)
    return " ".join("".join(out).split())


def shown_options(select: Node) -> list[str] | str:
    """The lines of a list box, or the chosen option of a drop-down: the last one marked as selected, else the first that can be chosen."""
    v = select.values()
    box = "multiple" in v or (size := v.get("size", "").strip().lstrip("0")).isdecimal() and size != "1"
    options, lines = [], []
    todo = [(c, False) for c in reversed(select.children)]
    while todo:
        x, off = todo.pop()
        if isinstance(x, str) or not x.seen():
            continue
        own = x.values()
        off = off or "disabled" in own
        if x.tag == "option":
            said = own.get("label") or words_in(x)
            lines.append(said)
            options.append((said, "selected" in own, off))
        else:
            if x.tag == "optgroup":
                lines.append(own.get("label", ""))
            todo += [(c, off) for c in reversed(x.children)]
    if box:
        return lines
    chosen = [t for t, marked, _ in options if marked][-1:] or [t for t, _, off in options if not off][:1]
    return chosen[0] if chosen else ""


class Tree:
    """The open elements, and where those of each name are among them."""

    def __init__(self) -> None:
        self.root = Node("html")
        self.stack, self.where = [self.root], {}

    def last(self, names) -> int:
        """The place of the innermost open element of these names, 0 if there is none."""
        return max((self.where[n][-1] for n in names if self.where.get(n)), default=0)

    def cut(self, size: int) -> None:
        while len(self.stack) > size:
            self.where[self.stack.pop().tag].pop()

    def push(self, tag: str, attributes: str = "") -> Node:
        node = Node(tag, attributes)
        self.stack[-1].children.append(node)
        self.where.setdefault(tag, []).append(len(self.stack))
        self.stack.append(node)
        return node

    def add(self, child) -> None:
        self.stack[-1].children.append(child)

    def close(self, names, until=()) -> None:
        """Closes the innermost open element of these names, unless one of `until` lies inside it."""
        i = self.last(names)
        if i and i >= self.last(until):
            self.cut(i)

    def back_to(self, names) -> bool:
        """Closes what is open inside the innermost of these names, if there is one in the present table."""
        i = self.last(names)
        if i and i > self.last(("table",)):
            self.cut(i + 1)
            return True
        return False

    def table_part(self, tag: str) -> None:
        """Opens the parents that a part of a table lacks."""
        bodies = ("thead", "tbody", "tfoot")
        if tag in ("td", "th"):
            if not self.back_to(("tr",)):
                if not self.back_to(bodies):
                    self.cut(self.last(("table",)) + 1)
                    self.push("tbody")
                self.push("tr")
        elif tag == "tr":
            if not self.back_to(bodies):
                self.cut(self.last(("table",)) + 1)
                self.push("tbody")
        else:
            self.cut(self.last(("table",)) + 1)

    def end(self, tag: str) -> None:
        if tag == "p" and not self.last(("p",)):
            self.add(Node("p"))
        elif tag == "br":
            self.add(Node("br"))
        elif tag not in VOID:
            self.close((tag,), () if tag in WHOLE else ("td", "th", "table"))

    def begin(self, tag: str, attributes: str) -> Node:
        if tag in ENDS_P:
            self.close(("p",), P_LIMITS)
            if tag in HEADINGS and self.stack[-1].tag in HEADINGS:
                self.cut(len(self.stack) - 1)
        if tag not in UNSEEN and tag not in VOID and 0 < self.last(("head",)) < 3:
            self.close(("head",))
        if tag == "li":
            self.close(("li",), ("ul", "ol", "table"))
        elif tag in ("dt", "dd"):
            self.close(("dt", "dd"), ("dl", "table"))
        elif tag == "option":
            self.close(("option",), ("select",))
        elif tag in TABLE_PARTS and self.last(("table",)):
            self.table_part(tag)
        return self.push(tag, attributes)


def build(page: str) -> Node:
    tree, of_root = Tree(), []
    at, n = 0, len(page)

    def after(mark: str, start: int) -> int:
        i = page.find(mark, start)
        return n if i < 0 else i + len(mark)

    while at < n:
        start = page.find("<", at)
        if start < 0 or start == n - 1:
            tree.add(unescape(page[at:]))
            break
        next_ = page[start + 1]
        m = TAG.match(page, start) if next_ not in "!?" else None
        if m is None and next_ not in "!?/":  # a sign like others
            end = page.find("<", start + 1)
            end = n if end < 0 else end
            tree.add(unescape(page[at:end]))
            at = end
            continue
        if start > at:
            tree.add(unescape(page[at:start]))
        if m is None:
            if page.startswith("<!--", start):
                at = start + 5 if page.startswith("<!-->", start) else start + 6 if page.startswith("<!--->", start) else after("-->", start + 4)
            elif page.startswith("<![CDATA[", start) and tree.last(ASIDE):
                at = after("]]>", start + 9)
                tree.add(page[start + 9 : at].removesuffix("]]>"))
            else:
                at = after(">", start)
            continue
        at = m.end()
        if not m[3]:  # the page ends inside the tag
            break
        tag, attributes = m[1].lower(), m[2]
        if next_ == "/":
            tree.end(tag)
            continue
        if tag in ("html", "body"):
            if tag == "html":
                of_root.append(attributes)
            else:
                tree.close(("head",))
            continue
        node = tree.begin(tag, attributes)
        foreign = tag in ASIDE or tree.last(ASIDE) > tree.last(("foreignobject",))
        if tag in VOID or foreign and attributes.endswith("/") and not VALUE_END.search(attributes):
            tree.cut(len(tree.stack) - 1)
        elif tag in RAW and not foreign:
            end = RAW_END[tag].search(page, at)
            inside = page[at : end.start() if end else n]
            node.children.append(unescape(inside).removeprefix("\n") if tag in ("textarea", "title") else inside)
            tree.cut(len(tree.stack) - 1)
            at = n if end is None else TAG.match(page, end.start()).end()
        elif tag == "plaintext":
            node.children.append(page[at:])
            break
    tree.root.attributes = " ".join(of_root)
    return tree.root


class Page:
    """Lines of text in the making. gap: empty lines wanted before the next text."""

    def __init__(self) -> None:
        self.lines: list[str] = []
        self.now: list[str] = []
        self.gap, self.indent, self.mark, self.blank = 0, 0, "", False

    def text(self, s: str) -> None:
        s = SPACES.sub(" ", s)
        if not s:
            return
        if s[0] == " ":
            self.blank, s = bool(self.now), s[1:]
        if not s:
            return
        if self.blank and self.now:
            self.now.append(" ")
        self.blank = s[-1] == " "
        self.now.append(s[:-1] if self.blank else s)

    def end_line(self, always: bool = False) -> None:
        line = "".join(self.now)
        if line or always or self.mark:
            if line or always:
                if self.gap > 1 and self.lines:
                    self.lines.append("")
                self.lines.append((" " * max(0, min(INDENT, self.indent) - len(self.mark)) + self.mark + line).rstrip())
                self.gap, self.mark = 0, ""
        self.now, self.blank = [], False

    def block(self, gap: int) -> None:
        self.end_line()
        self.gap = max(self.gap, gap)

    def raw(self, lines: list[str]) -> None:
        self.end_line()
        if self.gap > 1 and self.lines:
            self.lines.append("")
        self.lines += [(" " * min(INDENT, self.indent) + x).rstrip() for x in lines]
        self.gap = 0

    def done(self) -> list[str]:
        self.end_line()
        return self.lines


def span_of(node: Node, name: str, most: int) -> int:
    m = re.match(r"\s*\+?(\d{1,6})", node.values().get(name, "")) if name in node.attributes.lower() else None
    return min(most, int(m[1])) if m else 1


def placed(rows: list[list[tuple[str, int, int]]]) -> list[list[tuple[int, int, list[str]]]] | None:
    """(column, columns, lines) of the cells (text, columns, rows) of each row; None if there are too many columns."""
    out, held = [], []  # held: (first column, end, last row) of cells that reach below their row, in order
    for r, row in enumerate(rows):
        held = [h for h in held if h[2] >= r]
        cells, column, k = [], 0, 0
        for text, wide, high in row:
            while k < len(held) and held[k][0] <= column:
                column, k = max(column, held[k][1]), k + 1
            end = column + max(1, wide)
            if k < len(held):
                end = max(column + 1, min(end, held[k][0]))
            cells.append((column, end, text.split("\n"), len(rows) if high == 0 else r + high - 1))
            column = end
            if column > COLUMNS:
                return None
        held = sorted([*held, *((a, b, low) for a, b, _, low in cells if low > r)])
        out.append([(a, b - a, lines) for a, b, lines, _ in cells])
    return out


def aligned(rows: list[list[tuple[str, int, int]]]) -> list[str]:
    """Rows of cells (text, columns, rows), each column padded to its widest line; a cell of many lines takes as many lines."""
    grid = placed(rows)
    if grid is not None:
        columns = max((a + n for row in grid for a, n, _ in row), default=0)
        widths = [0] * columns
        for a, n, lines in sorted((c for row in grid for c in row), key=lambda c: c[1]):
            have = sum(widths[a : a + n]) + 3 * (n - 1)
            widths[a + n - 1] += max(0, max((len(x) for x in lines if len(x) <= WIDE), default=0) - have)
        heights = [max((len(lines) for _, _, lines in row), default=0) for row in grid]
        if sum(heights) * (sum(widths) + 3 * columns) <= 4 * sum(len(x) for row in rows for x, _, _ in row) + 20_000:
            return [line for row, high in zip(grid, heights) for line in side_by_side(row, high, widths)]
    out: list[str] = []
    for row in rows:
        if any("\n" in x for x, _, _ in row):
            out += [line for x, _, _ in row for line in x.split("\n")]
        else:
            out.append(" | ".join(x for x, _, _ in row).rstrip())
    return out


def side_by_side(row: list[tuple[int, int, list[str]]], high: int, widths: list[int]) -> list[str]:
    out = []
    for k in range(high):
        parts, column = [], 0
        for a, n, lines in row:
            parts += [" " * w for w in widths[column:a]]
            parts.append((lines[k] if k < len(lines) else "").ljust(sum(widths[a : a + n]) + 3 * (n - 1)))
            column = a + n
        out.append(" | ".join(parts).rstrip())
    return out


def render(root: Node) -> str:
    pages, tables, lists = [Page()], [], []
    todo: list[tuple[bool, object, bool, str]] = [(False, root, False, "")]  # the last: in a drawing, one of its texts, or a formula
    while todo:
        leaving, node, pre, where = todo.pop()
        out = pages[-1]
        if isinstance(node, str):
            if where == "svg":
                continue
            if not pre:
                out.text(node)
            else:
                first, *more = node.split("\n")
                out.now.append(first)
                for x in more:
                    out.end_line(always=True)
                    out.now.append(x)
            continue
        tag = node.tag
        if not leaving:
            if not node.seen() or tag in ASIDE.get("svg" if where == "drawn" else where, ()):
                continue
            if where in ("svg", "drawn") and ((v := node.values()).get("display") == "none" or v.get("visibility") in ("hidden", "collapse")):
                continue
            if tag == "br":
                out.end_line(always=True)
                continue
            if tag == "select":
                lines = shown_options(node)
                if isinstance(lines, str):
                    out.text(f" {lines} ")
                else:
                    out.block(1)
                    for x in lines:
                        out.text(x)
                        out.block(1)
                continue
            inside = where
            if tag in ASIDE:
                inside = tag
            elif where == "svg" and tag in DRAWN:
                inside = "drawn"
                out.block(1)
            elif where == "drawn" and tag == "tspan" and {"x", "y", "dy"} & node.values().keys():
                out.block(1)
            elif where == "math" and tag == "mspace":
                out.text(" ")
            if tag == "table":
                out.block(2)
                tables.append([])
            elif len(tables) > DEEP and tag in ("tr", "td", "th", "caption"):
                out.block(1)
            elif tag == "tr" and tables:
                tables[-1].append([])
            elif tag in ("td", "th", "caption") and tables:
                pages.append(Page())
            elif tag in BLOCK:
                out.block(2 if tag in SPACED and not (tag in ("ul", "ol") and lists) else 1)
                if tag in ("ul", "ol"):
                    lists.append(0 if tag == "ol" else None)
                    out.indent += 2 + (tag == "ol")
                elif tag == "blockquote":
                    out.indent += 2
                elif tag == "li":
                    out.mark = "- "
                    if lists and lists[-1] is not None:
                        lists[-1] += 1
                        out.mark = f"{lists[-1]}. "
                elif tag == "hr":
                    out.raw(["-" * 8])
            todo.append((True, node, pre, where))
            inner = pre or tag in ("pre", "textarea")
            children = [x for c in node.children for x in (c, " ")] if where == "math" and tag in APART else node.children
            todo += [(False, c, inner, inside) for c in reversed(children)]
            continue
        if tag == "table" and tables:
            rows = [r for r in tables.pop() if any(x for x, _, _ in r)]
            out.raw(aligned(rows)) if rows else None
            out.gap = max(out.gap, 2)
        elif len(tables) > DEEP and tag in ("tr", "td", "th", "caption"):
            out.block(1)
        elif tag in ("td", "th", "caption") and tables:
            text = "\n".join(pages.pop().done())
            if tag == "caption":
                pages[-1].text(text)
                pages[-1].block(1)
            elif tables[-1]:
                tables[-1][-1].append((text, span_of(node, "colspan", 1000), span_of(node, "rowspan", 65534)))
        elif tag == "tr" and tables:
            pass
        elif where == "svg" and tag in DRAWN:
            out.block(1)
        elif tag in BLOCK:
            out.block(2 if tag in SPACED and not (tag in ("ul", "ol") and len(lists) > 1) else 1)
            if tag in ("ul", "ol"):
                lists.pop()
                out.indent -= 2 + (tag == "ol")
            elif tag == "blockquote":
                out.indent -= 2
            elif tag == "li":
                out.mark = ""
    return "\n".join(pages[0].done()).strip("\n")


def text_of(page: str | None) -> str:
    return render(build(page)) if page else ""


def extract(df: DataFrame, html: str = "html", text: str = "text") -> DataFrame:
    """df with the visible text of each page."""

    def run(pages):
        return {"v": list(map(text_of, pages))}

    return df.withColumn(text, struct_udf(run, "v string")(F.col(html))["v"])
