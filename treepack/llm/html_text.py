"""Layout-aware text of HTML pages.

A tokenizer and tree builder put in the tags that authors leave out (items,
paragraphs, rows and cells close one another, the head ends where its content
does); visibility rules drop what a browser would not show; a renderer lays the rest out: blocks on lines of their
own, blank lines around paragraphs, list markers with indents, tables in
columns of even width.
"""

from __future__ import annotations

import hashlib
import html
import re
from bisect import bisect_left
from collections import Counter
from itertools import accumulate

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treepack.llm.common import map_groups

# Sets of element names of the HTML standard.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp iframe noembed noframes".split())
HIDDEN = frozenset("head script style template noscript iframe noembed noframes object audio video canvas svg datalist title meta link base param source track".split())
SPACED = frozenset("p h1 h2 h3 h4 h5 h6 blockquote pre ul ol dl table figure fieldset hr".split())
BLOCK = SPACED | frozenset("html body div section article aside nav header footer main address form li dt dd tr caption thead tbody tfoot figcaption details summary legend option select center td th".split())
CLOSES_P = (SPACED | frozenset("div section article aside nav header footer main address form details center li dt dd".split())) - {"td", "th"}
HEAD_CONTENT = frozenset("head base basefont bgsound link meta title noscript noframes style script template".split())
#: The standard's bounds on how many columns and rows a cell may span.
MAX_COLSPAN, MAX_ROWSPAN = 1000, 65534
#: name: (names that it closes when open, where the search for them ends)
IMPLIED = {
    "li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "option": ({"option"}, {"select", "datalist"}),
    "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "tr": ({"tr"}, {"table"}),
    "tbody": ({"tbody", "thead", "tfoot"}, {"table"}), "thead": ({"tbody", "thead", "tfoot"}, {"table"}), "tfoot": ({"tbody", "thead", "tfoot"}, {"table"}),
}
_TOKEN = re.compile(r"""<!--.*?(?:-->|\Z)|<[!?][^>]*+>?|<(/?)([A-Za-z][^\s/>]*+)((?:[^>"']|"[^"]*+"|'[^']*+')*+)>|<(/?)([A-Za-z][^\s/>]*+)([^>]*+)>""", re.S)
_ATTR = re.compile(r"""([^\s=/"'>]+)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""")
_WHITE = re.compile(r"[ \t\n\r\f]+")
_NO_SHOW = re.compile(r"(?:display\s*:\s*none|visibility\s*:\s*(?:hidden|collapse))", re.I)


class Node:
    __slots__ = ("name", "attrs", "children", "lines")

    def __init__(self, name: str, attrs: dict[str, str]):
        self.name, self.attrs, self.children, self.lines = name, attrs, [], None


class Open:
    """The open elements, innermost last, with their number by name, so that a search for none costs nothing."""

    def __init__(self, root: Node):
        self.stack, self.number = [root], Counter()

    def push(self, node: Node) -> None:
        self.stack.append(node)
        self.number[node.name] += 1

    def cut(self, k: int) -> None:
        for node in self.stack[k:]:
            self.number[node.name] -= 1
        del self.stack[k:]

    def close(self, names: set[str], bounds: frozenset[str] | set[str]) -> None:
        """Closes the innermost element of these names, unless one of the bounds lies further in."""
        if not any(self.number[n] for n in names):
            return
        for k in range(len(self.stack) - 1, 0, -1):
            if self.stack[k].name in names:
                return self.cut(k)
            if self.stack[k].name in bounds:
                return None
        return None

    def add(self, child: Node | str) -> None:
        """A child of the innermost element; what can't stand in the head ends it."""
        if self.number["head"] and (child.strip() if isinstance(child, str) else child.name not in HEAD_CONTENT) and self.stack[-1].name == "head":
            self.cut(len(self.stack) - 1)
        self.stack[-1].children.append(child)


def parse(source: str) -> Node:
    """The tree of a page; whatever the source, it has one."""
    root = Node("#root", {})
    tree, at, raw_end = Open(root), 0, {}
    for m in iter(lambda: _TOKEN.search(source, at), None):
        if m.start() > at:
            tree.add(html.unescape(source[at : m.start()]))
        at = m.end()
        closing, name, rest = (m[1], m[2], m[3]) if m[2] else (m[4], m[5], m[6])
        if not name:
            continue
        name = name.lower()
        if closing:
            _close(tree, name)
            continue
        attrs = {k.lower(): html.unescape(a or b or c or "") for k, a, b, c in _ATTR.findall(rest)} if rest.strip(" /") else {}
        _imply(tree, name)
        node = Node(name, attrs)
        tree.add(node)
        if name in VOID:
            continue
        if name in RAW:
            end = raw_end.setdefault(name, re.compile(rf"</{name}\s*>", re.I)).search(source, at)
            text = source[at : end.start() if end else len(source)]
            node.children.append(html.unescape(text) if name in ("textarea", "title") else text)
            at = end.end() if end else len(source)
            continue
        tree.push(node)
    if at < len(source):
        tree.add(html.unescape(source[at:]))
    return root


_PARTS = frozenset("table tr td th tbody thead tfoot body html".split())


def _close(tree: Open, name: str) -> None:
    """An end tag stays within its cell; one of a part of a table stays within the table."""
    tree.close({name}, {"td", "th", "table"} if name not in _PARTS else set() if name in ("table", "body", "html") else {"table"})


def _imply(tree: Open, name: str) -> None:
    if name in CLOSES_P:
        tree.close({"p"}, BLOCK)
    if name in IMPLIED:
        tree.close(*IMPLIED[name])
    if name in ("td", "th") and tree.stack[-1].name in ("table", "tbody", "thead", "tfoot"):
        row = Node("tr", {})
        tree.add(row)
        tree.push(row)


def visible(node: Node) -> bool:
    return not (node.name in HIDDEN or "hidden" in node.attrs or (node.name == "input" and node.attrs.get("type", "").lower() == "hidden") or ("style" in node.attrs and _NO_SHOW.search(node.attrs["style"])))


class Page:
    """Lines so far, the line being written, and what must come before its next word."""

    def __init__(self):
        self.lines: list[str] = []
        self.line: list[str] = []
        self.space, self.gap, self.indent, self.marker = False, 0, "", ""

    def words(self, text: str, pre: bool) -> None:
        if pre:
            first, *rest = text.split("\n")
            self._put(first.rstrip("\r")) if first else None
            for r in rest:
                self.end(0, force=True)
                self._put(r.rstrip("\r")) if r else None
            return
        flat = _WHITE.sub(" ", text)
        if not flat:
            return
        if flat[0] == " ":
            self.space = True
        if body := flat.strip(" "):
            self._put(body)
            self.space = flat[-1] == " "

    def _put(self, text: str) -> None:
        if not self.line:
            self._open()
            text = text if not self.space else text
        elif self.space:
            self.line.append(" ")
        self.space = False
        self.line.append(text)

    def _open(self) -> None:
        if self.lines:
            self.lines += [""] * self.gap
        self.gap = 0
        self.line.append(self.indent[: len(self.indent) - len(self.marker)] + self.marker)
        self.marker = ""

    def end(self, gap: int, force: bool = False) -> None:
        if self.line:
            self.lines.append("".join(self.line).rstrip())
            self.line = []
        elif force and self.lines:
            self.lines.append("")
        self.space = False
        self.gap = max(self.gap, gap)

    def block(self, lines: list[str]) -> None:
        self.end(0)
        for text in lines:
            self._put(text)
            self.end(0)

    def text(self) -> str:
        self.end(0)
        return "\n".join(self.lines).strip("\n")


def layout(root: Node) -> list[str]:
    """Lines of a page. Tables are laid out from the innermost out, so no depth of nesting needs recursion."""
    tables, todo = [], [root]
    while todo:
        node = todo.pop()
        if node.name == "table":
            tables.append(node)
        todo += [c for c in node.children if not isinstance(c, str)]
    for node in reversed(tables):
        node.lines = table_lines(node)
    return render(root)


def render(root: Node) -> list[str]:
    """Lines of a tree whose tables are laid out."""
    page, pre = Page(), 0
    lists: list[list] = []
    todo: list[tuple[Node | str, bool]] = [(c, False) for c in reversed(root.children)]
    while todo:
        node, done = todo.pop()
        if isinstance(node, str):
            page.words(node, pre > 0)
            continue
        name = node.name
        if not done:
            if not visible(node):
                continue
            if name == "br":
                page.end(0, force=True)
                continue
            if name == "img":
                page.words(node.attrs.get("alt", ""), False)
                continue
            if name == "input":
                page.words(node.attrs.get("value", ""), False)
                continue
            if name in BLOCK:
                page.end(1 if name in SPACED and not lists else 0)
            if name == "hr":
                page.block(["---"])
                page.end(1)
                continue
            if name == "table":
                page.block(node.lines)
                page.end(0 if lists else 1)
                continue
            if name == "pre":
                pre += 1
            elif name in ("ul", "ol", "menu"):
                lists.append([name, int(s) if (s := node.attrs.get("start", "")).isdigit() else 1, page.indent])
            elif name == "li":
                ordered = lists and lists[-1][0] == "ol"
                page.marker = f"{lists[-1][1]}. " if ordered else "- "
                if ordered:
                    lists[-1][1] += 1
                page.indent = (lists[-1][2] if lists else "") + " " * len(page.marker)
            elif name in ("dd", "blockquote"):
                page.indent += "    "
            todo.append((node, True))
            todo += [(c, False) for c in reversed(node.children)]
            continue
        if name == "pre":
            pre -= 1
        elif name in ("ul", "ol", "menu") and lists:
            page.end(0)
            page.indent = lists.pop()[2]
        elif name == "li":
            page.end(0)
            page.marker, page.indent = "", lists[-1][2] if lists else ""
        elif name in ("dd", "blockquote"):
            page.end(0)
            page.indent = page.indent[:-4]
        if name in BLOCK:
            page.end(1 if name in SPACED and not lists else 0)
    return page.text().split("\n")


def table_lines(table: Node) -> list[str]:
    """Rows as lines, cells padded to the width of their column.

    A cell that spans several columns counts for the width of none; one that
    spans rows keeps its columns free in the rows below.
    """
    rows: list[list[tuple[list[str], int, int]]] = []
    out: list[str] = []
    todo = [c for c in reversed(table.children)]
    while todo:
        node = todo.pop()
        if isinstance(node, str):
            if node.strip():
                rows.append([_cell(node)])
        elif visible(node):
            if node.name == "tr":
                cells = [c for c in node.children if not isinstance(c, str) or c.strip()]
                rows.append([_cell(c) for c in cells if isinstance(c, str) or visible(c)])
            elif node.name in ("tbody", "thead", "tfoot"):
                todo += reversed(node.children)
            elif node.name == "caption":
                out += [x for x in render(node) if x]
            elif node.name not in ("colgroup", "col"):
                rows.append([_cell(node)])
    placed, busy, width = [], {}, {}
    for r in rows:
        col, here = 0, []
        held = {c for c, n in busy.items() if n}
        busy = {c: n - 1 for c, n in busy.items() if n > 1}
        for lines, span, down in r:
            while col in held:
                col += 1
            here.append((col, lines))
            width[col] = max(width.get(col, 0), *map(len, lines), 0) if span == 1 else width.get(col, 0)
            if down > 1:
                busy |= {c: down - 1 for c in range(col, col + span)}
            col += span
        if any(any(lines) for _, lines in here):
            placed.append(here)
    columns = sorted(width)  # those where a cell begins
    begins = [0, *accumulate(width[c] + 2 for c in columns)]
    for here in placed:
        for k in range(max(len(lines) for _, lines in here)):
            line = ""
            for col, lines in here:
                if k < len(lines) and lines[k]:
                    line = line.ljust(max(begins[bisect_left(columns, col)], len(line) + 2 if line else 0)) + lines[k]
            out.append(line.rstrip())
    return out


def _cell(node: Node | str) -> tuple[list[str], int, int]:
    """(lines, columns, rows) of a cell."""
    if isinstance(node, str):
        return [_WHITE.sub(" ", node).strip()], 1, 1
    down = _span(node, "rowspan", MAX_ROWSPAN)
    return render(node), max(_span(node, "colspan", MAX_COLSPAN), 1), down or MAX_ROWSPAN


def _span(node: Node, name: str, most: int) -> int:
    """A span as the standard reads it: 1 if it is no number, cut to its bounds; 0 rows are all that follow."""
    text = node.attrs.get(name, "1").strip()
    return min(int(text[:9]), most) if text[:9].isascii() and text[:9].isdigit() else 1


def html_to_text(source: str | None) -> str:
    """Visible text of a page, laid out; empty for a null or empty page."""
    return "\n".join(layout(parse(source))).strip("\n") if source else ""


def extract_text(pages: DataFrame, id_column: str = "page_id", html_column: str = "html") -> DataFrame:
    """(id, text, n_lines, text_sha256) for each row: a null or empty page has the empty text and no lines; repeated rows repeat."""

    def many(rows):
        out = []
        for page_id, source in rows:
            text = html_to_text((source or b"").decode())
            out.append((page_id, text, text.count("\n") + 1 if text else 0, hashlib.sha256(text.encode()).hexdigest()))
        return out

    return map_groups(pages.select(F.col(id_column).cast("long"), html_column), many, f"{id_column} long, text string, n_lines long, text_sha256 string")
