"""Layout-aware rendering of HTML as plain text.

A tolerant scanner feeds a tree builder that supplies implied end tags, and a
renderer emits all text a reader would see: paragraphs apart, list items with
markers and indents, preformatted text as it stands, table cells in columns.
Elements may nest to any depth; beyond NESTED boxes (lists, quotes, cells) in
one another their text goes on without further indents.
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Boxes in boxes that are laid out; what nests deeper flows as plain blocks, with all its text.
NESTED = 40
#: A table's cells line up if its columns, but for the last, are no wider than this; in other tables two spaces part them.
ALIGNED = 48

# Element names by their part in layout.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp iframe noembed noframes".split())
UNSEEN = frozenset("head script style template title noscript iframe noembed noframes object video audio canvas datalist base link meta param source track area map".split())
APART = frozenset("p h1 h2 h3 h4 h5 h6 blockquote pre figure table ul ol dl menu hr fieldset".split())
BLOCK = APART | frozenset("html body address article aside center details dialog dd div dt figcaption footer form header hgroup legend li main nav optgroup option search section summary tr caption thead tbody tfoot".split())
ENDS_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre search section table ul li dd dt summary".split())

#: For a start tag: the open elements it ends, and those that shield them.
IMPLIED = {
    "li": ({"li"}, {"ul", "ol", "menu"}),
    "dt": ({"dt", "dd"}, {"dl"}),
    "dd": ({"dt", "dd"}, {"dl"}),
    "option": ({"option"}, {"select", "optgroup", "datalist"}),
    "optgroup": ({"option", "optgroup"}, {"select"}),
    "tr": ({"tr", "td", "th", "caption", "colgroup"}, {"table"}),
    "td": ({"td", "th"}, {"tr", "table"}),
    "th": ({"td", "th"}, {"tr", "table"}),
    "thead": ({"tr", "td", "th", "thead", "tbody", "tfoot", "caption", "colgroup"}, {"table"}),
    "tbody": ({"tr", "td", "th", "thead", "tbody", "tfoot", "caption", "colgroup"}, {"table"}),
    "tfoot": ({"tr", "td", "th", "thead", "tbody", "tfoot", "caption", "colgroup"}, {"table"}),
    "caption": ({"caption", "colgroup"}, {"table"}),
    "body": ({"head"}, set()),
}
IN_HEAD = frozenset("base basefont bgsound link meta title style script noscript template noframes".split())
#: What an end tag may not reach through: of those named, and of all others but these elements' own.
SCOPE = frozenset("table td th caption object template".split())
SHIELD = {"li": {"ul", "ol", "menu"}, "td": {"table"}, "th": {"table"}, "tr": {"table"}, "tbody": {"table"}, "thead": {"table"}, "tfoot": {"table"}}

_TAG = re.compile(r"<(?:!--(?:>|->|.*?(?:--!?>|\Z))|[!?][^>]*(?:>|\Z)|(/?)([a-zA-Z][^\s/>]*)([^>\"']*(?:(?:\"[^\"]*\"|'[^']*')[^>\"']*)*|[^>]*)(?:>|\Z))", re.S)
_ATTRIBUTE = re.compile(r"([^\s=/\"'>]+)(?:\s*=\s*(\"[^\"]*\"|'[^']*'|[^\s>]+))?")
_QUOTED = re.compile(r"/\*.*?(?:\*/|\Z)|\"(?:\\.|[^\"\\\n])*\"|'(?:\\.|[^'\\\n])*'", re.S)
_PART = re.compile(r"([^{}]*)([{}]|\Z)")
_SHOWN = re.compile(r"(?:only\s+)?(?:all|screen)|not\s+print", re.I)
_SAID = re.compile(r"(?:^|[;\s])(display|visibility)\s*:\s*([\w-]+)([^;]*)", re.I)
_HIDES = re.compile(r"display\s*:\s*none|visibility\s*:\s*(?:hidden|collapse)", re.I)
_SPACE = re.compile(r"[ \t\n\r\f]+")
_CLOSE = {t: re.compile(f"</{t}(?=[\\s/>]|\\Z)", re.I) for t in RAW}


Styles = dict[str, dict[str, tuple[bool, int, bool]]]


class Node:
    __slots__ = ("tag", "attrs", "kids")

    def __init__(self, tag: str, attrs: dict[str, str]):
        self.tag, self.attrs, self.kids = tag, attrs, []


def _attributes(text: str) -> dict[str, str]:
    if "=" not in text and not text.strip(" \t\n\r\f/"):
        return {}
    out: dict[str, str] = {}
    for name, value in _ATTRIBUTE.findall(text):
        out.setdefault(name.lower(), html.unescape(value[1:-1] if value[:1] in "\"'" and value else value))
    return out


class _Open:
    """The open elements, and where those of each name stand."""

    def __init__(self, root: Node):
        self.stack, self.places = [root], {}

    def push(self, node: Node) -> None:
        self.places.setdefault(node.tag, []).append(len(self.stack))
        self.stack.append(node)

    def last(self, tags: Iterable[str]) -> int:
        """The innermost open element of these names, 0 if there is none."""
        return max((self.places[t][-1] for t in tags if self.places.get(t)), default=0)

    def close(self, place: int) -> None:
        for node in self.stack[place:]:
            self.places[node.tag].pop()
        del self.stack[place:]

    def imply(self, ends: set[str], shields: set[str]) -> None:
        while (place := self.last(ends)) > self.last(shields):
            self.close(place)

    def end(self, tag: str) -> None:
        if tag == "br":
            self.stack[-1].kids.append(Node("br", {}))
            return
        shields = SHIELD.get(tag, () if tag in SCOPE else SCOPE)
        if (place := self.last((tag,))) > self.last(shields):
            self.close(place)


def parse(source: str) -> tuple[Node, list[str]]:
    """The element tree, and the contents of style elements."""
    root = Node("html", {})
    open_, styles, at, find, begun = _Open(root), [], 0, _TAG.search, False
    stack = open_.stack
    while True:
        m = find(source, at)
        text = source[at : m.start() if m else len(source)]
        if text:
            if text.strip(" \t\n\r\f"):
                if stack[-1].tag == "head":
                    open_.close(len(stack) - 1)
                begun = True
            stack[-1].kids.append(html.unescape(text) if "&" in text else text)
        if not m:
            return root, styles
        at = m.end()
        tag = m[2]
        if tag is None:
            continue
        tag = tag.lower()
        if m[1]:
            open_.end(tag)
            continue
        if tag in ("html", "body") and len(stack) == 1 and not m[3].strip() or tag == "head" and begun:
            continue
        if tag not in IN_HEAD:
            if stack[-1].tag == "head":
                open_.close(len(stack) - 1)
            begun = begun or tag not in ("html", "head")
        if tag in ENDS_P:
            open_.imply({"p"}, {"table", "td", "th", "button", "object", "caption"})
        if rule := IMPLIED.get(tag):
            open_.imply(*rule)
        node = Node(tag, _attributes(m[3]))
        stack[-1].kids.append(node)
        if tag in RAW:
            end = _CLOSE[tag].search(source, at)
            inner = source[at : end.start() if end else len(source)]
            if tag == "style" and _applies(node.attrs.get("media", "")):
                styles.append(inner)
            elif tag in ("textarea", "xmp"):
                node.kids.append(html.unescape(inner) if tag == "textarea" else inner)
            at = source.find(">", end.end()) + 1 if end else len(source)
            at = at or len(source)
        elif tag not in VOID:
            open_.push(node)


def _applies(media: str) -> bool:
    """Whether a media query list holds for every reader at a screen."""
    return not media.strip() or any(_SHOWN.fullmatch(q.strip()) for q in media.split(","))


def _holds(rule: str) -> bool:
    """Whether what an at-rule encloses holds for every reader."""
    name, _, rest = rule[1:].partition(" ") if "(" not in rule.split(" ")[0] else (rule[1 : rule.index("(")], "", rule[rule.index("(") :])
    name = name.lower()
    return name == "layer" or (name == "media" and _applies(rest)) or (name == "supports" and not rest.strip().lower().startswith("not"))


def _rules(sheet: str) -> Iterator[tuple[str, str]]:
    """(selectors, declarations) of the rules of a sheet that hold for every reader, in order; rules inside rules are left out."""
    sheet = _SPACE.sub(" ", _QUOTED.sub(" ", sheet))
    open_: list[tuple[str, bool, list[str]]] = []
    for m in _PART.finditer(sheet):
        text, mark = m.groups()
        if mark == "{":
            before, _, name = text.rpartition(";")
            live = open_[-1][1] and (open_[-1][0].startswith("@")) if open_ else True
            if open_:
                open_[-1][2].append(before + ";")
            name = name.strip()
            open_.append((name, live and (not name.startswith("@") or _holds(name)), []))
            continue
        if open_:
            open_[-1][2].append(text)
        while open_:
            name, live, body = open_.pop()
            if live and not name.startswith("@"):
                yield name, "".join(body)
            if mark:
                break


def _shows(body: str) -> Iterator[tuple[str, bool, bool]]:
    """(property, shows, important) of the declarations that show or hide; those that only inherit say nothing."""
    for name, value, rest in _SAID.findall(body):
        if value.lower() not in ("inherit", "unset", "revert"):
            yield name.lower(), value.lower() not in ("none", "hidden", "collapse"), "important" in rest.lower()


def _hidden_by_rules(styles: list[str]) -> Styles:
    """What simple selectors (tag, .class, #id) say of display and visibility, the last word of each: {selector: {property: (important, place, shows)}}."""
    out: Styles = {}
    if not any(map(_HIDES.search, styles)):
        return out
    place = 0
    for sheet in styles:
        for names, body in _rules(sheet):
            said = list(_shows(body))
            for name in (x.strip() for x in names.split(",")) if said else ():
                if re.fullmatch(r"[.#]?[\w-]+", name):
                    mine = out.setdefault(name if name[0] in ".#" else name.lower(), {})
                    for what, shows, important in said:
                        place += 1
                        mine[what] = max(mine.get(what, (False, 0, True)), (important, place, shows))
    return out


class Page:
    """Lines of a box, with the blank lines that blocks ask for between them."""

    def __init__(self) -> None:
        self.lines: list[str] = []
        self.inline: list[str] = []
        self.gap = 0

    def flush(self) -> None:
        if self.inline:
            text = _SPACE.sub(" ", "".join(self.inline)).strip(" ")
            self.inline = []
            if text:
                self.put([text])

    def put(self, lines: list[str]) -> None:
        if self.gap and self.lines:
            self.lines.extend([""] * self.gap)
        self.gap = 0
        self.lines.extend(lines)


class Renderer:
    def __init__(self, styles: Styles):
        self.styles = styles

    def looks(self, node: Node, shown: bool) -> tuple[bool, bool]:
        """Whether the element has a place in the page, and whether its text shows, given that its parent's does or not."""
        if node.tag in UNSEEN:
            return False, shown
        a = node.attrs
        if node.tag == "input" and a.get("type", "").lower() == "hidden":
            return False, shown
        own = a["style"] if "style" in a else ""
        if not self.styles and not own:
            return "hidden" not in a, shown
        # Important words come first, then the element's own, those by id, class and tag, the last of each.
        said: dict[str, tuple] = {}
        names = [(0, node.tag)]
        if a:
            names += [(1, "." + c) for c in a.get("class", "").split()]
            names.append((2, "#" + a.get("id", "")))
        for rank, name in names:
            for what, (important, place, shows) in self.styles.get(name, {}).items():
                said[what] = max(said.get(what, (False,)), (important, rank, place, shows))
        for place, (what, shows, important) in enumerate(_shows(own)):
            said[what] = max(said.get(what, (False,)), (important, 3, place, shows))
        return said["display"][-1] if "display" in said else "hidden" not in a, said["visibility"][-1] if "visibility" in said else shown

    def box(self, kids: list, shown: bool, level: int) -> list[str]:
        """Lines of what stands side by side in one box."""
        page = Page()
        self.flow(kids, shown, page, level)
        page.flush()
        return page.lines

    def flow(self, kids: list, shown: bool, page: Page, level: int) -> None:
        """Put text on the page, element after element; `level` boxes lie around it."""
        todo: list[tuple] = [(iter(kids), shown, None)]
        while todo:
            rest, shown, block = todo[-1]
            kid = next(rest, None)
            if kid is None:
                todo.pop()
                if block is not None:
                    page.flush()
                    page.gap = max(page.gap, block)
            elif type(kid) is str:
                if shown:
                    page.inline.append(kid)
            else:
                self.element(kid, shown, page, level, todo)

    def element(self, kid: Node, shown: bool, page: Page, level: int, todo: list[tuple]) -> None:
        tag = kid.tag
        placed, shown = self.looks(kid, shown)
        if not placed:
            return
        kids = kid.kids
        if tag == "details" and "open" not in kid.attrs:
            kids = [x for x in kids if type(x) is Node and x.tag == "summary"]
        if tag == "br":
            if not page.inline:
                page.put([""] if page.lines and page.lines[-1] else [])
            page.flush()
        elif tag in VOID and tag != "hr":
            return
        elif tag in BLOCK or level >= NESTED and tag in ("td", "th"):
            page.flush()
            apart = 1 if tag in APART else 0
            page.gap = max(page.gap, apart)
            lines = None
            if tag == "pre":
                lines = self.verbatim(kid, shown)
            elif level >= NESTED:
                pass
            elif tag == "table":
                lines = self.table(kid, shown, level + 1)
            elif tag in ("ul", "ol", "menu"):
                lines = self.items(kid, shown, level + 1)
            elif tag in ("blockquote", "dd"):
                lines = ["  " + x if x else x for x in self.box(kids, shown, level + 1)]
            elif tag == "li":
                lines = self.box(kids, shown, level + 1)
                lines = lines and ["- " + lines[0], *("  " + x if x else x for x in lines[1:])]
            if lines is None:
                todo.append((iter(kids), shown, apart))
                return
            if lines:
                page.put(lines)
            page.gap = max(page.gap, apart)
        elif tag in ("textarea", "xmp"):
            page.flush()
            if shown:
                page.put("".join(k for k in kids if type(k) is str).strip("\n").split("\n"))
        else:
            todo.append((iter(kids), shown, None))

    def items(self, node: Node, shown: bool, level: int) -> list[str]:
        start = node.attrs.get("start", "1").strip()
        number, out = int(start) if re.fullmatch(r"-?[0-9]{1,9}", start) else 1, []
        loose: list = []
        for kid in [*node.kids, None]:
            mark = ""
            if type(kid) is Node and kid.tag == "li":
                mark = f"{number}. " if node.tag == "ol" else "- "
            elif kid is not None:
                loose.append(kid)
                continue
            if loose:
                out.extend("  " + x if x else x for x in self.box(loose, shown, level))
                loose = []
            placed, seen = self.looks(kid, shown) if kid is not None else (False, False)
            if placed:
                lines = self.box(kid.kids, seen, level) or ([""] if seen else [])
                pad = " " * len(mark)
                out.extend((mark + lines[0]).rstrip(" ") if k == 0 else pad + x if x else x for k, x in enumerate(lines))
                number += 1
        return out

    def verbatim(self, node: Node, shown: bool) -> list[str] | None:
        parts: list[str] = []
        todo = [(x, shown) for x in reversed(node.kids)]
        while todo:
            x, shown = todo.pop()
            if type(x) is str:
                parts.append(x if shown else "")
                continue
            placed, shown = self.looks(x, shown)
            if x.tag == "br":
                parts.append("\n")
            elif placed:
                todo.extend((y, shown) for y in reversed(x.kids))
        text = "".join(parts).replace("\r\n", "\n").replace("\r", "\n").strip("\n")
        return text.split("\n") if text else []

    def table(self, node: Node, shown: bool, level: int) -> list[str]:
        """Captions, then rows with cells in columns, then what stands outside cells."""
        before: list[str] = []
        rows: list[list[tuple[Node, bool]]] = []
        loose: list = []
        todo = [(x, shown) for x in reversed(node.kids)]
        while todo:
            kid, shown = todo.pop()
            if type(kid) is str:
                if kid.strip() and shown:
                    loose.append(kid)
                continue
            placed, seen = self.looks(kid, shown)
            if not placed:
                continue
            if kid.tag in ("thead", "tbody", "tfoot"):
                todo.extend((x, seen) for x in reversed(kid.kids))
            elif kid.tag == "tr":
                cells = [(c, *self.looks(c, seen)) for c in kid.kids if type(c) is Node and c.tag in ("td", "th")]
                rows.append([(c, s) for c, p, s in cells if p])
                loose.extend(c for c in kid.kids if (type(c) is Node and c.tag not in ("td", "th")) or (type(c) is str and c.strip() and seen))
            elif kid.tag in ("td", "th"):
                rows.append([(kid, seen)])
            elif kid.tag == "caption":
                before.extend(self.box(kid.kids, seen, level))
            elif kid.tag not in ("col", "colgroup"):
                loose.append(kid)
        after = self.box(loose, True, level) if loose else []
        placed_cells = []
        width: dict[int, int] = {}
        taken: dict[int, int] = {}
        for row in rows:
            at, line, fresh = 0, [], {}
            for c, seen in row:
                while taken.get(at):
                    at += 1
                span, deep = _span(c, "colspan", 1000), _span(c, "rowspan", 65534)
                lines = [x for x in self.box(c.kids, seen, level) if x] or [""]
                line.append((at, lines))
                if span == 1:
                    width[at] = max(width.get(at, 0), max(map(len, lines)))
                if deep > 1:
                    fresh.update((k, deep - 1) for k in range(at, at + span))
                at += span
            taken = {k: n - 1 for k, n in taken.items() if n > 1} | fresh
            placed_cells.append(line)
        columns = sorted({at for line in placed_cells for at, _ in line})
        aligned = all(width.get(at, 0) <= ALIGNED for at in columns[:-1])
        left, run = {}, 0
        for at in columns:
            left[at] = run
            run += width.get(at, 0) + 2 if aligned else 0
        out = []
        for line in placed_cells:
            for k in range(max((len(x) for _, x in line), default=0)):
                text = ""
                for at, lines in line:
                    if k < len(lines) and lines[k]:
                        text = text.ljust(left[at]) + ("  " if text and len(text) >= left[at] and not text.endswith("  ") else "") + lines[k]
                out.append(text.rstrip(" "))
        return [*before, *out, *after]


def _span(cell: Node, name: str, most: int) -> int:
    """How many columns or rows a cell takes; 0 rows are all that follow."""
    text = cell.attrs.get(name, "1").strip()
    n = int(text[:6]) if text.isascii() and text.isdigit() else 1
    return min(most, n) if n else (most if name == "rowspan" else 1)


def render(source: str | None) -> str:
    """Visible text of one page; null and empty sources give an empty text."""
    if not source:
        return ""
    root, styles = parse(source)
    lines = Renderer(_hidden_by_rules(styles)).box(root.kids, True, 0)
    return "\n".join(lines).strip("\n")


def extract(pages: DataFrame, key: str = "page_id", source: str = "html", also: tuple[str, ...] = ()) -> DataFrame:
    """(key, `also` columns, text) of every row.

    Nulls, empty pages and pages without visible text give an empty text;
    broken markup is read as far as it goes. Repeated rows each keep their
    row, null ids stay, and an empty table gives no rows; columns of other
    names are not read. One pass, no shuffle; memory holds one page's tree.
    """
    chosen = pages.select(key, *also, F.col(source).alias("__html"))
    schema = pages.select(key, *also, F.lit("").alias("text")).schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [render(x) for x in batch.column(batch.num_columns - 1).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(texts, pa.string())], [*batch.schema.names[:-1], "text"])

    return chosen.mapInArrow(run, schema)
