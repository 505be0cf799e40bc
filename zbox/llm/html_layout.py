"""Layout-aware text of HTML pages.

A tree is built from the tags with the implied ones put in (list items, paragraphs, table parts and
options close where the next one opens; head and body appear where they are missing), hidden elements
are left out by rule, and the visible rest is laid out: blocks on lines of their own with blank lines
where the block has a margin, list items with bullets or numbers and indentation, table cells in
aligned columns (spans across rows and columns kept, wide characters counted as two), preformatted text
as it stands. Every visible character is emitted.

Hidden are: elements without text of their own by kind; the attribute ``hidden``; display none, by a style
attribute or by a rule of the page's style sheets whose selector is made of names, classes and ids (of
combinators the descendant one); visibility hidden, but for descendants that are visible again; the body
of a closed ``details``. Rules inside @media and the like do not count."""

from __future__ import annotations

import re
import unicodedata
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Element classes.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp iframe noembed noframes plaintext".split())
HIDDEN = frozenset("script style head title template noscript iframe object embed audio video canvas datalist noembed noframes meta link base param source track".split())
HEAD_ONLY = frozenset("base link meta title style script noscript template".split())
BLOCK = frozenset("address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol optgroup option p pre section summary table tbody td tfoot th thead tr ul caption".split())
MARGIN = frozenset("blockquote dl figure h1 h2 h3 h4 h5 h6 ol p pre table ul menu dir fieldset hr".split())
#: Opening one of these closes an open one of those, up to the element that holds them.
IMPLIED_END = {
    "li": ({"li"}, {"ul", "ol", "menu", "dir"}),
    "dt": ({"dt", "dd"}, {"dl"}),
    "dd": ({"dt", "dd"}, {"dl"}),
    "tr": ({"tr", "td", "th", "caption", "colgroup"}, {"table", "tbody", "thead", "tfoot"}),
    "td": ({"td", "th"}, {"tr", "table"}),
    "th": ({"td", "th"}, {"tr", "table"}),
    "tbody": ({"tbody", "thead", "tfoot", "tr", "td", "th", "caption", "colgroup"}, {"table"}),
    "thead": ({"tbody", "thead", "tfoot", "tr", "td", "th", "caption", "colgroup"}, {"table"}),
    "tfoot": ({"tbody", "thead", "tfoot", "tr", "td", "th", "caption", "colgroup"}, {"table"}),
    "option": ({"option"}, {"select", "datalist", "optgroup"}),
    "optgroup": ({"option", "optgroup"}, {"select"}),
}
#: Blocks that end an open paragraph.
ENDS_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section summary table ul".split())
FORMATTING = frozenset("a abbr b bdi bdo big cite code data dfn em font i ins kbd label mark q s samp small span strike strong sub sup time tt u var del".split())
_SCOPE = frozenset("table td th caption html template object button".split())

_TOKEN = re.compile(r"<!--.*?(?:-->|--!>|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|</?[a-zA-Z](?:[^>\"']|\"[^\"]*(?:\"|\Z)|'[^']*(?:'|\Z))*(?:>|\Z)", re.S)
_NAME = re.compile(r"</?([a-zA-Z][^\s/>]*)")
_ATTR = re.compile(r"([^\s\"'>/=]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'=<>`]+)))?", re.S)
_SPACE = re.compile(r"[ \t\n\r\f]+")
_DECLARED = re.compile(r"(?:^|[;{])\s*(display|visibility|content-visibility)\s*:\s*([a-z-]+)\s*(!\s*important)?", re.I)
_COMPOUND = re.compile(r"([a-z][\w-]*|\*)?((?:[.#][\w-]+)*)\Z", re.I)


class Node:
    __slots__ = ("attrs", "kids", "name")

    def __init__(self, name: str, attrs: dict | None = None):
        self.name, self.attrs, self.kids = name, attrs or {}, []


def _attributes(tag: str) -> dict:
    rest = tag[_NAME.match(tag).end() :].rstrip(">")
    found: dict = {}
    for m in _ATTR.finditer(rest):
        found.setdefault(m[1].lower(), unescape(next((g for g in m.groups()[1:] if g is not None), "")))
    return found


def parse(html: str | None) -> Node:
    """The tree of a page. Anything is accepted: end tags without a start are dropped, elements left
    open end with the page, an unknown element is inline."""
    root, body = Node("html"), None
    head = Node("head")
    root.kids.append(head)
    open_: list[Node] = [root]

    def into_body() -> None:
        nonlocal body
        if body is None:
            body = Node("body")
            root.kids.append(body)
            open_[:] = [root, body]

    def text(s: str, raw: bool = False) -> None:
        if not s:
            return
        if body is None and (len(open_) == 1 or open_[-1] is head):
            if not s.strip(" \t\n\r\f"):
                return
            into_body()
        open_[-1].kids.append(s if raw else unescape(s))

    def close(names, stop) -> None:
        for i in range(len(open_) - 1, 0, -1):
            if open_[i].name in stop:
                return
            if open_[i].name in names:
                del open_[i:]
                return close(names, stop)

    def start(name: str, tag: str) -> None:
        nonlocal body
        if name in ("html", "head", "body"):
            if name == "body" and body is None:
                into_body()
                body.attrs = _attributes(tag)
            elif name == "html":
                root.attrs = root.attrs or _attributes(tag)
            elif name == "head" and body is None and len(open_) == 1:
                open_.append(head)
            return
        if body is None:
            if name in HEAD_ONLY:
                if len(open_) == 1:
                    open_.append(head)
            else:
                into_body()
        if name in IMPLIED_END:
            close(*IMPLIED_END[name])
        if name in ENDS_P:
            close({"p"}, _SCOPE)
        top = open_[-1].name
        if name in ("td", "th") and top in ("table", "tbody", "thead", "tfoot"):
            row = Node("tr")
            open_[-1].kids.append(row)
            open_.append(row)
        node = Node(name, _attributes(tag) if len(tag) > len(name) + 2 else None)
        open_[-1].kids.append(node)
        if name not in VOID and not tag.endswith("/>"):
            open_.append(node)
        elif tag.endswith("/>") and name not in VOID:
            open_.append(node)  # the slash means nothing on other elements

    def end(name: str) -> None:
        if name == "br":
            return start("br", "<br>")
        if name in ("html", "body", "head"):
            if name == "head" and len(open_) == 2 and open_[1] is head:
                open_.pop()
            return None
        if name == "p" and not any(n.name == "p" for n in open_):
            return start("p", "<p>") or end("p")
        for i in range(len(open_) - 1, 0, -1):
            n = open_[i].name
            if n == name:
                del open_[i:]
                return None
            if name in FORMATTING and n in BLOCK and n not in ("p",):
                return None  # an inline end tag does not end the blocks around it
            if n in ("td", "th", "table") and name not in ("table", "tr", "td", "th", "tbody", "thead", "tfoot") and n != name:
                return None
        return None

    s, at, raw_end = html or "", 0, None
    while at < len(s):
        m = _TOKEN.search(s, at)
        if m is None:
            text(s[at:])
            break
        text(s[at : m.start()])
        at, tag = m.end(), m[0]
        if tag.startswith("<!") or tag.startswith("<?"):
            if tag.startswith("<![CDATA["):
                text(re.sub(r"\]\]>\Z", "", tag[9:]), raw=True)
            continue
        name = _NAME.match(tag)[1].lower()
        if tag[1] == "/":
            end(name)
            continue
        start(name, tag)
        if name in RAW:
            raw_end = re.compile(rf"</{re.escape(name)}(?=[\s/>]|\Z)[^>]*(?:>|\Z)", re.I).search(s, at) if name != "plaintext" else None
            stop = raw_end.start() if raw_end else len(s)
            if open_[-1].name == name:
                if s[at:stop]:
                    open_[-1].kids.append(unescape(s[at:stop]) if name in ("title", "textarea") else s[at:stop])
                open_.pop()
            at = raw_end.end() if raw_end else len(s)
    return root


def hidden(node: Node) -> bool:
    a = node.attrs
    return (
        node.name in HIDDEN
        or "hidden" in a and a["hidden"].lower() != "until-found"
        or node.name == "input"
        or node.name == "dialog" and "open" not in a
    )


def _declarations(css: str) -> dict[str, tuple[str, bool]]:
    """Of display and visibility: value and whether important; the last one of equal rank."""
    found: dict = {}
    for name, value, important in _DECLARED.findall(css):
        if important or not found.get(name.lower(), ("", False))[1]:
            found[name.lower()] = (value.lower(), bool(important))
    return found


def style_rules(sheets: list[str]) -> dict[str, list]:
    """Rules that say anything of display or visibility, by the last part's id, class or name: (parts,
    specificity, order, declarations)."""
    rules: dict[str, list] = {}
    for sheet in sheets:
        sheet = re.sub(r"/\*.*?(?:\*/|\Z)", " ", sheet, flags=re.S)
        depth_free = re.sub(r"@[^{};]*(?:;|\{(?:[^{}]|\{[^{}]*\})*(?:\}|\Z))", " ", sheet)
        for selectors, body in re.findall(r"([^{}]+)\{([^{}]*)(?:\}|\Z)", depth_free):
            said = _declarations(body)
            if not said:
                continue
            for selector in selectors.split(","):
                parts = [_COMPOUND.match(x) for x in selector.split()]
                if not parts or not all(parts):
                    continue
                parts = [((m[1] or "*").lower(), frozenset(re.findall(r"\.([\w-]+)", m[2])), frozenset(re.findall(r"#([\w-]+)", m[2]))) for m in parts]
                rank = (sum(len(i) for *_, i in parts), sum(len(c) for _, c, _ in parts), sum(n != "*" for n, *_ in parts))
                name, classes, ids = parts[-1]
                at = f"#{min(ids)}" if ids else f".{min(classes)}" if classes else name
                rules.setdefault(at, []).append((parts, rank, sum(map(len, rules.values())), said))
    return rules


def _meets(part, node: Node) -> bool:
    name, classes, ids = part
    return (name in ("*", node.name)) and classes <= set(node.attrs.get("class", "").split()) and ids <= {node.attrs.get("id")}


def _styled(node: Node, above: list[Node], rules: dict) -> dict[str, str]:
    """display and visibility that are declared for a node."""
    won: dict[str, tuple] = {}
    if rules:
        keys = [f"#{node.attrs['id']}"] if "id" in node.attrs else []
        for key in [*keys, *(f".{c}" for c in node.attrs.get("class", "").split()), node.name, "*"]:
            for parts, rank, order, said in rules.get(key, ()):
                if not _meets(parts[-1], node):
                    continue
                rest = len(parts) - 2
                for up in reversed(above):
                    if rest < 0:
                        break
                    rest -= _meets(parts[rest], up)
                if rest >= 0:
                    continue
                for what, (value, important) in said.items():
                    won[what] = max(won.get(what, ((False,),)), ((important, False, rank, order), value))
    for what, (value, important) in _declarations(node.attrs.get("style", "")).items():
        won[what] = max(won.get(what, ((False,),)), ((important, True, (0, 0, 0), 0), value))
    return {what: value for what, (_, value) in won.items()}


def visible(root: Node) -> Node:
    """The tree without what is not seen. Nesting is followed to any depth by an own stack."""
    sheets, todo = [], [root]
    while todo:
        node = todo.pop()
        if node.name == "style":
            sheets += [k for k in node.kids if isinstance(k, str)]
        todo += [k for k in node.kids if isinstance(k, Node)]
    rules = style_rules(sheets)
    top = Node(root.name, root.attrs)
    said = _styled(root, [], rules)
    if hidden(root) or said.get("display") == "none":
        return top
    stack = [(root, top, said.get("visibility", "visible") not in ("hidden", "collapse"), 0)]
    above: list[Node] = []
    while stack:
        node, new, seen, depth = stack.pop()
        del above[depth:]
        above.append(node)
        closed, shown = node.name == "details" and "open" not in node.attrs, False
        for kid in node.kids:
            if isinstance(kid, str):
                if seen and not closed and node.name != "svg":
                    new.kids.append(kid)
                continue
            said = _styled(kid, above, rules) if rules or "style" in kid.attrs else {}
            if said.get("display") == "none" or said.get("content-visibility") == "hidden":
                continue
            button = kid.name == "input" and kid.attrs.get("type", "").lower() in ("submit", "button", "reset") and "hidden" not in kid.attrs
            if hidden(kid) and not button:
                continue
            if closed and (kid.name != "summary" or shown):
                continue
            shown = shown or closed
            kept = seen if "visibility" not in said else said["visibility"] not in ("hidden", "collapse")
            if kid.name in ("img", "input", "hr") and not kept:
                continue
            child = Node(kid.name, kid.attrs)
            if button:
                child = Node("span")
                child.kids.append(kid.attrs.get("value", ""))
                new.kids.append(child)
                continue
            if kid.name == "svg" and any(k for k in kid.kids):
                new.kids += [" ", child, " "]
                child.kids += [x for t in _svg_texts(kid) for x in (t, " ")] if kept else []
                continue
            new.kids.append(child)
            stack.append((kid, child, kept, depth + 1))
    return top


def _svg_texts(node: Node) -> list[str]:
    """Of a drawing what stands in its text elements."""
    found, todo = [], [(node, False)]
    while todo:
        k, inside = todo.pop()
        if isinstance(k, str):
            found += [k] if inside and k.strip() else []
        elif not hidden(k):
            todo += [(x, inside or k.name == "text") for x in reversed(k.kids)]
    return found


class _Lines:
    """Lines being laid out: words flow into the last one, blocks begin new ones."""

    def __init__(self, pre: bool = False):
        self.pre = pre
        self.lines: list[str] = []
        self.flow: list[str] = []
        self.gap = self.pending = False

    def words(self, s: str) -> None:
        if not s:
            return
        if self.pending or (s[0] in " \t\n\r\f" and self.flow):
            if self.flow and not self.flow[-1].endswith((" ", "\n")):
                self.flow.append(" ")
        body = _SPACE.sub(" ", s).strip(" ")
        if body:
            self.flow.append(body)
            self.pending = s[-1] in " \t\n\r\f"
        else:
            self.pending = bool(self.flow)

    def line(self) -> None:
        """Ends the line that words flow into."""
        if self.flow:
            if self.gap and self.lines:
                self.lines.append("")
            self.gap = False
            line = "".join(self.flow)
            self.lines.append(line.rstrip(" ") if self.pre else line.strip(" "))
        self.flow, self.pending = [], False

    def put(self, lines: list[str], gap: bool) -> None:
        self.line()
        if lines:
            if (gap or self.gap) and self.lines:
                self.lines.append("")
            self.lines += lines
            self.gap = gap

    def margin(self) -> None:
        self.line()
        self.gap = True


def _width(s: str) -> int:
    """Columns that a line takes: wide characters two, marks on others none."""
    if s.isascii():
        return len(s)
    return sum(0 if unicodedata.combining(c) else 2 if unicodedata.east_asian_width(c) in "WF" else 1 for c in s)


def _layout(node: Node, out: _Lines, pre: bool, depth: int) -> None:
    """Lays ``node``'s children out. Nesting is followed to any depth by an own stack."""
    stack: list = [(iter(node.kids), node, pre, None)]
    while stack:
        kids, at, pre, done = stack[-1]
        kid = next(kids, None)
        if kid is None:
            stack.pop()
            if done:
                done()
            continue
        if isinstance(kid, str):
            if pre:
                parts = kid.replace("\r\n", "\n").split("\n")
                for i, p in enumerate(parts):
                    if i:
                        _hard_line(out)
                    if p:
                        out.flow.append(p)
            else:
                out.words(kid)
            continue
        name = kid.name
        if name == "br":
            _hard_line(out)
        elif name == "hr":
            out.put(["---"], True)
        elif name == "img":
            out.words(kid.attrs.get("alt", ""))
        elif name == "wbr":
            continue
        elif name in ("ul", "ol", "menu", "dir"):
            out.put(_list(kid, depth), at.name != "li")
        elif name == "table":
            out.put(_table(kid, depth), True)
        elif name == "pre":
            inner = _Lines(pre=True)
            _layout(kid, inner, True, depth + 1)
            _hard_line(inner)
            lines = inner.lines
            while lines and not lines[0]:
                lines.pop(0)
            while lines and not lines[-1]:
                lines.pop()
            out.put(lines, True)
        elif name == "blockquote" and depth < 100:
            out.put(["> " + x if x else ">" for x in _block(kid, depth)], True)
        elif name == "dd" and depth < 100:
            out.put(["  " + x if x else x for x in _block(kid, depth)], False)
        elif name in BLOCK:
            (out.margin if name in MARGIN else out.line)()
            stack.append((iter(kid.kids), kid, pre, out.margin if name in MARGIN else out.line))
        else:
            stack.append((iter(kid.kids), kid, pre, None))


def _hard_line(out: _Lines) -> None:
    """A line break that may leave an empty line."""
    if out.flow:
        out.line()
    elif out.lines and not out.gap:
        out.lines.append("")


def _block(node: Node, depth: int) -> list[str]:
    out = _Lines()
    _layout(node, out, False, depth + 1)
    out.line()
    while out.lines and not out.lines[-1]:
        out.lines.pop()
    return out.lines


def _list(node: Node, depth: int) -> list[str]:
    if depth >= 100:
        return _block(Node("div", None), depth) if not node.kids else _plain(node)
    lines: list[str] = []
    try:
        number = int(node.attrs.get("start", "1"))
    except ValueError:
        number = 1
    for kid in node.kids:
        if isinstance(kid, str) and not kid.strip(" \t\n\r\f"):
            continue
        item = kid if isinstance(kid, Node) and kid.name == "li" else None
        if item is None:
            holder = Node("div")
            holder.kids.append(kid)
            inner, mark = _block(holder, depth), "  "
        else:
            inner = _block(item, depth)
            mark = f"{number}. " if node.name == "ol" else "- "
            number += 1
        if inner:
            lines.append(mark + inner[0])
            lines += [" " * len(mark) + x if x else "" for x in inner[1:]]
    return lines


def _rows(node: Node) -> tuple[list[list[Node]], list[Node]]:
    """Rows of cells of a table, not of tables within; and what else stands in it."""
    rows, other, todo = [], [], [k for k in node.kids]
    while todo:
        k = todo.pop(0)
        if isinstance(k, str):
            if k.strip(" \t\n\r\f"):
                other.append(k)
        elif k.name in ("col", "colgroup"):
            continue
        elif k.name == "tr":
            cells = [c for c in k.kids if isinstance(c, Node) and c.name in ("td", "th")]
            other += [c for c in k.kids if (isinstance(c, str) and c.strip(" \t\n\r\f")) or (isinstance(c, Node) and c.name not in ("td", "th"))]
            rows.append(cells)
        elif k.name in ("thead", "tbody", "tfoot"):
            todo[:0] = k.kids
        else:
            other.append(k)
    return rows, other


def _span(cell: Node, name: str) -> int:
    try:
        return min(1000, max(0 if name == "rowspan" else 1, int(cell.attrs.get(name, "1"))))
    except ValueError:
        return 1


def _table(node: Node, depth: int) -> list[str]:
    """Cells in columns. A cell across rows keeps its columns free in the rows below and its text stands at
    its first row, running on into them."""
    if depth >= 100:
        return _plain(node)
    rows, other = _rows(node)
    lines: list[str] = []
    for k in other:  # captions, and what browsers move before the table
        holder = Node("div")
        holder.kids.append(k)
        lines += _block(holder, depth)
    taken: dict[int, int] = {}  # column: rows below that a cell above still covers
    grid, widths = [], {}
    for r in rows:
        col, placed = 0, []
        for cell in r:
            while taken.get(col, 0):
                col += 1
            across, down = _span(cell, "colspan"), _span(cell, "rowspan")
            down = down or len(rows)  # zero: to the end
            text = _block(cell, depth)
            placed.append((col, across, text))
            if across == 1:
                widths[col] = max(widths.get(col, 0), max(map(_width, text), default=0))
            for c in range(col, col + across):
                taken[c] = max(taken.get(c, 0), down)
            col += across
        taken = {c: n - 1 for c, n in taken.items() if n > 1}
        grid.append(placed)
    for placed in grid:
        for i in range(max((len(text) for _, _, text in placed), default=0)):
            line, at = "", 0
            for col, across, text in placed:
                if col > at:  # columns that cells above cover
                    line += " " * sum(widths.get(c, 0) + 2 for c in range(at, col))
                room = sum(widths.get(c, 0) for c in range(col, col + across)) + 2 * (across - 1)
                cell = text[i] if i < len(text) else ""
                line += cell + " " * (max(0, room - _width(cell)) + 2)
                at = col + across
            lines.append(line.rstrip(" "))
    return lines


def _plain(node: Node) -> list[str]:
    """Text of a very deep part: a line per block, cell and item, without columns and indentation."""
    lines, flow, todo = [], [], [node]

    def end() -> None:
        line = _SPACE.sub(" ", "".join(flow)).strip()
        lines.extend([line] if line else [])
        flow.clear()

    while todo:
        k = todo.pop()
        if k is None:
            end()
        elif isinstance(k, str):
            flow.append(k)
        elif k.name in BLOCK or k.name == "br":
            end()
            todo.append(None)
            todo += reversed(k.kids)
        else:
            flow.append(k.attrs.get("alt", "") if k.name == "img" else "")
            todo += reversed(k.kids)
    end()
    return lines


def render(html: str | None) -> str:
    """The visible text of a page, laid out. Null or empty: empty."""
    return "\n".join(_block(visible(parse(html)), 0))


def title(html: str | None) -> str:
    """The text of the first title element, spaces folded; empty if there is none."""
    m = re.search(r"<title(?:\s[^>]*)?>(.*?)(?:</title|\Z)", html or "", re.S | re.I)
    return _SPACE.sub(" ", unescape(m[1])).strip() if m else ""


def extract(pages: DataFrame, html: str = "html", keep: list[str] | None = None) -> DataFrame:
    """``keep`` (all columns but ``html`` by default), title and text of every page. Null and empty
    pages have empty title and text; pages are read whole, of any length and nesting. Repeated rows give
    equal rows. Columns named title or text, in any case, are replaced. An empty table gives an empty result."""
    keep = [c for c in (pages.columns if keep is None else keep) if c.lower() not in (html.lower(), "title", "text")]
    part = pages.select(*(F.col(f"`{c}`") for c in keep), F.col(f"`{html}`").alias("__html"))
    schema = part.drop("__html").withColumn("title", F.lit("")).withColumn("text", F.lit("")).schema

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                some = batch.slice(at, 256)
                raw = [x.as_py() for x in some.column(some.num_columns - 1)]
                yield pa.RecordBatch.from_arrays([*some.columns[:-1], pa.array([title(x) for x in raw], pa.string()), pa.array([render(x) for x in raw], pa.string())], names=[*some.schema.names[:-1], "title", "text"])

    return part.mapInArrow(run, schema)
