"""Layout-aware page text: a tree with implied tags, visibility rules, block spacing, lists and aligned tables.

Null or empty pages give empty text. These give nothing: comments, declarations, head, title, scripts, styles,
templates, data lists, what only stands in for something else that is shown (noscript, iframe, canvas, audio, video),
descriptions and definitions in svg, annotations in math, closed details but for their summary, closed dialogs, and
elements that are not displayed, at any depth: by the hidden attribute, a style attribute or a rule of a style element
whose selector is a tag, class, id or a compound of them (rules within at-rules and other selectors are passed over).
Text that is not visible gives nothing either, but what is made visible again inside it does.
A select gives its chosen option (else its first enabled one), a list box all of them; text fields, formulas, labels
in drawings and the content of object are text. Lists, quotes and tables nested deeper than LAYOUTS are not indented or
aligned any further, nor are cells beyond COLUMNS columns; their text stays. Cells that span columns or rows keep
the cells beside and below them in their own columns. Block elements stand on lines of their own with a
blank line around paragraphs and headings; list items carry a bullet or their number; table cells are
padded to the width of their column. White space is collapsed outside pre. Broken markup never fails:
end tags without a start are passed over, open elements end with the page, and a tag that the page ends in is
dropped; time is linear in the page. Rows that repeat an id, or have none, get their text each; an empty table
gives no rows; other columns are not read.
"""

from __future__ import annotations

import bisect
import html as entities
import re
from collections import defaultdict

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bounded_batches, map_batches

#: Fixed: element classes of the public HTML standard.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
FIELDS = frozenset(("", "text", "search", "url", "tel", "email", "number", "submit", "reset", "button"))
HIDDEN = frozenset("head script style template noscript title iframe canvas audio video datalist".split())
FOREIGN_HIDDEN = frozenset("desc defs metadata symbol clippath mask marker pattern annotation annotation-xml".split())
#: These end an svg or math element that is still open.
BREAKS_OUT = frozenset("b big br code em embed i img nobr ruby s small span strong strike sub sup tt u var font".split())
APART = frozenset("text td th".split())
LAYOUTS = 512
COLUMNS = 1000
RAW = frozenset("script style textarea title iframe noscript xmp".split())
BLOCK = frozenset("address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol p pre section summary table ul tr caption thead tbody tfoot".split())
SPACED = frozenset("p h1 h2 h3 h4 h5 h6 ul ol dl table blockquote pre figure hr fieldset".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
TABLE_PARTS = frozenset("tr td th thead tbody tfoot caption colgroup col".split())
#: A start tag closes these open elements, up to the given stops.
CLOSES = {
    "li": ({"li"}, {"ul", "ol", "menu", "dir"}),
    "dt": ({"dt", "dd"}, {"dl"}),
    "dd": ({"dt", "dd"}, {"dl"}),
    "optgroup": ({"option", "optgroup"}, {"select"}),
    "option": ({"option"}, {"select", "datalist"}),
    "tr": ({"tr", "td", "th", "caption", "colgroup"}, {"table"}),
    "td": ({"td", "th"}, {"tr", "table"}),
    "th": ({"td", "th"}, {"tr", "table"}),
} | {t: ({"tr", "td", "th", "caption", "colgroup", "thead", "tbody", "tfoot"}, {"table"}) for t in ("thead", "tbody", "tfoot")}
CLOSE_P = (BLOCK - TABLE_PARTS) - {"body", "html", "summary", "legend", "dialog"}

NAME = re.compile(r"[^\s/>]+")
ATTRIBUTE = re.compile(r"[\s/]*([^\s/>][^\s/>=]*)(\s*=\s*)?")
GAP = re.compile(r"[\s/]*")
VALUE = re.compile(r"[^\s>]*")
SELECTOR = re.compile(r"([A-Za-z][\w-]*|\*)?((?:[.#][\w-]+)*)\Z")
DECLARED = re.compile(r"(?:^|;)\s*(display|visibility)\s*:\s*([\w-]+)\s*(!\s*important)?", re.I)


class Node:
    __slots__ = ("tag", "attributes", "children", "styles", "gone", "seen")

    def __init__(self, tag: str, attributes: dict[str, str] | None = None):
        self.tag, self.attributes, self.children = tag, attributes or {}, []
        self.gone, self.seen = None, None  # whether it is not displayed; whether its text is visible, if it says so


def tokens(page: str, at: int):
    """The markup at a place, if any: kind ("start", "end", "text", or "" for what gives nothing), name, attributes,
    whether it closes itself, and the place after it. Each character is passed over once."""
    size = len(page)
    if page[at] != "<":
        end = page.find("<", at)
        end = size if end < 0 else end
        return "text", page[at:end], {}, False, end
    if page.startswith("<!--", at):
        end = page.find("-->", at + 2)
        return "", "", {}, False, size if end < 0 else end + 3
    closing = page.startswith("</", at)
    after = page[at + 1 + closing : at + 2 + closing]
    if not (after.isascii() and after.isalpha()):
        if closing or after in ("!", "?"):
            end = page.find(">", at)
            return "", "", {}, False, size if end < 0 else end + 1
        return "text", "<", {}, False, at + 1
    name = NAME.match(page, at + 1 + closing)
    at, attributes, itself = name.end(), {}, False
    while True:
        gap = GAP.match(page, at)
        at = gap.end()
        if at >= size:
            return "", "", {}, False, size
        if page[at] == ">":
            return "end" if closing else "start", name[0].lower(), attributes, gap[0].endswith("/"), at + 1
        found = ATTRIBUTE.match(page, at)
        at, value = found.end(), ""
        if found[2] and at < size:
            if page[at] in "\"'":
                end = page.find(page[at], at + 1)
                if end < 0:
                    return "", "", {}, False, size
                value, at = page[at + 1 : end], end + 1
            else:
                bare = VALUE.match(page, at)
                value, at = bare[0], bare.end()
        attributes.setdefault(found[1].lower(), value)


class Styles:
    """What the style elements of a page say about display and visibility, by the last part that an element must have."""

    def __init__(self):
        self.by: dict[str, list[tuple]] = {}
        self.count = 0

    def read(self, css: str) -> None:
        css = "".join(part.partition("*/")[2] if i else part for i, part in enumerate(css.split("/*")))
        plain, depth, at = [], 0, 0  # without at-rules
        for m in re.finditer(r"@[^;{}@]*[;{]?|[{}]", css):
            if not depth and m[0][0] == "@":
                plain.append(css[at : m.start()])
                depth, at = int(m[0][-1] == "{"), m.end()
            elif depth:
                depth += (m[0][-1] == "{") - (m[0] == "}")
                at = m.end() if not depth else at
        plain.append(css[at:] if not depth else "")
        for rule in "".join(plain).split("}"):
            selectors, _, body = rule.partition("{")
            said = DECLARED.findall(body)
            if not said:
                continue
            for selector in selectors.split(","):
                found = SELECTOR.match(selector.strip())
                if not found or not found[0]:
                    continue
                parts = re.findall(r"[.#][\w-]+", found[2])
                tag = (found[1] or "*").lower()
                weight = (sum(p[0] == "#" for p in parts), sum(p[0] == "." for p in parts), int(tag != "*"))
                self.count += 1
                self.by.setdefault(parts[-1] if parts else tag, []).append((weight, self.count, tag, parts, said))

    def of(self, node: Node) -> dict[str, str]:
        """display and visibility of an element, where anything says so."""
        a, said = node.attributes, []
        if self.by:
            own = {"." + c for c in a.get("class", "").split()} | ({"#" + a["id"]} if a.get("id") else set())
            for key in (node.tag, "*", *own):
                for weight, at, tag, parts, declared in self.by.get(key, ()):
                    if tag in ("*", node.tag) and own.issuperset(parts):
                        said += [((bool(loud), 0, weight, at), k.lower(), v.lower()) for k, v, loud in declared]
        if "style" in a:
            said += [((bool(loud), 1, (), i), k.lower(), v.lower()) for i, (k, v, loud) in enumerate(DECLARED.findall(a["style"]))]
        return {k: v for _, k, v in sorted(said, key=lambda x: x[0])}


def parse(page: str) -> Node:
    root = Node("#root")
    root.styles = styles = Styles()
    stack = [root]
    places: dict[str, list[int]] = defaultdict(list)  # depths of the open elements by tag

    def deepest(tags) -> int:
        return max((places[t][-1] for t in tags if places[t]), default=0)

    def push(node: Node) -> None:
        places[node.tag].append(len(stack))
        stack.append(node)

    def close(tags, stops) -> bool:
        depth = deepest(tags)
        if depth <= deepest(stops):
            return False
        while len(stack) > depth:
            places[stack.pop().tag].pop()
        return True

    at, size = 0, len(page)
    while at < size:
        kind, tag, attributes, itself, at = tokens(page, at)
        if kind == "text":
            stack[-1].children.append(entities.unescape(tag))
            continue
        if not kind:
            continue
        if kind == "end":
            if tag == "p" and not places["p"]:
                stack[-1].children.append(Node("p"))
            elif tag == "br":
                stack[-1].children.append(Node("br"))
            else:
                close({tag}, {"table"} if tag not in TABLE_PARTS and tag != "table" and tag not in ("body", "html") else {"table"} - {tag} if tag in TABLE_PARTS else ())
            continue
        if tag in ("html", "body") and places[tag]:
            continue
        foreign = deepest(("svg", "math")) > deepest(("foreignobject",))
        if foreign and (tag in BLOCK or tag in BREAKS_OUT):
            while close({"svg", "math"}, {"foreignobject"}):
                pass
            foreign = False
        if tag == "body":
            close({"head"}, ())
        elif stack[-1].tag == "head" and tag not in HIDDEN and tag not in VOID:
            close({"head"}, ())
        if tag in CLOSES:
            tags, stops = CLOSES[tag]
            while close(tags, stops):
                pass
        if tag in CLOSE_P:
            close({"p"}, {"table", "td", "th", "button", "caption"})
        if tag in ("td", "th") and stack[-1].tag not in ("tr",):
            row = Node("tr")
            stack[-1].children.append(row)
            push(row)
        if foreign and tag in FOREIGN_HIDDEN:
            attributes["hidden"] = ""
        node = Node(tag, attributes)
        stack[-1].children.append(node)
        if tag in VOID or (itself and (foreign or tag in ("svg", "math"))):
            continue
        if tag in RAW:
            end = re.compile(rf"</{re.escape(tag)}\b[^>]*>?", re.I).search(page, at)
            raw = page[at : end.start() if end else size]
            if tag == "style":
                styles.read(raw)
            node.children.append(entities.unescape(raw).removeprefix("\n") if tag == "textarea" else raw)
            at = end.end() if end else size
            continue
        push(node)
    return root


def mark(root: Node) -> None:
    """Settles which elements are not displayed, and which say whether their text is visible."""
    left = [root]
    while left:
        parent = left.pop()
        closed = parent.tag == "details" and "open" not in parent.attributes
        for node in parent.children:
            if isinstance(node, str):
                continue
            said = root.styles.of(node) if node.attributes or root.styles.by else {}
            display = said.get("display") or ("none" if "hidden" in node.attributes or node.tag == "dialog" and "open" not in node.attributes else "")
            node.gone = node.tag in HIDDEN or display == "none" or closed and node.tag != "summary"
            node.seen = {"visible": True, "hidden": False, "collapse": False}.get(said.get("visibility", ""))
            if not node.gone:
                left.append(node)
        if closed:
            parent.children = [c for c in parent.children if not isinstance(c, str)]


def hidden(node: Node) -> bool:
    return bool(node.gone)


class Layout:
    """Lines of text; inline pieces gather until a block ends them."""

    def __init__(self):
        self.lines: list[str] = []
        self.inline: list[str] = []
        self.blank = False
        self.seen = True

    def text(self, piece: str, keep: bool) -> None:
        if not self.seen:
            return
        if keep:
            first, *rest = piece.split("\n")
            self.inline.append(first)
            for line in rest:
                self.end(True)
                self.inline.append(line)
        else:
            self.inline.append(piece)

    def end(self, keep: bool = False) -> None:
        line = "".join(self.inline)
        self.inline = []
        line = line.rstrip() if keep else re.sub(r"\s+", " ", line).strip()
        if line or keep and self.lines:
            if self.blank and self.lines:
                self.lines.append("")
            self.blank = False
            self.lines.append(line)

    def gap(self) -> None:
        self.end()
        self.blank = True

    def result(self) -> list[str]:
        self.end()
        while self.lines and not self.lines[-1]:
            self.lines.pop()
        return self.lines


def cells_of(table: Node):
    """Rows of a table as lists of cells, and its caption, in order; nested sections are opened."""
    for child in table.children:
        if isinstance(child, str):
            if child.strip():
                yield [child]
        elif hidden(child):
            continue
        elif child.tag == "tr":
            yield [c for c in child.children if (isinstance(c, str) and c.strip()) or (isinstance(c, Node) and not hidden(c))]
        elif child.tag in ("thead", "tbody", "tfoot"):
            yield from cells_of(child)
        elif child.tag not in ("colgroup", "col"):
            yield [child]


def shown_options(select: Node) -> list[Node]:
    """The options that a select shows: all in a list box, else the last chosen or the first enabled one."""
    options, left = [], [(select, False)]
    while left:
        node, off = left.pop()
        off = off or node is not select and "disabled" in node.attributes
        if node.tag == "option":
            options.append((node, off))
        else:
            left.extend((c, off) for c in reversed(node.children) if isinstance(c, Node) and not hidden(c))
    if "multiple" in select.attributes or re.fullmatch(r"\s*0*([2-9]|[1-9][0-9]+)\s*", select.attributes.get("size", "")):
        return [o for o, _ in options]
    return [o for o, _ in options if "selected" in o.attributes][-1:] or [o for o, off in options if not off][:1]


def run(task):
    """What a task returns; the tasks it yields run before it goes on, on a list instead of Python's call stack."""
    waiting, value = [task], None
    while waiting:
        try:
            waiting.append(waiting[-1].send(value))
            value = None
        except StopIteration as end:
            waiting.pop()
            value = end.value
    return value


def render(node: Node, out: Layout, keep: bool = False, depth: int = 0):
    """A task for run(); depth counts the layouts around it."""
    before = out.seen
    for child in node.children:
        if not isinstance(child, str) and child.seen is not None:
            break
    else:
        return (yield render_all(node, node.children, out, keep, depth, [first_number(node)]))
    number = [first_number(node)]
    for child in node.children:
        if not isinstance(child, str) and child.seen is not None:
            out.seen = child.seen
        yield render_all(node, [child], out, keep, depth, number)
        out.seen = before
    return None


def first_number(node: Node) -> int:
    start = node.attributes.get("start", "1").strip() if node.tag == "ol" else "1"
    return int(start) if re.fullmatch(r"-?[0-9]{1,9}", start) else 1


def render_all(node: Node, children: list, out: Layout, keep: bool, depth: int, number: list[int]):
    """Some children of a node, one after the other; number holds that of the next list item."""
    for child in children:
        if isinstance(child, str):
            out.text(child, keep)
        elif hidden(child):
            continue
        elif child.tag == "br":
            out.end(keep)
        elif child.tag == "hr":
            out.gap()
        elif child.tag == "img":
            if child.attributes.get("alt"):
                out.text(entities.unescape(child.attributes["alt"]), False)
        elif child.tag == "input":
            if child.attributes.get("value") and child.attributes.get("type", "").strip().lower() in FIELDS:
                out.text(f" {entities.unescape(child.attributes['value'])} ", False)
        elif child.tag == "select":
            for option in shown_options(child):
                out.text(" ", False)
                if option.attributes.get("label"):
                    out.text(entities.unescape(option.attributes["label"]), False)
                else:
                    yield render(option, out, False, depth)
                out.text(" ", False)
        elif child.tag == "textarea":
            out.end(keep)
            yield render(child, out, True, depth)
            out.end(True)
        elif child.tag == "table" and depth < LAYOUTS:
            out.gap()
            seen = out.seen
            lines = yield table_lines(child, depth, seen)
            out.seen = True
            for line in lines:
                out.text(line, True)
                out.end(True)
            out.seen = seen
            out.gap()
        elif child.tag == "li" and depth < LAYOUTS:
            out.end()
            sign = f"{number[0]}. " if node.tag == "ol" else "- "
            number[0] += 1
            inner = Layout()
            inner.seen, out.seen = out.seen, True
            yield render(child, inner, keep, depth + 1)
            for i, line in enumerate(inner.result()):
                out.text((sign if i == 0 else " " * len(sign)) + line, True)
                out.end(True)
            out.seen = inner.seen
        elif child.tag in ("blockquote", "dd") and depth < LAYOUTS:
            (out.gap if child.tag == "blockquote" else out.end)()
            inner = Layout()
            inner.seen, out.seen = out.seen, True
            yield render(child, inner, keep, depth + 1)
            for line in inner.result():
                out.text("  " + line if line else "", True)
                out.end(True)
            out.seen = inner.seen
            (out.gap if child.tag == "blockquote" else out.end)()
        elif child.tag in BLOCK:
            nested = child.tag in ("ul", "ol") and node.tag == "li"
            (out.gap if child.tag in SPACED and not nested else out.end)()
            yield render(child, out, keep or child.tag == "pre", depth)
            out.end(keep or child.tag == "pre")
            if child.tag in SPACED and not nested:
                out.gap()
        else:
            apart = child.tag in APART
            if apart:
                out.text(" ", False)
            yield render(child, out, keep, depth)
            if apart:
                out.text(" ", False)


def span(cell, name: str) -> int:
    value = "" if isinstance(cell, str) else cell.attributes.get(name, "").strip()
    return min(COLUMNS, max(1, int(value))) if re.fullmatch("[0-9]{1,9}", value) else 1


def table_lines(table: Node, depth: int, seen: bool = True):
    """A task for run(): the lines of a table. Each cell stands in its column: the first that no cell before it or
    above it reaches into."""
    rows, over = [], []  # cells as (column, end, lines); those above that reach down, as [column, end, rows left]
    for row in cells_of(table):
        placed, at = [], 0
        for cell in row:
            inner = Layout()
            inner.seen = seen if isinstance(cell, str) or cell.seen is None else cell.seen
            holder = Node("#cell")
            holder.children = [cell] if isinstance(cell, str) else cell.children
            yield render(holder, inner, False, depth + 1)
            for a, b, _ in over:
                if a <= at < b:
                    at = b
            end = max(at + 1, min(COLUMNS, at + span(cell, "colspan")))
            placed.append((at, end, [x for x in inner.result() if x] or [""], span(cell, "rowspan")))
            at = end
        if placed:
            over = [[a, b, n - 1] for a, b, n in over if n > 1] + [[a, b, n - 1] for a, b, _, n in placed if n > 1 and b <= COLUMNS]
            over.sort()
            rows.append([x[:3] for x in placed])
    # Columns in which no cell starts take no room.
    starts = sorted({a for r in rows for a, _, _ in r})
    place = {a: i for i, a in enumerate(starts)}
    rows = [[(place[a], bisect.bisect_left(starts, b), lines) for a, b, lines in r] for r in rows]
    widths = [0] * len(starts)
    for r in rows:
        for a, b, lines in r:
            if len(r) > 1 and b - a == 1:
                widths[a] = max(widths[a], *map(len, lines))
    out = []
    for r in rows:
        for i in range(max(len(lines) for *_, lines in r)):
            parts, at = [], 0
            for a, b, lines in r:
                parts += ["".ljust(widths[c]) for c in range(at, a)]
                room = sum(widths[a:b]) + 3 * (b - a - 1) if len(r) > 1 else 0
                parts.append((lines[i] if i < len(lines) else "").ljust(room))
                at = b
            out.append(" | ".join(parts).rstrip())
    return [x for x in out if x.strip(" |")]


def page_text(page: str | None) -> str:
    if not page:
        return ""
    out, root = Layout(), parse(page)
    mark(root)
    run(render(root, out))
    return "\n".join(out.result())


def extract_text(pages: DataFrame, id_col: str = "page_id", html_col: str = "html") -> DataFrame:
    """One row per page: its id, the visible text and its length in code points."""
    bounded_batches(pages.sparkSession)

    def texts_of(batch):
        texts = [page_text(p) for p in batch.column(1).to_pylist()]
        return {id_col: batch.column(0), "text": texts, "n_chars": [len(t) for t in texts]}

    rows = pages.select(F.col(id_col).cast("long").alias(id_col), F.col(html_col).alias("html"))
    return map_batches(rows, texts_of, f"{id_col} long, text string, n_chars long")
