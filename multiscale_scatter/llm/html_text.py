"""Layout-aware text of web pages: a tree with implied tags, visibility rules, and a text rendering.

Tree: start tags close what they imply (a paragraph ends before a block, a list item before the next, a
cell before the next cell or row, and so on), an end tag closes the nearest element of its name within its
table or page, what is still open at the end is closed there.  Raw elements (scripts, styles) and
comments hold no markup.  Trees of any depth are built and rendered without recursion.

Visibility: head, scripts, styles, templates and the like are not shown; neither is what has display:none or
visibility:hidden or collapse after the cascade (importance, own style, specificity, order), the attribute
hidden or type="hidden" without a display of its own, a closed dialog, nor a closed details but for its
summary.  A child can be visible again under a hidden visibility, not under display:none.  Style sheets of the
page count where their media fit a screen of SCREEN pixels.  Selectors are compounds of tag, class, id and
attributes, joined by descendant and child combinators; rules with other selectors (siblings, pseudo-classes)
are passed over.  What hides text by color, size, clipping or position is not looked at.

Rendering: runs of white space are one space, but for pre and textarea; blocks stand on lines of their
own, paragraphs and headings between blank lines; list items have a bullet or their number and are
indented by depth, up to MAX_INDENT levels; a table's cells are padded to its columns' widths, below a cell
that spans rows its column stays empty, head rows come first and foot rows last; br ends a line, hr is a rule.
A display that makes an element a block, an inline element, a list item or a part of a table has that effect.

Defined cases: null html gives an empty text; an empty page too; repeated rows give a row each; null ids
are kept; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import bisect
import html as entities
import re
from collections.abc import Generator, Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame

# Element names by how they behave.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style xmp iframe noembed noframes textarea title".split())
UNSEEN = frozenset("head script style template noscript title meta link base param iframe noembed noframes datalist area source track col colgroup defs desc metadata annotation annotation-xml".split())
BLOCK = frozenset(
    "address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol optgroup option p pre section summary table ul".split()
)
SPACED = frozenset("p h1 h2 h3 h4 h5 h6 blockquote pre dl ol ul menu table figure".split())
CLOSES_P = BLOCK - {"html", "body", "li", "dd", "dt", "option", "optgroup", "legend", "summary"} | {"hr"}
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
#: What a start tag closes, and the element in which the search for it ends.
IMPLIED = {
    "li": ({"li"}, {"ul", "ol", "menu", "dir"}),
    "dt": ({"dt", "dd"}, {"dl"}),
    "dd": ({"dt", "dd"}, {"dl"}),
    "option": ({"option"}, {"select", "datalist", "optgroup"}),
    "optgroup": ({"option", "optgroup"}, {"select"}),
    "tr": ({"td", "th", "tr", "caption", "colgroup"}, {"table"}),
    "td": ({"td", "th"}, {"tr", "table"}),
    "th": ({"td", "th"}, {"tr", "table"}),
    "thead": ({"td", "th", "tr", "thead", "tbody", "tfoot", "caption", "colgroup"}, {"table"}),
    "tbody": ({"td", "th", "tr", "thead", "tbody", "tfoot", "caption", "colgroup"}, {"table"}),
    "tfoot": ({"td", "th", "tr", "thead", "tbody", "tfoot", "caption", "colgroup"}, {"table"}),
    "body": ({"head"}, set()),
}
#: Lists and quotations nested deeper are not indented further.
MAX_INDENT = 32
#: Width and height, in pixels, of the screen that media conditions are held against.
SCREEN = (1280, 800)
SCOPES = frozenset("table td th caption html template".split())

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|</([a-zA-Z][^\s/>]*)[^>]*(?:>|\Z)|<([a-zA-Z][^\s/>]*)((?:\"[^\"]*\"|'[^']*'|[^>\"'])*)(?:>|\Z)", re.S)
_ATTRIBUTE = re.compile(r"([^\s=/>\"']+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?", re.S)
_SPACES = re.compile(r"[ \t\n\r\f]+")
_CSS = re.compile(r"/\*.*?(?:\*/|\Z)|\"(?:\\.|[^\"\\])*\"?|'(?:\\.|[^'\\])*'?|[{};]", re.S)
_COMPOUND = re.compile(r"([\w-]+|\*)?((?:[.#][\w-]+|\[\s*[\w-]+\s*(?:[~^$*|]?=\s*(?:\"[^\"]*\"|'[^']*'|[^\]\s]+)\s*)?\])*)")
_TEST = re.compile(r"([.#])([\w-]+)|\[\s*([\w-]+)\s*(?:([~^$*|]?)=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\]\s]+))\s*)?\]")
_DECLARED = re.compile(r"(?:^|;)\s*(display|visibility)\s*:\s*([\w-]+)([^;]*)", re.I)
_FEATURE = re.compile(r"\(\s*([\w-]+)\s*(?::\s*([^)]*?)\s*)?\)")
# What a display makes of an element.
_AS = {
    **dict.fromkeys("block flex grid flow-root".split(), "div"),
    **dict.fromkeys("inline inline-block inline-flex inline-grid contents".split(), "span"),
    "table": "table", "inline-table": "table", "table-row": "tr", "table-cell": "td", "table-caption": "caption", "list-item": "li",
    "table-row-group": "tbody", "table-header-group": "thead", "table-footer-group": "tfoot",
}
_PARTS = frozenset("caption tbody thead tfoot tr td th".split())


class Node:
    __slots__ = ("tag", "attributes", "children")

    def __init__(self, tag: str, attributes: dict[str, str]):
        self.tag, self.attributes, self.children = tag, attributes, []


def _attributes(text: str) -> dict[str, str]:
    out: dict[str, str] = {}
    for m in _ATTRIBUTE.finditer(text):
        value = m[2] if m[2] is not None else m[3] if m[3] is not None else m[4]
        out.setdefault(m[1].lower(), entities.unescape(value) if value and "&" in value else value or "")
    return out


def parse(page: str) -> tuple[Node, list[str]]:
    """(root, style sheets that a screen uses)."""
    root = Node("#root", {})
    stack, sheets, at = [root], [], 0
    places: dict[str, list[int]] = {}  # where in the stack elements of a name are

    def nearest(names: set | frozenset) -> int:
        return max((places[n][-1] for n in names if places.get(n)), default=0)

    def cut(k: int) -> None:
        while len(stack) > k:
            places[stack.pop().tag].pop()

    def close(names: set | frozenset, stop: set | frozenset) -> None:
        # an element that is implied closed may lie in another one of the kind
        while (k := nearest(names)) and k > nearest(stop):
            cut(k)

    while at < len(page):
        m = _TOKEN.search(page, at)
        until = m.start() if m else len(page)
        if until > at:
            text = page[at:until]
            stack[-1].children.append(entities.unescape(text) if "&" in text else text)
        if not m:
            break
        at = m.end()
        if m[2]:
            tag = m[2].lower()
            if tag in IMPLIED:
                close(*IMPLIED[tag])
            if tag in CLOSES_P:
                close({"p"}, SCOPES)
            if tag in HEADINGS and stack[-1].tag in HEADINGS:
                cut(len(stack) - 1)
            node = Node(tag, _attributes(m[3]) if m[3] and not m[3].isspace() else {})
            stack[-1].children.append(node)
            if tag in VOID:
                continue
            if tag in RAW:
                end = re.compile(rf"</{tag}(?=[\s/>])[^>]*>", re.I).search(page, at)
                raw = page[at : end.start() if end else len(page)]
                if tag == "style" and fits_screen(node.attributes.get("media", "")):
                    sheets.append(raw)
                node.children.append(entities.unescape(raw) if tag in ("textarea", "title") else raw)
                at = end.end() if end else len(page)
            elif not m[3].endswith("/") or tag in BLOCK:
                places.setdefault(tag, []).append(len(stack))
                stack.append(node)
        elif m[1]:
            tag = m[1].lower()
            if tag == "br":
                stack[-1].children.append(Node("br", {}))
                continue
            stop = set() if tag in ("table", "body", "html") else {"table"} if tag in _PARTS else {"td", "th", "caption"}
            if (k := nearest({tag})) and k > nearest(stop - {tag}):
                cut(k)
        elif m[0].startswith("<![CDATA["):
            stack[-1].children.append(m[0][9:].removesuffix("]]>"))
    return root, sheets


def _feature(name: str, value: str) -> bool:
    """Whether a screen of SCREEN pixels has a media feature."""
    side = next((k for k, n in enumerate(("width", "height")) if name.removeprefix("min-").removeprefix("max-") in (n, "device-" + n)), None)
    if side is not None and (m := re.fullmatch(r"([\d.]+)(px|em|rem|)", value)):
        size = float(m[1]) * (16 if "em" in m[2] else 1)
        return SCREEN[side] >= size if name.startswith("min-") else SCREEN[side] <= size if name.startswith("max-") else SCREEN[side] == size
    return (name, value) in {("orientation", "landscape"), ("hover", "hover"), ("any-hover", "hover"), ("pointer", "fine"), ("prefers-color-scheme", "light"), ("color", "")}


def fits_screen(media: str) -> bool:
    """Whether a list of media queries holds for the screen; an empty one does."""
    for query in media.lower().split(","):
        m = re.match(r"\s*(not\b|only\b)?\s*([\w-]+)?", query)
        fits = (m[2] or "all") in ("all", "screen", "and") and all(_feature(n, v) for n, v in _FEATURE.findall(query))
        if fits != (m[1] == "not"):
            return True
    return False


@dataclass
class Rule:
    """compounds: (tag or "", tests) from the left; joins[i]: what stands before compound i; declared: property to (value, important)."""

    number: int
    compounds: list[tuple[str, list[tuple]]]
    joins: list[str]
    declared: dict[str, tuple[str, bool]]

    @property
    def specificity(self) -> tuple[int, int, int]:
        tests = [t for _, many in self.compounds for t in many]
        ids = sum(t[0] == "#" for t in tests)
        return ids, len(tests) - ids, sum(tag != "" for tag, _ in self.compounds)


def _declared(text: str) -> dict[str, tuple[str, bool]]:
    out: dict[str, tuple[str, bool]] = {}
    for name, value, rest in _DECLARED.findall(text):
        new = (value.lower(), "!important" in rest.replace(" ", "").lower())
        if new[1] or not out.get(name.lower(), ("", False))[1]:
            out[name.lower()] = new
    return out


def _selector(text: str) -> tuple[list, list] | None:
    """(compounds, joins), or nothing for a selector that is passed over."""
    compounds, joins, join = [], [], ""
    for word in re.sub(r"\s*>\s*", " > ", text.strip()).split():
        if word == ">":
            join = ">"
            continue
        m = _COMPOUND.fullmatch(word)
        if not m:
            return None
        tests = [(t[1], t[2]) if t[1] else ("[" + (t[4] or "="), t[3].lower(), next((v for v in t.groups()[4:] if v is not None), None)) for t in _TEST.finditer(m[2])]
        compounds.append(("" if m[1] in (None, "*") else m[1].lower(), tests))
        joins.append(join)
        join = " "
    return (compounds, joins) if compounds and joins[0] == "" and join == " " else None


def sheet_rules(sheets: list[str]) -> list[Rule]:
    """Rules about display and visibility that hold for the screen, in order."""
    out: list[Rule] = []
    for sheet in sheets:
        if "display" not in sheet.lower() and "visibility" not in sheet.lower():
            continue
        sheet = re.sub(r"/\*.*?(?:\*/|\Z)", " ", sheet, flags=re.S)
        holds = [True]  # of each block that is open, whether its rules count
        begin, owner = 0, None
        for m in _CSS.finditer(sheet):
            if m[0] == "{":
                before = sheet[begin : m.start()].strip()
                name = before[1:].split(None, 1)[0].lower() if before.startswith("@") and before[1:].strip() else ""
                if before.startswith("@"):
                    group = fits_screen(before[6:]) if name == "media" else name in ("layer", "scope") or (name == "supports" and " not " not in before[9:14])
                    holds.append(holds[-1] and group)
                    owner = None
                else:
                    holds.append(False)  # rules nested in a rule are passed over
                    owner = before if holds[-2] else None
                begin = m.end()
            elif m[0] == "}":
                if owner is not None:
                    declared = _declared(sheet[begin : m.start()])
                    for selector in owner.split(",") if declared else ():
                        if found := _selector(selector):
                            out.append(Rule(len(out), *found, declared))
                    owner = None
                if len(holds) > 1:
                    holds.pop()
                begin = m.end()
            elif m[0] == ";" and owner is None:
                begin = m.end()
    return out


def _passes(node: Node, tag: str, tests: list[tuple]) -> bool:
    if tag and node.tag != tag:
        return False
    a = node.attributes
    for kind, name, *value in tests:
        if kind == ".":
            ok = name in a.get("class", "").split()
        elif kind == "#":
            ok = a.get("id") == name
        elif name not in a:
            ok = False
        elif value[0] is None:
            ok = True
        else:
            has, want = a[name], value[0]
            ok = {
                "[=": has == want, "[~": want in has.split(), "[^": bool(want) and has.startswith(want), "[$": bool(want) and has.endswith(want),
                "[*": bool(want) and want in has, "[|": has == want or has.startswith(want + "-"),
            }[kind]
        if not ok:
            return False
    return True


@dataclass(frozen=True)
class Context:
    """shown: visibility that children inherit; above, at: beginnings of rules (number, compound) that some element above, or the parent, fits."""

    shown: bool = True
    above: frozenset = frozenset()
    at: frozenset = frozenset()


class Styles:
    def __init__(self, rules: list[Rule]):
        self.parts: dict[str, list[tuple[Rule, int]]] = {}
        for rule in rules:
            for i, (tag, tests) in enumerate(rule.compounds):
                key = next((k + n for kind in "#." for k, n, *_ in tests if k == kind), tag or "*")
                self.parts.setdefault(key, []).append((rule, i))

    def look(self, node: Node, around: Context) -> tuple[str, Context] | None:
        """(what the element is laid out as, the context of its children); nothing for one that isn't shown."""
        if node.tag in UNSEEN:
            return None
        a = node.attributes
        best: dict[str, tuple[tuple, str]] = {}
        here = []

        def declare(declared: dict, rank: tuple) -> None:
            for name, (value, important) in declared.items():
                if name not in best or best[name][0] <= (important, *rank):
                    best[name] = ((important, *rank), value)

        if self.parts:
            keys = [node.tag, "*", *("." + c for c in a.get("class", "").split())] + (["#" + a["id"]] if "id" in a else [])
            for key in keys:
                for rule, i in self.parts.get(key, ()):
                    before = (rule.number, i - 1)
                    if (i == 0 or before in (around.above if rule.joins[i] == " " else around.at)) and _passes(node, *rule.compounds[i]):
                        if i == len(rule.compounds) - 1:
                            declare(rule.declared, (False, *rule.specificity, rule.number))
                        else:
                            here.append((rule.number, i))
        if "style" in a:
            declare(_declared(a["style"]), (True,))
        display = best["display"][1] if "display" in best else ""
        if display == "none":
            return None
        hidden = "hidden" in a or (node.tag == "dialog" and "open" not in a)
        if (hidden and display not in _AS) or (node.tag == "input" and a.get("type", "").lower() == "hidden"):
            return None
        see = {"hidden": False, "collapse": False, "visible": True, "initial": True}.get(best["visibility"][1] if "visibility" in best else "", around.shown)
        kind = node.tag
        if display in _AS:
            new = _AS[display]
            changes = kind in ("li", "table") or kind in _PARTS or kind not in BLOCK if new == "div" else kind in BLOCK or kind in _PARTS if new == "span" else True
            kind = new if changes and kind not in VOID and kind not in ("pre", "textarea") else kind
        if see == around.shown and not here and not around.at:
            return kind, around
        at = frozenset(here)
        return kind, Context(see, around.above | at if at else around.above, at)


@dataclass
class _Lines:
    """The lines of a block's content; an empty string is a blank line."""

    out: list[str] = field(default_factory=list)
    run: list[str] = field(default_factory=list)

    def flush(self, force: bool = False) -> None:
        text = _SPACES.sub(" ", "".join(self.run)).strip(" ")
        self.run.clear()
        if text or force:
            self.out.append(text)

    def gap(self) -> None:
        self.flush()
        if self.out and self.out[-1] != "":
            self.out.append("")

    def whole(self) -> list[str]:
        self.flush()
        return _trim(self.out)


#: A step of the rendering: yields the steps that it waits for.
Step = Generator["Step", None, None]


def _walk(step: Step) -> None:
    """Runs a step and all that it waits for, with a stack of its own."""
    stack = [step]
    while stack:
        inner = next(stack[-1], None)
        if inner is None:
            stack.pop()
        else:
            stack.append(inner)


def _whole_number(text: str, least: int, most: int) -> int | None:
    return min(max(int(text), least), most) if re.fullmatch(r"-?[0-9]{1,9}", text) else None


class _Rendering:
    def __init__(self, rules: list[Rule]):
        self.styles = Styles(rules)

    def fill(self, node: Node, around: Context, to: _Lines, depth: int = 0) -> Step:
        """Lays the children of node out into `to`."""
        number = None
        closed = node.tag == "details" and "open" not in node.attributes
        for child in node.children:
            if isinstance(child, str):
                if around.shown and not closed:
                    to.run.append(child)
                continue
            if closed and child.tag != "summary":
                continue
            if (look := self.styles.look(child, around)) is None:
                continue
            kind, inside = look
            see = inside.shown
            if kind == "br":
                to.flush(force=True)
            elif kind == "hr":
                to.gap()
                if see:
                    to.out.append("---")
                to.gap()
            elif kind == "wbr":
                pass
            elif kind == "img":
                if see and child.attributes.get("alt", "").strip():
                    to.run.append(child.attributes["alt"])
            elif kind == "input":
                if see and child.attributes.get("type", "text").lower() in ("text", "submit", "button", "reset", "search"):
                    to.run.append(" " + child.attributes.get("value", "") + " ")
            elif kind in ("pre", "textarea"):
                to.gap()
                parts: list[str] = []
                yield self.raw(child, inside, parts)
                if text := "".join(parts).strip("\n"):
                    to.out.extend(text.split("\n"))
                to.gap()
            elif kind == "table":
                to.gap()
                yield self.table(child, inside, to, depth)
                to.gap()
            elif kind == "li":
                to.flush()
                ordered = node.tag == "ol"
                if ordered:
                    own, begin = (_whole_number(n.attributes.get(k, ""), -(10**9), 10**9) for n, k in ((child, "value"), (node, "start")))
                    number = own if own is not None else number + 1 if number is not None else begin if begin is not None else 1
                if depth >= MAX_INDENT:
                    yield self.fill(child, inside, to, depth)
                    to.flush()
                    continue
                mark = f"{number}. " if ordered else "- "
                item = _Lines()
                yield self.fill(child, inside, item, depth + 1)
                if lines := item.whole():
                    to.out.append(mark + lines[0])
                    to.out.extend((" " * len(mark) + x) if x else x for x in lines[1:])
            elif kind in ("ul", "ol", "menu", "dir") and node.tag == "li":
                to.flush()
                yield self.fill(child, inside, to, depth)
                to.flush()
            elif kind in ("dd", "blockquote") and depth < MAX_INDENT:
                end = to.gap if kind == "blockquote" else to.flush
                end()
                quoted = _Lines()
                yield self.fill(child, inside, quoted, depth + 1)
                to.out.extend(("  " + x) if x else x for x in quoted.whole())
                end()
            elif kind in SPACED:
                to.gap()
                yield self.fill(child, inside, to, depth)
                to.gap()
            elif kind in BLOCK or kind in _PARTS:
                to.flush()
                yield self.fill(child, inside, to, depth)
                to.flush()
            elif kind == "q":
                quote = ['"'] if see else []
                to.run.extend(quote)
                yield self.fill(child, inside, to, depth)
                to.run.extend(quote)
            else:
                yield self.fill(child, inside, to, depth)

    def raw(self, node: Node, around: Context, to: list[str]) -> Step:
        for child in node.children:
            if isinstance(child, str):
                if around.shown:
                    to.append(child)
            elif child.tag == "br":
                to.append("\n")
            elif (look := self.styles.look(child, around)) is not None:
                yield self.raw(child, look[1], to)

    def table(self, node: Node, around: Context, to: _Lines, depth: int) -> Step:
        grid = _Grid()
        yield self.rows(node, around, grid, "tbody", depth)
        to.out.extend([*grid.caption, *grid.loose, *grid.drawn()])

    def rows(self, node: Node, around: Context, grid: _Grid, section: str, depth: int) -> Step:
        """Puts what node, a part of a table, holds into the grid."""
        for child in node.children:
            if isinstance(child, str):
                if around.shown and child.strip():
                    grid.loose.append(_SPACES.sub(" ", child).strip())
                continue
            if (look := self.styles.look(child, around)) is None:
                continue
            kind, inside = look
            if kind in ("td", "th", "caption"):
                cell = _Lines()
                yield self.fill(child, inside, cell, depth)
                if kind == "caption":
                    grid.caption.extend(cell.whole())
                else:
                    if not grid.in_row:
                        grid.begin_row(section)
                    across, down = (_whole_number(child.attributes.get(k, ""), 0, most) for k, most in (("colspan", 1000), ("rowspan", 65534)))
                    grid.put([x for x in cell.whole() if x], across or 1, 65534 if down == 0 else down or 1)
            elif kind == "tr":
                grid.begin_row(section)
                yield self.rows(child, inside, grid, section, depth)
                grid.in_row = False
            elif kind in ("tbody", "thead", "tfoot", "form"):
                grid.carried.clear()
                yield self.rows(child, inside, grid, section if kind == "form" else kind, depth)
                grid.carried.clear()
                grid.in_row = False
            else:
                holder = Node("#loose", {})
                holder.children = [child]
                loose = _Lines()
                yield self.fill(holder, around, loose, depth)
                grid.loose.extend(loose.whole())


class _Grid:
    """Rows of cells (column, columns spanned, lines); a cell that spans rows keeps its columns from the rows below."""

    def __init__(self) -> None:
        self.caption: list[str] = []
        self.loose: list[str] = []
        self.sections: dict[str, list[list[tuple[int, int, list[str]]]]] = {"thead": [], "tbody": [], "tfoot": []}
        self.carried: dict[int, int] = {}
        self.taken: frozenset | set = frozenset()
        self.row: list[tuple[int, int, list[str]]] = []
        self.in_row = False

    def begin_row(self, section: str) -> None:
        self.row, self.in_row = [], True
        self.sections[section].append(self.row)
        self.taken = set(self.carried)
        self.carried = {c: n - 1 for c, n in self.carried.items() if n > 1}

    def put(self, lines: list[str], across: int, down: int) -> None:
        at = self.row[-1][0] + self.row[-1][1] if self.row else 0
        while at in self.taken:
            at += 1
        self.row.append((at, across, lines))
        if down > 1:
            self.carried.update(dict.fromkeys(range(at, at + across), down - 1))

    def drawn(self) -> list[str]:
        rows = [r for part in self.sections.values() for r in part]
        cells = [c for r in rows for c in r]
        # only columns in which a cell begins take room
        columns = sorted({at for at, _, _ in cells})
        place = {at: k for k, at in enumerate(columns)}
        width = [0] * len(columns)
        wide = []
        for at, across, lines in cells:
            last = _before(columns, at + across)
            if last == place[at]:
                width[last] = max([width[last], *map(len, lines)])
            else:
                wide.append((place[at], last, max(map(len, lines), default=0)))
        for first, last, size in wide:
            width[last] = max(width[last], size - sum(x + 2 for x in width[first:last]))
        offset = [0]
        for x in width:
            offset.append(offset[-1] + (x + 2 if x else 0))
        out = []
        for row in rows:
            for line in range(max((len(lines) for _, _, lines in row), default=0)):
                text = ""
                for at, _, lines in row:
                    if line < len(lines):
                        text = text.ljust(offset[place[at]]) + lines[line]
                out.append(text)
        return out


def _before(columns: list[int], end: int) -> int:
    """The place of the last of the sorted columns that lies before end."""
    return bisect.bisect_left(columns, end) - 1


def _trim(lines: list[str]) -> list[str]:
    a, b = 0, len(lines)
    while a < b and not lines[a].strip():
        a += 1
    while b > a and not lines[b - 1].strip():
        b -= 1
    return lines[a:b]


def render(page: str) -> str:
    """The visible text of a page."""
    root, sheets = parse(page)
    out: list[str] = []
    lines = _Lines()
    _walk(_Rendering(sheet_rules(sheets)).fill(root, Context(), lines))
    for line in lines.whole():
        if line or (out and out[-1]):
            out.append(line)
    return "\n".join(out)


def _render(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for a in range(0, batch.num_rows, 64):
            part = batch.slice(a, 64)
            texts = [render(x) if x else "" for x in part.column("html").to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [part.column("page_id"), pa.array(texts, pa.string()), pa.array([t.count("\n") + 1 if t else 0 for t in texts], pa.int64())],
                names=["page_id", "text", "n_lines"],
            )


def extract_text(pages: DataFrame) -> DataFrame:
    """For each row of pages(page_id, html): page_id, text, n_lines."""
    return pages.select("page_id", "html").mapInArrow(_render, "page_id long, text string, n_lines long")


def op2_html_text(spark, sf_dir) -> DataFrame:
    return extract_text(spark.read.parquet(f"{sf_dir}/pages.parquet"))
