"""Layout-aware text of HTML pages.

A tolerant tokenizer feeds a tree builder that supplies the tags HTML lets authors leave out
(paragraphs, list items, definition items, table sections, rows and cells, options, body), and a
renderer lays the visible text out: paragraphs and headings stand apart by a blank line, other
blocks by a line break, list items carry their mark and indent, quotations indent, preformatted
text keeps its blanks, and the cells of a table row are padded to aligned columns.

Visible means: not in the head, in scripts, styles, templates or embedded fallback content, not
under ``hidden``, ``display:none`` or ``visibility:hidden``, not in a closed ``details`` (but for
its summary) or ``dialog``, and of a ``select`` only the chosen option.  The page's own style sheets count
where their selectors name an element by tag, id, classes or a pair of these.

A page takes time in proportion to its length: tags are read in one pass, open elements are found by
name, indents end at 64 columns, cells are padded to 200 characters and span 256 columns at most, and
tables nested deeper than 16 are laid out as blocks.  A tag that the page's end cuts off is dropped, as browsers do; a
quote that never closes ends with its tag.

Defined results: null and empty pages give an empty text; text without tags is one flow; unknown
tags are inline; unmatched end tags are ignored, missing ones supplied; elements may nest to any
depth (no recursion); equal pages give equal texts; rows that repeat stay; an empty table gives an
empty result; extra columns are ignored.
"""

from __future__ import annotations

import html
import re

import pyarrow as pa
from pyspark.sql import DataFrame

# Element sets of the HTML standard and default margins of its rendering section.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp iframe noembed noframes".split())
UNSEEN = frozenset("head script style template title iframe noembed noframes object audio video canvas datalist map".split())
FOREIGN = frozenset(["svg", "math"])
#: Elements inside svg or math that are not rendered themselves.
FOREIGN_UNSEEN = frozenset("desc defs metadata symbol clippath mask pattern marker annotation annotation-xml".split())
CLOSES_P = frozenset(
    "address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section summary table ul li dd dt xmp".split()
)
BLOCK = CLOSES_P | frozenset("body html caption legend optgroup tbody td tfoot th thead tr".split())
MARGIN = dict.fromkeys("p h1 h2 h3 h4 h5 h6 blockquote pre dl figure fieldset table".split(), 1)
INDENT = {"blockquote": "    ", "dd": "    ", "figure": ""}
LISTS = frozenset("ul ol menu dir".split())

#: start tag -> (open elements it closes, elements that shield from that)
IMPLIED_END = {
    "li": (frozenset(["li"]), LISTS),
    "dt": (frozenset(["dt", "dd"]), frozenset(["dl"])),
    "dd": (frozenset(["dt", "dd"]), frozenset(["dl"])),
    "option": (frozenset(["option"]), frozenset(["select", "optgroup", "datalist"])),
    "optgroup": (frozenset(["option", "optgroup"]), frozenset(["select", "datalist"])),
    "td": (frozenset(["td", "th"]), frozenset(["tr", "table"])),
    "th": (frozenset(["td", "th"]), frozenset(["tr", "table"])),
    "tr": (frozenset(["tr", "td", "th", "caption"]), frozenset(["table"])),
    "tbody": (frozenset(["tbody", "thead", "tfoot", "caption", "colgroup"]), frozenset(["table"])),
    "thead": (frozenset(["tbody", "thead", "tfoot", "caption", "colgroup"]), frozenset(["table"])),
    "tfoot": (frozenset(["tbody", "thead", "tfoot", "caption", "colgroup"]), frozenset(["table"])),
}
BARRIER = frozenset(["table", "td", "th", "caption", "template", "html", "button", "object"])

_NAME = re.compile(r"(/?)([A-Za-z][^\s/>]*+)")
_REST = re.compile(r"((?:[\s/]++|[^\s/>][^\s/>=]*+(?:\s*+=\s*+(?:\"[^\"]*+\"|'[^']*+'|(?![\"'])[^\s>]*+))?+)*+)>")
_COMMENT_END = re.compile(r"--!?>")
_ATTRIBUTE = re.compile(r"([^\s\"'<>/=]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'=<>`]+)))?")
_BLANKS = re.compile(r"[ \t\n\f\r]+")
_NO_BOX = re.compile(r"display\s*:\s*none|content-visibility\s*:\s*hidden", re.I)
_DISPLAY = re.compile(r"(?<![\w-])display\s*:\s*([\w-]+)\s*(!\s*important)?", re.I)
_VISIBILITY = re.compile(r"(?<![\w-])visibility\s*:\s*(visible|initial|hidden|collapse)", re.I)
_COMMENT = re.compile(r"/\*.*?(?:\*/|\Z)", re.S)
_SIMPLE = re.compile(r"(\*|[A-Za-z][\w-]*)?((?:[.#][\w-]+)*)\Z")
_SHOWN_MEDIA = re.compile(r"@media\s+(?:only\s+)?(?:all|screen)\b|@layer|@supports", re.I)
MOST_INDENT, MOST_PADDING, MOST_COLUMNS, MOST_TABLES, MOST_CLASSES = 64, 200, 256, 16, 32
_BARE_VALUE = re.compile(r"=\s*[^\s\"'=<>`]+/\Z")


def visible(attrs: dict[str, str], inherited: bool, sheet: str | None = None) -> bool:
    """Whether an element's own text shows: the last visibility of its style, else that of the style sheets, else its parent's."""
    own = _VISIBILITY.findall(attrs["style"]) if "style" in attrs else []
    said = own[-1].lower() if own else sheet
    return said in ("visible", "initial") if said else inherited


def attributes(text: str) -> dict[str, str]:
    out: dict[str, str] = {}
    for m in _ATTRIBUTE.finditer(text):
        out.setdefault(m[1].lower(), html.unescape(m[2] or m[3] or m[4] or ""))
    return out


def tokens(page: str):
    """("text", s), ("start", name, attributes) and ("end", name) in page order; in svg and math a tag may close itself."""
    at, n, foreign, text = 0, len(page), 0, 0
    while at < n:
        at = page.find("<", at)
        if at < 0:
            break
        following = page[at + 1 : at + 2]
        if following in ("!", "?"):
            if at > text:
                yield "text", page[text:at], None
            if page.startswith("<!--", at):
                # a comment may close at once: its opening dashes count
                close = page.startswith((">", "->"), at + 4)
                end = page.find(">", at) + 1 if close else (m.end() if (m := _COMMENT_END.search(page, at + 4)) else n)
            else:
                end = page.find(">", at) + 1 or n
            at = text = end
            continue
        m = _NAME.match(page, at + 1)
        if m is None:
            at += 1
            continue
        if at > text:
            yield "text", page[text:at], None
        rest = _REST.match(page, m.end())
        if rest is None:
            return
        at = text = rest.end()
        name = m[2].lower()
        if m[1]:
            foreign -= foreign > 0 and name in FOREIGN
            yield "end", name, None
            continue
        given = rest[1]
        yield "start", name, attributes(given) if given else {}
        foreign += name in FOREIGN
        if foreign and given.endswith("/") and not _BARE_VALUE.search(given[-1000:]):
            foreign -= name in FOREIGN
            if name not in VOID:
                yield "end", name, None
            continue
        if name in RAW:
            close = re.compile(rf"</{re.escape(name)}(?=[\s/>])[^>]*>?", re.I).search(page, at)
            body = page[at : close.start()] if close else page[at:]
            at = text = close.end() if close else n
            if body:
                yield "raw", body, None
            yield "end", name, None
    if text < n:
        yield "text", page[text:], None


class Sheets:
    """What the page's style sheets say about showing elements: rules of one part (tag, .class, #id) or two."""

    def __init__(self):
        self.rules: dict[frozenset, dict[str, tuple]] = {}
        self.order = 0

    def add(self, text: str) -> None:
        context: list[bool] = []  # whether each enclosing block's rules count
        head = ""
        for piece in re.split(r"([{}])", _COMMENT.sub(" ", text)):
            if piece == "{":
                head = head.rpartition(";")[2].strip()
                if head.startswith("@") or context and not context[-1]:
                    context.append(bool(_SHOWN_MEDIA.match(head)) and all(context))
                else:
                    context.append(False)
                    self.selectors = head
                head = ""
            elif piece == "}":
                if context:
                    context.pop()
                    if self.selectors and all(context):
                        self.rule(self.selectors, head)
                self.selectors = head = ""
            else:
                head = piece

    selectors = ""

    def rule(self, selectors: str, body: str) -> None:
        said = {}
        for kind, found in (("box", _DISPLAY.findall(body)), ("visibility", _VISIBILITY.findall(body))):
            if found:
                value, weight = found[-1] if kind == "box" else (found[-1], "")
                said[kind] = (value.lower(), bool(weight))
        if not said:
            return
        for selector in selectors.split(","):
            m = _SIMPLE.match(selector.strip())
            if m is None:
                continue
            parts = frozenset(([m[1].lower()] if m[1] and m[1] != "*" else []) + re.findall(r"[.#][\w-]+", m[2]))
            if 0 < len(parts) <= 2:
                self.order += 1
                rank = (sum(p[0] == "#" for p in parts), sum(p[0] == "." for p in parts), len(parts))
                for kind, (value, weight) in said.items():
                    self.rules.setdefault(parts, {})[kind] = (weight, rank, self.order, value)

    def ask(self, name: str, attrs: dict[str, str]) -> dict[str, str]:
        """The winning values of an element: ``box`` (display) and ``visibility``."""
        if not self.rules:
            return {}
        parts = [name, *(f".{c}" for c in attrs.get("class", "").split()[:MOST_CLASSES])] + ([f"#{attrs['id']}"] if "id" in attrs else [])
        best: dict[str, tuple] = {}
        for i, p in enumerate(parts):
            for q in parts[i:]:
                for kind, rule in self.rules.get(frozenset((p, q)), {}).items():
                    best[kind] = max(best.get(kind, rule), rule)
        return {kind: rule[3] for kind, rule in best.items()}


class Flow:
    """Lines of one block context: the page or a table cell."""

    def __init__(self):
        self.lines: list[str] = []
        self.words: list[str] = []
        self.margin = 0
        self.blank = False  # a collapsed blank is due before the next word
        self.indents: list[str] = [""]
        self.mark: str | None = None

    def write(self, text: str) -> None:
        parts = _BLANKS.split(text)
        if not parts[0] and len(parts) > 1:
            self.blank = True
        for i, word in enumerate(parts):
            if not word:
                continue
            if (self.blank or i and parts[i - 1]) and self.words:
                self.words.append(" ")
            self.words.append(word)
            self.blank = False
        if not parts[-1]:
            self.blank = True

    def write_kept(self, text: str) -> None:
        lines = text.replace("\r\n", "\n").split("\n")
        for i, line in enumerate(lines):
            if i:
                self.break_line(True)
            if line:
                self.words.append(line)

    def break_line(self, keep_empty: bool = False) -> None:
        text = "".join(self.words).rstrip(" ")
        self.words.clear()
        self.blank = False
        if text or keep_empty and (self.lines or self.mark):
            self._put(text)

    def _put(self, text: str) -> None:
        if self.lines and self.margin:
            self.lines.extend([""] * self.margin)
        self.margin = 0
        indent = self.indents[-1]
        if self.mark is not None:
            indent = indent[: -len(self.mark)] + self.mark if len(indent) >= len(self.mark) else self.mark
            self.mark = None
        self.lines.append((indent + text).rstrip(" "))

    def indent(self, by: str) -> None:
        self.indents.append((self.indents[-1] + by)[:MOST_INDENT])

    def block(self, margin: int) -> None:
        self.break_line()
        self.margin = max(self.margin, margin)

    def put_lines(self, lines: list[str]) -> None:
        self.break_line()
        for line in lines:
            self._put(line)

    def close(self) -> list[str]:
        self.break_line()
        while self.lines and not self.lines[-1]:
            self.lines.pop()
        return self.lines


class Table:
    def __init__(self):
        self.rows: list[list[tuple[list[str], int, int]]] = []
        self.captions: list[str] = []

    def placed(self) -> list[list[tuple[int, int, list[str]]]]:
        """(first column, columns, lines) of the cells of each row; cells that span rows keep their columns there."""
        taken: dict[int, int] = {}  # column -> first row in which it is free again
        out = []
        free, until = 0, 0  # columns before ``free`` are taken up to row ``until``
        for r, row in enumerate(self.rows):
            if r >= until:
                free, until = 0, len(self.rows)
            at, cells = free, []
            for lines, span, down in row:
                while taken.get(at, 0) > r:
                    if at == free:
                        free, until = free + 1, min(until, taken[at])
                    at += 1
                span = span if at + span <= MOST_COLUMNS else 1
                cells.append((at, span, lines))
                if down != 1 and at < MOST_COLUMNS:
                    for k in range(at, at + span):
                        taken[k] = max(taken.get(k, 0), r + down if down else len(self.rows))
                at += span
            out.append(cells)
        return out

    def render(self) -> list[str]:
        """Rows with cells padded to the columns' widths; cells that span columns have the room of these."""
        rows = self.placed()
        widths: dict[int, int] = {}
        for spans in (False, True):
            for row in rows:
                for at, span, lines in row:
                    need = min(max(map(len, lines), default=0), MOST_PADDING)
                    if span == 1 and not spans:
                        widths[at] = max(widths.get(at, 0), need)
                    elif span > 1 and spans:
                        room = sum(widths.get(k, 0) for k in range(at, at + span)) + 2 * (span - 1)
                        if need > room:
                            widths[at + span - 1] = widths.get(at + span - 1, 0) + need - room
        starts = [0]  # where columns begin on the line
        for k in range(max(widths, default=-1) + 1):
            starts.append(starts[-1] + widths.get(k, 0) + 2)
        out = list(self.captions)
        for row in rows:
            for k in range(max((len(lines) for _, _, lines in row), default=0)):
                line, wide = [], 0
                for at, _, lines in row:
                    if k < len(lines) and lines[k]:
                        begin = starts[min(at, len(starts) - 1)] if row[0][0] or at != row[0][0] else 0
                        gap = begin - wide if begin > wide else 2 if wide else 0
                        line.append(" " * min(gap, MOST_PADDING) + lines[k])
                        wide += min(gap, MOST_PADDING) + len(lines[k])
                out.append("".join(line).rstrip(" "))
        return out


class Open:
    """An open element."""

    __slots__ = ("chosen", "down", "flow", "foreign", "hidden", "item", "keeps", "name", "options", "seen", "span", "table")

    def __init__(self, name: str, hidden: bool, keeps: bool):
        self.name, self.hidden, self.keeps = name, hidden, keeps
        self.flow = self.table = self.options = self.chosen = None
        self.item, self.span, self.down = 0, 1, 1
        self.seen, self.foreign = True, False


class Renderer:
    def __init__(self):
        root = Open("html", False, False)
        root.flow = Flow()
        self.stack = [root]
        self.flows = [root.flow]
        self.tables: list[Table | None] = []  # None: laid out as blocks
        self.places: dict[str, list[int]] = {"html": [0]}  # positions of the open elements of each name
        self.selects: list[Open] = []
        self.sheets = Sheets()

    # tree building -------------------------------------------------------------------------
    def feed(self, page: str) -> list[str]:
        for kind, value, attrs in tokens(page):
            if kind == "start":
                self.start(value, attrs)
            elif kind == "end":
                self.end(value)
            elif self.stack[-1].name == "style" and kind == "raw":
                self.sheets.add(value)
            else:
                self.text(html.unescape(value) if kind == "text" or self.stack[-1].name in ("textarea", "title") else value)
        while len(self.stack) > 1:
            self.pop()
        return self.flows[0].close()

    def start(self, name: str, attrs: dict[str, str]) -> None:
        if name in ("html", "body"):
            self.leave("head")
            if "hidden" in attrs or _NO_BOX.search(attrs.get("style", "")):
                self.stack[-1].hidden = True
            self.stack[-1].seen = visible(attrs, self.stack[-1].seen)
            return
        if name == "select" and self.places.get("select"):
            self.leave("select")  # a select in a select ends it
            return
        if name in CLOSES_P and self.reaches("p", BARRIER):
            self.leave("p")
        if name in IMPLIED_END:
            closes, shields = IMPLIED_END[name]
            while (i := self.nearest(closes)) > max(0, self.nearest(shields)):
                while len(self.stack) > i:
                    self.pop()
        if name in ("td", "th"):
            self.need("tr", ("table",))
        elif name == "tr" and not self.reaches("table", ()):
            return  # a row without a table is ignored
        if name in ("td", "th") and not self.reaches("tr", ("table",)):
            return
        if self.stack[-1].name == "head" and name not in ("title", "script", "style", "link", "meta", "base", "noscript", "template"):
            self.leave("head")
        self.push(name, attrs)
        if name in VOID:
            self.pop()

    def need(self, name: str, shields) -> None:
        if self.reaches("table", ()) and not self.reaches(name, shields):
            self.push(name, {})

    def nearest(self, names) -> int:
        """Position of the innermost open element of some names, -1 if there is none."""
        return max((self.places[n][-1] for n in names if self.places.get(n)), default=-1)

    def reaches(self, name: str, shields) -> bool:
        return bool(self.places.get(name)) and self.places[name][-1] >= self.nearest(shields)

    def leave(self, name: str) -> None:
        if self.places.get(name):
            while self.pop() != name:
                pass

    def end(self, name: str) -> None:
        if name in ("html", "body"):
            return
        if name == "p" and not self.reaches("p", BARRIER):
            self.push("p", {})
            self.pop()
            return
        if name == "br":
            self.start("br", {})
            return
        shields = () if name in ("table", "html") else ("table",) if name in ("tr", "td", "th", "tbody", "thead", "tfoot", "caption") else BARRIER
        if self.reaches(name, frozenset(shields) - {name}) and name != self.stack[0].name:
            while self.pop() != name:
                pass

    # layout --------------------------------------------------------------------------------
    def push(self, name: str, attrs: dict[str, str]) -> None:
        parent = self.stack[-1]
        said = self.sheets.ask(name, attrs)
        own = _DISPLAY.findall(attrs["style"]) if "style" in attrs else []
        boxless = bool(own) and own[-1][0].lower() == "none" or "style" in attrs and bool(_NO_BOX.search(attrs["style"])) or not own and said.get("box") == "none"
        hidden = parent.hidden or name in UNSEEN or "hidden" in attrs or boxless or parent.foreign and name in FOREIGN_UNSEEN
        if parent.name == "details" and parent.chosen is False and name != "summary" or name == "dialog" and "open" not in attrs:
            hidden = True
        e = Open(name, hidden, parent.keeps or name in ("pre", "textarea", "xmp"))
        e.seen = visible(attrs, parent.seen, said.get("visibility"))
        e.foreign = name in FOREIGN or parent.foreign and name != "foreignobject"
        self.places.setdefault(name, []).append(len(self.stack))
        self.stack.append(e)
        if name == "details":
            e.chosen = "open" in attrs
        if hidden:
            return
        flow = self.flows[-1]
        if name == "text" and e.foreign:
            flow.blank = True  # placed on its own
        elif name in ("br", "hr") and not e.seen:
            flow.break_line()
        elif name == "br":
            flow.break_line(True)
        elif name == "hr":
            flow.block(0)
            flow.put_lines(["-" * 8])
        elif name == "table":
            flow.block(1)
            e.chosen = True
            e.table = Table() if len(self.tables) < MOST_TABLES else None
            self.tables.append(e.table)
        elif name == "tr" and self.tables and self.tables[-1] is not None:
            self.tables[-1].rows.append([])
        elif name in ("td", "th", "caption") and self.tables and self.tables[-1] is not None:
            span, down = (attrs.get(k, "1") for k in ("colspan", "rowspan"))
            e.span = min(max(int(span), 1), MOST_COLUMNS) if span.isascii() and span.isdigit() and len(span) < 6 else 1
            e.down = min(int(down), 65534) if down.isascii() and down.isdigit() and len(down) < 7 else 1
            e.flow = Flow()
            self.flows.append(e.flow)
        elif name == "select":
            e.options = []
            self.selects.append(e)
        elif name == "option":
            e.flow = Flow()
            e.chosen = "selected" in attrs
            self.flows.append(e.flow)
        elif name in BLOCK:
            inside_list = name in LISTS and sum(len(self.places.get(x, ())) for x in LISTS) > 1
            flow.block(0 if name in LISTS and inside_list else 1 if name in LISTS else MARGIN.get(name, 0))
            if name in LISTS:
                e.item = int(attrs.get("start", "1")) - 1 if attrs.get("start", "1").isdigit() and len(attrs.get("start", "1")) < 10 else 0
                e.chosen = name == "ol"
            if name == "li":
                at = self.nearest(LISTS)
                owner = self.stack[at] if at > 0 else None
                mark = "* "
                if owner is not None and owner.chosen:
                    owner.item += 1
                    mark = f"{owner.item}. "
                flow.indent(" " * len(mark))
                flow.mark = mark
            elif name in INDENT:
                flow.indent(INDENT[name])

    def pop(self) -> str:
        e = self.stack.pop()
        self.places[e.name].pop()
        if e.hidden:
            return e.name
        if e.name == "text" and e.foreign:
            self.flows[-1].blank = True
        if e.name == "table":
            self.tables.pop()
            flow = self.flows[-1]
            if e.table is not None:
                flow.put_lines(e.table.render())
            flow.block(1)
        elif e.flow is not None and len(self.flows) > 1:
            self.flows.pop()
            lines = e.flow.close()
            if e.name == "option":
                if self.selects:
                    self.selects[-1].options.append((e.chosen, " ".join(lines)))
            elif e.name == "caption":
                self.tables[-1].captions.extend(lines)
            else:
                if not self.tables[-1].rows:
                    self.tables[-1].rows.append([])
                self.tables[-1].rows[-1].append((lines, e.span, e.down))
        elif e.options is not None:
            self.selects.pop()
            shown = next((text for chosen, text in e.options if chosen), e.options[0][1] if e.options else "")
            self.flows[-1].write(shown)
        elif e.name in BLOCK and e.name not in ("tr", "tbody", "thead", "tfoot"):
            flow = self.flows[-1]
            if e.name == "li":
                flow.break_line()
                flow.mark = None
                flow.indents.pop()
            elif e.name in INDENT:
                flow.break_line()
                flow.indents.pop()
            inside_list = any(self.places.get(x) for x in LISTS)
            flow.block((0 if inside_list else 1) if e.name in LISTS else MARGIN.get(e.name, 0))
        return e.name

    def text(self, value: str) -> None:
        e = self.stack[-1]
        if e.hidden or not e.seen:
            return
        if e.name == "details" and e.chosen is False:
            return
        if e.name in ("table", "tr", "tbody", "thead", "tfoot", "select") and not value.strip():
            return
        if e.keeps:
            if e.name == "pre" and e.item == 0 and value.startswith("\n"):
                value = value[1:]  # a line break right after the tag does not count
            e.item = 1
            self.flows[-1].write_kept(value)
        else:
            self.flows[-1].write(value)


def render(page: str | None) -> str:
    """The visible text of a page, laid out; lines end without blanks and no-break spaces become blanks."""
    if not page:
        return ""
    return "\n".join(Renderer().feed(page.replace("\x00", "�"))).replace("\xa0", " ")


def _render(batches):
    for batch in batches:
        texts = [render(p) for p in batch["html"].to_pylist()]
        yield pa.record_batch({"page_id": batch["page_id"], "url": batch["url"], "text": pa.array(texts, pa.string()), "n_lines": pa.array([t.count("\n") + 1 if t else 0 for t in texts], pa.int64())})


def extract_layout(pages: DataFrame) -> DataFrame:
    """page_id, url, text and n_lines of every row of ``pages`` (page_id, url, html)."""
    return pages.select("page_id", "url", "html").mapInArrow(_render, "page_id long, url string, text string, n_lines long")


def op10_layout_text(spark, sf_dir) -> DataFrame:
    return extract_layout(spark.read.parquet(f"{sf_dir}/pages.parquet"))
