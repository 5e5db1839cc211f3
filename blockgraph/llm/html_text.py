"""HTML extraction by tree scoring: the main text of a page without menus, headers, footers, sidebars, notices, adverts, forms.

The page becomes a tree (unclosed and stray tags mended as browsers do for the common cases), in time linear in its length. Each
paragraph passes points to its ancestors, for itself, its commas and its length, less with distance; an element's points are then
discounted by its link density. The best container is kept with those of its siblings, at every level above it, whose
points come near its own or that read like prose, and with a title beside it. What the elements' kinds say is furniture (nav, footer, forms
...) is left out. Class names and ids are evidence only: an element so named goes unless the article or most of the page's points
are in it; where the name is ambiguous ("related", "form"), unless it reads like prose. Blocks come in page order, joined by one newline.
"""

from __future__ import annotations

import html as entities
import re
from bisect import bisect_right
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from blockgraph.llm.text import blocks

_COMMENT = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*>?", re.S)
_OPEN = re.compile(r"<(/?)([a-zA-Z][^\s/>]*+)")
_REST = re.compile(r"((?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+)>")
_RAW_END = {t: re.compile(rf"</{t}\s*>", re.I) for t in ("script", "style", "textarea", "title", "noscript", "iframe", "template", "xmp", "noembed", "noframes", "select", "svg", "math", "object", "canvas", "video", "audio")}
_ATTR = re.compile(r"\b(class|id|role|style|hidden|aria-hidden)\b\s*+(?:=\s*+(\"[^\"]*+\"|'[^']*+'|[^\s>]++))?", re.I)
_SENTENCE = re.compile(r"[.!?…。]")
_PART = re.compile(r"[a-z]+|[0-9]+")
# fixed values: element kinds of HTML
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_BLOCK = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
_HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
_CLOSES_P = _BLOCK - {"body", "caption", "html", "legend", "tbody", "td", "tfoot", "th", "thead", "tr"}
_P_STAYS = ("td", "th", "button", "table")
_SAME = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",), "tbody": ("thead", "tbody", "tfoot", "tr", "td", "th"), "tfoot": ("thead", "tbody", "tr", "td", "th")}
_STOP = {"li": ("ul", "ol", "menu", "dir"), "dt": ("dl",), "dd": ("dl",), "tr": ("table",), "td": ("tr", "table"), "th": ("tr", "table"), "option": ("select",), "tbody": ("table",), "tfoot": ("table",)}
_HIDDEN = frozenset("head title script style noscript template iframe textarea select button input svg math object canvas video audio xmp noembed noframes map datalist dialog".split())
_FURNITURE = frozenset("nav footer aside form menu".split())
_ROLES = frozenset("navigation banner contentinfo complementary search dialog alert menu menubar form".split())
# fixed values: words in class names and ids that tell of furniture, surely or perhaps, and of content
_SURELY = frozenset("ad ads advert adverts advertisement advertising adsense sponsor sponsored promo promos promotion popup modal banner cookie cookies consent gdpr notice notices alert alerts newsletter subscribe signup comment comments disqus respond replies sidebar aside menu nav navbar navigation breadcrumb breadcrumbs pager pagination footer masthead topbar toolbar share sharing login skip".split())
_PERHAPS = frozenset("social related recommended recommendations widget rail side tags meta search overlay header foot form hidden byline".split())
_CONTENT = frozenset("article articles body content entry hentry main page post posts text blog story prose".split())
SHORTEST_SCORED = 25
PROSE = 80
SEMANTIC = 25.0
NEAR, FAR = 0.2, 0.3
CONFUSED = 50


class Node:
    __slots__ = ("children", "hidden", "holds", "links", "name", "parent", "parts", "points", "prose", "said", "score", "size")

    def __init__(self, name: str, parent: "Node | None", said: str = ""):
        self.name, self.parent, self.said, self.children = name, parent, said, []
        self.score, self.points, self.size, self.links, self.holds, self.prose = 0.0, 0.0, 0, 0, False, False
        self.parts, self.hidden = frozenset(), False

    def look(self) -> None:
        """Reads the attributes: the parts of class names and ids, and whether the element is hidden."""
        if not self.said or self.said.isspace():
            return
        names = []
        for key, value in _ATTR.findall(self.said):
            key, value = key.lower(), value.strip("\"'")
            if key in ("class", "id"):
                names.append(value.lower())
            elif key == "hidden" or (key == "aria-hidden" and value.lower() == "true"):
                self.hidden = True
            elif key == "style":
                self.hidden |= bool(re.search(r"display\s*+:\s*+none|visibility\s*+:\s*+hidden", value, re.I))
            elif key == "role":
                self.hidden |= value.lower() in _ROLES
        self.parts = frozenset(_PART.findall(" ".join(names)))


class _Open:
    """The open elements, with the places of each kind, so that no search walks up the tree."""

    def __init__(self, root: Node):
        self.stack, self.places = [root], {}

    @property
    def here(self) -> Node:
        return self.stack[-1]

    def last(self, names: tuple[str, ...]) -> int:
        return max((p[-1] for n in names if (p := self.places.get(n))), default=0)

    def push(self, node: Node) -> None:
        self.places.setdefault(node.name, []).append(len(self.stack))
        self.stack.append(node)

    def close(self, place: int) -> None:
        """Ends the element at a place and all in it; the root stays."""
        while len(self.stack) > max(place, 1):
            self.places[self.stack.pop().name].pop()

    def make_room(self, name: str) -> None:
        """Ends what a new element of this kind ends."""
        if name in _CLOSES_P and (p := self.last(("p",))) > self.last(_P_STAYS):
            self.close(p)
        if name in _SAME:
            stop = self.last(_STOP[name])
            if name in ("tr", "tbody", "tfoot"):  # the outermost one inside the table
                ends = [p[i] for n in _SAME[name] if (p := self.places.get(n)) and (i := bisect_right(p, stop)) < len(p)]
                if ends:
                    self.close(min(ends))
            elif (p := self.last(_SAME[name])) > stop:
                self.close(p)


def parse(page: str) -> Node:
    """The page as a tree of elements and texts (character references decoded)."""
    root = Node("html", None)
    open_, at, end, confused = _Open(root), 0, len(page), 0

    def say(text: str) -> None:
        if text:
            open_.here.children.append(text)

    while at < end:
        lt = page.find("<", at)
        if lt < 0:
            say(entities.unescape(page[at:]))
            break
        if page.startswith(("<!", "<?"), lt):
            say(entities.unescape(page[at:lt]))
            m = _COMMENT.match(page, lt)
            at = m.end()
            if m[0].startswith("<![CDATA["):
                say(m[0][9:].removesuffix("]]>"))
            continue
        m = _OPEN.match(page, lt)
        if m is None:  # a bare sign
            say(entities.unescape(page[at : lt + 1]))
            at = lt + 1
            continue
        say(entities.unescape(page[at:lt]))
        rest = _REST.match(page, m.end()) if confused < CONFUSED else None
        if rest is not None:
            said, at = rest[1], rest.end()
        else:  # quotes that never end: the tag ends at the next sign that could end it
            confused += 1
            gt = page.find(">", m.end())
            if gt < 0:  # the page ends inside a tag
                break
            said, at = page[m.end() : gt], gt + 1
        name = m[2].lower()
        if m[1]:
            if name not in ("html", "body") and (p := open_.last((name,))):
                open_.close(p)
            elif name == "br":
                say(" ")
            continue
        if name == "html":
            continue
        if name == "body":
            open_.close(1)  # whatever the head left open ends
            root.said = said
            continue
        if name in ("br", "wbr"):
            say(" " if name == "br" else "")
            continue
        open_.make_room(name)
        node = Node(name, open_.here, said)
        node.look()
        open_.here.children.append(node)
        if name in _VOID or (said.endswith("/") and name in ("svg", "path")):
            continue
        if name in _RAW_END:
            stop = _RAW_END[name].search(page, at)
            if name in ("title", "textarea"):
                node.children.append(entities.unescape(page[at : stop.start() if stop else end]))
            at = stop.end() if stop else end
            continue
        open_.push(node)
    return root


def _order(root: Node) -> list[Node]:
    """All elements, parents first."""
    out = [root]
    for node in out:
        out.extend(c for c in node.children if not isinstance(c, str))
    return out


def _direct(node: Node) -> str:
    """Text of an element outside inner blocks."""
    out, stack = [], [*reversed(node.children)]
    while stack:
        c = stack.pop()
        if isinstance(c, str):
            out.append(c)
        elif c.name not in _BLOCK:
            stack.extend(reversed(c.children))
    return " ".join("".join(out).split())


def _points(text: str) -> float:
    return 1 + text.count(",") + text.count("，") + min(len(text) // 100, 3) if len(text) >= SHORTEST_SCORED else 0.0


def measure(root: Node) -> list[Node]:
    """Sizes of text and link text, points of all paragraphs below, whether one of them is prose and whether an article is in it; elements, parents first."""
    order = _order(root)
    for node in reversed(order):
        node.size = node.links = 0
        text = _direct(node) if node.name in _BLOCK else ""
        node.points, node.holds = 0.0 if node.name in _HEADINGS else _points(text), node.name in ("article", "main")
        node.prose = len(text) >= PROSE and bool(_SENTENCE.search(text))
        for c in node.children:
            if isinstance(c, str):
                node.size += len(c.strip())
            else:
                node.size += c.size
                node.links += c.size if c.name == "a" else c.links
                node.points += c.points
                node.holds |= c.holds and c.size > 0
                node.prose |= c.prose
    return order


def _density(node: Node) -> float:
    return node.links / node.size if node.size else 0.0


def prune(root: Node) -> None:
    """Takes furniture out of the tree: first by the elements' kinds, then by names where the points allow it."""
    stack: list[tuple[Node, bool]] = [(root, False)]
    while stack:
        node, inside = stack.pop()
        inside = inside or node.name in ("article", "main")
        kept = []
        for c in node.children:
            if isinstance(c, str):
                kept.append(c)
            elif c.name in _HIDDEN or c.name in _FURNITURE or c.hidden:
                continue
            elif c.name == "header":
                if inside:  # of an article's own header its headings stay
                    kept.extend(x for x in _order(c) if x.name in _HEADINGS)
            else:
                kept.append(c)
        node.children = kept
        for c in kept:
            if not isinstance(c, str):
                c.parent = node
                stack.append((c, inside))
    measure(root)
    todo = [root]
    while todo:
        node = todo.pop()
        node.children = [c for c in node.children if isinstance(c, str) or not _named_furniture(c, root)]
        todo.extend(c for c in node.children if not isinstance(c, str))
    measure(root)


def _named_furniture(node: Node, root: Node) -> bool:
    """Whether an element goes by its names: not if an article is in it, or most of the page's points where the page has no article."""
    if node.name in ("article", "main") or not node.parts or node.holds:
        return False
    if node.parts & _SURELY:
        return root.holds or node.points < root.points / 2 or not root.points
    return bool(node.parts & _PERHAPS) and not _reads_like_prose(node)


def _reads_like_prose(node: Node) -> bool:
    """Few links, and a paragraph of some length with the end of a sentence."""
    return node.prose and _density(node) <= 0.25


def best(root: Node) -> list[Node]:
    """The best container and the siblings that go with it, in page order."""
    order = _order(root)
    scored: set[int] = set()
    for node in order:
        if node.name in ("article", "main") and node.size:
            node.score += SEMANTIC
            scored.add(id(node))
        if node.name not in _BLOCK or node.name in _HEADINGS:
            continue
        points = _points(_direct(node))
        if not points:
            continue
        up, level = (node if node.name in ("div", "section", "article", "main", "td") else node.parent), 0
        while up is not None and level < 5:
            scored.add(id(up))
            up.score += points / (1 if level == 0 else 2 if level == 1 else level * 3)
            up, level = up.parent, level + 1
    if not scored:
        return [root]
    for node in order:
        if node.parts & _CONTENT:
            node.score *= 1.2
        if node.parts & _PERHAPS:
            node.score *= 0.8
        node.score *= 1 - _density(node)
    top = max((n for n in order if id(n) in scored), key=lambda n: n.score)
    up = top
    while up is not None and up.name not in ("article", "main"):
        up = up.parent
    here = up if up is not None else top
    if here.parent is None:
        return [root]
    unit, titled, share = [here], any(x.name == "h1" for x in _order(here)), NEAR
    while here.parent is not None:
        siblings = here.parent.children
        at = next(i for i, c in enumerate(siblings) if c is here)
        keep = {i for i, c in enumerate(siblings) if not isinstance(c, str) and c is not here and ((id(c) in scored and c.score >= share * top.score and _reads_like_prose(c)) or _is_prose(c))}
        between = range(min(keep, default=at), max(keep, default=at))
        keep |= {i for i in between if i != at and not isinstance(siblings[i], str) and siblings[i].size and _density(siblings[i]) < 0.3}
        if not titled and (i := next((i for i in range(at - 1, -1, -1) if not isinstance(siblings[i], str) and siblings[i].name == "h1" and siblings[i].size and not siblings[i].links), None)) is not None:
            keep.add(i)
            titled = True
        unit = [siblings[i] for i in sorted(keep) if i < at] + unit + [siblings[i] for i in sorted(keep) if i > at]
        here, share = here.parent, FAR
    return unit


def _is_prose(node: Node) -> bool:
    """A paragraph that reads like a part of the text beside it."""
    if node.name != "p" or not node.size:
        return False
    text = _direct(node)
    return (len(text) > PROSE and _density(node) < 0.25) or (not node.links and bool(re.search(r"[.!?…。](\s|$)", text)))


def block_texts(nodes: list[Node]) -> list[str]:
    """The texts of blocks in page order, white space in each turned into single blanks; empty blocks are left out."""
    out: list[str] = []
    run: list[str] = []

    def end() -> None:
        if run:
            text = " ".join("".join(run).split())
            if text:
                out.append(text)
            run.clear()

    stack: list = [*reversed(nodes)]
    while stack:
        c = stack.pop()
        if c is None:
            end()
        elif isinstance(c, str):
            run.append(c)
        elif c.name in _BLOCK:
            end()
            stack.append(None)
            stack.extend(reversed(c.children))
        else:
            stack.extend(reversed(c.children))
    end()
    return out


def main_text(page: str | None) -> str:
    """The main text of a page; empty for a null or empty one."""
    if not page:
        return ""
    root = parse(page)
    prune(root)
    return "\n".join(block_texts(best(root)))


def _extract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in blocks(batches, "html", 4 << 20):
        texts = [main_text(x) for x in b.column("html").to_pylist()]
        yield pa.RecordBatch.from_arrays([b.column("page_id"), b.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars of each row of pages (page_id, url, html); null pages give empty text, repeated rows repeat, further
    columns are left out, an empty table gives an empty one."""
    source = pages.select("page_id", "url", pages["html"].cast("string").alias("html"))
    return source.mapInArrow(_extract, source.select("page_id", "url").schema.add("text", "string").add("n_chars", "long"))
