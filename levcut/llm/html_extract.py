"""Main text of web pages by a minimum cut over their blocks.

A page is cut into blocks of text at block-level tags. The graph has a node for
each block and one for each element that holds blocks. A linear classifier of a
block's own features (tag, length, links, punctuation) gives it a cost of being
called content and one of being called boilerplate; so do the tag and the name of
an element, softened by what stands around it. These costs are the capacities to
the terminals. Smoothness edges join a block to its element, elements to their
parents and blocks to their neighbours in the page; across a named container they
are weak. A maximum flow finds the labelling of least total cost, so a container
speaks for its blocks only as far as its edges and its cost carry.

Scripts, styles, templates, the head, form controls and comments in the markup
never become blocks. Character references are decoded after the markup is read.
White space inside a block becomes one space; blocks are joined by one space.

Nulls: null html counts as empty and gives an empty text; so does a page without
content. Truncated or unbalanced markup is read as far as it goes. Very long pages
are read whole; memory grows with one page's blocks. Repeated rows give repeated
results; empty tables empty ones; other columns are ignored.
"""

from __future__ import annotations

import html
import re
from collections import deque
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levcut.llm.common import map_arrow

TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)"
    r"|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^>\"']|\"[^\"]*(?:\"|\Z)|'[^']*(?:'|\Z))*)(?:>|\Z)",
    re.S,
)
NAMES = re.compile(r"\b(class|id|role|aria-label)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
#: Tags whose content is raw text that no reader sees.
RAW = {"script", "style", "template", "noscript", "svg", "math", "iframe", "object", "canvas", "textarea", "title", "select"}
#: Tags without content.
VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"}
#: Tags that stay inside a block.
INLINE = set("a abbr acronym b bdi bdo big cite code data del dfn em font i img ins kbd label mark nobr q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
#: An open element of the set ends where its key begins.
CLOSES = {
    "p": {"p"}, "li": {"li", "p"}, "dt": {"dt", "dd", "p"}, "dd": {"dt", "dd", "p"}, "tr": {"tr", "td", "th", "p"},
    "td": {"td", "th", "p"}, "th": {"td", "th", "p"}, "option": {"option"},
}
#: Containers, and the words of their names, that tell boilerplate.
BOILER_TAGS = {"nav", "footer", "aside", "form", "button", "dialog", "menu", "fieldset"}
BOILER_WORDS = set(
    "ad ads adv advert advertisement advertising banner breadcrumb breadcrumbs comment comments commentlist consent contentinfo cookie cookies "
    "copyright disclaimer disqus footer form gdpr header login masthead menu modal nav navbar navigation newsletter notice notices notification "
    "outbrain overlay pager pagination popup promo promoted promotion reader related reply replies respond search share sharing shoutbox sidebar sidenav "
    "signup skip social sponsor sponsored subscribe subscription taboola tags toc toolbar topbar widget widgets alert complementary".split()
)
#: Words beside such a word that leave its meaning as it is.
PLAIN_WORDS = set(
    "area articles bar body bottom box btn button buttons card cards column container content controls el entry global group holder icons inner item items "
    "left level line link links list main mobile module page panel policy post posts primary right row second secondary section site slot small stories story "
    "text thread top unit view wrap wrapper".split()
)
#: Whole names that mark the main text, and words that put a header inside it.
MAIN_WORDS = set("article articlebody body content entry entrycontent main maincontent post postbody postcontent story text".split())
TITLE_WORDS = {"article", "entry", "post", "story", "content"}
WORDS_OF_NAME = re.compile(r"[A-Za-z][a-z]+|[A-Z]+(?![a-z])")
BLANK = re.compile(r"\s+")
#: Tags of text rather than of containers.
TEXT_TAGS = {"p", "h1", "h2", "h3", "h4", "h5", "h6", "li", "dt", "dd", "td", "th", "blockquote", "pre", "figcaption", "caption"}
#: Weights of the classifier: positive speaks for content. First of blocks, then of elements.
WEIGHTS = {
    "base": -0.3, "paragraph": 1.0, "heading": 0.6, "item": 0.0, "long": 1.5, "sentence": 0.7, "links": -3.0, "short": -0.2,
    "boiler": -6.0, "hint": -1.5, "article": 2.0, "main": 1.0, "outside": -0.6,
}
#: What is left of an element's leaning one level below, and its bounds.
FADE, LOWEST, HIGHEST = 0.85, -6.0, 2.5
#: Capacities of smoothness: block and element, element and parent (for each block
#: below), neighbours; across a named container.
TO_ELEMENT, TO_PARENT, TO_NEXT, ACROSS = 3.5, 0.6, 0.8, 0.1


@dataclass
class Element:
    parent: int
    leaning: float
    named: bool
    article: bool


@dataclass
class Block:
    element: int
    tag: str
    parts: list[str]
    linked: int = 0
    text: str = field(default="")


@dataclass
class _Open:
    tag: str
    element: int


def named(tag: str, attributes: str, in_article: bool) -> tuple[float, bool, bool]:
    """An element's own leaning, whether it is a border, and whether it marks the main text."""
    w = WEIGHTS
    boiler = tag in BOILER_TAGS or tag == "header" and not in_article
    hint, main = False, False
    for match in NAMES.finditer(attributes):
        for name in BLANK.split(match[2] or match[3] or match[4] or ""):
            parts = {x.lower() for x in WORDS_OF_NAME.findall(name)}
            told = parts & BOILER_WORDS
            plain = re.sub(r"[^a-z]", "", name.lower())
            if told == {"header"} and parts & TITLE_WORDS:
                continue
            if plain in BOILER_WORDS or told and not parts - told - PLAIN_WORDS:
                boiler = True
            elif told:
                hint = True
            elif plain in MAIN_WORDS:
                main = True
    marks = tag in ("article", "main")
    # The name of an article's own element says how it is shown, not what it is.
    if boiler and marks and main:
        boiler, hint = False, True
    leaning = w["boiler"] * boiler + w["hint"] * (hint and not boiler) + w["article"] * marks + w["main"] * main
    return leaning, boiler or marks or main, (marks or main) and not boiler


def blocks(page: str) -> tuple[list[Block], list[Element]]:
    """The page's blocks of text in order, and the elements that hold them."""
    found: list[Block] = []
    elements = [Element(-1, 0.0, False, False)]
    stack: list[_Open] = [_Open("", 0)]
    current: Block | None = None
    at, links, skip = 0, 0, ""
    in_head = False

    def text(raw: str) -> None:
        nonlocal current
        if not raw or skip or in_head:
            return
        decoded = html.unescape(raw)
        if current is None:
            current = Block(stack[-1].element, stack[-1].tag, [])
        current.parts.append(decoded)
        if links:
            current.linked += len(decoded.strip())

    def end_block() -> None:
        nonlocal current
        if current is not None:
            current.text = BLANK.sub(" ", "".join(current.parts)).strip()
            if current.text:
                found.append(current)
        current = None

    for match in TOKEN.finditer(page):
        text(page[at : match.start()])
        at = match.end()
        if match[2] is None:
            continue
        closing, tag, attributes = bool(match[1]), match[2].lower(), match[3] or ""
        if skip:
            if closing and tag == skip:
                skip = ""
            continue
        if tag in RAW:
            if not closing and not attributes.rstrip().endswith("/"):
                skip = tag
            continue
        if tag in ("head", "body", "html"):
            end_block()
            in_head = tag == "head" and not closing
            continue
        if tag in INLINE:
            if tag == "a":
                links = max(0, links + (-1 if closing else 1))
            continue
        end_block()
        if tag in VOID:
            continue
        links = 0
        if closing:
            for i in range(len(stack) - 1, 0, -1):
                if stack[i].tag == tag:
                    del stack[i:]
                    break
            continue
        in_head = False
        while len(stack) > 1 and stack[-1].tag in CLOSES.get(tag, {"p"}):
            stack.pop()
        above = stack[-1].element
        around = elements[above]
        own, border, marks = named(tag, attributes, around.article)
        if tag in TEXT_TAGS and not own:
            # Its blocks stand in the element around it.
            stack.append(_Open(tag, above))
            continue
        leaning = min(HIGHEST, max(LOWEST, own + FADE * around.leaning))
        elements.append(Element(above, leaning, border, marks or around.article and own > WEIGHTS["boiler"] / 2))
        stack.append(_Open(tag, len(elements) - 1))
    # Text that opens a tag which never ends is markup, not text.
    rest = page[at:]
    text(rest if not re.match(r"<[a-zA-Z/!?]", rest) else "")
    end_block()
    return found, elements


def leaning(block: Block) -> float:
    """Log odds of content by what the block itself is."""
    w, n = WEIGHTS, len(block.text)
    value = w["base"]
    if block.tag == "p":
        value += w["paragraph"]
    elif re.fullmatch(r"h[1-6]", block.tag):
        value += w["heading"]
    elif block.tag in ("li", "td", "th", "dd", "dt"):
        value += w["item"]
    value += w["long"] * min(1.0, n / 120)
    if n < 25:
        value += w["short"]
    if re.search(r"[.!?:…。！？]['\"”’)]?$", block.text):
        value += w["sentence"]
    return value + w["links"] * min(1.0, block.linked / max(1, n))


class FlowNetwork:
    """Maximum flow by level graphs and blocking flows."""

    def __init__(self, nodes: int):
        self.heads: list[list[int]] = [[] for _ in range(nodes)]
        self.to: list[int] = []
        self.room: list[float] = []

    def join(self, a: int, b: int, there: float, back: float = 0.0) -> None:
        self.heads[a].append(len(self.to))
        self.to.append(b)
        self.room.append(there)
        self.heads[b].append(len(self.to))
        self.to.append(a)
        self.room.append(back)

    def source_side(self, source: int, sink: int) -> list[bool]:
        """Saturates the network; the nodes the source still reaches."""
        while True:
            level = [-1] * len(self.heads)
            level[source] = 0
            queue = deque([source])
            while queue:
                a = queue.popleft()
                for e in self.heads[a]:
                    if self.room[e] > 1e-9 and level[self.to[e]] < 0:
                        level[self.to[e]] = level[a] + 1
                        queue.append(self.to[e])
            if level[sink] < 0:
                return [x >= 0 for x in level]
            following = [0] * len(self.heads)
            path: list[int] = []
            a = source
            while True:
                if a == sink:
                    least = min(self.room[e] for e in path)
                    for e in path:
                        self.room[e] -= least
                        self.room[e ^ 1] += least
                    path, a = [], source
                    continue
                moved = False
                while following[a] < len(self.heads[a]):
                    e = self.heads[a][following[a]]
                    if self.room[e] > 1e-9 and level[self.to[e]] == level[a] + 1:
                        path.append(e)
                        a = self.to[e]
                        moved = True
                        break
                    following[a] += 1
                if not moved:
                    if not path:
                        break
                    a = self.to[path.pop() ^ 1]
                    following[a] += 1


def graph(found: list[Block], elements: list[Element]) -> tuple[list[float], list[tuple[int, int, float]]]:
    """Leaning of every node and (node, node, capacity) of the smoothness edges.

    Nodes are the blocks in order, then the elements that hold blocks. An element
    weighs as much as the blocks that stand in it directly.
    """
    used: dict[int, int] = {}
    below = [0] * len(elements)
    for block in found:
        e = block.element
        below[e] += 1
        while e >= 0 and e not in used:
            used[e] = len(found) + len(used)
            e = elements[e].parent
    any_article = any(elements[b.element].article and elements[b.element].leaning > 0 for b in found)
    costs = [leaning(b) for b in found] + [0.0] * len(used)
    edges: list[tuple[int, int, float]] = []
    for i, block in enumerate(found):
        element = elements[block.element]
        node = used[block.element]
        costs[node] += element.leaning + (WEIGHTS["outside"] if any_article and not element.article else 0.0)
        edges.append((i, node, TO_ELEMENT))
        if i:
            before = found[i - 1].element
            crosses = before != block.element and (_border(elements, before) != _border(elements, block.element))
            edges.append((i - 1, i, ACROSS if crosses else TO_NEXT))
    # A parent comes before its children.
    for e in sorted(used, reverse=True):
        parent = elements[e].parent
        if parent >= 0:
            below[parent] += below[e]
            edges.append((used[e], used[parent], ACROSS if elements[e].named else TO_PARENT * below[e]))
    return costs, edges


def _border(elements: list[Element], e: int) -> int:
    """The named container around an element."""
    while e > 0 and not elements[e].named:
        e = elements[e].parent
    return e


def label(found: list[Block], elements: list[Element]) -> list[bool]:
    """True for the blocks on the content side of the cut."""
    costs, edges = graph(found, elements)
    if all(c >= 0 for c in costs) or all(c <= 0 for c in costs):
        return [c > 0 or any(x > 0 for x in costs) for c in costs[: len(found)]]
    n = len(costs)
    network = FlowNetwork(n + 2)
    for i, cost in enumerate(costs):
        if cost > 0:
            network.join(n, i, cost)
        elif cost < 0:
            network.join(i, n + 1, -cost)
    for a, b, weight in edges:
        network.join(a, b, weight, weight)
    return network.source_side(n, n + 1)[: len(found)]


def main_text(page: str | None) -> str:
    if not page:
        return ""
    found, elements = blocks(page)
    return " ".join(b.text for b, keep in zip(found, label(found, elements), strict=True) if keep)


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars: one row a page."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(x) for x in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(x) for x in texts], pa.int64())],
                names=["page_id", "url", "text", "n_chars"],
            )

    chosen = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return map_arrow(chosen, run, "page_id long, url string, text string, n_chars long")
