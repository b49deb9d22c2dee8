"""Main text of web pages by tree scoring.

The whole page is parsed into a tree and scored: every paragraph gives points for its length and its commas to its
ancestors, half as many at each step up, and a tenth of that from within a part that is marked as beside an article (a
menu, header, footer, sidebar, notice, advert, form or comments, by element, role and class words); a container's points
are discounted by its link density. The container worth most is chosen; an ``article`` or ``main`` around it
takes its place if it is worth a quarter of it by the same measure, and otherwise siblings that score well or read as
text are kept with it. Only inside that choice are marked parts left out.

Text: character references are decoded, white space inside a block becomes one space, blocks are trimmed and joined
in page order by one space. Nothing else is dropped or cut.

Inputs: null or empty html gives an empty text; unclosed, stray or deeply nested tags are accepted, and pages of any
length are read in time in proportion to it; of containers worth the same the first in page order is chosen; repeated rows
give repeated results; an empty table gives none; extra columns, of whatever name, are not returned.
"""

from __future__ import annotations

import re
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame

from cubedensity.llm.markup import tokens

#: fixed values: HTML element classes
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr img".split())
OUT = frozenset("head script style noscript template nav header footer aside form button input select textarea iframe object embed svg canvas audio video dialog menu title".split())
CLOSES_P = frozenset("address article aside blockquote details div dl fieldset figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())
SAME = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}, "tbody": {"tr", "td", "th", "thead", "tbody"}}
FENCE = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"tr", "table"}, "th": {"tr", "table"}, "option": {"select"}, "tbody": {"table"}}
P_FENCE = {"table", "td", "th", "button"}
#: fixed values: class and id words of parts beside the article
OUT_WORDS = frozenset(
    "ad ads adv advert advertisement advertising adsense sponsor sponsored promo promotion banner nav navbar navigation menu breadcrumb breadcrumbs "
    "header masthead footer sidebar aside rail widget cookie cookies consent gdpr notice notices alert popup modal overlay newsletter subscribe "
    "subscription signup login form search comment comments disqus reply replies respond share sharing social related recommended pagination pager toolbar skip".split()
)
OUT_ROLES = frozenset("navigation banner contentinfo complementary search alert dialog form menu menubar toolbar".split())
KEEP_TAGS = frozenset("html body article main".split())
PARAGRAPH = frozenset("p pre td blockquote li dd figcaption".split())
HEADING = frozenset("h1 h2 h3 h4 h5 h6".split())
#: share of its points that a paragraph inside a marked part gives
BESIDE = 0.1
#: worth, as a share of the best, of an article around it and of a sibling that is kept with it
AROUND, SIBLING = 0.25, 0.2
#: steps up that points go
STEPS = 5

_ATTR = re.compile(r"""(?<![\w-])(class|id|role|style|hidden|aria-hidden)(?:\s*=\s*("[^"]*"|'[^']*'|[^\s"'>]+))?(?![\w-])""", re.I)
_WORDS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")


class Node:
    __slots__ = ("tag", "items", "parent", "marked", "beside", "linking", "home", "block", "score", "text", "linked", "commas", "size")

    def __init__(self, tag, parent, marked):
        self.tag, self.parent, self.marked = tag, parent, marked
        self.items: list = []
        self.score = 0.0
        self.text = self.linked = self.commas = self.size = 0
        if parent is None:
            self.beside = self.linking = self.home = False
            self.block = self
        else:
            self.beside = parent.beside or marked
            self.linking = parent.linking or tag == "a"
            self.home = parent.home or tag in ("article", "main")
            self.block = parent.block if tag in INLINE else self


def _beside(tag: str, attrs: str) -> bool:
    """Whether an element is marked as a part beside the article."""
    if tag in OUT:
        return True
    if not attrs or tag in KEEP_TAGS:
        return False
    for name, value in _ATTR.findall(attrs):
        name, value = name.lower(), value.strip("\"'")
        if name in ("class", "id"):
            if any(w.lower() in OUT_WORDS for w in _WORDS.findall(value)):
                return True
        elif name == "role":
            if value.lower() in OUT_ROLES:
                return True
        elif name == "hidden" or name == "aria-hidden" and value == "true" or name == "style" and "display:none" in value.replace(" ", "").lower():
            return True
    return False


def parse(html: str) -> list[Node]:
    """The nodes of a page, parents before children, in page order."""
    root = Node("#root", None, False)
    order, stack = [root], [root]
    open_at: dict[str, list[int]] = {}  # places in the stack of the open elements of a name

    def cut(to: int) -> None:
        while len(stack) > to:
            open_at[stack.pop().tag].pop()

    def deepest(tags) -> int:
        return max((open_at[t][-1] for t in tags if open_at.get(t)), default=-1)

    for kind, tag, attrs in tokens(html):
        node = stack[-1]
        if kind == "text":
            node.items.append(tag)
        elif kind == "close":
            if open_at.get(tag):
                cut(open_at[tag][-1])
            elif tag == "p":
                order.append(Node("p", node, False))
                node.items.append(order[-1])
        elif kind == "open":
            if tag in CLOSES_P or tag in SAME:
                shut, fence = (SAME[tag], FENCE[tag]) if tag in SAME else ({"p"}, P_FENCE)
                at = deepest(shut)
                if at > deepest(fence):
                    cut(at)
                    node = stack[-1]
            if tag in VOID and tag not in ("br", "hr"):
                continue
            child = Node(tag, node, _beside(tag, attrs))
            order.append(child)
            node.items.append(child)
            if tag in VOID or attrs.endswith("/") and tag in ("path", "circle", "use"):
                continue
            open_at.setdefault(tag, []).append(len(stack))
            stack.append(child)
        else:  # the content of a raw element is no text of the page
            cut(len(stack) - 1)
    return order


def score(order: list[Node]) -> None:
    """Text and link sizes of all nodes, and the points that reach them."""
    for node in reversed(order):
        own = "".join([x for x in node.items if type(x) is str])
        size = len(" ".join(own.split()))
        node.text += size
        if size and not node.linking:
            node.block.size += size
            node.block.commas += own.count(",") + own.count("，") + own.count("、")
        if node.tag == "a":
            node.linked = node.text
        if node.parent is not None:
            node.parent.text += node.text
            node.parent.linked += node.linked
    for node in order:
        if node.size and node.parent is not None:
            # the text of a paragraph counts for the block around it, text directly in a container for the container
            up, points = node.parent if node.tag in PARAGRAPH or node.tag in HEADING else node, 1 + node.commas + min(3.0, node.size / 100)
            points *= BESIDE if node.beside else 1.0
            for _ in range(STEPS):
                if up.parent is None:
                    break
                up.score += points
                up, points = up.parent, points / 2


def worth(node: Node) -> float:
    linked = node.linked / node.text if node.text else 0.0
    return node.score * (1 - linked)


def article(order: list[Node]) -> list[Node]:
    """The nodes that hold the article, in page order."""
    score(order)
    best, most = order[0], 0.0
    for node in order:
        if node.tag not in INLINE and node.tag not in ("#root", "html"):
            value = worth(node)
            if value > most:
                best, most = node, value
    if not most:
        return [best]
    up = best
    while up is not None and up.tag not in ("article", "main"):
        up = up.parent
    if up is not None and worth(up) >= AROUND * most:
        return [up]
    kept = []
    for x in best.parent.items:
        if type(x) is Node and (x is best or not x.marked):
            prose = x.tag in PARAGRAPH and x.text and x.linked < 0.25 * x.text
            if x is best or x.tag in HEADING or prose or worth(x) >= SIBLING * most:
                kept.append(x)
    return kept


def text_of(nodes: list[Node]) -> str:
    """The text of the chosen nodes without the marked parts in them; of an article's own header the headings are kept."""
    parts: list[str] = []
    for top in nodes:
        stack: list = [(top, True)]
        while stack:
            x, wanted = stack.pop()
            if type(x) is str:
                if wanted:
                    parts.append(unescape(x) if "&" in x else x)
                continue
            if x.marked and x is not top:
                if x.tag != "header" or not x.parent.home:
                    continue
                wanted = False
            elif not wanted and x.tag in ("h1", "h2", "h3"):
                wanted = True
            if x.tag not in INLINE:
                parts.append(" ")
                stack.append((" ", True))
            stack += [(y, wanted) for y in reversed(x.items)]
    return " ".join("".join(parts).split())


def extract(html: str | None) -> str:
    """Main text of a page."""
    return text_of(article(parse(html))) if html else ""


def main_text(pages: DataFrame) -> DataFrame:
    """``pages(page_id, url, html) -> (page_id, url, text, n_chars)``."""

    def run(batches):
        for batch in batches:
            texts = [extract(h.as_py()) for h in batch.column("html")]
            yield pa.RecordBatch.from_arrays(
                [batch.column("page_id"), batch.column("url"), pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())],
                names=["page_id", "url", "text", "n_chars"],
            )

    kind = dict(pages.dtypes)["page_id"]
    return pages.select("page_id", "url", "html").mapInArrow(run, f"page_id {kind}, url string, text string, n_chars bigint")
