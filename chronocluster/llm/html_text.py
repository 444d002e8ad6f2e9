"""Main text of web pages by tree scoring.

The page becomes a light tree.  Navigation, notices, forms and the like are pruned by tag, role
and name.  Every paragraph then passes points for its length and its commas to its ancestors, the
farther the fewer; a container's points are discounted by the share of its text that lies in
links.  The best container is kept with those siblings that score well enough beside it.
"""

from __future__ import annotations

import html
import re
from functools import lru_cache

from pyspark.sql import DataFrame

from .common import map_texts

# Names of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style title textarea noscript template iframe xmp".split())
PRUNED = frozenset("head script style noscript template iframe object svg canvas nav aside footer form button select textarea input dialog menu title".split())
BLOCK = frozenset(
    "address article aside blockquote body center dd details div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html li main nav ol p pre section summary table tbody td tfoot th thead tr ul".split()
)
CLOSES_P = BLOCK - frozenset("body html".split())
SAME_CLOSES = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
BARRIER = frozenset("table ul ol dl article section div main body html td th".split())
P_STOPS = BARRIER - {"div", "section"}
LIST_STOPS = frozenset("ul ol dl table select".split())
CELLS, TABLE_PARTS = frozenset("td th table".split()), frozenset("tr tbody table".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
PARAGRAPH = frozenset("p pre blockquote td h1 h2 h3 h4 h5 h6 li dd".split())
MAIN = frozenset(("article", "main"))
CONTAINER = frozenset("article main section div body td blockquote html".split())
UNLIKELY = re.compile(
    r"(?i)(?:^|[\s_-])(?:ads?|advert\w*|sponsor\w*|promo\w*|banner\w*|cookies?|consent|notice\w*|newsletter|subscri\w*|sidebar\w*|side|menu\w*|nav\w*|navbar|breadcrumbs?|footer\w*|masthead|comments?\w*|disqus|replies|respond|share\w*|sharing|social\w*|related\w*|recommend\w*|popup|modal|overlay|widget\w*|toolbar|pagination|pager|login|signup|skip\w*|copyright|legal|hidden)(?:$|[\s_-])"
)
ROLES = frozenset("navigation banner contentinfo complementary search dialog alert alertdialog menu menubar toolbar form".split())

TAG = re.compile(r"""<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>"']++|"[^"]*"|'[^']*')*+)(?:>|\Z)|[^<]+|<""", re.S)
LOOSE_TAG = re.compile(r"<(/?)([a-zA-Z][^\s/>]*)([^>]*)(?:>|\Z)", re.S)
NAMED = re.compile(r"""(?is)\b(class|id|role|hidden|aria-hidden|style)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""")


class Node:
    __slots__ = ("tag", "parent", "items", "pruned", "points", "size", "linked", "run", "commas", "inner")

    def __init__(self, tag: str, parent: Node | None, pruned: bool = False):
        self.tag, self.parent, self.pruned = tag, parent, pruned
        self.items: list[Node | str] = []
        #: Points, characters and those in links below; characters and commas outside of inner blocks; whether there are such.
        self.points, self.size, self.linked, self.run, self.commas, self.inner = 0.0, 0, 0, 0, 0, False
        if parent is not None:
            parent.items.append(self)

    def kept(self) -> list[Node]:
        return [x for x in self.items if not isinstance(x, str) and not x.pruned]


class Open:
    """The open elements; for each tag the places of those that bear it."""

    def __init__(self, root: Node):
        self.nodes, self.places = [root], {}

    def push(self, node: Node) -> None:
        self.places.setdefault(node.tag, []).append(len(self.nodes))
        self.nodes.append(node)

    def last(self, tags) -> int:
        """The place of the innermost open element of these tags, 0 without one."""
        return max((p[-1] for t in tags if (p := self.places.get(t))), default=0)

    def close(self, tags, stop) -> None:
        """Leave the innermost open element of the tags, unless one of stop lies within it."""
        at = self.last(tags)
        if at > self.last(stop):
            while len(self.nodes) > at:
                self.places[self.nodes.pop().tag].pop()


@lru_cache(maxsize=4096)
def unwanted(tag: str, attributes: str) -> bool:
    if tag in PRUNED:
        return True
    for name, *values in NAMED.findall(attributes):
        name, value = name.lower(), "".join(values)
        if name in ("class", "id") and tag not in ("body", "html", "article", "main") and UNLIKELY.search(value):
            return True
        if name == "role" and value.lower() in ROLES or name == "hidden" or name == "aria-hidden" and value == "true":
            return True
        if name == "style" and re.search(r"(?i)display\s*:\s*none|visibility\s*:\s*hidden", value):
            return True
    return False


def parse(page: str) -> Node:
    root = Node("#root", None)
    open_ = Open(root)
    at, end = 0, len(page)
    while at < end:
        m = TAG.match(page, at)
        at = m.end()
        if m.group(2) is None:
            s = m.group()
            if s == "<" and (loose := LOOSE_TAG.match(page, m.start())):
                m, at = loose, loose.end()
            else:
                if not s.startswith(("<!", "<?")):
                    open_.nodes[-1].items.append(html.unescape(s))
                continue
        tag = m.group(2).lower()
        if m.group(1):
            open_.close({tag}, () if tag in BARRIER or tag in TABLE_PARTS else CELLS)
            continue
        if tag in ("html", "body") and open_.places.get(tag):
            continue
        if tag in CLOSES_P:
            open_.close({"p"}, P_STOPS)
        if tag in SAME_CLOSES:
            open_.close(SAME_CLOSES[tag], LIST_STOPS)
        if tag == "body":
            open_.close({"head"}, ())
        banner = tag == "header" and open_.nodes[-1].tag in ("#root", "html", "body")
        made = Node(tag, open_.nodes[-1], banner or unwanted(tag, m.group(3)))
        if tag in RAW:
            close = re.compile(rf"</{re.escape(tag)}\b[^>]*>|\Z", re.I).search(page, at)
            at = close.end()
        elif tag not in VOID and not m.group(3).rstrip().endswith("/"):
            open_.push(made)
    return root


def blocks(node: Node) -> list[str]:
    """The texts of the blocks below node, in page order."""
    out: list[str] = []
    held: list[str] = []

    def flush() -> None:
        if s := " ".join("".join(held).split()):
            out.append(s)
        held.clear()

    stack: list[Node | str | None] = [node]
    while stack:
        x = stack.pop()
        if x is None:
            flush()
        elif isinstance(x, str):
            held.append(x)
        elif x.tag == "br":
            held.append("\n")
        elif not x.pruned or x is node:
            if x.tag in BLOCK:
                flush()
                stack.append(None)
            stack.extend(reversed(x.items))
    flush()
    return out


def _measure(root: Node) -> list[Node]:
    """Set the numbers of every node that is kept, each in one visit; returns the nodes in page order.

    A paragraph gives points to its container.  A container passes all it has to its parent, and half if
    the parent has text elsewhere too, so wrappers around one thing cost nothing and no depth is too deep.
    """
    order: list[Node] = []
    stack = [(root, False)]
    while stack:
        node, link = stack.pop()
        order.append(node)
        link = link or node.tag == "a"
        texts = [s for s in node.items if isinstance(s, str)]
        node.size = node.run = sum(len(s.strip()) for s in texts)
        node.linked, node.commas = node.size if link else 0, sum(s.count(",") for s in texts)
        stack.extend((x, link) for x in reversed(node.kept()))
    for node in reversed(order):
        children = node.kept()
        parts = sum(x.size > 0 for x in children) + (node.size > 0)
        for x in children:
            if x.tag in BLOCK or x.inner:
                node.inner = True
            else:
                node.run += x.run
                node.commas += x.commas
            node.size += x.size
            node.linked += x.linked
            node.points += x.points if parts < 2 or x.tag in PARAGRAPH else x.points / 2
        if node.run and node.tag in (BLOCK | {"#root"}):
            node.points += (1 + node.commas + min(node.run / 100, 3)) * (0.25 if node.tag in HEADINGS else 1)
    return order


def _density(node: Node) -> float:
    return node.linked / node.size if node.size else 1.0


def _stands(x: Node, least: float) -> bool:
    """A sibling of the best container, or a part of one that was widened, that belongs to the text."""
    if not x.size or x.tag == "header":
        return False
    if x.tag in HEADINGS:
        return x.linked < x.size
    return x.points * (1 - _density(x)) >= least or _density(x) < 0.25 and (x.size > 80 or not x.linked and any(re.search(r"[.!?]$", b) for b in blocks(x)))


def extract(page: str | None) -> str:
    """The main text of a page: blocks joined by an empty line; empty if there is none."""
    if not page:
        return ""
    root = parse(page)
    order = _measure(root)
    scored = [((x.points * 1.5 + 5 * (x.size > 0) if x.tag in MAIN else x.points) * (1 - _density(x)), x) for x in order if x.tag in CONTAINER or x is root]
    points, best = max(scored, key=lambda x: x[0])
    if points <= 0:
        return "\n\n".join(blocks(root))
    around = best
    while around is not None and around.tag not in MAIN:
        around = around.parent
    best = around or best
    least = max(3.0, 0.2 * best.points * (1 - _density(best)))
    wide = best
    if around is None:
        # Ancestors that hold another container of like score are parts of one text.
        below = best
        while (up := below.parent) is not None:
            if any(x is not below and x.tag not in PARAGRAPH and x.tag != "header" and x.points * (1 - _density(x)) >= least for x in up.kept()):
                wide = up
            below = up
    if wide is not best:
        keep = {id(x) for x in wide.kept() if _stands(x, least)}
        for x in wide.kept():
            x.pruned = x.pruned or x.tag in BLOCK and id(x) not in keep
        kept = [wide]
    elif best.parent is not None:
        beside = around is None or best.parent.tag == "main"
        kept = [x for x in best.parent.kept() if x is best or (_stands(x, least) if beside else x.tag == best.tag and x.points * (1 - _density(x)) >= max(10.0, least))]
    else:
        kept = [best]
    return "\n\n".join(b for x in kept for b in blocks(x))


def main_texts(pages: DataFrame, keys: list[str], markup: str = "html") -> DataFrame:
    """Per row: keys, text, n_chars (code points).  Null or empty markup gives an empty text; nothing is shuffled."""

    def kernel():
        def run(rows):
            texts = [extract(r) for r in rows]
            return [texts, [len(t) for t in texts]]

        return run

    return map_texts(pages, keys, markup, kernel, [("text", "string"), ("n_chars", "bigint")])
