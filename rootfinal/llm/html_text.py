"""Main text of a page by composite text density.

For each DOM node that a browser would show: characters of text, characters inside links, tags, and link tags below it. Density is
characters per tag, lowered as the share of link characters rises relative to the body's. A node's density sum adds those of its
children. Nothing else is removed before this scoring. The threshold is the least density on the path from the densest node to the
body. Of the nodes above it, the one of the largest sum is climbed from to the node that holds every block of text of a quarter or
more of its own blocks' mean density, and the page's heading. Containers outgrow their blocks, so blocks are held against blocks.

Elements of a furniture role (nav, footer, aside, forms, a page's header) and block elements with a furniture class word only lower what
density must show: a role counts a tenth, a class word a half of its blocks' mean density against that of the page's other
blocks, and what falls short is rejected, so the heading's wrappers and dense wrappers stay. Where an article or main element stands,
such nodes outside of it are rejected at any density. A class word on a wrapper of half of the page's text or on an inline element says nothing.

Null and empty pages, and those without text, give an empty text; pages of any length are read whole. Broken markup is read as a
browser would: unclosed paragraphs end at the next block, stray end tags are passed over. Of equal sums the node with more
characters wins, then the first. Rows are independent, repeated ones too; an empty table gives no rows. A kept column named like an output gets `_in` behind its name.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from html.parser import HTMLParser

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .shared import carried

# fixed values: HTML element names by role
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr b bdi bdo cite code data dfn em font i kbd mark q s samp small span strong sub sup time tt u var wbr del ins label big strike acronym".split())
FORMAT = (INLINE - {"a"}) | {"br", "wbr", "img"}
UNSEEN = frozenset("script style head noscript template svg iframe object button select textarea datalist".split())
HARD_ROLES = frozenset("nav footer aside menu dialog".split())
CLOSES_P = frozenset("address article aside blockquote div dl fieldset figure footer form h1 h2 h3 h4 h5 h6 header hr main nav ol p pre section table ul".split())
# fixed values: class and id words of page furniture
FURNITURE = re.compile(r"(?:^|[\s_-])(?:ads?|advert\w*|banner|promo\w*|sponsor\w*|cookies?|consent|notice|sidebar|menu|nav\w*|breadcrumbs?|header|footer|comments?|related|share|social|subscribe|newsletter|popup|modal|widget|login)(?:$|[\s_-])", re.I)
_BLANK = re.compile(r"\s+")


class Node:
    __slots__ = ("tag", "parent", "children", "drop", "named", "role", "chars", "links", "tags", "link_tags", "density", "total")

    def __init__(self, tag: str, parent: Node | None, drop: bool, named: bool = False, role: bool = False):
        self.tag, self.parent, self.drop, self.named, self.role = tag, parent, drop, named, role
        self.children: list[Node | str] = []
        self.chars = self.links = self.tags = self.link_tags = 0
        self.density = self.total = 0.0


class _Tree(HTMLParser):
    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.root = self.at = Node("#root", None, False)
        self.open: dict[str, int] = {}

    def handle_starttag(self, tag, attrs):
        if tag in CLOSES_P and self.open.get("p"):
            self.handle_endtag("p")
        if tag in ("li", "tr", "td", "th", "dd", "dt", "option") and self.at.tag == tag:
            self.handle_endtag(tag)
        named = " ".join(v for k, v in attrs if k in ("class", "id", "role") and v)
        # a page's header is furniture, an article's own header is not
        role = tag in HARD_ROLES or tag == "form" or tag == "header" and not self.open.get("article")
        word = bool(named and tag not in INLINE and tag not in ("html", "body", "article", "main") and FURNITURE.search(named))
        node = Node(tag, self.at, self.at.drop or tag in UNSEEN, word, role)
        self.at.children.append(node)
        if tag not in VOID:
            self.at = node
            self.open[tag] = self.open.get(tag, 0) + 1

    def handle_startendtag(self, tag, attrs):
        self.handle_starttag(tag, attrs)
        if tag not in VOID and tag not in ("div", "p", "span", "a"):
            self.handle_endtag(tag)

    def handle_endtag(self, tag):
        if not self.open.get(tag):
            return
        while self.at.parent is not None:
            closed = self.at.tag
            self.open[closed] -= 1
            self.at = self.at.parent
            if closed == tag:
                return

    def handle_data(self, data):
        self.at.children.append(data)


def _score(root: Node) -> list[Node]:
    """Nodes in page order with their counts, densities and sums."""
    order, todo = [], [root]
    while todo:
        n = todo.pop()
        order.append(n)
        todo.extend(c for c in reversed(n.children) if isinstance(c, Node))
    for n in reversed(order):
        for c in n.children:
            if isinstance(c, str):
                n.chars += 0 if n.drop else len(_BLANK.sub("", c))
            elif not c.drop:
                n.chars += c.chars
                n.links += c.links
                n.tags += c.tags + (c.tag not in FORMAT)
                n.link_tags += c.link_tags + (c.tag == "a")
        if n.tag == "a":
            n.links = n.chars
    whole = root.chars or 1
    share = root.links / whole
    for n in reversed(order):
        if n.chars and not n.drop:
            plain = max(1, n.chars - n.links)
            base = math.log(n.chars / plain * n.links + share * n.chars + math.e)
            n.density = n.chars / max(1, n.tags) * max(0.0, math.log(1 + n.chars / max(1, n.links) * max(1, n.tags) / max(1, n.link_tags)) / max(1.0, math.log(base + 1)))
        # text formatting makes no node of its own: a block that holds text adds its density once
        own = any(c.strip() if isinstance(c, str) else c.chars and c.tag in INLINE for c in n.children)
        n.total = sum(c.density for c in n.children if isinstance(c, Node) and c.tag not in INLINE) + (n.density if own else 0.0)
    return order


def _path(n: Node | None) -> list[Node]:
    """`n` and its ancestors, the root last."""
    out = []
    while n is not None:
        out.append(n)
        n = n.parent
    return out


def _usable(order: list[Node]) -> list[Node]:
    return [n for n in order if not n.drop and n.chars and n.tag not in INLINE]


def _is_block(n: Node) -> bool:
    return any(c.strip() if isinstance(c, str) else c.tag in INLINE and c.chars and not c.drop for c in n.children)


def _mean_density(blocks: list[Node]) -> float:
    """By characters, so that short lines weigh little."""
    return sum(n.density * n.chars for n in blocks) / (sum(n.chars for n in blocks) or 1)


def _inside(order: list[Node], tops: set[Node]) -> set[Node]:
    out: set[Node] = set()
    for n in order:
        if n in tops or n.parent in out:
            out.add(n)
    return out


def _blocks_of(top: Node) -> list[Node]:
    out, todo = [], [top]
    while todo:
        n = todo.pop()
        if not n.drop and n.chars and n.tag not in INLINE and _is_block(n):
            out.append(n)
        todo.extend(c for c in n.children if isinstance(c, Node))
    return out


def _reject_furniture(root: Node) -> list[Node]:
    """Scored nodes in page order once furniture whose density falls short is dropped."""
    order = _score(root)
    hinted = [n for n in order if (n.named or n.role) and not n.drop]
    if not hinted:
        return order
    usable = _usable(order)
    hard = _inside(order, {n for n in hinted if n.tag in HARD_ROLES})
    kept = {p for n in usable if n.tag in ("article", "main", "h1") and n not in hard for p in _path(n)}
    blocks = [n for n in usable if _is_block(n)]
    marked = _inside(order, {n for n in hinted if n not in kept})
    least = _mean_density([n for n in blocks if n not in marked] or blocks)
    core = _inside(order, {n for n in usable if n.tag in ("article", "main") and n not in marked})
    for n in hinted:
        if n in kept:
            continue
        if core and n not in core:
            n.drop = True
        elif n.role:
            n.drop = 0.1 * _mean_density(_blocks_of(n)) < least
        else:
            n.drop = 2 * n.chars < root.chars and 2 * _mean_density(_blocks_of(n)) < least
    for n in order:
        n.drop = n.drop or n.parent is not None and n.parent.drop
        n.chars = n.links = n.tags = n.link_tags = 0
        n.density = n.total = 0.0
    return _score(root)


def _main(root: Node) -> list[Node]:
    """The tops of the main text, in page order."""
    order = _reject_furniture(root)
    usable = _usable(order)
    if not usable:
        return [root]
    n = max(usable, key=lambda n: n.density)
    least = n.density
    while n is not None and n.tag != "#root":
        least = min(least, n.density)
        if n.tag == "body":
            break
        n = n.parent
    best = max((n for n in usable if n.density >= least and n.tag not in ("#root", "html")), key=lambda n: (n.total, n.chars), default=root)
    trail = _path(best)
    place = {n: i for i, n in enumerate(trail)}

    def held(n: Node) -> int:
        """How far to climb for a node that holds `n` too."""
        while n not in place:
            n = n.parent
        return place[n]

    blocks = [n for n in usable if _is_block(n)]
    enough = 0.25 * _mean_density([n for n in blocks if not held(n)])
    aside = _inside(order, {n for n in order if (n.named or n.role) and n not in place})
    up = max((held(n) for n in blocks if n.density >= enough and n not in aside), default=0)
    heads = [n for n in usable if n.tag == "h1"]
    if heads:
        head = min(heads, key=held)
        if held(head) > up and trail[held(head)].tag in ("body", "html", "#root"):
            # on the way to the whole body only the heading is taken along
            return sorted([trail[up], head], key=order.index)
        up = max(up, held(head))
    return [trail[up]]


def main_text(html: str) -> str:
    tree = _Tree()
    tree.feed(html)
    tree.close()
    blocks: list[str] = []
    part: list[str] = []

    def end() -> None:
        text = _BLANK.sub(" ", "".join(part)).strip()
        part.clear()
        if text:
            blocks.append(text)

    todo: list[Node | str | None] = _main(tree.root)[::-1]
    while todo:
        n = todo.pop()
        if n is None:
            end()
        elif isinstance(n, str):
            part.append(n)
        elif not n.drop:
            if n.tag not in INLINE:
                end()
                todo.append(None)
            todo.extend(reversed(n.children))
    end()
    return " ".join(blocks)


def extract(pages: DataFrame, keep: list[str], html: str = "html") -> DataFrame:
    base = pages.select(*carried(keep, ["text", "n_chars"]), F.col(html).alias("__html"))
    schema = T.StructType([*base.schema.fields[:-1], T.StructField("text", T.StringType()), T.StructField("n_chars", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(t.as_py() or "") for t in batch.column("__html")]
            yield pa.RecordBatch.from_arrays([*[batch.column(i) for i in range(len(keep))], pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())], names=[f.name for f in schema])

    return base.mapInArrow(run, schema)
