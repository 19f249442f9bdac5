"""Main text of HTML pages by composite text density."""

from __future__ import annotations

import html
import math
import re
from collections import Counter
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Element names by role.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript iframe noembed noframes xmp svg math template".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
CLOSES_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section table ul".split())
SIBLINGS = {"li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr", "td", "th"}, {"table"}), "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "option": ({"option"}, {"select"}), "tbody": ({"tbody", "thead", "tfoot", "tr", "td", "th"}, {"table"})}
DROPPED = frozenset("head nav aside footer form button select input script style noscript iframe template svg math canvas object embed audio video dialog menu title textarea".split())
#: Words of class and id names and roles that mark what is not the article.
FRAME_WORDS = frozenset("nav navbar navigation menu menus breadcrumb breadcrumbs footer sidebar aside ad ads advert adverts advertisement advertising sponsor sponsored promo promotion banner cookie cookies consent gdpr notice notices alert popup modal newsletter subscribe subscription signup share sharing social related recommended comment comments reply replies respond disqus widget widgets toolbar pagination pager login search skip copyright masthead complementary contentinfo paywall disclaimer".split())
HEADER_WORDS = frozenset("header topbar".split())
COMMENT_WORDS = frozenset("comment comments reply replies respond disqus".split())

_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[(?P<cdata>.*?)(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(?P<close>/?)(?P<name>[A-Za-z][^\s/>]*)(?P<attrs>(?:=\s*+(?:\"[^\"]*\"|'[^']*')|[^>=]++|=)*+)(?:>|\Z)", re.S)
#: One attribute: its name, and its value in double, single or no quotes.
_ATTR = re.compile(r"([^\s\"'<>/=][^\s/>=]*)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>][^\s>]*)))?")
_HIDING = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden", re.I)
_WORD = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")


FOREIGN = frozenset("svg math".split())


class Node:
    __slots__ = ("chars", "density", "framed", "hidden", "items", "link_chars", "link_tags", "name", "parent", "sum", "tags", "words")

    def __init__(self, name: str, parent: Node | None, words: frozenset = frozenset(), hidden: bool = False):
        self.name, self.parent, self.words, self.hidden = name, parent, words, hidden
        self.items: list[Node | str] = []


def attributes(source: str) -> tuple[frozenset, bool, bool]:
    """Of the attributes of a tag: words of class, id and role, whether it is hidden, and whether a slash ends the tag."""
    words, hidden, end = [], False, 0
    for a in _ATTR.finditer(source):
        key, value, end = a[1].lower(), a[2] or a[3] or a[4] or "", a.end()
        if key in ("class", "id", "role"):
            words += [w.lower() for w in _WORD.findall(value)]
        elif key == "hidden" or (key == "aria-hidden" and value.lower() == "true") or (key == "style" and _HIDING.search(value)):
            hidden = True
    return frozenset(words), hidden, "/" in source[end:]


def parse(page: str) -> Node:
    """A tree of the page; end tags that HTML lets authors leave out are supplied, unknown ones ignored. Linear in the
    page: open elements are counted by name, so a tag that closes nothing looks at none of them."""
    root = Node("html", None)
    stack, opened = [root], Counter()
    pos, n = 0, len(page)

    def close(depth: int) -> None:
        for x in stack[depth:]:
            opened[x.name] -= 1
        del stack[depth:]

    while pos < n:
        m = _TAG.search(page, pos)
        if m is None:
            stack[-1].items.append(html.unescape(page[pos:]))
            break
        if m.start() > pos:
            stack[-1].items.append(html.unescape(page[pos : m.start()]))
        pos = max(m.end(), m.start() + 1)
        if m["cdata"] is not None:
            stack[-1].items.append(m["cdata"])
        name = (m["name"] or "").lower()
        if not name:
            continue
        if m["close"]:
            at = len(stack) - 1
            while opened[name] and at and stack[at].name != name:
                if stack[at].name in ("article", "table", "td", "th") and name not in ("html", "body", "article", "main", "table", "div", "section"):
                    break
                at -= 1
            if at and stack[at].name == name:
                close(at)
            continue
        if name == "html":
            continue
        if name in CLOSES_P and opened["p"]:
            at = len(stack) - 1
            while at and stack[at].name in INLINE:
                at -= 1
            if stack[at].name == "p":
                close(at)
        if name in SIBLINGS and any(opened[x] for x in SIBLINGS[name][0]):
            ends, scope = SIBLINGS[name]
            at, last = len(stack) - 1, None
            while at and stack[at].name not in scope:
                if stack[at].name in ends:
                    last = at
                at -= 1
            if last is not None:
                close(last)
        words, hidden, ended = attributes(m["attrs"]) if m["attrs"] and not m["attrs"].isspace() else (frozenset(), False, False)
        node = Node(name, stack[-1], words, hidden)
        stack[-1].items.append(node)
        if ended and (name in FOREIGN or name not in RAW):
            continue
        if name in RAW:
            end = re.compile(rf"</{re.escape(name)}(?=[\s/>])[^>]*(?:>|\Z)", re.I).search(page, pos)
            pos = end.end() if end else n
        elif name not in VOID:
            stack.append(node)
            opened[name] += 1
    return root


def _nodes(root: Node) -> list[Node]:
    """All nodes, parents first."""
    out = [root]
    for node in out:
        out += [x for x in node.items if isinstance(x, Node)]
    return out


def _own_chars(node: Node) -> int:
    return sum(len("".join(x.split())) for x in node.items if isinstance(x, str))


def measure(root: Node) -> list[Node]:
    """Fill in characters, tags and their parts in links, composite density and density sum of each node.

    Inline elements are part of the text they stand in: they have no density of their own, and but for links
    they are no tags; block elements inside them count for the block around."""
    nodes = _nodes(root)
    for node in reversed(nodes):
        kids = [x for x in node.items if isinstance(x, Node)]
        node.chars = _own_chars(node) + sum(k.chars for k in kids)
        node.tags = sum(k.tags + (k.name not in INLINE or k.name == "a") for k in kids)
        node.link_chars = node.chars if node.name == "a" else sum(k.link_chars for k in kids)
        node.link_tags = node.tags if node.name == "a" else sum(k.link_tags + (k.name == "a") for k in kids)
    share = root.link_chars / max(1, root.chars)
    for node in reversed(nodes):
        c, t, lc, lt = node.chars, max(1, node.tags), max(1, node.link_chars), max(1, node.link_tags)
        plain = max(1, c - node.link_chars)
        base = math.log(c / plain * node.link_chars + share * c + math.e)
        node.density = c / t * math.log(max(c / lc * (t / lt), 1e-9)) / math.log(base) if c and base > 1 else float(c) / t
        node.sum = sum(x.sum if x.name in INLINE else x.density for x in node.items if isinstance(x, Node))
    return nodes


def _prune(root: Node) -> None:
    """Take out what never is article text: menus, forms, notices and the like, by element and by name.
    A wrapper whose name alone speaks against it stays if it holds the article or most of the text. Linear: what a
    node holds is counted once, from the leaves up."""
    nodes = _nodes(root)
    for node in reversed(nodes):
        kids = [x for x in node.items if isinstance(x, Node)]
        node.chars = _own_chars(node) + sum(k.chars for k in kids)
        node.framed = node.name in ("article", "main") or any(k.framed for k in kids)
    total = max(1, root.chars)
    todo = [(root, False)]
    while todo:
        node, inside = todo.pop()
        inside = inside or node.name in ("article", "main")
        kept = []
        for x in node.items:
            if isinstance(x, Node):
                drop = x.hidden or x.name in DROPPED or (x.name == "header" and not inside)
                if not drop and x.name not in ("body", "html", "main") and (x.words & FRAME_WORDS or (x.words & HEADER_WORDS and not inside)):
                    drop = not (x.words.isdisjoint(COMMENT_WORDS) and (x.framed or x.chars > 0.6 * total))
                if drop:
                    kept.append(" " if x.name in INLINE else Node("br", node))
                    continue
                todo.append((x, inside))
            kept.append(x)
        node.items = kept


def _texts(node: Node) -> list[str]:
    """Blocks of text in page order, white space made single."""
    blocks, now = [], []

    def end() -> None:
        text = " ".join("".join(now).split())
        now.clear()
        if text:
            blocks.append(text)

    work: list = [node]
    while work:
        x = work.pop()
        if x is None:
            end()
        elif isinstance(x, str):
            now.append(x)
        else:
            block = x.name not in INLINE
            if block:
                end()
                work.append(None)
            work += reversed(x.items)
    end()
    return blocks


def main_text(page: str) -> str:
    """The article of a page: blocks in page order joined by one space; empty if there is none.

    Densities are characters per tag, lowered by the share of links. The node whose children's densities
    sum highest leads; the least density on its path up to the body is the threshold. From the body down,
    each node at or over the threshold gives the subtree with the highest sum in it; of nodes below
    the threshold, only children are looked at. Where the body itself leads, there is nothing to choose by: marked
    articles are given, or else all that is left of the body.
    """
    root = parse(page)
    _prune(root)
    nodes = measure(root)
    body = next((x for x in nodes if x.name == "body"), root)
    if not body.chars:
        return ""
    inside = _nodes(body)
    lead = max((x for x in inside if x.name not in INLINE), key=lambda x: x.sum)
    if lead.sum <= 0 or lead is body:
        return " ".join(t for x in _outermost(body, ("article", "main")) or [body] for t in _texts(x))
    threshold, up = lead.density, lead
    while up is not body:
        up = up.parent
        threshold = min(threshold, up.density)
    best: dict[int, Node] = {}
    for node in reversed(inside):
        kids = [best[id(x)] for x in node.items if isinstance(x, Node)]
        best[id(node)] = max([*([] if node.name in INLINE else [node]), *kids], key=lambda x: x.sum, default=node)
    chosen, work = [], [body]
    while work:
        node = work.pop()
        if node.density >= threshold and best[id(node)].sum > 0:
            chosen.append(best[id(node)])
        else:
            work += [x for x in reversed(node.items) if isinstance(x, Node)]
    ids = {id(x) for x in chosen}
    order = [x for x in _in_order(body) if id(x) in ids]
    return " ".join(t for x in order for t in _texts(x))


def _outermost(root: Node, names: tuple[str, ...]) -> list[Node]:
    """Nodes of these names that hold text and are in no other such node, in page order."""
    out, work = [], [root]
    while work:
        node = work.pop()
        if node.name in names and node.chars:
            out.append(node)
        else:
            work += [x for x in reversed(node.items) if isinstance(x, Node)]
    return out


def _in_order(root: Node) -> Iterator[Node]:
    work = [root]
    while work:
        node = work.pop()
        yield node
        work += [x for x in reversed(node.items) if isinstance(x, Node)]


def extract(pages: DataFrame, html_col: str = "html") -> DataFrame:
    """pages (page_id, url) with text and n_chars, one row per row of pages.

    Null and empty pages give empty text, an empty table no rows; damaged markup is repaired as parse() says; repeated
    rows are each extracted; extra columns are not read. Work is linear in a page, however deep it is nested.
    """

    @F.pandas_udf("string")
    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for page in batches:
            yield pd.Series([main_text(x) for x in page], dtype=object)

    return pages.select("page_id", "url", run(F.coalesce(F.col(html_col), F.lit(""))).alias("text")).withColumn("n_chars", F.length("text").cast("long"))
