"""Main text of web pages by tree scoring.

A page is read into a tree of elements. Boilerplate elements (menus, headers, footers, sidebars, notices,
adverts, forms, comments, hidden parts), known by tag, role or a whole word of class or id, are left out.
Every paragraph earns one point, one for each comma and one for each hundred characters up to three, and passes
them to its parent in full, to its grandparent by half and to further ancestors by shrinking shares. A container's points are
discounted by its link density. The best container is kept with all its siblings
that are not mostly links, however short; an article or main element that holds it, with siblings whose points come near.

Edge cases: null or empty html, or a page without text, gives the empty text; unclosed and stray tags are
repaired; nothing is capped, so very long pages and deep nesting are read whole (the tree is walked with loops).
"""

from __future__ import annotations

import html as entities
import re
from collections import Counter
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript template iframe noembed noframes xmp svg object audio video canvas select".split())
BLOCK = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol p pre search section summary table tbody td tfoot th thead tr ul head".split())
DROPPED = frozenset("nav header footer aside form menu dialog search head fieldset datalist".split())
DROPPED_ROLES = frozenset("navigation banner contentinfo complementary search dialog alert alertdialog form menu menubar toolbar tablist".split())
#: Whole words of class or id that mark boilerplate.
DROPPED_WORDS = frozenset(
    "ad ads adv advert adverts advertisement advertising adsense sponsor sponsored sponsors promo promotion promoted banner banners breadcrumb breadcrumbs comment comments commentlist disqus replies cookie cookies consent gdpr notice notices alert footer foot header masthead topbar menu menus nav navbar navigation navigator pager pagination popup modal overlay related recommended recommendations outbrain taboola share sharing social sidebar sidebars sidenav rail widget widgets toolbar subscribe subscription newsletter signup login search form hidden skip tags meta-nav".split()
)
#: Of these, words that may also name the main text.
VAGUE_WORDS = frozenset("share sharing related widget widgets tags promo promoted promotion".split())
KEPT_TAGS = frozenset("html body article main".split())
#: A new start tag of the key closes an open element of the values, no further than the barrier elements.
CLOSES = {"li": "li", "dt": "dt dd", "dd": "dt dd", "tr": "tr td th", "td": "td th", "th": "td th", "thead": "tr td th", "tbody": "thead tbody tr td th", "tfoot": "tbody tr td th", "option": "option"}
BARRIERS = {"li": "ul ol menu", "dt": "dl", "dd": "dl", "tr": "table", "td": "table", "th": "table", "thead": "table", "tbody": "table", "tfoot": "table", "option": "select"}
BONUS = {"article": 10.0, "main": 10.0, "section": 3.0, "div": 2.0, "td": 1.0, "blockquote": 1.0}
PARAGRAPHS = frozenset("p pre td blockquote li dd h1 h2 h3 h4 h5 h6 figcaption".split())

#: Part of its text in links from which a sibling of the best container is boilerplate.
MAX_LINKS = 0.25

_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^<>\"']|\"[^\"]*\"|'[^']*')*)>|<[!?][^<>]*>", re.S)
_ATTRIBUTE = re.compile(r"([^\s=\"'/>]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
_WORD = re.compile(r"[a-z0-9]+")
_HIDDEN = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden")
_COMMAS = re.compile(r"[,、，،]")


class Node:
    __slots__ = ("tag", "parent", "children", "dropped", "points", "text_chars", "link_chars")

    def __init__(self, tag: str, parent: "Node | None", dropped: bool = False):
        self.tag, self.parent, self.dropped = tag, parent, dropped
        self.children: list[Node | str] = []
        self.points, self.text_chars, self.link_chars = 0.0, 0, 0


def _boilerplate(tag: str, attributes: str, names: frozenset[str]) -> bool:
    if tag in DROPPED:
        return True
    if not attributes or attributes.isspace():
        return False
    found = {m[1].lower(): (m[2] or m[3] or m[4] or "").lower() for m in _ATTRIBUTE.finditer(attributes)}
    if "hidden" in found or found.get("aria-hidden") == "true" or _HIDDEN.search(found.get("style", "")):
        return True
    if found.get("role") in DROPPED_ROLES:
        return True
    if tag in KEPT_TAGS or found.get("role") in ("main", "article"):
        return False
    own = f"{found.get('class', '')} {found.get('id', '')}"
    return not names.isdisjoint(_WORD.findall(own)) or not names.isdisjoint(_WORD.findall(own.replace("-", "").replace("_", "")))  # side-bar, too


def parse(page: str, names: frozenset[str] = DROPPED_WORDS) -> Node:
    """The element tree; text of dropped elements is not kept. names: words of class or id that make an element boilerplate."""
    root = at = Node("#root", None)
    opened: Counter = Counter()  # so that a stray tag need not look for its element

    def leave(node: Node) -> Node:
        """The parent of an open element, which ends here with all that is open in it."""
        up = at
        while up is not node.parent:
            opened[up.tag] -= 1
            up = up.parent
        return up

    place, found = 0, _TAG.search(page)
    while found:
        if found.start() > place and not at.dropped:
            at.children.append(page[place : found.start()])
        place, tag = found.end(), (found[2] or "").lower()
        if not tag:
            pass
        elif found[1]:
            node = at
            while opened[tag] and node.parent and node.tag != tag and not (tag not in BLOCK and node.tag in BLOCK):
                node = node.parent
            if node.parent and node.tag == tag:
                at = leave(node)
        elif tag in RAW:
            if not found[3].endswith("/"):
                end = re.compile(rf"</{re.escape(tag)}\s*>", re.I).search(page, place)
                place = end.end() if end else len(page)
        elif tag in VOID:
            if not at.dropped:
                at.children.append(Node(tag, at))
        else:
            if tag in BLOCK and opened["p"]:  # ends an open paragraph, with what is open in it
                node = at
                while node.parent and (node.tag not in BLOCK or node.tag == "p"):
                    if node.tag == "p":
                        at = leave(node)
                        break
                    node = node.parent
            if tag in CLOSES and any(opened[x] for x in CLOSES[tag].split()):
                node, ends, stops = at, CLOSES[tag].split(), BARRIERS[tag].split()
                while node.parent and node.tag not in stops:
                    if node.tag in ends:
                        at = leave(node)
                    node = node.parent
            child = Node(tag, at, at.dropped or _boilerplate(tag, found[3], names))
            if not child.dropped:
                at.children.append(child)
            if not found[3].endswith("/") or tag in BLOCK:
                at = child
                opened[tag] += 1
        found = _TAG.search(page, place)
    if place < len(page) and not at.dropped:
        at.children.append(page[place:])
    return root


def _score(root: Node) -> list[Node]:
    """Passes the paragraphs' points up; returns the candidates. Text sizes are summed on the way back from a depth-first walk."""
    order, stack = [], [root]
    while stack:
        node = stack.pop()
        order.append(node)
        stack += [c for c in node.children if isinstance(c, Node)]
    own: dict[Node, list[str]] = {}
    for node in reversed(order):
        pieces = [c for c in node.children if isinstance(c, str)]
        node.text_chars += sum(len(x) - x.count("\n") for x in pieces if not x.isspace())
        if node.tag == "a":
            node.link_chars = node.text_chars
        inner = own.pop(node, []) + pieces
        if node.parent:
            node.parent.text_chars += node.text_chars
            node.parent.link_chars += node.link_chars
            if node.tag not in BLOCK:
                own.setdefault(node.parent, []).extend(inner)
        if inner and node.tag in BLOCK and node.parent and (size := len(text := " ".join(" ".join(inner).split()))) and (node.tag in PARAGRAPHS or size >= 25):
            points = (1 + len(_COMMAS.findall(text)) + min(3.0, size / 100)) * (1 - _density(node))
            up, level = node.parent if node.tag in PARAGRAPHS else node, 0
            while up.parent and level < 32:  # further shares are under a hundredth of a point
                up.points += points / (1, 2)[level] if level < 2 else points / (3 * level)
                up, level = up.parent, level + 1
    return [n for n in order if n.points > 0]


def _density(node: Node) -> float:
    return node.link_chars / node.text_chars if node.text_chars else 0.0


def _worth(node: Node) -> float:
    return (node.points + BONUS.get(node.tag, 0.0)) * (1 - _density(node))


def _blocks(nodes: list["Node | str"]) -> list[str]:
    """The texts of the blocks in page order, white space made one space."""
    out, now = [], []

    def close() -> None:
        if text := " ".join(entities.unescape("".join(now)).split()):
            out.append(text)
        now.clear()

    stack: list = list(reversed(nodes))
    while stack:
        node = stack.pop()
        if node is None:
            close()
        elif isinstance(node, str):
            now.append(node)
        elif node.tag == "br":
            now.append(" ")
        elif node.tag in BLOCK:
            close()
            stack.append(None)
            stack += reversed(node.children)
        else:
            stack += reversed(node.children)
    close()
    return out


def main_text(page: str | None) -> str:
    """The page's main text, its blocks joined by one newline; a page whose only text has one of VAGUE_WORDS for a name keeps it."""
    return _main_text(page, DROPPED_WORDS) or _main_text(page, DROPPED_WORDS - VAGUE_WORDS) if page else ""


def _main_text(page: str, names: frozenset[str]) -> str:
    root = parse(page, names)
    candidates = _score(root)
    if not candidates:
        return "\n".join(_blocks(root.children))
    best = max(candidates, key=_worth)
    up = best
    while up:
        if up.tag in ("article", "main"):
            best = up
        up = up.parent
    kept: list[Node | str] = [best]
    if best.parent and best.parent.tag != "#root" and best.tag not in ("article", "main"):
        kept = [c for c in best.parent.children if c is best or isinstance(c, str) or _density(c) < MAX_LINKS]
    elif best.parent and best.parent.tag != "#root":
        least = max(10.0, 0.2 * _worth(best))
        kept = [c for c in best.parent.children if c is best or isinstance(c, Node) and _keeps(c, least)]
    return "\n".join(_blocks(kept))


def _keeps(node: Node, least: float) -> bool:
    """Beside an article or main element, which marks the main text itself."""
    if node.tag in ("h1", "h2"):
        return False
    if node.tag == "p":
        return node.text_chars > 80 and _density(node) < MAX_LINKS
    return node.points > 0 and _worth(node) >= least


def extract_main_text(pages: DataFrame) -> DataFrame:
    """page_id, url, text (never null) and n_chars for every row of pages; one pass, nothing is shuffled."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            texts = [main_text(x) for x in batch["html"]]
            yield pd.DataFrame({"page_id": batch["page_id"], "url": batch["url"], "text": texts, "n_chars": [len(t) for t in texts]})

    # Ids go through pandas as strings: beside nulls it would read them as floats.
    rows = pages.select(F.col("page_id").cast("string").alias("page_id"), "url", "html").mapInPandas(run, "page_id string, url string, text string, n_chars long")
    return rows.withColumn("page_id", F.col("page_id").cast(pages.schema["page_id"].dataType))
