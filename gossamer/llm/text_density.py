"""Main text of web pages by composite text density.

A tolerant scanner builds the tree (void and optional end tags, raw-text elements, unclosed and stray
tags). Elements that are chrome by what they are or are named - scripts, styles, menus, page headers and
footers, asides, forms, adverts, notices, sidebars, reader comments - leave the tree. Each remaining node
gets characters per tag, lowered by the share of link characters and link tags; a node's density sum is
that of its children. The node of the largest sum is the core; the smallest density on its path
to the body is the threshold, and the core grows to the outermost ancestor, the body left out, whose
density reaches it. Other subtrees outside it that reach the threshold are main text too, in page order.
Only where the body itself is the core, article and main elements decide.

Cases: null and empty pages, and pages without text, give the empty string; broken markup is read as far as
it goes; pages of any length and depth are read whole (no recursion); repeated rows stay; an empty table
gives no rows; other columns are not read.
"""

from __future__ import annotations

import html
import math
import re
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

_MARK = re.compile(r"<(?:!--(?P<comment>.*?)(?:-->|\Z)|(?P<other>[!?][^>]*)>|(?P<slash>/?)(?P<tag>[A-Za-z][^\s/>]*)(?P<attributes>(?:[^>\"']|\"[^\"]*\"|'[^']*')*)>)", re.DOTALL)
_ATTRIBUTE = re.compile(r"""([^\s"'<>/=]+)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'=<>`]+)))?""")
_SPACE = re.compile(r"\s+")

VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp iframe noembed noframes".split())
BLOCKS = frozenset("address article aside blockquote body br caption center dd details dialog dir div dl dt fieldset figcaption figure footer form frameset h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li listing main menu nav noscript ol optgroup option p pre section summary table tbody td tfoot th thead title tr ul".split())
CLOSES_P = BLOCKS - frozenset("br option optgroup legend td th tr tbody thead tfoot caption body html head title".split())
DROPPED = frozenset("script style noscript template iframe object embed canvas svg math nav aside footer form button select textarea input menu dialog title head noembed noframes map audio video".split())
#: start tag -> open elements that it ends, and where the search for them stops
ENDED_BY = {
    "li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "option": ({"option"}, {"select"}), "tr": ({"tr", "td", "th"}, {"table"}),
    "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "tbody": ({"tbody", "thead", "tfoot", "tr", "td", "th"}, {"table"}), "tfoot": ({"tbody", "thead", "tr", "td", "th"}, {"table"}), "body": ({"head"}, {"html"}),
}
#: words in class, id or role that name chrome
CHROME = re.compile(
    r"(?:^|[\s_-])(?:ads?|advert\w*|adsense|adbox|adslot|banner|sponsor\w*|promo\w*|nav|navbar|navigation|menu\w*|breadcrumbs?|sidebar\w*|side|rail|widget\w*|footer\w*|masthead|toolbar|topbar|cookies?|consent|gdpr|notice\w*|alert\w*|popup|modal|overlay|newsletter|subscribe\w*|signup|login|paywall|"
    r"comments?|commentlist|comment-\w+|disqus\w*|respond|replies|discussion|reader-comments|share|sharing|social\w*|related\w*|recommend\w*|trending|outbrain|taboola|pagination|pager|skip-link|search\w*|tags?|tagcloud|complementary|contentinfo|search|dialog|alertdialog|hidden|print-only|disclaimer)(?:$|[\s_-])",
    re.IGNORECASE,
)
#: names that tell of a layout, not of the element's own role: no-sidebar, has-banner
LAYOUT = re.compile(r"(?:no|has|with|without|not|hide|show)[-_]", re.IGNORECASE)
PAGE_HEADER = re.compile(r"(?:^|[\s_-])(?:header|site-header|page-header|top|hero)(?:$|[\s_-])", re.IGNORECASE)


class Node:
    __slots__ = ("tag", "parent", "items", "attributes", "chars", "tags", "link_chars", "link_tags", "density", "sum")

    def __init__(self, tag: str, parent: Node | None, attributes: str = ""):
        self.tag, self.parent, self.attributes = tag, parent, attributes
        self.items: list[Node | str] = []

    def named(self) -> dict[str, str]:
        return {m[1].lower(): html.unescape(m[2] or m[3] or m[4] or "") for m in _ATTRIBUTE.finditer(self.attributes)} if self.attributes else {}


def tree(source: str) -> Node:
    """The document; text items are still encoded."""
    root = Node("#document", None)
    at, size = 0, len(source)
    stack = [root]
    while at < size:
        m = _MARK.search(source, at)
        if m is None:
            if at < size:
                stack[-1].items.append(source[at:])
            break
        if m.start() > at:
            stack[-1].items.append(source[at : m.start()])
        at = m.end()
        tag = m["tag"]
        if tag is None:
            continue
        tag = tag.lower()
        if m["slash"]:
            if tag == "p" and not any(n.tag == "p" for n in stack):
                stack[-1].items.append(Node("p", stack[-1]))
            elif tag == "br":
                stack[-1].items.append(Node("br", stack[-1]))
            else:
                for k in range(len(stack) - 1, 0, -1):
                    if stack[k].tag == tag:
                        del stack[k:]
                        break
            continue
        if tag in CLOSES_P:
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].tag == "p":
                    del stack[k:]
                    break
                if stack[k].tag in BLOCKS:
                    break
        if rule := ENDED_BY.get(tag):
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].tag in rule[1]:
                    break
                if stack[k].tag in rule[0]:
                    del stack[k:]
                    break
        node = Node(tag, stack[-1], m["attributes"])
        stack[-1].items.append(node)
        if tag in RAW:
            end = re.compile(rf"</{tag}[\s/>]", re.IGNORECASE).search(source, at)
            stop = end.start() if end else size
            node.items.append(source[at:stop])
            at = stop
            if end:
                close = source.find(">", stop)
                at = size if close < 0 else close + 1
        elif tag not in VOID and not (m["attributes"] or "").rstrip().endswith("/") or tag in ("div", "p", "span", "a") and tag not in VOID:
            stack.append(node)
    return root


def _is_chrome(node: Node, in_article: bool) -> bool:
    if node.tag in DROPPED:
        return True
    if node.tag == "header" and not in_article:
        return True
    if not node.attributes or node.tag in ("html", "body", "article", "main"):
        return False
    names = node.named()
    if "hidden" in names or names.get("aria-hidden") == "true" or re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", names.get("style", ""), re.IGNORECASE):
        return True
    said = " ".join(w for k in ("class", "id", "role") for w in names.get(k, "").split() if not LAYOUT.match(w))
    if not said:
        return False
    if CHROME.search(said):
        return True
    return not in_article and bool(PAGE_HEADER.search(said)) and names.get("role") != "main"


def _holders(root: Node) -> set[int]:
    """The nodes around the first article and the first main element: they are not chrome, whatever their names."""
    found, todo, seen = set(), [root], set()
    while todo and len(seen) < 2:
        node = todo.pop()
        if node.tag in DROPPED:
            continue
        if node.tag in ("article", "main") and node.tag not in seen:
            seen.add(node.tag)
            above = node
            while above is not None:
                found.add(id(above))
                above = above.parent
        todo += [i for i in reversed(node.items) if not isinstance(i, str)]
    return found


def pruned(root: Node) -> list[Node]:
    """Takes chrome out; the nodes that stay, parents first."""
    order, todo, holds = [], [(root, False)], _holders(root)
    while todo:
        node, inside = todo.pop()
        order.append(node)
        inside = inside or node.tag in ("article", "main")
        keep = []
        for item in node.items:
            if isinstance(item, str):
                keep.append(html.unescape(item) if "&" in item else item)
            elif id(item) in holds or not _is_chrome(item, inside):
                keep.append(item)
                todo.append((item, inside))
        node.items = keep
    return order


def measure(order: list[Node], body: Node) -> None:
    """Characters, tags, links, composite density and density sums, children first."""
    for node in reversed(order):
        node.chars = node.tags = node.link_chars = node.link_tags = 0
        for item in node.items:
            if isinstance(item, str):
                node.chars += len(item.strip())
            else:
                node.chars, node.tags = node.chars + item.chars, node.tags + item.tags + 1
                node.link_chars, node.link_tags = node.link_chars + item.link_chars, node.link_tags + item.link_tags + (item.tag == "a")
        if node.tag == "a":
            node.link_chars = node.chars
    share = body.link_chars / body.chars if body.chars else 0.0
    for node in reversed(order):
        if not node.chars:
            node.density = 0.0
        else:
            tags, links, link_tags = max(1, node.tags), max(1, node.link_chars), max(1, node.link_tags)
            plain = max(1, node.chars - node.link_chars)
            base = math.log(node.chars / plain * links + share * node.chars + math.e)  # above 1.3
            node.density = node.chars / tags * math.log(max(node.chars / links * tags / link_tags, 1)) / math.log(base)
        node.sum = sum(i.density for i in node.items if not isinstance(i, str))


_ARTICLE = re.compile(r"(?:^|[\s_-])(?:article|main)(?:$|[\s_-])")


def _is_article(node: Node) -> bool:
    return node.tag in ("article", "main") or bool(node.attributes) and _ARTICLE.search(" ".join(node.named().get(k, "") for k in ("role", "id", "class"))) is not None


def cores(order: list[Node]) -> list[Node]:
    """The subtrees that hold the main text, in page order, none inside another."""
    body = next((n for n in order if n.tag == "body"), order[0])
    measure(order, body)
    inside, todo = [], [body]
    while todo:
        node = todo.pop()
        inside.append(node)
        todo += [i for i in node.items if not isinstance(i, str)]
    best = max(inside, key=lambda n: (n.sum, n.chars))
    if not best.sum:
        best = max(inside, key=lambda n: (n.density, n.chars)) if any(n.density for n in inside) else body
    path, node = [], best
    while node is not None and node is not body:
        path.append(node)
        node = node.parent
    threshold = min(n.density for n in [*path, body])

    def grows(node: Node) -> bool:
        return node.chars - node.link_chars > 0 and not (node.chars > 1.5 * best.chars and node.link_chars > 0.3 * node.chars)

    top, article = next((n for n in reversed(path) if grows(n)), best), False
    if best is body:
        articles = [n for n in inside[1:] if n.tag in ("article", "main") and n.chars > n.link_chars]
        if not articles:
            # lists of links stay out
            body.items = [i for i in body.items if isinstance(i, str) or i.tag not in BLOCKS or i.density >= threshold or i.link_tags < 2 or 2 * i.link_chars <= i.chars]
            return [body]
        top, article = max(articles, key=lambda n: (n.sum, n.chars)), True
    above, node = set(), top.parent
    while node is not None:
        above.add(id(node))
        node = node.parent
    found, todo = [], [body]
    while todo:
        node = todo.pop()
        if node is top:
            found.append(node)
        elif id(node) not in above and node.density >= threshold and grows(node) and 2 * node.link_chars <= node.chars and (not article or _is_article(node) and not CHROME.search(" ".join(node.named().get(k, "") for k in ("class", "id", "role")))):
            found.append(node)
        else:
            todo += [i for i in reversed(node.items) if not isinstance(i, str)]
    return found


def text_of(root: Node) -> str:
    """Blocks in page order, each with single spaces, joined by one space."""
    blocks: list[str] = []
    now: list[str] = []

    def end() -> None:
        if now:
            if joined := _SPACE.sub(" ", "".join(now)).strip():
                blocks.append(joined)
            now.clear()

    todo: list = [(root, iter(root.items))]
    while todo:
        node, rest = todo[-1]
        for item in rest:
            if isinstance(item, str):
                now.append(item)
            elif item.tag in BLOCKS:
                end()
                todo.append((item, iter(item.items)))
                break
            else:
                todo.append((item, iter(item.items)))
                break
        else:
            todo.pop()
            if node.tag in BLOCKS:
                end()
    end()
    return " ".join(blocks)


def extract(source: str | None) -> str:
    if not source:
        return ""
    order = pruned(tree(source))
    return " ".join(t for t in map(text_of, cores(order)) if t)


def main_text(pages: DataFrame) -> DataFrame:
    """``page_id, url, text, n_chars`` for every page."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in common.slices(batches, "html"):
            known: dict[str | None, str] = {}
            many = part.column(2).to_pylist()
            for t in many:
                if t not in known:
                    known[t] = extract(t)
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array([known[t] for t in many], pa.string()), pa.array([len(known[t]) for t in many], pa.int64())], ["page_id", "url", "text", "n_chars"])

    return pages.select(F.col("page_id").cast("long").alias("page_id"), "url", F.coalesce("html", F.lit("")).alias("html")).mapInArrow(run, "page_id long, url string, text string, n_chars long")
