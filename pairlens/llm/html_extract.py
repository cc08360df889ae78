"""Main text of web pages by tree scoring: paragraphs pass points to what holds them, the best container is kept."""

from __future__ import annotations

import html as entities
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Element names of HTML.
RAW = frozenset(("script", "style", "textarea", "title", "xmp", "iframe", "noembed", "noframes"))
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
DROPPED = frozenset("script style noscript template iframe object embed svg math canvas nav header footer aside form button select textarea input head title menu dialog".split())
BLOCKS = frozenset("address article aside blockquote body caption center dd details div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html li main nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
CLOSES_P = BLOCKS - frozenset("html body caption td th tr tbody thead tfoot li dd dt".split())
#: Words in class, id or role that name what is not the article, and what is.
UNLIKELY = re.compile(r"(?:^|[^a-z])(?:ads?|advert\w*|adsense|banner|breadcrumbs?|combx|comments?|community|consent|cookies?|disqus|disclaimer|extra|foot(?:er)?|gdpr|head(?:er)?|legends|masthead|menu|modal|nav(?:bar|igation)?|newsletter|notices?|outbrain|pager|pagination|popup|promo(?:ted|tion)?|related|remark|replies|respond|rss|share|sharing|shoutbox|side(?:bar)?|skyscraper|social|sponsor\w*|subscribe|taboola|teaser|toolbar|topbar|widgets?)(?![a-z])")
LIKELY = re.compile(r"article|body|content|entry|main|post|story|text")
TOKEN = re.compile(r"<!--.*?(?:-->|$)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>|<[!?][^>]*>", re.S)
ATTRIBUTE = re.compile(r"([a-zA-Z-]+)\s*(?:=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?")
SPACE = re.compile(r"\s+")
BREAK = "\x00"


class Node:
    __slots__ = ("tag", "kids", "parent", "score", "bonus", "chars", "linked", "commas")

    def __init__(self, tag: str, parent: Node | None, bonus: float = 0.0):
        self.tag, self.parent, self.bonus = tag, parent, bonus
        self.kids: list = []
        self.score = self.chars = self.linked = self.commas = 0


def parse(page: str) -> Node:
    """A tree of what may be text: unwanted elements are read by the same rules and left out. Ends of elements that are missing are supplied."""
    root = node = Node("html", None)
    unwanted: list[Node] = []
    pos = 0
    for m in _tokens(page):
        start, end, closing, tag, attrs = m
        if start > pos:
            node.kids.append(page[pos:start])
        pos = end
        if tag is None:
            continue
        if closing:
            if tag == "p" or tag not in VOID:
                up = node
                while up is not root and up.tag != tag:
                    up = up.parent if not (tag not in BLOCKS and up.tag in BLOCKS) else root
                if up is not root:
                    node = up.parent
            continue
        if tag in CLOSES_P or tag in ("li", "dd", "dt", "td", "th", "tr"):
            same = {"li": ("li",), "dd": ("dd", "dt"), "dt": ("dd", "dt"), "td": ("td", "th"), "th": ("td", "th"), "tr": ("tr",)}.get(tag, ("p",))
            up = node
            while up is not root and up.tag not in same and (up.tag not in BLOCKS or up.tag == "p"):
                up = up.parent
            if up.tag in same and up is not root:
                node = up.parent
        bonus, wanted = 0.0, tag not in DROPPED or tag == "header" and node.tag == "article"
        if attrs:
            own = {k.lower(): a or b or c for k, a, b, c in ATTRIBUTE.findall(attrs)}
            named = f"{own.get('class', '')} {own.get('id', '')} {own.get('role', '')}".lower()
            hidden = "hidden" in own or "display:none" in own.get("style", "").replace(" ", "").lower() or own.get("aria-hidden") == "true"
            if hidden or (named.strip() and UNLIKELY.search(named) and tag not in ("html", "body", "article", "main")):
                wanted = False
            bonus = 25.0 if LIKELY.search(named) else 0.0
        if not wanted and tag in VOID:
            continue
        if tag in VOID:
            if tag in ("br", "hr", "wbr"):
                node.kids.append({"br": " ", "hr": BREAK, "wbr": ""}[tag])
            continue
        child = Node(tag, node, bonus + {"article": 50.0, "main": 25.0, "section": 5.0, "div": 5.0, "pre": 3.0, "td": 3.0, "blockquote": 3.0}.get(tag, 0.0))
        node.kids.append(child)
        node = child
        if not wanted:
            unwanted.append(child)
    if pos < len(page):
        tail = page[pos:]
        node.kids.append(tail if not re.match(r"</?[a-zA-Z!]", tail) else "")
    for n in unwanted:
        n.kids.clear()
        n.tag, n.bonus = "span", 0.0
    return root


def _tokens(page: str) -> Iterator[tuple]:
    """(start, end, closing, tag or None, attributes); the inside of raw-text elements is not read as markup."""
    pos = 0
    while True:
        m = TOKEN.search(page, pos)
        if not m:
            return
        tag = m[2].lower() if m[2] else None
        yield m.start(), m.end(), bool(m[1]), tag, m[3]
        pos = m.end()
        if tag in RAW and not m[1]:
            close = re.compile(rf"</{tag}(?=[\s/>])[^>]*>", re.I).search(page, pos)
            stop, pos = (close.start(), close.end()) if close else (len(page), len(page))
            yield stop, pos, True, tag, ""


def measure(node: Node, linked: bool = False) -> None:
    """Characters, linked characters and commas of each subtree, children before parents."""
    order, stack = [], [(node, linked)]
    while stack:
        n, inside = stack.pop()
        inside = inside or n.tag == "a"
        order.append((n, inside))
        stack.extend((k, inside) for k in n.kids if isinstance(k, Node))
    for n, inside in reversed(order):
        for k in n.kids:
            if isinstance(k, Node):
                n.chars, n.linked, n.commas = n.chars + k.chars, n.linked + k.linked, n.commas + k.commas
            elif k is not BREAK:
                size = len(k) - k.count(" ") if k.strip() else 0
                n.chars, n.linked, n.commas = n.chars + size, n.linked + size * inside, n.commas + k.count(",")
    for n, _ in order:
        own = any(isinstance(k, str) and k is not BREAK and k.strip() for k in n.kids)
        if n.tag in ("p", "pre", "td", "blockquote", "li", "dd") or (own and n.tag in BLOCKS):
            if n.chars < 2 or n.tag == "li" and n.linked > n.chars / 2:
                continue
            points, share, up = 1 + n.commas + min(n.chars / 100, 3), 1.0, n.parent if n.tag in ("p", "pre", "li", "dd", "td", "blockquote") and n.parent else n
            for _ in range(5):
                if up is None:
                    break
                up.score += points * share
                share = 0.5 if share == 1.0 else share * 2 / 3 * (share <= 0.5)
                up = up.parent


def density(n: Node) -> float:
    return n.linked / n.chars if n.chars else 0.0


def best(root: Node) -> list[Node]:
    """The container with the most points after its links are discounted, with siblings that read like it."""
    top, most, stack = root, -1.0, [root]
    while stack:
        n = stack.pop()
        if n.score or n.bonus:
            value = (n.score + n.bonus * (n.chars > 0)) * (1 - density(n))
            if n.score and value > most:
                top, most = n, value
        stack.extend(k for k in reversed(n.kids) if isinstance(k, Node))
    while top.parent is not None and top.tag in ("p", "b", "i", "em", "strong", "span", "a", "font", "li", "ul", "ol", "h1", "h2", "h3", "h4", "h5", "h6", "tr", "td", "tbody", "pre", "blockquote", "dd", "dl"):
        top = top.parent
    if top.tag in ("article", "main") or top.parent is None:
        return [top]
    kept = []
    for k in top.parent.kids:
        if isinstance(k, Node) and (k is top or k.score + k.bonus > max(10.0, 0.2 * most) and density(k) < 0.33 and k.chars > 0 or k.tag == "p" and k.chars > 80 and density(k) < 0.25 or k.tag in ("h1", "h2") and k.chars > 0 and density(k) < 0.5):
            kept.append(k)
    return kept


def blocks(nodes: list[Node]) -> list[str]:
    """Texts of the blocks in page order: white space inside one becomes one space."""
    out: list[list[str]] = [[]]
    stack: list = list(reversed(nodes))
    while stack:
        k = stack.pop()
        if k is BREAK or k is None:
            out.append([])
        elif isinstance(k, str):
            out[-1].append(k)
        else:
            cut = k.tag in BLOCKS
            if cut:
                out.append([])
                stack.append(None)
            stack.extend(reversed(k.kids))
    done = (SPACE.sub(" ", entities.unescape("".join(b))).strip() for b in out)
    return [b for b in done if b]


def main_text(page: str | None) -> str:
    root = parse(page or "")
    measure(root)
    return "\n".join(blocks(best(root))) if root.chars else ""


def extract(pages: DataFrame, html: str = "html", key: str = "page_id", url: str = "url") -> DataFrame:
    """key, url, text, n_chars for each row: the whole page is read, a null or empty one gives an empty text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [main_text(x.as_py()) for x in b.column(2)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["key", "url", "text", "n_chars"])

    kind, kind2 = (pages.schema[c].dataType.simpleString() for c in (key, url))
    plain = pages.select(F.col(key).alias("key"), F.col(url).alias("url"), F.col(html).alias("html"))
    return plain.mapInArrow(run, f"key {kind}, url {kind2}, text string, n_chars bigint").withColumnRenamed("key", key).withColumnRenamed("url", url)
