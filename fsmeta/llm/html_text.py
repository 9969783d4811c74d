"""Main text of web pages by tree scoring.

A tolerant one-pass parser builds the element tree. Page furniture (navigation, side bars,
notices, adverts, forms, comments ...) is taken out by element and role, and by class words where
the text under them doesn't overrule the words (see ``judge_words``). Text blocks
pass points for their length and commas on to the elements above them, less with each level;
an element's points are discounted by its link density. The best element, or the article
element around it, is kept with those siblings that score or read like it.

Defined results: null and empty pages give an empty text; unclosed, crossed and unknown tags
are tolerated; depth is not limited (no recursion); repeated rows give repeated rows; extra
columns are not read.
"""

from __future__ import annotations

import re
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame

from fsmeta.llm.common import lean

#: A quote opens a value only after an equals sign; a value without one ends at white space or at the tag's end.
TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?>[^>=]++|=\s*+(?:\"[^\"]*+\"|'[^']*+')|=)*+)(?:>|\Z)", re.S)
ATTRIBUTE = re.compile(r"([a-zA-Z_:@][^\s=/>\"']*)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>][^\s>]*)))?")
WORDS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+|\d+")
#: Element sets and the class words of page furniture.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template iframe svg math object canvas textarea title".split())
BLOCK = frozenset("address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul br caption legend option optgroup select head".split())
ENDS_P = BLOCK - {"br", "td", "th", "tr", "tbody", "thead", "tfoot", "caption", "option", "optgroup", "head", "html", "body", "legend"}
SAME = {"li": {"ul", "ol", "menu", "dir"}, "dt": {"dl"}, "dd": {"dl"}, "td": {"tr", "table"}, "th": {"tr", "table"}, "tr": {"table"}, "option": {"select"}}
AWAY = frozenset("nav aside form button select input dialog menu head".split())
FRAME = frozenset(["header", "footer"])
ROLES = frozenset("navigation banner contentinfo complementary search dialog alert alertdialog menu menubar form".split())
WORDS_AWAY = frozenset("ad ads advert adverts advertisement advertising adsense sponsor sponsored sponsors promo promotion promoted banner cookie cookies consent gdpr notice notices popup modal overlay newsletter subscribe subscription signup share sharing social comment comments disqus reply replies respond sidebar sidebars related recommended recommendations menu menus nav navbar navigation breadcrumb breadcrumbs pagination pager toolbar widget widgets skip hidden paywall login search".split())
#: Of these, the words that prose sections are named with too: text that reads like prose overrules them.
WORDS_WEAK = frozenset("notice notices promotion modal newsletter subscription social widget widgets skip hidden search menu menus toolbar login consent".split())
WORDS_FRAME = frozenset("header footer masthead copyright".split())
WORDS_ARTICLE = frozenset("article post entry story content main body text".split())
SCORED = frozenset("p pre td blockquote li dd div section article h2 h3".split())


class Node:
    __slots__ = ("tag", "parent", "children", "away", "article", "frame", "points", "length", "linked", "doubted", "weak")

    def __init__(self, tag: str, parent: Node | None):
        self.tag, self.parent, self.children = tag, parent, []
        self.away = self.article = self.frame = self.doubted = self.weak = False
        self.points, self.length, self.linked = 0.0, 0, 0


def classify(node: Node, raw: str, by_words: bool = True) -> None:
    tag = node.tag
    node.away, node.frame, node.article = tag in AWAY, tag in FRAME, tag in ("article", "main")
    if not raw or raw.isspace():
        return
    words: set[str] = set()
    for name, a, b, c in ATTRIBUTE.findall(raw):
        name, value = name.lower(), a or b or c
        if name in ("class", "id"):
            words.update(w.lower() for w in WORDS.findall(unescape(value)))
        elif name == "role":
            role = value.strip().lower()
            node.away |= role in ROLES
            node.article |= role in ("main", "article")
        elif name == "hidden" or name == "aria-hidden" and value == "true" or name == "style" and "display:none" in value.replace(" ", "").lower():
            node.away = True
    if words and tag not in ("html", "body", "article", "main"):
        node.doubted = by_words and bool(words & WORDS_AWAY)
        node.weak = node.doubted and (words & WORDS_AWAY) <= WORDS_WEAK
        node.frame |= bool(words & WORDS_FRAME)
        node.article |= tag in ("div", "section", "td") and bool(words & WORDS_ARTICLE) and not node.away and not node.doubted


def parse(html: str, by_words: bool = True) -> Node:
    """Tree of elements and texts; texts are decoded strings among the children."""
    root = now = Node("html", None)
    at, n = 0, len(html)
    while at < n:
        m = TOKEN.search(html, at)
        text = html[at : m.start() if m else n]
        if text:
            now.children.append(unescape(text) if "&" in text else text)
        if m is None:
            break
        at, tag = m.end(), m[2]
        if tag is None:
            continue
        tag = tag.lower()
        if m[1]:
            up = now
            while up is not None and up.tag != tag:
                # a cell or list ends at its own table or list only
                up = None if up.tag in ("table", "td", "th") and tag in ("p", "b", "i", "span", "a") else up.parent
            if up is not None and up.parent is not None:
                now = up.parent
            continue
        if tag in RAW:
            if not m[3].rstrip().endswith("/"):
                end = re.compile(rf"</{re.escape(tag)}\s*[^>]*(?:>|\Z)", re.I).search(html, at)
                at = end.end() if end else n
            continue
        if tag in ("html", "body"):
            if tag == "body" and now.tag != "body":
                while now.parent is not None:
                    now = now.parent
                child = Node(tag, now)
                now.children.append(child)
                now = child
            continue
        if tag in ENDS_P:
            up, steps = now, 0
            while up is not None and up.tag != "p" and up.tag not in ENDS_P and up.tag not in ("td", "th", "body"):
                up = up.parent
            if up is not None and up.tag == "p":
                now = up.parent
        if tag in SAME:
            up = now
            twins = {"dt", "dd"} if tag in ("dt", "dd") else {"td", "th"} if tag in ("td", "th") else {tag}
            while up is not None and up.tag not in twins and up.tag not in SAME[tag]:
                up = up.parent
            if up is not None and up.tag in twins:
                now = up.parent
        if now.tag == "head" and tag in BLOCK:
            now = now.parent
        child = Node(tag, now)
        classify(child, m[3], by_words)
        now.children.append(child)
        if tag not in VOID and not m[3].rstrip().endswith("/"):
            now = child
    return root


PROSE = frozenset("p pre blockquote li dd".split())


def judge_words(root: Node) -> None:
    """Elements with class words of furniture are taken out, but not those that hold the page's
    article, or most of its unlinked text where no article is elsewhere; nor, where all their
    furniture words are weak, those that read like prose: two long paragraphs or more, few links
    and a tenth of the page's unlinked text."""
    nodes, stack = [], [(root, False, 0)]
    while stack:  # parents before children
        node, linked, above = stack.pop()
        if node.away:
            continue
        linked |= node.tag == "a"
        nodes.append((node, linked, above))
        above += node.article
        stack += [(c, linked, above) for c in node.children if isinstance(c, Node)]
    if not any(node.doubted for node, _, _ in nodes):
        return
    plain, every, held, real, long = {}, {}, {}, {}, {}
    for node, linked, _ in reversed(nodes):
        inner = [c for c in node.children if isinstance(c, Node) and c in plain]
        own = sum(len(c.strip()) for c in node.children if isinstance(c, str))
        plain[node] = sum(plain[c] for c in inner) + (0 if linked else own)
        every[node] = sum(every[c] for c in inner) + own
        held[node] = sum(held[c] for c in inner) + node.article
        real[node] = any(real[c] or c.tag in ("article", "main") for c in inner)
        long[node] = sum(long[c] for c in inner) + (node.tag in PROSE and plain[node] >= 80)
    for node, _, above in nodes:
        if node.doubted:
            article = real[node] and not above
            most = 2 * plain[node] > plain[root] and held[root] == held[node] + above
            prose = node.weak and long[node] >= 2 and 10 * plain[node] >= 8 * every[node] and 10 * plain[node] >= plain[root]
            node.away = not (article or most or prose)


def ordered(root: Node) -> list[Node]:
    """Elements in page order, without what is taken out. Frames inside an article stay if they hold its heading."""
    out, stack = [], [(root, False)]
    while stack:
        node, inside = stack.pop()
        if node.away or node.frame and not (inside and node.tag == "header"):
            node.away = True
            continue
        out.append(node)
        inside |= node.article
        stack += [(c, inside) for c in reversed(node.children) if isinstance(c, Node)]
    return out


def score(nodes: list[Node]) -> None:
    for node in reversed(nodes):  # children before parents
        own = [c for c in node.children if isinstance(c, str)]
        length = sum(len(c.strip()) for c in own)
        inner = [c for c in node.children if isinstance(c, Node) and not c.away]
        node.linked += length if node.tag == "a" else 0
        for c in inner:
            node.linked += c.length if node.tag == "a" else c.linked
            length += c.length
        node.length = length
        direct = sum(len(c.strip()) for c in own) + sum(c.length for c in inner if c.tag not in BLOCK)
        if node.tag in SCORED and direct:
            commas = sum(c.count(",") for c in own)
            points = (1 + commas + min(3.0, direct / 100)) * (1 - node.linked / max(1, node.length))
            up, share = node.parent, 1.0
            for level in range(3):
                if up is None:
                    break
                up.points += points * share
                up, share = up.parent, 1 / (level + 2)


def density(node: Node) -> float:
    return node.linked / max(1, node.length)


def text_of(nodes: list[Node]) -> str:
    parts: list[str] = []
    stack: list = list(reversed(nodes))
    while stack:
        item = stack.pop()
        if isinstance(item, str):
            parts.append(item)
        elif not item.away:
            if item.tag in BLOCK:
                parts.append(" ")
                stack.append(" ")
            stack += reversed(item.children)
    return " ".join("".join(parts).split())


def main_text(html: str | None) -> str:
    """Where class words would take out everything, they are not heeded."""
    if not html:
        return ""
    return _main_text(html, True) or _main_text(html, False)


def _main_text(html: str, by_words: bool) -> str:
    root = parse(html, by_words)
    judge_words(root)
    nodes = ordered(root)
    score(nodes)
    worth = lambda x: (x.points + (25 if x.article else 0) * bool(x.length)) * (1 - density(x))
    best = max(nodes, key=worth, default=root)
    if worth(best) <= 0:
        best = root
    up, outer = best, None
    while up is not None:
        if up.tag in ("article", "main") or up.article and density(up) < 0.5:
            outer = up
        if up.tag == "article":
            break
        up = up.parent
    best = outer or best
    if best.parent is None:
        return text_of([best])
    top, kept = worth(best), []
    for c in best.parent.children:
        if c is best:
            kept.append(c)
        elif isinstance(c, Node) and not c.away and outer is None:
            good = worth(c) >= max(10.0, 0.2 * top)
            reads = c.tag in ("p", "pre", "blockquote", "h1", "h2", "h3") and density(c) < 0.25 and (c.length > 80 or c.tag[0] == "h")
            if good or reads:
                kept.append(c)
        elif isinstance(c, Node) and not c.away and c.tag == "article" and worth(c) >= max(10.0, 0.2 * top):
            kept.append(c)
    return text_of(kept)


def extract(pages: DataFrame, key: str = "page_id", url: str = "url", html: str = "html") -> DataFrame:
    """key, url, text and n_chars of each row."""
    rows = pages.select(key, url, html)
    names = [key, url, "text", "n_chars"]

    def read(batches):
        for b in lean(batches):
            texts = [main_text(h) for h in b.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=names)

    kinds = [f.dataType.simpleString() for f in rows.schema.fields]
    return rows.mapInArrow(read, f"`{key}` {kinds[0]}, `{url}` {kinds[1]}, text string, n_chars long")
