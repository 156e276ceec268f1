"""Operator 4: the main text of a page by tree scoring.

The page becomes a tree by a forgiving scan: unclosed elements close where HTML lets
them, scripts, styles and comments never enter it. Parts whose role or name says menu,
header, footer, sidebar, notice, advert, form or reader comments are left out.
Each paragraph then passes points for its length and its commas on: all to its
parent, half to its grandparent, a third and a fourth to the next two. A container's points are discounted by its link density.
The best container is the article; siblings of it that score near it, or are prose with few links, belong to it.
Its text is read in page order, one block after another.

Defined results: null or empty html, and pages without text, give an empty text.
Character references are decoded once; white space inside a block becomes one
space; blocks are joined by two line feeds. Nothing is capped. Rows are handled one
by one, so repeated rows get equal results; extra columns are not read.
"""

from __future__ import annotations

import html as _html
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Fixed values of HTML: element names by their role.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
SKIPPED = frozenset("script style template noscript iframe object svg math canvas audio video head title select option textarea button datalist dialog".split())
RAW = frozenset("script style textarea title noscript iframe template".split())
BOILER = frozenset("nav footer aside form menu".split())
BLOCK = frozenset("address article aside blockquote body center dd details div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html legend li main nav ol p pre section summary table tbody td tfoot th thead tr ul caption".split())
CLOSES_P = BLOCK - frozenset("html body td th tr tbody thead tfoot caption".split())
#: What may stand in the head of a page; anything else ends it.
IN_HEAD = frozenset("base basefont bgsound link meta noframes noscript script style template title".split())
HEADING = frozenset("h1 h2 h3 h4 h5 h6".split())
#: An open element of the key's kind ends where one of these begins.
ENDS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr"}, "td": {"td", "th", "tr"}, "th": {"td", "th", "tr"}, "option": {"option"}}
SCOPE = frozenset("ul ol dl table article section div body html main nav aside footer header form td th blockquote".split())
#: Names in class, id or role of what isn't the article.
UNLIKELY = re.compile(r"(?:^|[\s_-])(?:ads?|adverts?|advert\w*|sponsor\w*|promo\w*|banner|breadcrumbs?|comments?|commentlist|disqus|replies|respond|cookies?|consent|gdpr|notices?|alert|popup|modal|overlay|subscribe|newsletter|signup|login|footer|nav\w*|menu\w*|sidebar|widget\w*|related|recommend\w*|share\w*|sharing|social|tags?|toolbar|pagination|pager|skip-link|skiplink|hidden|copyright)(?:$|[\s_-])", re.I)
#: Names of what is a header: of the site, or of the article if inside it.
HEADER = re.compile(r"(?:^|[\s_-])(?:header|masthead)(?:$|[\s_-])", re.I)
#: Elements that hold the article, headers included.
HOLDERS = frozenset("article main".split())
LIKELY = re.compile(r"article|body|content|entry|main|post|story|text", re.I)

_TOKEN = re.compile(r"<!--.*?(?:-->|$)|<!\[CDATA\[.*?(?:\]\]>|$)|<[!?][^>]*(?:>|$)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)(?:>|$)|<(/?)([a-zA-Z][^\s/>]*)([^>]*)(?:>|$)", re.S)
_NAMES = re.compile(r"\b(class|id|role|hidden|style|aria-hidden)\b(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)
_SPACE = re.compile(r"\s+")


class Node:
    __slots__ = ("children", "header", "name", "parent", "points", "unlikely", "weight")

    def __init__(self, name: str, parent: Node | None, attributes: str = "") -> None:
        self.name, self.parent, self.children = name, parent, []
        self.points, self.unlikely, self.weight, self.header = 0.0, name in BOILER, 0.0, name == "header"
        if attributes:
            for m in _NAMES.finditer(attributes):
                key, value = m[1].lower(), m[2] or m[3] or m[4] or ""
                if key in ("class", "id", "role"):
                    self.unlikely |= name not in ("body", "main", "article") and any(UNLIKELY.search(x) and not x.startswith(("has-", "with-", "no-", "has_", "with_", "no_")) for x in value.split()) or value.lower() in ("navigation", "banner", "contentinfo", "complementary", "search", "form", "alert", "dialog")
                    self.header |= name not in ("body", "main", "article") and any(HEADER.search(x) and not x.startswith(("has-", "with-", "no-", "has_", "with_", "no_")) for x in value.split())
                    self.weight += 25.0 * bool(LIKELY.search(value))
                elif key == "hidden" or (key == "aria-hidden" and value.lower() == "true") or (key == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value, re.I)):
                    self.unlikely = True


def parse(page: str) -> Node:
    """The tree of a page; text stands as strings among the children, its references decoded."""
    root = at = Node("html", None)
    pos, n, find, opened = 0, len(page), _TOKEN.search, False  # whether a head is open

    def head(node: Node | None) -> Node | None:
        while node is not None and node.name != "head":
            node = node.parent
        return node

    def text(a: int, b: int) -> None:
        nonlocal at
        if a < b:
            t = page[a:b]
            if at.name == "head" and not t.isspace():
                at = at.parent
            at.children.append(_html.unescape(t) if "&" in t else t)

    while pos < n:
        m = find(page, pos)
        if not m:
            text(pos, n)
            break
        text(pos, m.start())
        pos = m.end()
        close, name, attributes = (m[1], m[2], m[3]) if m[5] is None else (m[4], m[5], m[6])  # the latter with an unmatched quote: the tag ends at the next ">"
        if name is None:
            if m[0].startswith("<![CDATA["):
                at.children.append(m[0][9:].removesuffix("]]>"))
            continue
        name = name.lower()
        if close:
            if name == "head":  # ends whatever is open in it
                up = head(at) if opened else None
                at, opened = (up.parent, False) if up is not None else (at, opened)
                continue
            up = at
            while up is not None and up.name != name:
                # inline ends do not close blocks around them, nor do stray ones anything
                up = None if name not in BLOCK and up.name in BLOCK else up.parent
            if up is not None and up.parent is not None:
                at = up.parent
            elif up is None and name == "p":
                at.children.append(Node("p", at))
            continue
        if opened and name not in IN_HEAD and name not in ("html", "head"):
            up = head(at)
            at, opened = up.parent if up is not None else at, False
        if name in ("html", "body"):
            continue
        if name in CLOSES_P:
            up = at
            while up.name != "p" and up.name not in SCOPE and up.parent is not None:
                up = up.parent
            if up.name == "p":
                at = up.parent
        if name in ENDS:
            up = at
            while up.parent is not None and up.name not in SCOPE - {name, "td", "th"} and not (up.name in ENDS and name in ENDS[up.name]):
                up = up.parent
            if up.name in ENDS and name in ENDS[up.name]:
                at = up.parent
                if name == "tr" and at.name == "tr":
                    at = at.parent
        opened |= name == "head"
        node = Node(name, at, attributes)
        at.children.append(node)
        if name in RAW:
            end = re.compile(rf"</{name}\s*>?", re.I).search(page, pos)
            pos = end.end() if end else n
        elif name not in VOID and not attributes.endswith("/"):
            at = node
    return root


def _kept(node: Node, inside: bool) -> bool:
    if node.name in SKIPPED or node.unlikely:
        return False
    return inside or not node.header  # an article's own header holds its headline


def blocks(node: Node, inside: bool = False) -> list[str]:
    """The texts of a subtree in page order, white space settled."""
    out: list[str] = []
    run: list[str] = []

    def end() -> None:
        t = _SPACE.sub(" ", "".join(run)).strip()
        run.clear()
        if t:
            out.append(t)

    todo: list = [(node, inside)]
    while todo:
        x, within = todo.pop()
        if x is None:
            end()
        elif isinstance(x, str):
            run.append(x)
        elif x is node or _kept(x, within):
            if x.name == "br":
                run.append(" ")
                continue
            block = x.name in BLOCK
            if block:
                end()
                todo.append((None, False))
            todo += [(c, within or x.name in HOLDERS) for c in reversed(x.children)]
    end()
    return out


def _measure(root: Node) -> tuple[dict[int, tuple[int, int, int]], list[Node]]:
    """Text length, linked length and commas below each kept node, and the nodes in page order."""
    order: list[tuple[Node, bool, bool]] = []
    todo = [(root, False, False)]
    while todo:
        x, linked, within = todo.pop()
        if x is not root and not _kept(x, within):
            continue
        order.append((x, linked, within))
        todo += [(c, linked or x.name == "a", within or x.name in HOLDERS) for c in reversed(x.children) if isinstance(c, Node)]
    size: dict[int, tuple[int, int, int]] = {}
    for x, linked, _ in reversed(order):
        n = a = k = 0
        for c in x.children:
            if isinstance(c, str):
                t = len(c.strip())
                n += t
                a += t if linked or x.name == "a" else 0
                k += c.count(",")
            elif id(c) in size:
                m, b, j = size[id(c)]
                n, a, k = n + m, a + b, k + j
        size[id(x)] = (n, a, k)
    return size, [x for x, _, _ in order]


def main_text(page: str | None) -> str:
    """The main text of one page."""
    if not page:
        return ""
    root = parse(page)
    size, nodes = _measure(root)
    if not size[id(root)][0]:
        return ""
    scored: dict[int, Node] = {}
    for x in nodes:
        n, _, k = size[id(x)]
        own = x.name in ("p", "pre", "td", "blockquote", "dd", "li") or (x.name in BLOCK and any(isinstance(c, str) and c.strip() for c in x.children))
        if not own or n < 25:
            continue
        points, up, share = 1.0 + k + min(n / 100, 3.0), x.parent, 1
        while up is not None and share <= 4:
            up.points += points / share
            scored[id(up)] = up
            up, share = up.parent, share + 1
    value = {}
    for key, x in scored.items():
        if key in size:
            n, a, _ = size[key]
            bonus = x.weight + (25.0 if x.name in ("article", "main") else 0.0)
            value[key] = (x.points + (bonus if x.points else 0.0)) * (1 - a / max(1, n))
    if not value:
        return "\n\n".join(blocks(root))
    best = scored[max(value, key=value.__getitem__)]
    inside = best
    while inside is not None and inside.name not in HOLDERS:
        inside = inside.parent
    if best.parent is None:
        return "\n\n".join(blocks(best, inside is not None))
    near, chosen = max(10.0, 0.2 * value[id(best)]), []
    for x in best.parent.children:
        if isinstance(x, str) or (x is not best and id(x) not in size):
            continue
        n, a, _ = size[id(x)]
        if x is best or value.get(id(x), 0.0) >= near or (x.name == "p" and ((n > 80 and a < 0.25 * n) or (0 < n <= 80 and not a))) or (x.name in HEADING and n and not a):
            chosen += blocks(x, inside is not None)
    return "\n\n".join(chosen)


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """``page_id, url, text, n_chars``."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, max(1, whole.num_rows), 512):
                b = whole.slice(at, 512)
                texts = [main_text(h.as_py()) for h in b.column(2)]
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html")).mapInArrow(run, "page_id long, url string, text string, n_chars long")


def query(spark, sf_dir: str) -> DataFrame:
    from patternwalk.sources.tables import table

    return extract(table(spark, sf_dir, "pages"))
