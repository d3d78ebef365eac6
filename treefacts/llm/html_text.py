"""Main text of web pages by composite text density.

A tolerant parser builds the tree of a page. For each node, characters, link characters, tags and link tags below it
give the composite density: characters per tag, adjusted by how much of them is links. The node whose children have
the largest sum of densities holds the main text; the least density on its way up to the body is the threshold, and every
largest subtree beside that way that reaches it and isn't mostly links is main text as well. A chosen node inside an `article`
(or, on a page without one, a `main`) stands for that element, and for its siblings of the same name and class: a
page may hold several articles.

Parts that are never main text go first, by what the page says they are: elements (nav, footer, aside, form, script and so
on), roles, and words of class and id. Outside articles a word may be a part of a class name ("site-nav"); inside, the class
has to be that word ("notice"), but for a few words of adverts and comments, so that a "related-work" section stays.

Null or empty html: empty text. Broken and truncated markup is closed as browsers do, roughly. Repeated rows are worked
on each on its own, pages one at a time and whole, in time linear in their nodes; other columns are ignored, whatever their names.
"""

from __future__ import annotations

import html as entities
import math
import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from treefacts.llm import common

# Element names of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template textarea title xmp iframe noembed noframes".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
CUT = frozenset("script style noscript template textarea iframe noembed noframes xmp title head nav footer aside form button select option input svg canvas object embed audio video map dialog menu".split())
ENDS_P = frozenset("address article aside blockquote details div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())
CLOSES = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "option": {"option"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "thead": {"tr", "td", "th"}, "tbody": {"thead", "tr", "td", "th", "tbody"}, "tfoot": {"tbody", "tr", "td", "th"}}
SCOPES = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"table"}, "th": {"table"}, "thead": {"table"}, "tbody": {"table"}, "tfoot": {"table"}, "option": {"select"}}
CUT_ROLES = frozenset("navigation banner contentinfo complementary search form dialog alertdialog alert menu menubar toolbar".split())
#: Words of class and id that mark other things than the main text.
CUT_WORDS = frozenset(
    "ad ads adv advert adverts advertisement advertisements advertising adslot adbox adbanner banner banners sponsor sponsored sponsors promo promos promotion promoted "
    "nav navbar navigation navi menu menus submenu topnav breadcrumb breadcrumbs crumbs pagination pager toc skip sitemap "
    "sidebar sidebars aside rail widget widgets related recommended recommendations recommend more-articles trending popular teaser teasers outbrain taboola "
    "header masthead site-header topbar footer site-footer colophon copyright legal disclaimer imprint "
    "cookie cookies consent gdpr notice notices alert alerts popup modal overlay lightbox paywall subscribe subscription newsletter signup login register banner-cookie "
    "comment comments commentlist comment-list respond replies reply discussion disqus thread "
    "share sharing social socials follow tags tagcloud byline-links search searchbox form hidden".split()
)
ARTICLE_PARTS = frozenset(("article", "main"))
#: Words that inside an article mark its own parts, and those that mark others even as a part of a class name.
OWN_WORDS = frozenset("header masthead copyright legal thread discussion promotion follow".split())
OTHERS_WORDS = frozenset("ad ads adv advert advertisement adslot sponsored promo newsletter cookie comment comments share sharing".split())
INSIDE_WORDS = CUT_WORDS - OWN_WORDS
TAG = re.compile(
    r"<!--.*?(?:--!?>|\Z)|<!\[CDATA\[(?P<cdata>.*?)(?:\]\]>|\Z)|<[!?][^>]*+(?:>|\Z)"
    r"|<(?P<end>/?)(?P<name>[a-zA-Z][^\s/>]*)(?P<atts>(?:[^>\"']++|\"[^\"]*+\"|'[^']*+'|[\"'])*+)(?P<close>>|\Z)",
    re.S,
)
ATT = re.compile(r"([^\s=/\"'>]+)\s*(?:=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
SPACE = re.compile(r"[ \t\n\r\f\v]+")
PARTS = re.compile(r"[\s_\-:]+")


class Node:
    __slots__ = ("article", "atts", "chars", "children", "cut", "density", "link_chars", "link_tags", "name", "parent", "sum", "tags")

    def __init__(self, name: str, parent: Node | None, atts: dict[str, str]):
        self.name, self.parent, self.atts = name, parent, atts
        self.children: list[Node | str] = []
        self.chars = self.link_chars = self.tags = self.link_tags = 0
        self.density = self.sum = 0.0
        self.cut = self.article = False  #: article: an article or main element lies below


def attributes(text: str) -> dict[str, str]:
    return {k.lower(): entities.unescape(a or b or c) for k, a, b, c in reversed(ATT.findall(text))} if text and not text.isspace() else {}


def parse(page: str) -> Node:
    """The tree of a page; leaves are texts with character references decoded."""
    root = Node("#page", None, {})
    open_, opened = [root], Counter()  # how many elements of a name are open
    at, n = 0, len(page)

    def close(k: int) -> None:
        opened.subtract(x.name for x in open_[k:])
        del open_[k:]

    def add(text: str) -> None:
        if text:
            open_[-1].children.append(entities.unescape(text))

    while at < n:
        m = TAG.search(page, at)
        if not m:
            add(page[at:])
            break
        add(page[at : m.start()])
        at = m.end()
        if m["cdata"]:
            open_[-1].children.append(m["cdata"])
        if not m["name"] or not m["close"]:  # comments, declarations, and a tag that the end of the page cuts
            continue
        name = m["name"].lower()
        if m["end"]:
            if opened[name] > 0:
                close(next(k for k in range(len(open_) - 1, 0, -1) if open_[k].name == name))
            continue
        if name in ENDS_P and opened["p"] > 0:
            for k in range(len(open_) - 1, 0, -1):
                if open_[k].name == "p":
                    close(k)
                    break
                if open_[k].name not in INLINE and open_[k].name != "p":
                    break
        if name in CLOSES:
            for k in range(len(open_) - 1, 0, -1):
                if open_[k].name in CLOSES[name]:
                    close(k)
                    break
                if open_[k].name in SCOPES.get(name, ()):
                    break
        node = Node(name, open_[-1], attributes(m["atts"]))
        open_[-1].children.append(node)
        if name in ARTICLE_PARTS:
            for x in open_:
                x.article = True
        if name in VOID or m["atts"].endswith("/"):
            continue
        if name in RAW:
            end = re.compile(f"</{name}\\b[^>]*(?:>|\\Z)", re.I).search(page, at)
            node.children.append(page[at : end.start() if end else n])
            at = end.end() if end else n
            continue
        open_.append(node)
        opened[name] += 1
    return root


def is_cut(node: Node, in_article: bool) -> bool:
    name, atts = node.name, node.atts
    if name in CUT:
        return True
    if name == "header":
        return not in_article
    if not atts:
        return False
    if "hidden" in atts or atts.get("aria-hidden") == "true" or atts.get("role", "").lower() in CUT_ROLES or re.search(r"display\s*:\s*none", atts.get("style", "")):
        return True
    if name in ("html", "body", "main") or node.article:  # a wrapper of the article may be named for what stands beside it
        return False
    words, parts = (INSIDE_WORDS, OTHERS_WORDS) if in_article else (CUT_WORDS, CUT_WORDS)
    for key in ("class", "id"):
        for word in atts.get(key, "").lower().split():
            if word in words or not parts.isdisjoint(PARTS.split(word)):
                return True
    return False


def nodes(root: Node) -> list[Node]:
    """Nodes that stay, parents before children; marks those that are cut."""
    out, todo = [], [(root, False)]
    while todo:
        node, inside = todo.pop()
        out.append(node)
        inside = inside or node.name in ARTICLE_PARTS
        for x in node.children:
            if isinstance(x, Node):
                x.cut = is_cut(x, inside)
                if not x.cut:
                    todo.append((x, inside))
    return out


def weigh(found: list[Node], body: Node) -> None:
    """Counts below each node, then densities and sums of the children's densities."""
    for node in reversed(found):
        own = sum(len(SPACE.sub(" ", x).strip()) for x in node.children if isinstance(x, str))
        kids = [x for x in node.children if isinstance(x, Node) and not x.cut]
        node.chars = own + sum(x.chars for x in kids)
        node.tags = len(kids) + sum(x.tags for x in kids)
        if node.name == "a":
            node.link_chars, node.link_tags = node.chars, 1 + node.tags
        else:
            node.link_chars, node.link_tags = sum(x.link_chars for x in kids), sum(x.link_tags for x in kids)
    links = body.link_chars / max(1, body.chars)
    for node in found:
        if not node.chars:
            continue
        c, lc, t, lt = node.chars, max(1, node.link_chars), max(1, node.tags), max(1, node.link_tags)
        base = math.log(c / max(1, c - node.link_chars) * node.link_chars + links * c + math.e)
        ratio = c / lc * t / lt
        node.density = c / t * (math.log(ratio) / math.log(base) if base > 1 and ratio > 0 else math.log(max(ratio, 1e-9)))
    for node in found:
        node.sum = sum(x.density for x in node.children if isinstance(x, Node) and not x.cut) or (node.density if node.chars else 0.0)


def is_article(node: Node, names: tuple[str, ...] = ("article",)) -> bool:
    return node.name in names or node.atts.get("role") in names or node.atts.get("itemprop") == "articleBody"


def main_parts(root: Node) -> list[Node]:
    """Subtrees that hold the main text, in page order."""
    found = nodes(root)
    body = next((x for x in found if x.name == "body"), root)
    weigh(found, body)
    below, todo = [], [body]
    while todo:
        x = todo.pop()
        below.append(x)
        todo += [k for k in reversed(x.children) if isinstance(k, Node) and not k.cut]
    holders = [x for x in below if x.chars]
    if not holders:
        return []
    best = max(holders, key=lambda x: x.sum)
    way = [best]
    while way[-1] is not body:
        way.append(way[-1].parent)
    threshold = min(x.density for x in way)
    on_way = {id(x) for x in way}
    good = lambda k: isinstance(k, Node) and not k.cut and k.chars and k.link_chars < 0.5 * k.chars
    chosen = [best, *(k for x in way[1:] for k in x.children if good(k) and id(k) not in on_way and k.density >= threshold)]
    headings = ("h1", "h2", "h3", "h4", "h5", "h6", "p", "blockquote", "pre")
    if best is not body:
        chosen += [k for k in best.parent.children if good(k) and k.name in headings]
    keep: set[int] = set()
    names = ("article",) if any(is_article(x) for x in below) else ("article", "main")
    whole = {}
    for x in chosen:
        around, outer = x, None
        while True:
            if is_article(around, names):
                outer = around
            if around is body:
                break
            around = around.parent
        if outer is not None:
            whole[id(outer)] = outer
        else:
            keep.add(id(x))
    if whole:  # what stands beside declared articles isn't theirs
        keep = set()
        for x in whole.values():
            keep |= {id(k) for k in x.parent.children if k is x or good(k) and k.name == x.name and k.atts.get("class") == x.atts.get("class")}
    return ordered(body, keep)


def ordered(body: Node, keep: set[int]) -> list[Node]:
    out, todo = [], [body]
    while todo:
        x = todo.pop()
        if id(x) in keep:
            out.append(x)
        else:
            todo += [k for k in reversed(x.children) if isinstance(k, Node) and not k.cut]
    return out


def text_of(parts: list[Node]) -> str:
    """Text of subtrees, without what is cut; a space between blocks, none between inline elements."""
    out: list[str] = []
    todo: list[Node | str] = [x for p in reversed(parts) for x in (" ", p)]
    while todo:
        x = todo.pop()
        if isinstance(x, str):
            out.append(x)
        elif not x.cut:
            block = x.name not in INLINE
            todo += [" "] * block
            todo += reversed(x.children)
            todo += [" "] * block
    return SPACE.sub(" ", "".join(out)).strip(" ")


def main_text(page: str | None) -> str:
    return text_of(main_parts(parse(page))) if page else ""


def extract(pages: DataFrame, id_col: str = "page_id", html_col: str = "html", keep_cols: tuple[str, ...] = ("url",)) -> DataFrame:
    """id, keep_cols, text and n_chars of each row of pages."""
    common.ship(pages.sparkSession)
    fields = [T.StructField(c, pages.schema[c].dataType) for c in (id_col, *keep_cols)]
    schema = T.StructType([*fields, T.StructField("text", T.StringType()), T.StructField("n_chars", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(x.as_py()) for x in batch.column(batch.num_columns - 1)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(texts, pa.string()), pa.array([len(x) for x in texts], pa.int64())], names=schema.names)

    return pages.select(*[pages[c] for c in (id_col, *keep_cols, html_col)]).mapInArrow(run, schema)
