"""Trees from text: strict XML and permissive HTML, one document in each row, parsed where the row is.

Node numbers, shapes and chains are made while parsing; no numbered document is ever produced. White-space-only runs and
comments are dropped. Null text gives no nodes; text that isn't well-formed XML is an error.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from html.parser import HTMLParser
from xml.parsers import expat

import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treefacts import model
from treefacts.functions import keys

# Elements of HTML that have no content, and which open elements a start tag ends.
VOID = frozenset("area base br col embed hr img input link meta source track wbr".split())
ENDS = {"li": ("li", ("ul", "ol")), "p": ("p", ()), "dt": ("dt", ("dl",)), "dd": ("dd", ("dl",)), "tr": ("tr", ("table",)), "td": ("td", ("tr", "table"))}


class Element:
    __slots__ = ("atts", "children", "tag")

    def __init__(self, tag: str, atts: dict[str, str]):
        self.tag, self.atts, self.children = tag, atts, []


def parse_xml(text: str, strip_text: bool = True) -> Element | None:
    top = Element("", {})
    open_ = [top]
    parser = expat.ParserCreate()
    parser.buffer_text = True

    def start(tag: str, atts: dict[str, str]) -> None:
        element = Element(tag, atts)
        open_[-1].children.append(element)
        open_.append(element)

    def data(run: str) -> None:
        if run.strip() or not strip_text and run:
            run = run.strip() if strip_text else run
            kids = open_[-1].children
            if kids and isinstance(kids[-1], str):
                kids[-1] += run
            else:
                kids.append(run)

    parser.StartElementHandler, parser.EndElementHandler, parser.CharacterDataHandler = start, lambda tag: open_.pop(), data
    parser.Parse(text, True)
    return top.children[0] if top.children else None


class _Html(HTMLParser):
    def __init__(self, strip_text: bool):
        super().__init__(convert_charrefs=True)
        self.top, self.strip = Element("", {}), strip_text
        self.open = [self.top]

    def handle_starttag(self, tag, atts):
        if tag in ENDS:
            ended, stops = ENDS[tag]
            for i in range(len(self.open) - 1, 0, -1):
                if self.open[i].tag == ended:
                    del self.open[i:]
                    break
                if self.open[i].tag in stops:
                    break
        element = Element(tag, {k: v or "" for k, v in reversed(atts)})
        self.open[-1].children.append(element)
        if tag not in VOID:
            self.open.append(element)

    def handle_startendtag(self, tag, atts):
        self.handle_starttag(tag, atts)
        if tag not in VOID:
            self.open.pop()

    def handle_endtag(self, tag):
        for i in range(len(self.open) - 1, 0, -1):
            if self.open[i].tag == tag:
                del self.open[i:]
                break

    def handle_data(self, run):
        if run.strip() and len(self.open) > 1:
            self.open[-1].children.append(run.strip() if self.strip else run)


def parse_html(text: str, strip_text: bool = True) -> Element | None:
    parser = _Html(strip_text)
    parser.feed(text)
    parser.close()
    return next((x for x in parser.top.children if isinstance(x, Element)), None)


def signature(element: Element) -> tuple[list[str], list[str]]:
    tags = sorted({model.TEXT if isinstance(x, str) else x.tag for x in element.children})
    return tags, sorted(element.atts)


def chain_id(parent: int, tag: str, child_tags: list[str], att_names: list[str]) -> int:
    raw = f"{parent}\x1f{tag}\x1f{','.join(child_tags)}\x1f{','.join(att_names)}".encode()
    return xxhash.xxh64_intdigest(raw) - (1 << 63)


def is_leaf(element: Element) -> bool:
    return not element.atts and all(isinstance(x, str) for x in element.children)


def rows_of(doc_id: int, root: Element) -> Iterator[tuple]:
    """NODES rows of a tree in document order."""
    todo: list[tuple[Element | str, tuple[int, ...], int]] = [(root, (1,), 0)]
    while todo:
        x, node, above = todo.pop()
        okey = keys.encode(node)
        if isinstance(x, str):
            yield doc_id, okey, model.TEXT, model.RUN, {}, x, [], [], above, above
        elif is_leaf(x):
            yield doc_id, okey, x.tag, model.LEAF, {}, "".join(x.children), [], [], above, above
        else:
            tags, atts = signature(x)
            chain = chain_id(above, x.tag, tags, atts)
            yield doc_id, okey, x.tag, model.INNER, x.atts, None, tags, atts, chain, above
            todo += [(c, (*node, i), chain) for i, c in reversed(list(enumerate(x.children, 1)))]


def _from_text(df: DataFrame, id_col: str, text_col: str, parse: Callable[[str, bool], Element | None], strip_text: bool) -> DataFrame:
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            rows = []
            for doc_id, text in zip(frame["doc_id"], frame["text"], strict=True):
                if text is not None and (root := parse(text, strip_text)) is not None:
                    rows += rows_of(int(doc_id), root)
                if len(rows) > 20_000:
                    yield pd.DataFrame(rows, columns=model.NODES.names)
                    rows = []
            yield pd.DataFrame(rows, columns=model.NODES.names)

    source = df.where(F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    return source.mapInPandas(run, model.NODES)


def from_xml_text(df: DataFrame, id_col: str = "doc_id", text_col: str = "xml", strip_text: bool = True) -> DataFrame:
    return _from_text(df, id_col, text_col, parse_xml, strip_text)


def from_html(df: DataFrame, id_col: str = "page_id", html_col: str = "html", strip_text: bool = True) -> DataFrame:
    return _from_text(df, id_col, html_col, parse_html, strip_text)


def from_xml_file(spark, path: str, row_tag: str, root_tag: str, strip_text: bool = True) -> DataFrame:
    """Records of one huge file, split where they end, as one document; a record may not hold its own tag."""
    from treefacts.sources.publish import global_rank

    raw = spark.read.option("lineSep", f"</{row_tag}>").text(path).select(F.col("_metadata.file_path").alias("file"), F.col("_metadata.file_block_start").alias("start"), F.monotonically_increasing_id().alias("at"), F.col("value"))
    begin = F.regexp_instr("value", F.lit(f"<{row_tag}[\\s>/]"))
    found = raw.where(begin > 0).withColumn("xml", F.concat(F.expr(f"substring(value, regexp_instr(value, '<{row_tag}[\\\\s>/]'))"), F.lit(f"</{row_tag}>"))).drop("value")
    ranked = global_rank(found, ["file", "start", "at"])

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            rows = []
            above = chain_id(0, root_tag, [row_tag], [])
            for ordinal, text in zip(frame["ordinal"], frame["xml"], strict=True):
                holder = Element(root_tag, {})
                holder.children = [parse_xml(text, strip_text)]
                for r in list(rows_of(1, holder))[1:] if not is_leaf(holder) else []:
                    node = keys.decode(r[1])
                    rows.append((r[0], keys.encode((1, int(ordinal), *node[2:])), *r[2:]))
            del above
            yield pd.DataFrame(rows, columns=model.NODES.names)

    top = spark.createDataFrame([(1, keys.encode([1]), root_tag, model.INNER, {}, None, [row_tag], [], chain_id(0, root_tag, [row_tag], []), 0)], model.NODES)
    return top.unionByName(ranked.mapInPandas(run, model.NODES))
