"""Relational tables as trees, without ever making text of them.

A Level says how the rows of a table become records: their tag, attributes and leaves (missing values are left out), the
columns that tie them to the records above, and the order of siblings. Records of the top level get their ordinals from
a range sort; those below by a window inside their parent. Shapes come with the nodes, as a row knows its children.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from treefacts import model
from treefacts.functions import keys
from treefacts.session import materialise


@dataclass
class Level:
    table: DataFrame
    tag: str | Column
    key: list[str]  #: columns that tell records apart for the levels below
    order: list[str]  #: of siblings
    parent: list[str] = field(default_factory=list)  #: columns equal to the key of the level above
    atts: dict[str, Column] = field(default_factory=dict)
    leaves: list[tuple[str | Column, Column]] = field(default_factory=list)  #: of tag and value; a null value is no leaf
    text: Column | None = None  #: a text run before the leaves
    below: list[Level] = field(default_factory=list)
    is_leaf: bool = False  #: the record is a leaf whose value is the first of leaves


def global_rank(df: DataFrame, order: list[str], name: str = "ordinal") -> DataFrame:
    """df with ordinals 1 to n in a global order: a range sort that is written, then counts of each range added up."""
    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = df.repartitionByRange(n, *order).sortWithinPartitions(*order).withColumn("_id", F.monotonically_increasing_id())
    written = materialise(dealt, "ranked")
    part, local = F.shiftright("_id", 33), F.col("_id").bitwiseAND(F.lit((1 << 33) - 1))
    counts = sorted((r[0], r[1]) for r in written.groupBy(part.alias("p")).count().collect())  # one row for each range
    offsets, total = {}, 0
    for p, c in counts:
        offsets[p] = total
        total += c
    start = F.element_at(F.create_map(*[F.lit(x) for p, o in offsets.items() for x in (p, o)]), part) if offsets else F.lit(0)
    return written.withColumn(name, start + local + 1).drop("_id")


def texts(column: Column, df: DataFrame) -> Column:
    """A value as text; a list as its entries between blanks."""
    kind = df.select(column.alias("x")).schema["x"].dataType.typeName()
    if kind == "array":
        return F.array_join(column.cast("array<string>"), " ")
    if kind in ("timestamp", "timestamp_ntz"):
        micros = F.unix_micros(column.cast("timestamp")) % 1_000_000
        return F.when(micros == 0, F.date_format(column, "yyyy-MM-dd'T'HH:mm:ss")).otherwise(F.date_format(column, "yyyy-MM-dd'T'HH:mm:ss.SSSSSS"))
    return column.cast("string")


def _chain(parent: Column, tag: Column, child_tags: Column, att_names: Column) -> Column:
    return F.xxhash64(parent, tag, F.array_join(child_tags, ","), F.array_join(att_names, ","))


def _records(level: Level) -> DataFrame:
    """Rows of a level with _tag."""
    return level.table.withColumn("_tag", F.lit(level.tag) if isinstance(level.tag, str) else level.tag)


def _with_values(level: Level, rows: DataFrame) -> DataFrame:
    """rows with _atts and _inner (present texts and leaves in order), made of the table's columns only after these have been dealt and sorted."""
    parts = [] if level.text is None else [F.struct(F.lit(model.TEXT).alias("tag"), level.text.cast("string").alias("value"))]
    parts += [F.struct((F.lit(t) if isinstance(t, str) else t).alias("tag"), texts(v, level.table).alias("value")) for t, v in level.leaves]
    made = F.filter(F.array(*parts), lambda x: x["value"].isNotNull()) if parts else F.array().cast("array<struct<tag:string,value:string>>")
    pairs = [F.struct(F.lit(k).alias("key"), texts(v, level.table).alias("value")) for k, v in level.atts.items()]
    atts = F.map_from_entries(F.filter(F.array(*pairs), lambda x: x["value"].isNotNull())) if pairs else F.create_map().cast("map<string,string>")
    return rows.withColumns({"_inner": made, "_atts": atts})


def publish(root_tag: str, top: list[Level], doc_id: int = 1) -> DataFrame:
    """Nodes of one document whose root holds the records of the top levels, one level after the other."""
    out: list[DataFrame] = []
    root_key = keys.encode([1])
    tops = []
    before = F.lit(0)
    for level in top:
        ranked = global_rank(_records(level), level.order, "_ordinal")
        tops.append((level, ranked.withColumn("_okey", keys.child(root_key, before + F.col("_ordinal")))))
        before = before + F.lit(ranked.count()) if len(top) > 1 else before
    root_tags = F.array(*[F.lit(x.tag) for x in top]) if all(isinstance(x.tag, str) for x in top) else None
    if root_tags is None:
        names = sorted({r[0] for _, df in tops for r in df.select("_tag").distinct().collect()})
        root_tags = F.array(*[F.lit(t) for t in names])
    spark = top[0].table.sparkSession
    root = spark.range(1).select(F.lit(doc_id).cast("long").alias("doc_id"), F.lit(root_key).alias("okey"), F.lit(root_tag).alias("tag"), F.lit(model.INNER).alias("kind"), F.create_map().cast("map<string,string>").alias("atts"), F.lit(None).cast("string").alias("value"), F.array_sort(root_tags).alias("child_tags"), F.array().cast("array<string>").alias("att_names"))
    names = sorted({r[0] for _, df in tops for r in df.select("_tag").distinct().collect()}) if any(not isinstance(x.tag, str) for x in top) else sorted(x.tag for x in top)
    root_chain = _chain(F.lit(0).cast("long"), F.lit(root_tag), F.array(*[F.lit(x) for x in names]), F.array().cast("array<string>"))
    out.append(root.select("*", root_chain.alias("chain"), F.lit(0).cast("long").alias("parent_chain")))
    for level, rows in tops:
        _emit(level, rows.withColumn("_parent_chain", root_chain), doc_id, out)
    nodes = out[0]
    for df in out[1:]:
        nodes = nodes.unionByName(df)
    return nodes.select(*model.NODES.names)


def _emit(level: Level, rows: DataFrame, doc_id: int, out: list[DataFrame]) -> None:
    """Nodes of rows (with _okey and _parent_chain) and of the levels below."""
    empty_map, nothing = F.create_map().cast("map<string,string>"), F.array().cast("array<string>")
    rows = _with_values(level, rows)
    if level.is_leaf:
        out.append(rows.select(F.lit(doc_id).cast("long").alias("doc_id"), F.col("_okey").alias("okey"), F.col("_tag").alias("tag"), F.lit(model.LEAF).alias("kind"), empty_map.alias("atts"), F.col("_inner")[0]["value"].alias("value"), nothing.alias("child_tags"), nothing.alias("att_names"), F.col("_parent_chain").alias("chain"), F.col("_parent_chain").alias("parent_chain")))
        return
    tags = F.transform("_inner", lambda x: x["tag"])
    children: list[tuple[Level, DataFrame]] = []
    for k, low in enumerate(level.below):
        made = _records(low)
        counts = made.groupBy(*low.parent).agg(F.count("*").alias(f"_n{k}"), F.collect_set("_tag").alias(f"_tags{k}"))
        rows = rows.join(counts.withColumnsRenamed(dict(zip(low.parent, level.key, strict=True))), level.key, "left").withColumns({f"_n{k}": F.coalesce(f"_n{k}", F.lit(0)), f"_tags{k}": F.coalesce(f"_tags{k}", nothing)})
        tags = F.concat(tags, F.col(f"_tags{k}"))
        children.append((low, made))
    rows = rows.withColumns({"_child_tags": F.array_sort(F.array_distinct(tags)), "_att_names": F.array_sort(F.map_keys("_atts"))})
    # a level is worked out once: its nodes, its leaves, the level below and all passes over the nodes read it from here
    kept = list(dict.fromkeys([*level.key, "_okey", "_parent_chain", "_tag", "_atts", "_inner", "_child_tags", "_att_names", *[f"_n{k}" for k in range(len(children))]]))
    rows = materialise(rows.select(*kept).withColumn("_chain", _chain(F.col("_parent_chain"), F.col("_tag"), F.col("_child_tags"), F.col("_att_names"))), "level")
    out.append(rows.select(F.lit(doc_id).cast("long").alias("doc_id"), F.col("_okey").alias("okey"), F.col("_tag").alias("tag"), F.lit(model.INNER).alias("kind"), F.col("_atts").alias("atts"), F.lit(None).cast("string").alias("value"), F.col("_child_tags").alias("child_tags"), F.col("_att_names").alias("att_names"), F.col("_chain").alias("chain"), F.col("_parent_chain").alias("parent_chain")))
    if level.leaves or level.text is not None:
        parts = rows.select("_okey", "_chain", F.posexplode("_inner").alias("_i", "_part"))
        out.append(parts.select(F.lit(doc_id).cast("long").alias("doc_id"), keys.child(F.col("_okey"), F.col("_i") + 1).alias("okey"), F.col("_part.tag").alias("tag"), F.when(F.col("_part.tag") == model.TEXT, model.RUN).otherwise(model.LEAF).alias("kind"), empty_map.alias("atts"), F.col("_part.value").alias("value"), nothing.alias("child_tags"), nothing.alias("att_names"), F.col("_chain").alias("chain"), F.col("_chain").alias("parent_chain")))
    shift = F.size("_inner")
    for k, (low, made) in enumerate(children):
        parents = rows.select(*[F.col(a).alias(b) for a, b in zip(level.key, low.parent, strict=True)], F.col("_okey").alias("_above"), F.col("_chain").alias("_parent_chain"), shift.alias("_shift"))
        rank = F.row_number().over(Window.partitionBy(*low.parent).orderBy(*low.order))
        numbered = made.withColumn("_rank", rank).join(parents, low.parent)
        _emit(low, numbered.withColumn("_okey", keys.child(F.col("_above"), F.col("_shift") + F.col("_rank"))).drop("_above", "_shift", "_rank"), doc_id, out)
        shift = shift + F.col(f"_n{k}")
