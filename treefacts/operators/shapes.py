"""Record shapes (schema rules): signatures, similarity, type numbers, chains.

A shape is a tag, a set of child tags and a set of attribute names under a chain of such shapes from the root. One
aggregation over the nodes makes the dictionary; type numbers are then worked out on it, level by level.
"""

from __future__ import annotations

from collections import defaultdict
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from treefacts import model
from treefacts.functions import keys
from treefacts.session import materialise

MAX_SHAPES = 100_000  #: the planner holds so many at most


@dataclass(frozen=True)
class Shape:
    chain: int
    parent_chain: int
    depth: int
    tag: str
    child_tags: tuple[str, ...]
    att_names: tuple[str, ...]
    first: tuple[int, str]
    n_nodes: int
    typ: int = 0
    child_typ: int = 0

    @property
    def signature(self) -> tuple:
        return self.tag, self.child_tags, self.att_names

    @property
    def preds(self) -> tuple[str, ...]:
        """What the rule's body calls: children, then attributes."""
        return self.child_tags + tuple(model.attribute(a) for a in self.att_names)


@dataclass
class Rules:
    """The dictionary of shapes as the planner holds it."""

    shapes: list[Shape]
    by_chain: dict[int, Shape] = field(init=False)
    below: dict[int, list[Shape]] = field(init=False)

    def __post_init__(self):
        self.by_chain = {s.chain: s for s in self.shapes}
        self.below = defaultdict(list)
        for s in self.shapes:
            self.below[s.parent_chain].append(s)

    @property
    def roots(self) -> list[Shape]:
        return self.below[0]

    def distinct(self) -> list[tuple]:
        """Schema rules: tag, head type, child tags, attributes, children's type; each once."""
        return sorted({(s.tag, s.typ, s.child_tags, s.att_names, s.child_typ) for s in self.shapes}, key=lambda r: (r[1], r[0], r[4]))

    def patterns(self, tag: str) -> list[tuple]:
        """The pattern set of a tag: its distinct record shapes."""
        return sorted({(s.child_tags, s.att_names) for s in self.shapes if s.tag == tag})

    def types_of(self, tag: str, pattern: tuple) -> set[int]:
        """The type numbers of a pattern of a tag."""
        return {s.typ for s in self.shapes if s.tag == tag and (s.child_tags, s.att_names) == pattern}


def relation(a: tuple, b: tuple) -> str:
    """similar, weak (one tag, another structure) or distinct, for signatures."""
    return "distinct" if a[0] != b[0] else "similar" if a == b else "weak"


def dictionary(nodes: DataFrame) -> DataFrame:
    """One row for each chain: the shape, its first place and how many nodes have it."""
    inner = nodes.where(F.col("kind") == model.INNER)
    return inner.groupBy("chain", "parent_chain", keys.depth(F.col("okey")).alias("depth"), "tag", "child_tags", "att_names").agg(F.min(F.struct("doc_id", "okey")).alias("first"), F.count("*").alias("n_nodes"))


def type_numbers(shapes: list[Shape], mode: str = "classes") -> list[Shape]:
    """Types by level: children of a shape get its type + n + 1, where n counts the distinct shapes of its tag that came
    earlier on its level. mode unique: a number for each chain instead."""
    if mode == "unique":
        number = {s.chain: i for i, s in enumerate(sorted(shapes, key=lambda s: (s.depth, s.first)), 1)}
        return [replace(s, typ=number[s.chain], child_typ=number[s.chain]) for s in shapes]
    out: list[Shape] = []
    typ_of = {0: 1}
    for depth in sorted({s.depth for s in shapes}):
        level = [s for s in shapes if s.depth == depth]
        first: dict[tuple, tuple] = {}
        for s in level:
            first[s.signature] = min(first.get(s.signature, s.first), s.first)
        rank: dict[tuple, int] = {}
        for tag in {s.tag for s in level}:
            for n, sig in enumerate(sorted((x for x in first if x[0] == tag), key=first.__getitem__)):
                rank[sig] = n
        for s in level:
            typ = typ_of[s.parent_chain]
            typ_of[s.chain] = typ + rank[s.signature] + 1
            out.append(replace(s, typ=typ, child_typ=typ_of[s.chain]))
    return out


def added_types(old: list[Shape], new: list[Shape]) -> list[Shape]:
    """Types of shapes that come to a dictionary later: types given out stay, a new structure gets the next number of its tag
    and level."""
    out, typ_of = [], {0: 1} | {s.chain: s.child_typ for s in old}
    rank = {(s.depth, s.signature): s.child_typ - s.typ - 1 for s in old}
    following: dict[tuple, int] = defaultdict(int)
    for (depth, signature), n in rank.items():
        following[depth, signature[0]] = max(following[depth, signature[0]], n + 1)
    for s in sorted(new, key=lambda s: (s.depth, s.first)):
        key = s.depth, s.signature
        if key not in rank:
            rank[key] = following[s.depth, s.tag]
            following[s.depth, s.tag] += 1
        typ = typ_of[s.parent_chain]
        typ_of[s.chain] = typ + rank[key] + 1
        out.append(replace(s, typ=typ, child_typ=typ_of[s.chain]))
    return out


def rules(nodes: DataFrame, mode: str = "classes", max_shapes: int = MAX_SHAPES) -> Rules:
    found = dictionary(nodes).limit(max_shapes + 1).collect()
    if len(found) > max_shapes:
        raise ValueError(f"over {max_shapes} record shapes; publish with chains by path only")
    if len({r.chain for r in found}) < len(found):
        raise ValueError("two shapes share a chain")
    shapes = [Shape(r.chain, r.parent_chain, r.depth, r.tag, tuple(r.child_tags), tuple(r.att_names), (r.first.doc_id, r.first.okey), r.n_nodes) for r in found]
    return Rules(type_numbers(sorted(shapes, key=lambda s: (s.depth, s.first)), mode))


def signature_text(similarity: str = "shallow") -> Column:
    return F.concat_ws("|", F.col("tag"), F.array_join("child_tags", ","), F.array_join("att_names", ","))


def deep_signatures(nodes: DataFrame) -> DataFrame:
    """doc_id, okey, tag, deep: a signature of the whole structure below each inner node, from the deepest level up."""
    inner = nodes.where(F.col("kind") == model.INNER).select("doc_id", "okey", "tag", "child_tags", "att_names", keys.depth(F.col("okey")).alias("depth"))
    inner = materialise(inner, "inner")
    deepest = inner.agg(F.max("depth")).first()[0] or 0
    done: DataFrame | None = None
    own = F.xxhash64("tag", F.array_join("child_tags", ","), F.array_join("att_names", ","))
    below = None
    for depth in range(deepest, 0, -1):
        level = inner.where(F.col("depth") == depth)
        if below is not None:
            sets = below.groupBy("doc_id", keys.parent(F.col("okey")).alias("okey")).agg(F.array_sort(F.collect_set("deep")).alias("parts"))
            level = level.join(sets, ["doc_id", "okey"], "left")
            deep = F.xxhash64(own, F.coalesce(F.array_join(F.col("parts").cast("array<string>"), ","), F.lit("")))
        else:
            deep = own
        below = materialise(level.select("doc_id", "okey", "tag", deep.alias("deep")), "deep")
        done = below if done is None else done.union(below)
    return done


def literal_types(nodes: DataFrame) -> DataFrame:
    """doc_id, okey, n: the literal reading, in which n counts earlier inner elements (not shapes) that are weakly distinct
    from a node on its level."""
    inner = nodes.where(F.col("kind") == model.INNER).select("doc_id", "okey", "tag", signature_text().alias("sig"), keys.depth(F.col("okey")).alias("depth"))
    before = (Window.unboundedPreceding, -1)
    all_, same = Window.partitionBy("doc_id", "depth", "tag").orderBy("okey").rowsBetween(*before), Window.partitionBy("doc_id", "depth", "sig").orderBy("okey").rowsBetween(*before)
    return inner.select("doc_id", "okey", "tag", (F.count("*").over(all_) - F.count("*").over(same)).alias("n"))
