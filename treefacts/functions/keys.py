"""Order keys: a node number as text, 16 hexadecimal digits for each component.

Text order is document order, an ancestor's key is a prefix, and the keys below x are the range from x to x + 'g'.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F

WIDTH = 16


def encode(node: Sequence[int]) -> str:
    return "".join(f"{i:016x}" for i in node)


def decode(okey: str) -> tuple[int, ...]:
    return tuple(int(okey[i : i + WIDTH], 16) for i in range(0, len(okey), WIDTH))


def digit(ordinal: Column) -> Column:
    return F.lpad(F.lower(F.hex(ordinal.cast("long"))), WIDTH, "0")


def child(parent: Column | str, ordinal: Column) -> Column:
    return F.concat(F.lit(parent) if isinstance(parent, str) else parent, digit(ordinal))


def depth(okey: Column) -> Column:
    return (F.length(okey) / WIDTH).cast("int")


def parent(okey: Column) -> Column:
    return F.substring(okey, F.lit(1), F.length(okey) - WIDTH)


def cut(okey: Column, to_depth: int) -> Column:
    """Key of the ancestor at a depth; of deeper or equal nodes only."""
    return F.substring(okey, 1, WIDTH * to_depth)


def components(okey: Column) -> Column:
    """The node number as an array of longs."""
    places = F.sequence(F.lit(0), depth(okey) - 1)
    return F.transform(places, lambda i: F.conv(F.substring(okey, i * WIDTH + 1, F.lit(WIDTH)), 16, 10).cast("long"))


def dotted(okey: Column) -> Column:
    return F.array_join(components(okey).cast("array<string>"), ".")


def reversed_list(okey: Column) -> Column:
    """The node number with the own digit first and the record's tail behind it."""
    return F.reverse(components(okey))


def last(okey: Column) -> Column:
    return F.conv(F.substring(okey, -WIDTH, WIDTH), 16, 10).cast("long")


def is_below(okey: Column, ancestor: Column) -> Column:
    return okey.startswith(ancestor) & (F.length(okey) > F.length(ancestor))


def below(okey: Column, ancestor: str) -> Column:
    """A range that file statistics can use."""
    return (okey > ancestor) & (okey < ancestor + "g")
