"""Typed forms of fact values."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def number(value: Column) -> Column:
    return F.trim(value).try_cast("double")


def number_list(value: Column) -> Column:
    """The value as a list of numbers, if it is two or more numbers between blanks."""
    parts = F.split(F.trim(value), r"\s+")
    numbers = F.transform(parts, lambda x: x.try_cast("double"))
    return F.when((F.size(parts) > 1) & F.forall(numbers, lambda x: x.isNotNull()), numbers)


def timestamp(value: Column) -> Column:
    return F.try_to_timestamp(value)
