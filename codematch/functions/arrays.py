"""Column helpers over arrays that stay in the JVM."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value), with value computed once however often body names it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def tail(a: Column, n: int) -> Column:
    """The array without its first n elements."""
    return F.slice(a, n + 1, F.size(a))


def head(a: Column, n: Column) -> Column:
    """The first n elements, none if n is below 0."""
    return F.slice(a, F.lit(1), F.greatest(n, F.lit(0)))


def lower_ascii(text: Column) -> Column:
    """A-Z to a-z, all else untouched."""
    return F.when(text.rlike(r"[^\x00-\x7F]"), F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")).otherwise(F.lower(text))


def text_key(text: Column) -> tuple[Column, Column]:
    """Two independent 64-bit hashes of a text; null counts as empty."""
    t = F.coalesce(text, F.lit(""))
    return F.xxhash64(t), F.xxhash64(F.lit(7), t)
