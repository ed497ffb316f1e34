"""Column expressions for scanning and rewriting matches of a pattern inside a text, without leaving the JVM."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F


def chars(s: Column) -> Column:
    return F.filter(F.split(s, ""), lambda c: c != "")


def matches(text: Column, pattern: str) -> Column:
    """All matches in order, as an array of strings; none for a null text."""
    return F.coalesce(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), F.array().cast("array<string>"))


def gaps(text: Column, pattern: str) -> Column:
    """What stands before, between and behind the matches: one more than there are matches."""
    return F.split(text, pattern, -1)


def weave(between: Column, instead: Column) -> Column:
    """The text with its matches replaced: the gaps with ``instead`` between them."""
    return F.array_join(F.zip_with(between, instead, lambda g, m: F.concat(F.coalesce(g, F.lit("")), F.coalesce(m, F.lit("")))), "")


def when_found(text: Column, pattern: str, then: Column, otherwise: Column) -> Column:
    return F.when(text.rlike(pattern), then).otherwise(otherwise)


def fold(first: Column, n: int, step: Callable[[Column, Column], Column]) -> Column:
    """step(step(first, 0), 1) ... for 0 .. n - 1."""
    return F.aggregate(F.array(*map(F.lit, range(n))), first, step)
