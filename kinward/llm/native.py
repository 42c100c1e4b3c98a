"""Small helpers for operators that stay within Spark's own functions."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Java patterns for the six ASCII space characters and their complement.
GAP, INK = r"[\x20\x09-\x0D]+", r"[^\x20\x09-\x0D]"
SPACES = " \t\n\x0b\x0c\r"


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body(value)`` with the value computed once, also inside nested lambdas."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def words_of(text: Column) -> Column:
    """The words of a text, in order; none for an empty one."""
    return let(
        F.btrim(text, F.lit(SPACES)),
        lambda t: F.when(t == "", F.array().cast("array<string>")).otherwise(F.split(t, GAP)),
    )


def lines_of(text: Column) -> Column:
    return F.split(text, "\n")


def has_ink(line: Column) -> Column:
    return line.rlike(INK)
