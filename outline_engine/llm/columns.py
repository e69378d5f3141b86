"""Column helpers for the native operators."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

#: A word is a run of characters other than blank and the ASCII controls from tab to carriage return.
WORD = r"[^\x20\x09-\x0D]+"


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of ``value``, with ``value`` computed once however often the body names it."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def text_of(name: str = "text") -> Column:
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def words_of(text: Column) -> Column:
    """The words of a text.  Only blanks are left as separators, so the split needs no regular expression."""
    for separator in "\t\n\x0b\x0c\r":
        text = F.replace(text, F.lit(separator), F.lit(" "))
    return F.array_remove(F.split(text, " "), "")


def indices(n: Column) -> Column:
    """0 .. n-1, empty for n below 1."""
    return F.when(n > 0, F.sequence(F.lit(0), n - 1)).otherwise(F.array().cast("array<int>"))
