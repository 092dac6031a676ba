"""Column helpers shared by the DataFrame-only operators."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

#: The characters that separate words (space, 0x09-0x0D).
BLANKS = " \t\n\x0b\f\r"
BLANK_RUN = "[ \\t-\\r]+"


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` with ``value`` bound once.

    A plain column reference inside a lambda may be inlined by the optimizer
    and then runs once per element; a lambda variable is always a value.
    """
    return F.transform(F.array(value), body)[0]


def words_of(text: Column) -> Column:
    """The words of a text as an array; null and blank texts have none."""
    body = F.trim(F.coalesce(text, F.lit("")), F.lit(BLANKS))
    return F.when(body == "", F.array().cast("array<string>")).otherwise(F.split(body, BLANK_RUN))


def n_words_of(text: Column) -> Column:
    """The number of words, without building strings for them."""
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit("[^ \\t-\\r]+")).cast("long")
