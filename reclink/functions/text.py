"""Manipulation functions: Column to Column, built-ins only.

A function maps a value to the token that goes into a signature; null stays null.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

Manipulation = Callable[[Column], Column]


def whole(c: Column) -> Column:
    return c.cast("string")


def normalise(c: Column) -> Column:
    """Lower case, inner white space as one blank, no white space at the ends; blank is null."""
    text = F.trim(F.regexp_replace(F.lower(c.cast("string")), r"\s+", " "))
    return F.when(F.length(text) > 0, text)


def year_of(c: Column) -> Column:
    return F.year(c).cast("string")


def street_name(c: Column) -> Column:
    """First word of letters only: '43 Skye Pl' gives 'Skye'."""
    found = F.regexp_extract(c, r"(?:^|\s)([A-Za-z]+)(?=\s|$)", 1)
    return F.when(F.length(found) > 0, found)


def prefix(n: int) -> Manipulation:
    return lambda c: F.substring(c, 1, n)


def suffix(n: int) -> Manipulation:
    return lambda c: F.right(c, F.lit(n))


def nth_token(i: int) -> Manipulation:
    """The i-th word (from 1), null if there are fewer."""
    return lambda c: F.nullif(F.split_part(c, F.lit(" "), F.lit(i)), F.lit(""))


def initials(c: Column) -> Column:
    return F.array_join(F.transform(F.filter(F.split(c, " "), lambda w: F.length(w) > 0), lambda w: F.substring(w, 1, 1)), "")


def digits(c: Column) -> Column:
    found = F.regexp_replace(c, "[^0-9]", "")
    return F.when(F.length(found) > 0, found)


def phonetic(c: Column) -> Column:
    return F.soundex(c)


def qgrams(q: int) -> Manipulation:
    """Array of the q-grams of a text; shorter texts are one gram."""

    def grams(c: Column) -> Column:
        n = F.length(c) - q + 1
        return F.when(n < 1, F.array(c)).otherwise(F.transform(F.sequence(F.lit(1), F.greatest(n, F.lit(1))), lambda i: F.substring(c, i, F.lit(q))))

    return grams
