"""Tokenising: words, q-grams and characters, as native expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Characters that words are made of, after lower-casing; all others separate words.
SEPARATORS = "[^0-9a-zà-öø-ÿß]+"


def plain(text: Column) -> Column:
    """The text in lower case with one space between words and none around; null is empty."""
    return F.trim(F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), SEPARATORS, " "))


def words(text: Column, unit: str = "word", q: int = 3) -> Column:
    """The ordered tokens of a text: words, q-grams of the plain text, or its characters."""
    if unit == "word":
        return F.array_remove(F.split(plain(text), " "), "")
    size = 1 if unit == "char" else q
    p = plain(text)
    return F.when(F.length(p) < size, F.array().cast("array<string>")).otherwise(
        F.transform(F.sequence(F.lit(1), F.greatest(F.length(p) - size + 1, F.lit(1))), lambda i: p.substr(i, F.lit(size))))


def is_subrecord(s: Column, r: Column) -> Column:
    """Whether ``s`` is ``r`` with words deleted, order kept: a fold that walks a pointer over r."""
    at = F.aggregate(r, F.lit(0), lambda i, w: F.when(w == F.get(s, i), i + 1).otherwise(i))
    return at >= F.size(s)


def is_run(s: Column, r: Column) -> Column:
    """Whether ``s`` is a run of consecutive words of ``r``."""
    return F.contains(F.concat(F.lit(" "), F.array_join(r, " "), F.lit(" ")),
                      F.concat(F.lit(" "), F.array_join(s, " "), F.lit(" ")))


def jaccard(a: Column, b: Column) -> Column:
    """Similarity of two arrays as sets; of two empty ones 1."""
    both = F.size(F.array_intersect(a, b))
    union = F.size(F.array_union(a, b))
    return F.when(union == 0, F.lit(1.0)).otherwise(both / union)


def cents(money: Column) -> Column:
    """A price as text of its cents: the same text in any engine."""
    return F.round(money * 100).cast("long").cast("string")
