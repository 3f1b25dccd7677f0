"""Candidate-signature families: which subrecords of a record are tried.

A family turns a record (``rid``, ``source`` and attributes that are arrays of words) into an array of
signatures, as one native expression.  Words of a signature are joined by one space; parts that come
from different attributes are joined by `` | ``.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from itertools import product

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

_NONE = "array<string>"


@dataclass(frozen=True)
class Family:
    """``expr()`` gives the signatures; ``run`` is (attribute, words) for families of consecutive words."""

    name: str
    expr: Callable[[], Column]
    run: tuple[str, int] | None = None


def _guard(condition: Column, value: Column) -> Column:
    return F.when(condition, value).otherwise(F.array().cast(_NONE))


def consecutive(attr: str, n: int) -> Family:
    """Every run of n consecutive words."""
    def expr() -> Column:
        a = F.col(attr)
        starts = F.sequence(F.lit(1), F.greatest(F.size(a) - n + 1, F.lit(1)))
        return _guard(F.size(a) >= n, F.transform(starts, lambda i: F.array_join(F.slice(a, i, n), " ")))
    return Family(f"run{n}({attr})", expr, (attr, n))


def word_pairs(attr: str) -> Family:
    """Every unordered pair of words at two places, the smaller word first."""
    def expr() -> Column:
        a = F.col(attr)
        firsts = F.sequence(F.lit(1), F.greatest(F.size(a) - 1, F.lit(1)))
        pair = lambda x, y: F.concat(F.least(x, y), F.lit(" "), F.greatest(x, y))
        return _guard(F.size(a) >= 2, F.flatten(F.transform(firsts, lambda i: F.transform(
            F.slice(a, i + 1, F.size(a)), lambda y: pair(F.element_at(a, i), y)))))
    return Family(f"pairs({attr})", expr)


def last_digits(attr: str, n: int = 6) -> Family:
    """The last n digits of a number attribute; nothing if it has fewer."""
    def expr() -> Column:
        digits = F.regexp_replace(F.array_join(attr, ""), "[^0-9]", "")
        return _guard(F.length(digits) >= n, F.array(F.right(digits, F.lit(n))))
    return Family(f"tail{n}({attr})", expr)


def whole(attr: str) -> Family:
    """The whole value of an attribute; nothing if it is empty."""
    return Family(f"whole({attr})", lambda: _guard(F.size(attr) > 0, F.array(F.array_join(attr, " "))))


def shifted(attr: str, by_source: dict[int, int]) -> Family:
    """A number attribute moved by a constant per source, such as an age in an older snapshot."""
    def expr() -> Column:
        shift = F.lit(0)
        for source, by in by_source.items():
            shift = F.when(F.col("source") == source, by).otherwise(shift)
        value = F.element_at(attr, 1).cast("long")
        return _guard(F.size(attr) > 0, F.array((value + shift).cast("string")))
    return Family(f"shift({attr})", expr)


def _beside(left: Column, right: Column) -> Column:
    return F.flatten(F.transform(left, lambda x: F.transform(right, lambda y: F.concat(x, F.lit(" | "), y))))


def compose(*families: Family) -> Family:
    """One signature of each family, side by side."""
    def expr() -> Column:
        out = families[0].expr()
        for f in families[1:]:
            out = _beside(out, f.expr())
        return out
    return Family(" + ".join(f.name for f in families), expr)


def random_subrecords(attr: str, length: int, count: int, seed: int = 0) -> Family:
    """``count`` subrecords of ``length`` words at places drawn by a fixed arithmetic of rid; fewer words
    where places coincide.  Never ``rand``: reruns and other engines give the same."""
    def expr() -> Column:
        a = F.col(attr)

        def one(i: Column) -> Column:
            places = F.array_sort(F.array_distinct(F.transform(F.sequence(F.lit(1), F.lit(length)), lambda j: F.pmod(
                F.col("rid") * 7919 + i * 104729 + j * 1299709 + seed, F.size(a)) + 1)))
            return F.array_join(F.transform(places, lambda p: F.element_at(a, p.cast("int"))), " ")
        return _guard(F.size(a) > 0, F.array_distinct(F.transform(F.sequence(F.lit(1), F.lit(count)), one)))
    return Family(f"random{length}x{count}({attr})", expr)


def grammar(attrs: list[str], lengths: tuple[int, ...] = (1, 2, 3), pairs: bool = True, compose_two: bool = True) -> list[Family]:
    """All families of a small grammar: runs of each length, pairs, and two different attributes combined."""
    base = [consecutive(a, n) for a in attrs for n in lengths] + ([word_pairs(a) for a in attrs] if pairs else [])
    two = [compose(consecutive(a, 1), whole(b)) for a, b in product(attrs, attrs) if a < b] if compose_two else []
    return base + two


def nested(families: list[Family]) -> bool:
    """Whether a signature of one family can be part of another's: runs of different lengths of one attribute."""
    runs = [f.run for f in families if f.run]
    return any(x[0] == y[0] and x[1] < y[1] for x in runs for y in runs)


def emit(records: DataFrame, families: list[Family], namespace: bool = False) -> DataFrame:
    """records -> distinct (rid, source, sig); no shuffle, as repeats are removed inside the record.

    With ``namespace`` equal words of two families are two signatures.
    """
    def named(i: int, f: Family) -> Column:
        return F.transform(f.expr(), lambda s: F.concat(F.lit(f"{i}: "), s)) if namespace else f.expr()
    sigs = F.array_distinct(F.concat(*[named(i, f) for i, f in enumerate(families)]))
    return records.select("rid", "source", F.explode(sigs).alias("sig"))


def emit_by_family(records: DataFrame, families: list[Family]) -> DataFrame:
    """(rid, source, fam, sig), distinct inside each family."""
    per = F.array(*[F.struct(F.lit(f.name).alias("fam"), F.array_distinct(f.expr()).alias("sigs")) for f in families])
    rows = records.select("rid", "source", F.explode(per).alias("x"))
    return rows.select("rid", "source", F.col("x.fam").alias("fam"), F.explode("x.sigs").alias("sig"))


def hashed(postings: DataFrame) -> DataFrame:
    """Signatures as two 64-bit hashes: 16 bytes in the shuffle whatever their words."""
    return postings.select("rid", "source", F.struct(F.xxhash64("sig").alias("h1"), F.xxhash64(F.lit(1), "sig").alias("h2")).alias("sig"))
