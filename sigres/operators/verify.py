"""Verification of links by similarity or domain rules."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sigres.functions.text import jaccard

Rule = Callable[[Column, Column], Column]


def verify(links: DataFrame, records: DataFrame, rule: Callable[[str, str], Column] | None, cols: list[str]) -> DataFrame:
    """Links whose records pass ``rule(prefix of one, prefix of other)``; columns are x_<name>, y_<name>.

    Both joins are on rid: with records bucketed by rid neither side is shuffled again.
    """
    if rule is None:
        return links
    side = lambda p, key: records.select(F.col("rid").alias(key), *[F.col(c).alias(f"{p}_{c}") for c in cols])
    both = links.join(side("x", "lo"), "lo").join(side("y", "hi"), "hi")
    return both.where(rule("x", "y")).select(*links.columns)


def by_jaccard(col: str, least: float):
    """Set similarity; the sizes are compared first, as their ratio bounds it."""
    def rule(x: str, y: str) -> Column:
        a, b = F.col(f"{x}_{col}"), F.col(f"{y}_{col}")
        na, nb = F.size(a), F.size(b)
        return (F.least(na, nb) >= least * F.greatest(na, nb)) & (jaccard(a, b) >= least)
    return rule


def by_levenshtein(col: str, most: int):
    """Edit distance of the joined words, given up beyond ``most``."""
    def rule(x: str, y: str) -> Column:
        a, b = F.array_join(f"{x}_{col}", " "), F.array_join(f"{y}_{col}", " ")
        return (F.abs(F.length(a) - F.length(b)) <= most) & (F.levenshtein(a, b, most) >= 0)
    return rule


def jaro(a: str, b: str) -> float:
    """Jaro similarity: matches within half the longer length, and transpositions."""
    if a == b:
        return 1.0
    if not a or not b:
        return 0.0
    reach = max(0, max(len(a), len(b)) // 2 - 1)
    taken = [False] * len(b)
    mine = []
    for i, c in enumerate(a):
        for j in range(max(0, i - reach), min(len(b), i + reach + 1)):
            if not taken[j] and b[j] == c:
                taken[j] = True
                mine.append(c)
                break
    m = len(mine)
    if not m:
        return 0.0
    theirs = [c for c, t in zip(b, taken) if t]
    swaps = sum(x != y for x, y in zip(mine, theirs)) // 2
    return (m / len(a) + m / len(b) + (m - swaps) / m) / 3


def jaro_winkler(a: str, b: str, scale: float = 0.1, least: float = 0.7) -> float:
    """Jaro similarity raised for a common beginning of up to four characters, above ``least``."""
    j = jaro(a, b)
    if j <= least:
        return j
    same = 0
    for x, y in zip(a[:4], b[:4]):
        if x != y:
            break
        same += 1
    return j + same * scale * (1 - j)


def similarity_udf(winkler: bool):
    """An Arrow UDF over two text columns; Spark has no such function of its own."""
    f = jaro_winkler if winkler else jaro

    @F.pandas_udf("double")
    def column(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([f(x, y) for x, y in zip(a, b)], dtype="float64")
    return column


def by_jaro(col: str, least: float, winkler: bool = False):
    def rule(x: str, y: str) -> Column:
        return similarity_udf(winkler)(F.array_join(f"{x}_{col}", " "), F.array_join(f"{y}_{col}", " ")) >= least
    return rule


def by_rules(rules: list):
    """All rules hold."""
    def rule(x: str, y: str) -> Column:
        out = F.lit(True)
        for r in rules:
            out = out & r(x, y)
        return out
    return rule


def _present(x: str, y: str, col: str) -> Column:
    return (F.size(f"{x}_{col}") > 0) & (F.size(f"{y}_{col}") > 0)


def not_co_residents(address: str = "res", name: str = "name"):
    """Vetoes two given names at one address: co-residents, not one person."""
    def rule(x: str, y: str) -> Column:
        same = _present(x, y, address) & (F.col(f"{x}_{address}") == F.col(f"{y}_{address}"))
        other = F.element_at(f"{x}_{name}", 1) != F.element_at(f"{y}_{name}", 1)
        return ~(same & _present(x, y, name) & other)
    return rule


def not_person_and_company(company: str = "company"):
    """Vetoes a person against a record that names a company."""
    return lambda x, y: (F.size(f"{x}_{company}") > 0) == (F.size(f"{y}_{company}") > 0)


def not_account_only(account: str = "account", name: str = "name"):
    """Vetoes records that share an account and no word of the name: branches of one firm."""
    def rule(x: str, y: str) -> Column:
        shared = _present(x, y, account) & (F.col(f"{x}_{account}") == F.col(f"{y}_{account}"))
        return ~(shared & ~F.arrays_overlap(f"{x}_{name}", f"{y}_{name}"))
    return rule
