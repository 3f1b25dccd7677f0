"""Parameter search on labelled pairs: one pass over recurrences scores the whole grid."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sigres.functions.posterior import k_max
from sigres.operators.metrics import with_rates
from sigres.operators.pairs import recurrences


def grid(as_, bs, rhos, taus) -> list[tuple[float, float, float, float, int]]:
    return [(a, b, r, t, k_max(r, a, b)) for a in as_ for b in bs for r in rhos for t in taus]


def _linked(pairs: DataFrame, truth: DataFrame, points: list[tuple[float, float, float, float, int]], *keys: Column) -> DataFrame:
    """A row per grid point, pattern of recurrences that it links, and keys: g, n pairs, and t, which is null if they are not true.

    p depends on k only, so a pair is scored from the number of its candidates of each k; the
    postings and counts are made once for all points.  Pairs are counted by pattern before the points
    are tried: there are few patterns, however many pairs.
    """
    # neither side's size is known before it is made, so neither may be broadcast
    scored = recurrences(pairs).hint("merge").join(truth.select("lo", "hi", F.lit(1).alias("t")), ["lo", "hi"], "left")
    patterns = scored.groupBy(*keys, F.map_entries("ks").alias("ks"), "t").agg(F.count("*").alias("n"))
    cells = F.explode(F.array(*[F.struct(*[F.lit(x).alias(n) for n, x in zip(("a", "b", "rho", "tau", "most"), p)]) for p in points])).alias("g")
    rows = patterns.select("*", cells)

    def doubt(k: Column, n: Column) -> Column:
        x = k * F.ln("g.a") + F.ln("g.b")
        return F.when(k <= F.col("g.most"), -n * F.log1p(F.exp(-x))).otherwise(F.lit(0.0))
    total = F.aggregate("ks", F.lit(0.0), lambda s, e: s + doubt(e["key"], e["value"]))
    return rows.where(total < F.log1p(-F.col("g.tau")))


def _tp_fp() -> tuple[Column, Column]:
    """True and false pairs among the patterns that are linked."""
    of = lambda test, name: F.coalesce(F.sum(F.when(test, F.col("n"))), F.lit(0)).alias(name)
    return of(F.col("t").isNotNull(), "tp"), of(F.col("t").isNull(), "fp")


def tune(pairs: DataFrame, truth: DataFrame, points: list[tuple[float, float, float, float, int]]) -> DataFrame:
    """pairs (lo, hi, sig, k) up to the largest k_max -> a row per grid point: a, b, rho, tau, tp, fp, fn, rates."""
    linked, truths = _linked(pairs, truth, points), truth.count()
    n = linked.groupBy("g.a", "g.b", "g.rho", "g.tau").agg(*_tp_fp())
    return with_rates(n.withColumn("fn", F.lit(truths) - F.col("tp")))


def fold_of(folds: int) -> Column:
    """Fold of a pair, by its smaller record."""
    return F.pmod(F.floor(F.col("lo") / 2), F.lit(folds))


def f_measure(tp: int, fp: int, fn: int) -> float:
    return 2 * tp / (2 * tp + fp + fn) if tp else 0.0


def tune_held_out(pairs: DataFrame, truth: DataFrame, points: list[tuple[float, float, float, float, int]], folds: int = 5) -> tuple[int, int, int]:
    """(tp, fp, fn) over all folds, each scored at the point that is best on the others; only counts reach the driver."""
    fold = fold_of(folds).alias("fold")
    rows = _linked(pairs, truth, points, fold).groupBy("fold", "g.a", "g.b", "g.rho", "g.tau").agg(*_tp_fp()).collect()
    truths = {r.fold: r["count"] for r in truth.groupBy(fold).count().collect()}
    counts = {(r.fold, (r.a, r.b, r.rho, r.tau)): (r.tp, r.fp) for r in rows}
    total = [0, 0, 0]
    for k in range(folds):
        def rest(point, k=k):
            got = [counts.get((j, point), (0, 0)) for j in range(folds) if j != k]
            tp, fp = sum(x[0] for x in got), sum(x[1] for x in got)
            return f_measure(tp, fp, sum(v for j, v in truths.items() if j != k) - tp)
        chosen = max((p[:4] for p in points), key=lambda p: (rest(p), [-x for x in p]))
        tp, fp = counts.get((k, chosen), (0, 0))
        total = [total[0] + tp, total[1] + fp, total[2] + truths.get(k, 0) - tp]
    return tuple(total)


def best(scores: DataFrame) -> DataFrame:
    """The point with the largest F; ties go to the larger precision, then to the smaller parameters."""
    return scores.orderBy(F.desc("f"), F.desc("precision"), "a", "b", "rho", "tau").limit(1)


def a_b_from_rates(lam: float, mu: float, c: float) -> tuple[float, float]:
    return mu / lam, math.exp(lam - mu) * (1 - c) / c
