"""Accuracy, blocking, drift, growth and cost measures."""

from __future__ import annotations

import math
import time

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sigres.functions.posterior import posterior


def _pairs(df: DataFrame) -> DataFrame:
    return df.select(F.least("lo", "hi").alias("lo"), F.greatest("lo", "hi").alias("hi")).distinct()


def pair_quality(links: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: tp, fp, fn, precision, recall, f, by one full outer join of both pair sets."""
    both = _pairs(links).withColumn("l", F.lit(1)).join(_pairs(truth).withColumn("t", F.lit(1)), ["lo", "hi"], "full")
    n = both.agg(F.coalesce(F.sum(F.expr("l * t")), F.lit(0)).alias("tp"), F.count(F.expr("case when t is null then 1 end")).alias("fp"),
                 F.count(F.expr("case when l is null then 1 end")).alias("fn"))
    return with_rates(n)


def with_rates(n: DataFrame) -> DataFrame:
    p = F.coalesce(F.try_divide("tp", F.col("tp") + F.col("fp")), F.lit(0.0))
    r = F.coalesce(F.try_divide("tp", F.col("tp") + F.col("fn")), F.lit(0.0))
    f = F.coalesce(F.try_divide(2 * F.col("tp"), 2 * F.col("tp") + F.col("fp") + F.col("fn")), F.lit(0.0))
    return n.withColumns({"precision": F.round(p, 6), "recall": F.round(r, 6), "f": F.round(f, 6)})


def cluster_pairs(components: DataFrame, truth_entity: DataFrame) -> DataFrame:
    """Pair quality of a partition against true entities, without making pairs: group sizes give them.

    components (rid, entity_id), truth_entity (rid, entity); only records with a true entity count.
    """
    both = components.join(truth_entity, "rid")
    pairs = lambda *keys: F.sum(F.expr("n * (n - 1) div 2"))
    count = lambda keys: both.groupBy(*keys).agg(F.count("*").alias("n")).agg(F.coalesce(pairs(), F.lit(0)).alias("v"))
    tp = count(["entity_id", "entity"]).withColumnRenamed("v", "tp")
    found = count(["entity_id"]).withColumnRenamed("v", "found")
    true = count(["entity"]).withColumnRenamed("v", "true")
    one = tp.crossJoin(F.broadcast(found)).crossJoin(F.broadcast(true))  # one row each
    return with_rates(one.select("tp", (F.col("found") - F.col("tp")).alias("fp"), (F.col("true") - F.col("tp")).alias("fn")))


def cluster_sizes(components: DataFrame) -> DataFrame:
    """(size, components)."""
    return components.groupBy("entity_id").agg(F.count("*").alias("size")).groupBy("size").agg(F.count("*").alias("components"))


def blocking_quality(pairs: DataFrame, truth: DataFrame, n_left: int, n_right: int | None = None) -> DataFrame:
    """Pair completeness, pair quality and reduction ratio of candidate pairs."""
    total = n_left * (n_left - 1) // 2 if n_right is None else n_left * n_right
    q = pair_quality(pairs, truth)
    return q.select(F.col("recall").alias("pair_completeness"), F.col("precision").alias("pair_quality"),
                    F.round(1 - (F.col("tp") + F.col("fp")) / total, 6).alias("reduction_ratio"), (F.col("tp") + F.col("fp")).alias("candidate_pairs"))


def block_sizes(postings: DataFrame) -> DataFrame:
    """Distribution of block sizes: blocks, largest, and exact total of pairs."""
    k = postings.groupBy("sig").agg(F.count("*").alias("k"))
    return k.agg(F.count("*").alias("blocks"), F.max("k").alias("largest"), F.sum(F.expr("k * (k - 1) div 2")).alias("pairs"))


def drift_report(a: DataFrame, b: DataFrame, attrs: list[str]) -> DataFrame:
    """Share of records in both snapshots whose attribute differs; joined on ``key``."""
    both = a.select("key", *[F.col(c).alias(f"a_{c}") for c in attrs]).join(b.select("key", *[F.col(c).alias(f"b_{c}") for c in attrs]), "key")
    changed = [F.round(F.avg((F.col(f"a_{c}") != F.col(f"b_{c}")).cast("double")), 6).alias(c) for c in attrs]
    return both.agg(F.count("*").alias("common"), *changed)


def coverage(records: DataFrame, entries: DataFrame) -> DataFrame:
    """Records with and without a surviving candidate."""
    have = entries.select("rid").distinct().withColumn("has", F.lit(1))
    return records.select("rid").join(have, "rid", "left").agg(
        F.count("*").alias("records"), F.count("has").alias("covered"), (F.count("*") - F.count("has")).alias("unresolvable"))


def size_report(records: DataFrame, postings: DataFrame, truth: DataFrame) -> DataFrame:
    """Per source: records and subrecords; and the number of true pairs."""
    n = records.groupBy("source").agg(F.count("*").alias("records"))
    m = postings.groupBy("source").agg(F.count("*").alias("subrecords"))
    return n.join(m, "source", "left").crossJoin(F.broadcast(truth.agg(F.count("*").alias("truth"))))


def growth(postings_of, parts: list[int]) -> DataFrame:
    """Largest and mean recurrence as the data grows: ``postings_of(m)`` are those of every m-th record."""
    out = None
    for m in parts:
        k = postings_of(m).groupBy("sig").agg(F.count("*").alias("k"))
        row = k.agg(F.lit(m).alias("every"), F.count("*").alias("candidates"), F.max("k").alias("max_k"), F.round(F.avg("k"), 6).alias("mean_k"))
        out = row if out is None else out.unionByName(row)
    return out


# ---- laws of recurrence ----

def ln_choose(n: int, k: Column) -> Column:
    return F.aggregate(F.sequence(F.lit(1), F.greatest(k.cast("int"), F.lit(1))), F.lit(0.0),
                       lambda s, i: F.when(i > k, s).otherwise(s + F.ln((F.lit(float(n)) - i + 1) / i)))


def binomial_mixture_pmf(rates: DataFrame, n: int, ks: list[int]) -> DataFrame:
    """rates (p, weight) -> (k, mixture, poisson): the law of recurrence and its Poisson approximation."""
    k = F.explode(F.array(*[F.lit(x) for x in ks])).alias("k")
    rows = rates.select("p", "weight", k)
    ln_f = F.aggregate(F.sequence(F.lit(1), F.greatest("k", F.lit(1))), F.lit(0.0), lambda s, i: s + F.ln(i.cast("double")))
    binom = F.exp(ln_choose(n, F.col("k")) + F.col("k") * F.ln("p") + (n - F.col("k")) * F.log1p(-F.col("p")))
    poisson = F.exp(F.col("k") * F.ln(n * F.col("p")) - n * F.col("p") - ln_f)
    w = F.sum("weight")
    return rows.groupBy("k").agg((F.sum(F.col("weight") * binom) / w).alias("mixture"), (F.sum(F.col("weight") * poisson) / w).alias("poisson"))


def poisson_fit_error(histogram: DataFrame, lam: float, mu: float, c: float) -> DataFrame:
    """Total variation between a recurrence histogram and one and two zero-truncated Poisson laws."""
    ln_f = F.aggregate(F.sequence(F.lit(1), F.col("k").cast("int")), F.lit(0.0), lambda s, i: s + F.ln(i.cast("double")))
    law = lambda m: F.exp(F.col("k") * math.log(m) - m - ln_f) / -math.expm1(-m)
    mean = lam * c / -math.expm1(-lam) + mu * (1 - c) / -math.expm1(-mu)
    lo, hi = 1e-9, mean
    for _ in range(80):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if mid / -math.expm1(-mid) < mean else (lo, mid)
    total = histogram.agg(F.sum("signatures")).first()[0]
    seen = F.col("signatures") / total
    # mass of the laws beyond what was seen counts as well
    two, one = c * law(lam) + (1 - c) * law(mu), law(lo)
    return histogram.agg(F.round((F.sum(F.abs(seen - one)) + 1 - F.sum(one)) / 2, 6).alias("one_poisson"),
                         F.round((F.sum(F.abs(seen - two)) + 1 - F.sum(two)) / 2, 6).alias("two_poissons"))


def posterior_curves(spark, ks: list[int], as_: list[float], bs: list[float]) -> DataFrame:
    """(k, a, b, p) over a grid."""
    rows = None
    for a in as_:
        for b in bs:
            one = spark.range(1).select(F.explode(F.array(*[F.lit(k) for k in ks])).alias("k")).select(
                "k", F.lit(a).alias("a"), F.lit(b).alias("b"), F.round(posterior(F.col("k"), a, b), 6).alias("p"))
            rows = one if rows is None else rows.unionByName(one)
    return rows


def posterior_curves_of(histogram: DataFrame, as_: list[float], bs: list[float]) -> DataFrame:
    """(k, signatures) -> (k, signatures, a, b, p) over a grid: the curves at the recurrences that a table has."""
    curves = F.explode(F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), F.round(posterior(F.col("k"), a, b), 6).alias("p")) for a in as_ for b in bs])).alias("x")
    return histogram.select("k", "signatures", curves).select("k", "signatures", "x.a", "x.b", "x.p")


class StageReport:
    """Sizes and seconds of the stages of a run."""

    def __init__(self) -> None:
        self.rows: list[tuple[str, int, float]] = []

    def stage(self, name: str, df: DataFrame, scratch) -> DataFrame:
        began = time.time()
        out = scratch.save(df, name)
        self.rows.append((name, out.count(), round(time.time() - began, 3)))
        return out

    def frame(self, spark) -> DataFrame:
        rows = [*self.rows, ("overall", self.rows[-1][1], round(sum(r[2] for r in self.rows), 3))]
        return spark.createDataFrame(rows, "stage string, size long, seconds double")
