"""Pairs of records that share candidates, and their joint probability."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sigres.functions.posterior import ln_doubt
from sigres.functions.text import is_run, is_subrecord


def generate(index: DataFrame, scope: str = "dedupe") -> DataFrame:
    """(sig, rid, source, k) -> (lo, hi, sig, k), lo < hi, for every two records of a candidate.

    ``scope``: 'dedupe' or 'both' all pairs, 'cross' pairs of two sources.  Lists are at most k_max
    long, as the index holds no longer ones.
    """
    lists = index.groupBy("sig", "k").agg(F.array_sort(F.collect_list(F.struct("rid", "source"))).alias("r"))
    pairs = F.flatten(F.transform("r", lambda x, i: F.transform(
        F.slice("r", i + 2, F.size("r")), lambda y: F.struct(x.alias("x"), y.alias("y")))))
    rows = lists.select("sig", "k", F.explode(pairs).alias("p"))
    if scope == "cross":
        rows = rows.where("p.x.source <> p.y.source")
    return rows.select(F.col("p.x.rid").alias("lo"), F.col("p.y.rid").alias("hi"), "sig", "k")


def eliminate(pairs: DataFrame, containment: str = "gapped") -> DataFrame:
    """Drop a candidate of a pair if the pair shares a longer one that contains it.

    'gapped' allows deleted words in between, 'contiguous' does not.  Containment is strict.
    """
    test = is_subrecord if containment == "gapped" else is_run
    per = pairs.groupBy("lo", "hi").agg(F.collect_list(F.struct(F.split("sig", " ").alias("w"), "sig", "k")).alias("s"))

    def stays(x: Column) -> Column:
        return ~F.exists("s", lambda y: (F.size(y["w"]) > F.size(x["w"])) & test(x["w"], y["w"]))
    kept = per.select("lo", "hi", F.explode(F.filter("s", stays)).alias("x"))
    return kept.select("lo", "hi", "x.sig", "x.k")


def combine(pairs: DataFrame, a: float, b: float) -> DataFrame:
    """(lo, hi, n_sig, ln_doubt, prob): one minus the product of (1 - p), as a sum of logarithms."""
    total = F.sum(ln_doubt(F.col("k"), a, b))
    return pairs.groupBy("lo", "hi").agg(F.count("*").alias("n_sig"), total.alias("ln_doubt")).withColumn("prob", -F.expm1("ln_doubt"))


def threshold(links: DataFrame, tau: float) -> DataFrame:
    """Links with probability above tau, compared in logarithms."""
    if tau >= 1:
        return links.where(F.lit(False))
    return links.where(F.col("ln_doubt") < math.log1p(-tau)) if tau > 0 else links


def star_links(index: DataFrame, a: float, b: float, tau: float, scope: str = "dedupe") -> DataFrame:
    """Links of candidates that are above tau alone, to the smallest record of each: k - 1 edges, not k (k - 1) / 2.

    The closure equals that of all pairs which share such a candidate.  With scope 'cross' only candidates of
    two sources count: every record of one source then has a partner in another, so all of them are connected.
    """
    own = index.where(ln_doubt(F.col("k"), a, b) < math.log1p(-tau)) if 0 < tau < 1 else index.where(F.lit(tau <= 0))
    hub = own.groupBy("sig").agg(F.min("rid").alias("lo"), F.min("source").alias("first"), F.max("source").alias("last"))
    if scope == "cross":
        hub = hub.where("first <> last")
    return own.join(hub.select("sig", "lo"), "sig").where("rid > lo").select("lo", F.col("rid").alias("hi")).distinct()


def recurrences(pairs: DataFrame) -> DataFrame:
    """(lo, hi, ks): per pair how many shared candidates recur k times, as a map; enough to score any (a, b).

    Pairs are dealt by their two records once, which serves both groupings and a join by pair.
    """
    per = pairs.repartition("lo", "hi").groupBy("lo", "hi", "k").agg(F.count("*").alias("n"))
    return per.groupBy("lo", "hi").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("k", "n")))).alias("ks"))
