"""Inverted index: how often a candidate recurs, and the postings of those that may identify."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sigres.functions.posterior import k_max, posterior
from sigres.plans.scratch import Scratch

#: Candidates up to which their table is broadcast (about 30 bytes each as hashes).
BROADCAST_SIGNATURES = 500_000
#: Records from which on the postings of a candidate that cannot identify are dropped before the shuffle.
HOT = 10_000


def dictionary(postings: DataFrame, most: int | None = None, least: int = 2) -> DataFrame:
    """(sig, k) of candidates in at least ``least`` and at most ``most`` distinct records.

    Counts combine before the shuffle, so a candidate of all records costs a row per task.
    """
    counts = postings.groupBy("sig").agg(F.count("*").alias("k")).where(F.col("k") >= least)
    return counts if most is None else counts.where(F.col("k") <= most)


def meet(postings: DataFrame, counts: DataFrame) -> DataFrame:
    """Postings of the counted candidates, by a shuffle of both sides.

    Postings are exploded from records, and Spark takes them for about as large as the records' file; left to
    itself it broadcasts them, tens of millions of rows at 60 times sf0.1, through the driver.
    """
    return postings.hint("merge").join(counts, "sig")


def build_index(postings: DataFrame, a: float, b: float, rho: float, scratch: Scratch | None = None) -> DataFrame:
    """(sig, rid, source, k): the postings of candidates with p > rho and k >= 2.

    p > rho is k <= k_max.  With ``scratch`` the counts are written first: candidates of one record, most
    of all, are gone then; if those that stay are few they are broadcast and no posting is shuffled, else
    the postings of hot candidates go before the shuffle, so no task meets all records of one candidate.
    """
    most = k_max(rho, a, b)
    if scratch is None:
        return meet(postings, dictionary(postings, most))
    counts = scratch.save(dictionary(postings), "counts")
    good = scratch.save(counts.where(F.col("k") <= most), "good")
    if good.count() <= BROADCAST_SIGNATURES:
        return postings.join(F.broadcast(good), "sig")
    hot = scratch.save(counts.where(F.col("k") > max(most, HOT)).select("sig"), "hot")
    if 0 < hot.count() <= BROADCAST_SIGNATURES:
        postings = postings.join(F.broadcast(hot), "sig", "left_anti")
    return meet(postings, good)


def with_posterior(entries: DataFrame, a: float, b: float) -> DataFrame:
    return entries.withColumn("p", posterior(F.col("k"), a, b))


def recurrence_histogram(postings: DataFrame) -> DataFrame:
    """(k, signatures): how many candidates recur in exactly k records."""
    return dictionary(postings, least=1).groupBy("k").agg(F.count("*").alias("signatures"))


def family_report(by_family: DataFrame, most: int) -> DataFrame:
    """Per family: candidates, share that recurs, share that is distinctive, records covered."""
    k = by_family.groupBy("fam", "sig").agg(F.count("*").alias("k"))
    shares = k.groupBy("fam").agg(F.count("*").alias("candidates"),
                                  F.round(F.avg((F.col("k") >= 2).cast("double")), 6).alias("recurrence_rate"),
                                  F.round(F.avg((F.col("k") <= most).cast("double")), 6).alias("distinctiveness"))
    covered = by_family.groupBy("fam").agg(F.count_distinct("rid").alias("coverage"))
    return shares.join(covered, "fam")


def link_economy(entries: DataFrame) -> DataFrame:
    """Links stored when records link to records, and when they link to signatures."""
    k = entries.select("sig", "k").distinct()
    return k.agg(F.sum(F.expr("k * (k - 1) div 2")).alias("record_links"), F.sum("k").alias("signature_links"))
