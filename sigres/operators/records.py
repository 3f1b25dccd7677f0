"""Records: exact duplicates removed, one representative each, members carried along."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def dedupe_exact(df: DataFrame, cols: list[str], key: str, digest: bool = True) -> DataFrame:
    """Distinct rows by ``cols`` with the smallest ``key`` as rid and the number of members.

    With ``digest`` the shuffle is by two 64-bit hashes of the columns instead of the columns
    themselves, so long texts stay where they are; min and count combine before it.
    """
    if not digest:
        return df.groupBy(*cols).agg(F.min(key).alias("rid"), F.count("*").alias("members"))
    h1, h2 = F.xxhash64(*cols), F.xxhash64(F.lit(1), *cols)
    return df.groupBy(h1.alias("_h1"), h2.alias("_h2")).agg(F.min(key).alias("rid"), F.count("*").alias("members")).drop("_h1", "_h2")


def members(df: DataFrame, cols: list[str], key: str) -> DataFrame:
    """(rid, key): every row with its representative.  Joined on the digest, not by a window, so that
    a large group of copies is not one task."""
    h1, h2 = F.xxhash64(*cols).alias("_h1"), F.xxhash64(F.lit(1), *cols).alias("_h2")
    keyed = df.select(key, h1, h2)
    least = keyed.groupBy("_h1", "_h2").agg(F.min(key).alias("rid"))
    return keyed.join(least, ["_h1", "_h2"]).select("rid", key)


def distinct_records(df: DataFrame, cols: list[str], key: str) -> DataFrame:
    """The representatives with all their columns."""
    reps = dedupe_exact(df, cols, key).select(F.col("rid").alias(key))
    return df.join(reps, key, "left_semi")
