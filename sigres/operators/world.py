"""Labelled worlds: all subrecords, exact signatures, and the properties that linking rests on."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sigres.functions.text import is_run, is_subrecord


def all_subrecords(words: Column, max_len: int | None = None) -> Column:
    """Every distinct non-empty subrecord as joined words: a fold that keeps or skips each word.

    Exponential in the number of words unless ``max_len`` bounds the length; for small records.
    """
    grown = F.aggregate(words, F.array(F.array().cast("array<string>")), lambda have, w: F.array_distinct(F.concat(
        have, F.transform(have if max_len is None else F.filter(have, lambda s: F.size(s) < max_len), lambda s: F.array_append(s, w)))))
    return F.transform(F.filter(grown, lambda s: F.size(s) > 0), lambda s: F.array_join(s, " "))


def enumerate_world(labelled: DataFrame, max_len: int | None = None) -> DataFrame:
    """(entity, words) -> distinct (entity, sig)."""
    return labelled.select("entity", F.explode(all_subrecords(F.col("words"), max_len)).alias("sig")).distinct()


def true_signatures(owned: DataFrame) -> DataFrame:
    """(entity, sig) -> signatures that only one entity owns, with that entity."""
    return owned.groupBy("sig").agg(F.count_distinct("entity").alias("n"), F.min("entity").alias("entity")).where("n = 1").select("sig", "entity")


def upward_violations(owned: DataFrame, signatures: DataFrame) -> DataFrame:
    """Longer subrecords that contain a signature of one entity but are not signatures: must be empty."""
    longer = owned.select(F.col("entity"), F.col("sig").alias("longer")).distinct()
    pairs = longer.join(signatures.withColumnRenamed("sig", "shorter"), "entity").where(
        is_subrecord(F.split("shorter", " "), F.split("longer", " ")))
    return pairs.join(signatures.select(F.col("sig").alias("longer")), "longer", "left_anti")


def common_violations(owned: DataFrame, signatures: DataFrame) -> DataFrame:
    """Owners of a signature other than its entity: must be empty."""
    return owned.join(signatures.withColumnRenamed("entity", "owner"), "sig").where("entity <> owner")


# ---- relations by which a record can be a variant of another ----

def relation_equality(left: DataFrame, right: DataFrame) -> DataFrame:
    return left.join(right, left["lv"] == right["rv"]).select("lid", "rid")


def relation_regex(left: DataFrame, right: DataFrame, pattern: str) -> DataFrame:
    """Both sides have the same first group of the pattern: an equi-join on the extracted text."""
    x = left.withColumn("_x", F.regexp_extract("lv", pattern, 1)).where("_x <> ''")
    y = right.withColumn("_y", F.regexp_extract("rv", pattern, 1)).where("_y <> ''")
    return x.join(y, F.col("_x") == F.col("_y")).select("lid", "rid")


def relation_distance(left: DataFrame, right: DataFrame, most: int) -> DataFrame:
    """Edit distance at most ``most``, without comparing all pairs: texts of close distance share one of
    most + 1 consecutive pieces up to a shift of ``most``; pieces meet in an equi-join."""
    parts = most + 1

    def pieces(df: DataFrame, value: str, shifts: bool) -> DataFrame:
        v = F.col(value)
        n = F.length(v)
        sizes = F.sequence(F.greatest(n - most, F.lit(0)), n + most) if shifts else F.array(n)
        steps = F.sequence(F.lit(-most), F.lit(most)) if shifts else F.array(F.lit(0))
        rows = df.select("*", F.explode(sizes).alias("_n"))
        rows = rows.select("*", F.explode(F.sequence(F.lit(0), F.lit(most))).alias("_p"))
        rows = rows.withColumn("_a", F.floor(F.col("_p") * F.col("_n") / parts)).withColumn("_b", F.floor((F.col("_p") + 1) * F.col("_n") / parts))
        rows = rows.select("*", F.explode(steps).alias("_s")).where("_a + _s >= 0")
        return rows.select(*df.columns, "_n", "_p", F.substring(v, (F.col("_a") + F.col("_s") + 1).cast("int"), (F.col("_b") - F.col("_a")).cast("int")).alias("_piece"))
    near = pieces(left, "lv", False).join(pieces(right, "rv", True), ["_n", "_p", "_piece"]).select("lid", "lv", "rid", "rv").distinct()
    return near.where(F.levenshtein("lv", "rv", most) >= 0).select("lid", "rid")


def relation_subrecord(short: DataFrame, long: DataFrame, anchor: int = 3, contiguous: bool = True) -> DataFrame:
    """short (lid, lv words) inside long (rid, rv words): runs of ``anchor`` words meet, then the test.

    Short records of fewer words than ``anchor`` are left out.
    """
    first = short.where(F.size("lv") >= anchor).withColumn("_g", F.array_join(F.slice("lv", 1, anchor), " "))
    grams = F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.size("rv") - anchor + 1, F.lit(1))),
                                         lambda i: F.array_join(F.slice("rv", i, anchor), " ")))
    every = long.where(F.size("rv") >= anchor).select("*", F.explode(grams).alias("_g"))
    test = is_run if contiguous else is_subrecord
    return first.join(every, "_g").where(test(F.col("lv"), F.col("rv"))).select("lid", "rid").distinct()


def equality_classes(df: DataFrame, cols: list[str], key: str) -> DataFrame:
    """(key, class_id, links): rows with equal ``cols`` as one class, its smallest key and how many others each row equals.

    Counts combine before the shuffle and are joined back, so a large group is not one task.
    """
    keyed = df.select(key, F.xxhash64(*cols).alias("_h1"), F.xxhash64(F.lit(1), *cols).alias("_h2"))
    classes = keyed.groupBy("_h1", "_h2").agg(F.min(key).alias("class_id"), (F.count("*") - 1).alias("links"))
    return keyed.join(classes, ["_h1", "_h2"]).select(key, "class_id", "links")
