"""Benchmark decontamination by spaced-seed hashing, in DataFrame functions only.

A seed is a mask over consecutive tokens; the tokens at its zeros are ignored, so a passage in
which such a token was replaced still gives the same hash.  Seeds of all benchmark items are joined
with seeds at every position of every document.  A hit fixes an alignment (document position minus
item position); the item is compared token by token along it, and the best window decides.

Plan: one pass splits, explodes positions, hashes and probes a broadcast table inside one stage, so
no token is shuffled.  The seed table is broadcast only up to ``BROADCAST_SEEDS`` rows; beyond it the
hashes are shuffled and joined.  Hits are distinct alignments, a few rows per copied passage; the
documents that have one are read again and compared.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sigres.plans.scratch import Scratch, small_side

#: Fixed masks: weight 6 over 9 tokens and weight 5 over 7 tokens.
MASKS = ("111001101", "1101011")
#: Tokens of the window that decides, and the share of them that must be equal.
WINDOW, SHARE = 20, 0.75
#: Tokens from which on an item tolerates replaced ones, and tokens that an item has at least.
TOLERANT, SHORTEST = 9, 5
#: Seeds and alignments up to which a table is broadcast (about 30 bytes each).
BROADCAST_SEEDS, BROADCAST_HITS = 1_000_000, 500_000


def tokens(text: Column) -> Column:
    """Runs of letters and digits in lower case; null and blank texts have none."""
    return F.array_remove(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+"), "")


def seeds(rows: DataFrame, masks=MASKS) -> DataFrame:
    """(id, words) -> (id, pos, mask, seed): the hash of every mask at every position where it fits."""
    n, shortest = len(masks), min(map(len, masks))
    last = n * (F.size("words") - shortest + 1) - 1
    placed = rows.where(F.size("words") >= shortest).select("id", "words", F.explode(F.sequence(F.lit(0), last)).alias("p"))
    pos, seed = F.floor(F.col("p") / n).cast("int"), None
    for k, mask in enumerate(masks):
        picked = [F.get("words", pos + i) for i, bit in enumerate(mask) if bit == "1"]
        fits = pos + len(mask) <= F.size("words")
        here = F.when(fits, F.xxhash64(F.lit(k), *picked))
        seed = here if seed is None else F.when(F.col("p") % n == k, here).otherwise(seed)
    return placed.select("id", pos.alias("pos"), (F.col("p") % n).alias("mask"), seed.alias("seed")).where("seed is not null")


def alignments(docs: DataFrame, items: DataFrame, scratch: Scratch, masks=MASKS,
               broadcast_seeds: int = BROADCAST_SEEDS) -> DataFrame:
    """(id, words) of both sides -> distinct (doc, item, shift) that share a seed.

    Items of fewer than ``TOLERANT`` tokens have one seed, all of their tokens; such masks are made for
    the lengths that occur, four at most.
    """
    size = F.size("words")
    short = sorted(r[0] for r in items.where(size.between(SHORTEST, TOLERANT - 1)).select(size).distinct().collect())
    every = (*masks, *("1" * n for n in short))
    long = seeds(items.where(size >= TOLERANT), masks).select("id", "pos", "seed")
    whole = [items.where(size == n).select("id", F.lit(0).alias("pos"), F.xxhash64(F.lit(len(masks) + k), *[F.get("words", F.lit(i)) for i in range(n)]).alias("seed"))
             for k, n in enumerate(short)]
    for more in whole:
        long = long.unionByName(more)
    known = long.select(F.col("id").alias("item"), F.col("pos").alias("ipos"), "seed").distinct()
    known = small_side(scratch.save(known, "seeds"), broadcast_seeds)
    hits = seeds(docs, every).join(known, "seed")
    return hits.select(F.col("id").alias("doc"), "item", (F.col("pos") - F.col("ipos")).alias("shift")).distinct()


def tolerated(width: Column) -> Column:
    """Replaced tokens that a window of this many tokens may have: a third of those beyond five.

    So many are found with probability 0.95 or more: 0.98 to 1.00 for widths of 9, 11 and 17 to 20, 0.96 for 14.
    """
    return F.when(width >= TOLERANT, F.floor((width - 5) / 3)).otherwise(F.lit(0))


def best_window(equal: Column, window: int = WINDOW) -> Column:
    """Largest share of true values in any ``window`` consecutive ones (all, if there are fewer)."""
    width = F.least(F.size(equal), F.lit(window))
    most = F.aggregate(F.sequence(F.lit(1), F.size(equal) - width + 1), F.lit(0),
                       lambda best, s: F.greatest(best, F.size(F.filter(F.slice(equal, s, width), lambda x: x))))
    return most / width


def contaminated(docs: DataFrame, benchmark: DataFrame, share: float = SHARE, window: int = WINDOW,
                 masks=MASKS, broadcast_seeds: int = BROADCAST_SEEDS, broadcast_hits: int = BROADCAST_HITS) -> DataFrame:
    """Distinct doc_id of ``docs`` (doc_id, text) with the items it repeats: doc_id, items, overlap.

    An item (item_id, text) is repeated if in some window of 20 of its tokens (all, if it is shorter)
    at least 75% are equal to the document's tokens at the same distance, around a common seed, and of
    n tokens at most (n - 5) / 3 are not.  Items of 5 to 8 tokens must be repeated as they are.  Items of
    fewer tokens, null and empty ones included, match nothing.  Rows without a doc_id or item_id are left out; rows that repeat a doc_id are
    judged together.  Empty tables give an empty result.
    """
    scratch = Scratch(docs.sparkSession, "leaks")
    doc_words = docs.where("doc_id is not null").select(F.col("doc_id").alias("id"), tokens(F.col("text")).alias("words"))
    items = benchmark.where("item_id is not null").select(F.col("item_id").alias("id"), tokens(F.col("text")).alias("words"))
    items = scratch.save(items.distinct(), "items")
    hits = scratch.save(alignments(doc_words, items, scratch, masks, broadcast_seeds), "hits")
    wanted = small_side(hits.withColumnRenamed("doc", "id"), broadcast_hits)
    asked = scratch.save(items.select(F.col("id").alias("item"), F.col("words").alias("asked")), "asked")
    sides = small_side(asked, broadcast_seeds // 50)
    pairs = (doc_words.join(wanted, "id").join(sides, "item")
             .select("id", "item", F.transform("asked", lambda w, j: F.coalesce(
                 w == F.get("words", F.col("shift") + j), F.lit(False))).alias("equal")))
    width = F.least(F.size("equal"), F.lit(window))
    judged = pairs.select("id", "item", width.alias("width"), best_window(F.col("equal"), window).alias("overlap"))
    judged = judged.where((F.col("overlap") >= share) & (F.round((1 - F.col("overlap")) * F.col("width")) <= tolerated(F.col("width"))))
    return judged.groupBy(F.col("id").alias("doc_id")).agg(
        F.array_sort(F.collect_set("item")).alias("items"), F.max("overlap").alias("overlap"))


def decontaminate(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """The rows of ``docs`` that repeat no item, with all their columns."""
    scratch = Scratch(docs.sparkSession, "clean")
    found = scratch.save(contaminated(docs, benchmark, **options).select("doc_id"), "found")
    found = small_side(found, BROADCAST_HITS).alias("leaking")
    return docs.alias("judged").join(found, F.col("judged.doc_id") == F.col("leaking.doc_id"), "left_anti")


def judge(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """One row per row of ``docs``: doc_id, contaminated, items (sorted ids), overlap (0 if none)."""
    scratch = Scratch(docs.sparkSession, "judged")
    found = scratch.save(contaminated(docs, benchmark, **options), "found")
    return (docs.select("doc_id").join(small_side(found, BROADCAST_HITS // 10), "doc_id", "left")
            .select("doc_id", F.col("items").isNotNull().alias("contaminated"),
                    F.coalesce("items", F.array().cast("array<long>")).alias("items"),
                    F.coalesce("overlap", F.lit(0.0)).alias("overlap")))
