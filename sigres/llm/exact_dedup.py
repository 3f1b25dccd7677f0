"""Exact duplicates by most-significant-digit radix partitioning, distributed.

A digit is a run of successive bytes of the normalised text.  Documents split by their first digit;
groups of more than one text split again by the next, wider digit, until a group is a single text
or its texts have ended.  Equality is decided by the bytes alone, never by a digest.

The first digits of all texts are counted before: only texts that share theirs are written and split further.

Skew: every task first runs the same radix on its own batches, so of a group of copies only one
text per batch takes part in the shuffled rounds, however large the group is.  Counts combine
before each shuffle, and the split table is written before it is joined, so that the join has two
plain exchanges which adaptive execution can split.
"""

from __future__ import annotations

import hashlib

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sigres.llm.batches import map_text, row_counter
from sigres.plans.scratch import Scratch, small_side

#: Bytes of the first digit and the factor by which digits widen in each round.
FIRST_DIGIT, WIDEN = 64, 4
#: Rows up to which a side of a join is broadcast (about 13 MB for digits of 64 bytes).
BROADCAST_ROWS = 100_000
_WHITE = b"\x20\t\n\x0b\x0c\r"
_LOCAL = ("key long, rep_key long, doc_id long, n_points long, text_sha256 string, digit binary, rest binary")


def normalise(text: str | None) -> bytes:
    """UTF-8 of the text without the characters U+0020 and U+0009 to U+000D; null counts as empty."""
    return (text or "").encode().translate(None, _WHITE)


def radix_classes(texts: list[bytes], first: int = FIRST_DIGIT, widen: int = WIDEN) -> list[list[int]]:
    """Indices of equal texts, by splitting on successive digits until singleton or ended."""
    done: list[list[int]] = []
    open_ = [(list(range(len(texts))), 0, first)]
    while open_:
        group, at, width = open_.pop()
        if len(group) == 1:
            done.append(group)
            continue
        buckets: dict[bytes, list[int]] = {}
        for i in group:
            buckets.setdefault(texts[i][at:at + width], []).append(i)
        for digit, members in buckets.items():
            if len(members) == 1 or len(digit) < width:
                done.append(members)
            else:
                open_.append((members, at + width, width * widen))
    return done


def _heads(part: pa.RecordBatch) -> dict:
    """First digits of a slice's different texts."""
    blobs = {normalise(t) for t in part.column("text").to_pylist()}
    return {"digit": [b[:FIRST_DIGIT] for b in blobs]}


def _local(part: pa.RecordBatch, counter: list[int]) -> dict:
    ids = part.column("doc_id").to_pylist()
    texts = part.column("text").to_pylist()
    points = [len(t or "") for t in texts]
    blobs = [normalise(t) for t in texts]
    del texts
    base = counter[0]
    counter[0] += len(blobs)
    out = {"key": list(range(base, base + len(blobs))), "rep_key": [0] * len(blobs), "doc_id": ids, "n_points": points,
           "text_sha256": [""] * len(blobs), "digit": [None] * len(blobs), "rest": [None] * len(blobs)}
    for members in radix_classes(blobs):
        first = members[0]
        sha = hashlib.sha256(blobs[first]).hexdigest()
        for i in members:
            out["rep_key"][i], out["text_sha256"][i] = base + first, sha
        out["digit"][first], out["rest"][first] = blobs[first][:FIRST_DIGIT], blobs[first][FIRST_DIGIT:]
    return out


def radix_partition(texts: DataFrame, scratch: Scratch, first: int = FIRST_DIGIT, widen: int = WIDEN,
                    broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """(key, digit, rest) of distinct keys -> (key, class) for every text that has an equal one.

    ``digit`` holds the first ``first`` bytes of a text and ``rest`` what follows.
    """
    found = []
    heads = texts.groupBy("digit").agg(F.count("*").alias("n"), F.min("key").alias("group")).where("n > 1")
    heads = scratch.save(heads, "heads")
    active = (texts.join(small_side(heads, broadcast_rows), "digit")
              .select("key", "group", "rest", (F.octet_length("digit") < first).alias("ended")))
    width = first
    while True:
        now = scratch.save(active, "active")
        found.append(now.where("ended").select("key", F.col("group").alias("class")))
        live = now.where("not ended")
        if not live.take(1):
            break
        width *= widen
        digit = F.substring("rest", 1, width)
        split = live.select("key", "group", digit.alias("digit")).groupBy("group", "digit").agg(
            F.count("*").alias("n"), F.min("key").alias("next")).where("n > 1")
        split = small_side(scratch.save(split, "split"), broadcast_rows)
        active = (live.withColumn("digit", digit).join(split, ["group", "digit"])
                  .select("key", F.col("next").alias("group"),
                          F.expr(f"substring(rest, {width} + 1)").alias("rest"),
                          (F.octet_length("digit") < width).alias("ended")))
    out = found[0]
    for more in found[1:]:
        out = out.unionByName(more)
    return out


def exact_duplicates(docs: DataFrame, broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """One row per row of ``docs`` (doc_id, text): doc_id, keep_id, group_size, kept, text_sha256.

    Texts are equal when identical after deleting U+0020 and U+0009 to U+000D; null counts as empty,
    so null, empty and blank texts form one group.  Of a group the row with the most code points in
    the original text stays, then the one with the smallest doc_id (null last), then the one read
    first, so of repeated rows exactly one stays.  An empty table gives an empty result; other
    columns are not read.
    """
    scratch = Scratch(docs.sparkSession, "exact")
    narrow = docs.select("doc_id", "text")
    heads = map_text(narrow.select("text"), _heads, "digit binary").groupBy("digit").agg(F.count("*").alias("n")).where("n > 1")
    heads = scratch.save(heads.select("digit", F.lit(True).alias("again")), "recurring")
    # only texts whose first digit recurs, in another slice or another text, are written
    # rows that stand for no text have a join key of their own, so a shuffle does not gather them
    at = F.coalesce("digit", F.encode(F.col("key").cast("string"), "UTF-8"))
    rows = map_text(narrow, _local, _LOCAL, setup=row_counter).withColumn("at", at).join(
        small_side(heads.withColumnRenamed("digit", "at"), broadcast_rows), "at", "left")
    rows = scratch.save(rows.select("key", "rep_key", "doc_id", "n_points", "text_sha256", F.when(F.col("again"), F.col("digit")).alias("digit"),
                                    F.when(F.col("again"), F.col("rest")).alias("rest")), "local")
    reps = rows.where("digit is not null").select("key", "digit", "rest")
    classes = scratch.save(radix_partition(reps, scratch, broadcast_rows=broadcast_rows), "classes")
    ids = rows.select("key", "rep_key", "doc_id", "n_points", "text_sha256")
    side = small_side(classes.withColumnRenamed("key", "rep_key"), 10 * broadcast_rows)
    ids = ids.join(side, "rep_key", "left").withColumn("class", F.coalesce("class", "rep_key"))
    ids = scratch.save(ids, "ids")
    order = F.struct((-F.col("n_points")).alias("o"), F.col("doc_id").isNull().alias("u"), "doc_id", "key")
    best = ids.groupBy("class").agg(F.count("*").alias("group_size"), F.min(order).alias("best")).where("group_size > 1")
    best = scratch.save(best, "best")
    return (ids.join(small_side(best, 10 * broadcast_rows), "class", "left")
            .select("doc_id", F.when(F.col("best").isNull(), F.col("doc_id")).otherwise(F.col("best.doc_id")).alias("keep_id"),
                    F.coalesce("group_size", F.lit(1)).cast("long").alias("group_size"),
                    F.coalesce(F.col("best.key") == F.col("key"), F.lit(True)).alias("kept"), "text_sha256"))


ORACLE = r"""
WITH n AS (
  SELECT doc_id, coalesce(text, '') AS t, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g') AS m FROM documents
), g AS (
  SELECT m, count(*) AS group_size, first(doc_id ORDER BY length(t) DESC, doc_id) AS keep_id FROM n GROUP BY m
)
SELECT n.doc_id, g.keep_id, g.group_size, n.doc_id = g.keep_id AS kept, sha256(n.m) AS text_sha256
FROM n JOIN g ON n.m = g.m
"""
