"""Corpus pipeline over ``documents``: quality, exact copies, near copies, benchmark passages, the mix.

Each stage takes (spark, docs, sf_dir) and works on all rows that its predecessor kept, written as
Parquet and read again; the first four return the columns of ``docs``, the last one the training
order.  A stage defines what becomes of odd rows as its operator does; rows without a doc_id pass
every filter but that of exact copies.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sigres.llm import decontaminate, exact_dedup, mixing, quality, simhash
from sigres.plans.scratch import Scratch, small_side
from sigres.sources.tables import load_table

#: Ids up to which a table of dropped documents is broadcast.
BROADCAST_IDS = 1_000_000


def _matching(docs: DataFrame, ids: DataFrame, label: str, how: str) -> DataFrame:
    """The rows of ``docs`` whose doc_id is ('left_semi') or is not ('left_anti') in ``ids``; other columns may have any names."""
    ids = Scratch(docs.sparkSession, label).save(ids.select("doc_id").distinct(), "ids")
    mine, others = docs.alias("documents_here"), small_side(ids, BROADCAST_IDS).alias("documents_there")
    return mine.join(others, F.col("documents_here.doc_id").eqNullSafe(F.col("documents_there.doc_id")), how)


def _without(docs: DataFrame, dropped: DataFrame, label: str) -> DataFrame:
    """The rows of ``docs`` whose doc_id is not in ``dropped``."""
    return _matching(docs, dropped, label, "left_anti")


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the language model rejects go."""
    return quality.keep_good(docs, load_table(spark, sf_dir, "labels"))


def exact_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of equal texts stays.

    Rows that repeat a doc_id with an equal text are one row afterwards, the one with the longest text.
    """
    judged = exact_dedup.exact_duplicates(docs)
    # the id of a row that stays may also be that of a dropped row, if the row is repeated
    found = Scratch(spark, "copies").save(judged.groupBy("doc_id").agg(F.max("kept").alias("stays"), F.count("*").alias("n"))
                                          .where("not stays or n > 1"), "found")
    kept = _without(docs, found.where("not stays"), "copies")
    repeated = found.where("stays")
    if not repeated.take(1):
        return kept
    once = _matching(docs, repeated, "again", "left_semi")
    # the longest name and more is no column's name
    norm = max(docs.columns, key=len) + "_normalised"
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns])
    once = once.withColumn(norm, F.regexp_replace(F.coalesce("text", F.lit("")), r"[\x20\x09-\x0D]", ""))
    once = once.groupBy("doc_id", norm).agg(F.max_by(row, F.struct(F.length("text"), "text")).alias("row")).select("row.*")
    return _without(kept, repeated, "repeated").unionByName(once)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of near-duplicates the document with the smallest doc_id stays."""
    classes = simhash.near_duplicates(docs)
    return _without(docs, classes.where("doc_id <> component_id"), "near")


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that repeat a benchmark item go."""
    return decontaminate.decontaminate(docs, load_table(spark, sf_dir, "benchmark"))


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The training order: a row per document and pass, sorted by position."""
    return mixing.curriculum(docs)


STAGES = [
    ("quality_classifier", quality_classifier),
    ("exact_dedup", exact_dedup_stage),
    ("simhash_near_dedup", near_dedup),
    ("benchmark_decontamination", decontamination),
    ("mixing", mixing_stage),
]

#: The first and third stage cannot be written in SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; what each but the last returns is written and read again."""
    scratch = Scratch(spark, "pipeline")
    docs = load_table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = scratch.save(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
