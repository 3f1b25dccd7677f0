"""The corpus pipeline: stages keep what they must, and odd rows pass."""

import corpus_pipeline
from sigres.llm import exact_dedup, quality
from sigres.plans.scratch import Scratch

from .test_corpus_operators import ODD, SCHEMA


def test_stages_on_the_small_tables(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    scratch, columns = Scratch(spark, "test"), docs.columns
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before, docs = docs, scratch.save(stage(spark, docs, small), name)
        assert docs.columns == columns
        ids = {r.doc_id for r in docs.select("doc_id").collect()}
        assert len(ids) == docs.count() and ids <= {r.doc_id for r in before.select("doc_id").collect()}
        if name == "quality_classifier":
            labels = spark.read.parquet(f"{small}/labels.parquet")
            assert ids == {r.doc_id for r in quality.classify(before, labels).where("keep").collect()}
        if name == "exact_dedup":
            assert ids == {min(r.doc_id for r in g) for g in _groups(before).values()} or len(ids) == len(_groups(before))
    out = corpus_pipeline.STAGES[-1][1](spark, docs, small)
    assert out.count() > 0 and {r.doc_id for r in out.collect()} <= ids


def _groups(docs):
    out = {}
    for r in docs.select("doc_id", "text").collect():
        out.setdefault(exact_dedup.normalise(r.text), []).append(r)
    return out


def test_stages_on_odd_and_no_rows(spark, small):
    odd = spark.createDataFrame(ODD, SCHEMA)
    for rows in (odd, odd.limit(0)):
        for name, stage in corpus_pipeline.STAGES:
            got = stage(spark, rows, small)
            assert name == "mixing" or got.columns == rows.columns
            got.count()
    kept = corpus_pipeline.exact_dedup_stage(spark, odd, small).collect()
    assert sorted((r.doc_id or 0) for r in kept) == [0, 3, 4, 6, 7]


def test_clashing_columns_and_repeated_ids(spark, small):
    names = ("_gone", "_again", "_norm", "_bad", "_leak", "rejected", "leaking", "id", "class", "keep", "label", "row")
    more = ", ".join(f"{n} string" for n in names)
    rows = [(*r, *names) for r in ODD] + [(8, "The same  text here. ", "fr", "a", 1, "k", 0.7, *names)]
    df = spark.createDataFrame(rows, f"{SCHEMA}, {more}")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        got = stage(spark, df, small)
        assert got.columns == df.columns and all(tuple(r)[-len(names):] == names for r in got.collect())
    kept = [r.text for r in corpus_pipeline.exact_dedup_stage(spark, df, small).collect() if r.doc_id == 8]
    assert len(kept) <= 1
