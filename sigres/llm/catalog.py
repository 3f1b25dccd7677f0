"""Queries of the corpus operators with production parameters, and their DuckDB oracles."""

from __future__ import annotations

from pyspark.sql import functions as F

from sigres.llm import decontaminate, exact_dedup, html_text, language_id, mixing, pii, quality, simhash, toxicity, url_filter
from sigres.sources.tables import load_table


def _documents(spark, sf_dir):
    return load_table(spark, sf_dir, "documents")


def op1_mixing(spark, sf_dir):
    mixed = mixing.training_order(_documents(spark, sf_dir))
    return mixed.select("doc_id", "size", "source_size", F.round("target", 6).alias("target"), "taken", "epochs", F.round("position", 6).alias("position"))


def op2_language_id(spark, sf_dir):
    return language_id.identify(_documents(spark, sf_dir))


def op3_exact_dedup(spark, sf_dir):
    return exact_dedup.exact_duplicates(_documents(spark, sf_dir))


def op4_pii(spark, sf_dir):
    return pii.find_personal_data(_documents(spark, sf_dir))


def op5_simhash(spark, sf_dir):
    found = simhash.linked_components(_documents(spark, sf_dir))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op6_quality(spark, sf_dir):
    return quality.classify(_documents(spark, sf_dir), load_table(spark, sf_dir, "labels"))


def op7_html_extraction(spark, sf_dir):
    return html_text.extract_pages(load_table(spark, sf_dir, "pages"))


def op8_url_filter(spark, sf_dir):
    return url_filter.filter_urls(load_table(spark, sf_dir, "pages"))


def op9_decontamination(spark, sf_dir):
    return decontaminate.judge(_documents(spark, sf_dir), load_table(spark, sf_dir, "benchmark"))


def op10_toxicity(spark, sf_dir):
    return toxicity.score(_documents(spark, sf_dir), load_table(spark, sf_dir, "labels"))


QUERIES = {
    "op1_mixing": op1_mixing,
    "op2_language_id": op2_language_id,
    "op3_exact_dedup": op3_exact_dedup,
    "op4_pii": op4_pii,
    "op5_simhash": op5_simhash,
    "op6_quality": op6_quality,
    "op7_html_extraction": op7_html_extraction,
    "op8_url_filter": op8_url_filter,
    "op9_decontamination": op9_decontamination,
    "op10_toxicity": op10_toxicity,
}

ORACLES = {
    "op1_mixing": mixing.ORACLE,
    "op3_exact_dedup": exact_dedup.ORACLE,
    "op8_url_filter": url_filter.ORACLE,
}
