"""Name -> query and name -> DuckDB oracle for the methods, workloads and operators of the library."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from sigres.plans import comparisons, methods, relational, streams, tables

_MODULES = (methods, comparisons, relational, streams, tables)


def queries() -> dict:
    return {k: v for m in _MODULES for k, v in m.QUERIES.items()}


def oracles() -> dict[str, str]:
    return {k: v for m in _MODULES for k, v in m.ORACLES.items()}


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    return methods.resolve_documents(spark, sf_dir)
