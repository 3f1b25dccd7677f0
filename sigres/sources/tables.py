"""Scans of the given tables and of files in other formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One table of a scale-factor directory; Catalyst prunes columns and pushes filters."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load(spark: SparkSession, path: str, fmt: str, schema: str, **options) -> DataFrame:
    """A scan in any built-in format under an explicit schema (no inference pass)."""
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def save(df: DataFrame, path: str, fmt: str = "parquet", partition_by: list[str] | None = None,
         mode: str = "overwrite", **options) -> None:
    """A sink in any built-in format."""
    writer = df.write.format(fmt).mode(mode).options(**options)
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    writer.save(path)


def save_bucketed(df: DataFrame, table: str, key: str, buckets: int) -> None:
    """A bucketed and sorted catalog table, so later joins on the key need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)
