"""Functions for SQL users: table functions and a grouped aggregate, registered on a session."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf


class Subrecords:
    """Every subrecord of a text of words, up to a length."""

    def eval(self, text: str, longest: int):
        have = [()]
        for w in (text or "").split():
            have += [h + (w,) for h in have if len(h) < longest]
        for h in sorted(set(have)):
            if h:
                yield " ".join(h), len(h)


def noisy_or():
    """1 - product(1 - p) as a grouped aggregate, to check the native sum of logarithms against."""
    @pandas_udf("double")
    def f(p: pd.Series) -> float:
        return float(1 - (1 - p).prod())
    return f


def register(spark: SparkSession) -> None:
    spark.udtf.register("subrecords", udtf(Subrecords, returnType="sig string, words int"))
    spark.udf.register("noisy_or", noisy_or())
