"""SQL functions: ``phrase_count``, ``smallest_period``, ``lpf_array`` and the table function ``greedy_phrases``."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from phraseloom.functions import kernels as k


@F.udtf(returnType="ord long, lo long, hi long, src long, sym string")
class GreedyPhrases:
    def eval(self, body: str):
        for ordinal, phrase in enumerate(k.parse_with_sources(body or ""), 1):
            yield (ordinal, *phrase)


@F.pandas_udf("long")
def phrase_count(bodies: pd.Series) -> pd.Series:
    return bodies.map(lambda s: None if s is None else sum(1 for _ in k.parse(s))).astype("Int64")


@F.pandas_udf("long")
def smallest_period(bodies: pd.Series) -> pd.Series:
    return bodies.map(lambda s: None if s is None else k.smallest_period(s)).astype("Int64")


@F.pandas_udf("array<long>")
def lpf_array(bodies: pd.Series) -> pd.Series:
    return bodies.map(lambda s: None if s is None else k.lpf(s))


def register(spark: SparkSession) -> None:
    spark.udtf.register("greedy_phrases", GreedyPhrases)
    for name, f in (("phrase_count", phrase_count), ("smallest_period", smallest_period), ("lpf_array", lpf_array)):
        spark.udf.register(name, f)
