"""Methods callable from SQL: temporary SQL functions that inline into Catalyst, and table functions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf

_FUNCTIONS = {
    "length_score(len DOUBLE, correct BOOLEAN, least DOUBLE, most DOUBLE) RETURNS DOUBLE": "CASE WHEN correct OR len >= most THEN 1D WHEN len <= least THEN 0D ELSE (len - least) / (most - least) END",
    "repetition_factor(ratio DOUBLE) RETURNS DOUBLE": "greatest(0.1D, 1D - ratio)",
    "cosine(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": "try_divide(aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x), sqrt(aggregate(a, 0D, (s, x) -> s + x * x)) * sqrt(aggregate(b, 0D, (s, x) -> s + x * x)))",
}


@udtf(returnType="i int, gram string")
class Ngrams:
    """ngrams(text, n): runs of n blank-separated words."""

    def eval(self, text: str, n: int):
        words = (text or "").split()
        for i in range(max(len(words) - n + 1, 1 if words else 0)):
            yield i, " ".join(words[i : i + n])


@udtf(returnType="i int, part string")
class Windows:
    """windows(text, size, step): word windows of a text."""

    def eval(self, text: str, size: int, step: int):
        words = (text or "").split()
        for i, at in enumerate(range(0, max(1, len(words) - size + step), step) if words else ()):
            yield i, " ".join(words[at : at + size])


@pandas_udf("string")
def majority(answers: pd.Series) -> str:
    """majority(answer): the answer with most votes, then the smallest; nulls do not vote. Of one group at a time, so for groups that fit a task."""
    votes = answers.dropna().value_counts()
    return min(votes.index[votes == votes.max()]) if len(votes) else None


def register(spark: SparkSession) -> None:
    for head, body in _FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    spark.udf.register("majority", majority)
    spark.udtf.register("ngrams", Ngrams)
    spark.udtf.register("windows", Windows)
