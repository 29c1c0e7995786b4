"""Length-quantile stratified sampling and the draws it is compared with.

A row stays if its hashed unit number lies below its stratum's rate: a filter, stable under
retries and repartitioning, and nested in the rate. Exact quantiles come from a histogram of
the (integer) lengths, which is small whatever the row count; sketches are the alternative.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cotengine.functions.hashing import unit

QUANTILES, RATES = (0.2, 0.5, 0.75), (0.0, 0.1, 0.5, 1.0)
OTHER_RATES = (0.0, 0.9, 0.5, 1.0)


def length_quantiles(df: DataFrame, length: str, qs=QUANTILES, *, by: list[str] = [], method: str = "exact") -> DataFrame:
    """One row (per group) with ``t``, the array of thresholds."""
    if method == "exact":
        counted = df.groupBy(*by, F.col(length).alias("_len")).agg(F.count("*").alias("_n"))
        t = F.percentile("_len", F.array(*map(F.lit, qs)), F.col("_n"))
        return counted.groupBy(*by).agg(t.alias("t"))
    if method == "approx":
        return df.groupBy(*by).agg(F.percentile_approx(length, list(qs), 10_000).cast("array<double>").alias("t"))
    if method == "kll":
        sketch = df.groupBy(*by).agg(F.kll_sketch_agg_bigint(F.col(length).cast("long")).alias("s"))
        return sketch.select(*by, F.array(*[F.kll_sketch_get_quantile_bigint("s", F.lit(q)).cast("double") for q in qs]).alias("t"))
    raise ValueError("method is 'exact', 'approx' or 'kll'")


def stratum(length: Column, t: Column, k: int = 3) -> Column:
    """How many of the k thresholds the length is strictly above."""
    return sum((F.when(length > F.element_at(t, i + 1), 1).otherwise(0) for i in range(k)), F.lit(0))


def with_stratum(df: DataFrame, length: str, qs=QUANTILES, *, by: list[str] = [], method: str = "exact") -> DataFrame:
    """Rows with ``stratum`` (0 is the shortest); thresholds are one broadcast row (per group)."""
    t = F.broadcast(length_quantiles(df, length, qs, by=by, method=method))
    joined = df.join(t, by) if by else df.crossJoin(t)  # a cross with exactly one row
    return joined.withColumn("stratum", stratum(F.col(length), F.col("t"), len(qs))).drop("t")


def stratified_by_length(df: DataFrame, length: str = "n_tokens", *, key: str = "doc_id", qs=QUANTILES, rates=RATES, seed: int = 42, by: list[str] = [], method: str = "exact", scope: Column | None = None) -> DataFrame:
    """Keep every row of the longest stratum and a rate of the others.

    With ``scope`` quantiles and rates hold for the rows in it; all others stay, without a stratum.
    """
    if scope is not None:
        inside = F.coalesce(scope, F.lit(False))
        drawn = stratified_by_length(df.where(inside), length, key=key, qs=qs, rates=rates, seed=seed, by=by, method=method)
        return drawn.unionByName(df.where(~inside).withColumn("stratum", F.lit(None).cast("int")))
    rate = F.element_at(F.array(*map(F.lit, map(float, rates))), F.col("stratum") + 1)
    return with_stratum(df, length, qs, by=by, method=method).where(unit(F.col(key), seed) < rate)


def stratified_by_level(df: DataFrame, levels: list[str], *, level: str = "edu_level", key: str = "doc_id", rates=RATES, seed: int = 42) -> DataFrame:
    """The annotation-based baseline: the rates go by annotated level, lowest first."""
    rate = F.lit(0.0)
    for name, r in zip(levels, rates, strict=True):
        rate = F.when(F.col(level) == name, F.lit(float(r))).otherwise(rate)
    return df.where(unit(F.col(key), seed) < rate)


def longest_n(df: DataFrame, n: int, *, length: str = "n_tokens", key: str = "doc_id") -> DataFrame:
    return df.orderBy(F.col(length).desc(), key).limit(n)


def uniform_n(df: DataFrame, n: int, *, seed: int = 42, key: str = "doc_id") -> DataFrame:
    """Exactly n rows (all, if fewer), the least by hash: a top-n, no full sort."""
    return df.withColumn("_u", unit(F.col(key), seed)).orderBy("_u", key).limit(n).drop("_u")


def weighted_draw(df: DataFrame, n: int, weight: Column, *, seed: int = 42, key: str = "doc_id") -> DataFrame:
    """n rows without replacement with chances by weight: least exponential keys -ln(u)/w; zero weights are never drawn."""
    u = (unit(F.col(key), seed) * (1 << 32) + 0.5) / float(1 << 32)
    return df.where(weight > 0).withColumn("_k", -F.log(u) / weight).orderBy("_k", key).limit(n).drop("_k")


def rank_error(df: DataFrame, length: str, qs=QUANTILES, method: str = "kll") -> DataFrame:
    """|rank of a sketch quantile - target| for each quantile."""
    t = F.broadcast(length_quantiles(df, length, qs, method=method))
    parts = [F.abs(F.avg(F.when(F.col(length) <= F.element_at("t", i + 1), 1.0).otherwise(0.0)) - q).alias(f"e{i}") for i, q in enumerate(qs)]
    row = df.crossJoin(t).agg(*parts)
    return row.select(F.explode(F.array(*[F.struct(F.lit(q).alias("q"), F.col(f"e{i}").alias("rank_error")) for i, q in enumerate(qs)])).alias("x")).select("x.q", "x.rank_error")


def top_share(df: DataFrame, fraction: float, order: list[Column]) -> DataFrame:
    """The first ``fraction`` of the rows in order (relative rank below it): counted, then a top-n, no window over all rows."""
    n = df.count()
    return df.orderBy(*order).limit(n if n < 2 else math.ceil(fraction * (n - 1)))
