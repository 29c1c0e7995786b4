"""Distributions as tables: density ratios, weighted risks, tilts, distances, mixtures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def empirical(df: DataFrame, cells: list[str], name: str, weight: Column | None = None) -> DataFrame:
    """Share of the (weighted) rows in each cell: a partial aggregate and a one-row total."""
    counted = df.groupBy(*cells).agg(F.sum(weight if weight is not None else F.lit(1.0)).alias("_w"))
    total = F.broadcast(counted.agg(F.sum("_w").alias("_t")))
    return counted.crossJoin(total).select(*cells, F.try_divide("_w", "_t").alias(name))


def density_ratio(base: DataFrame, target: DataFrame, cells: list[str]) -> DataFrame:
    """p0, p1, rho = p1 / p0 of each cell. Cells without base mass are reported as uncovered, not dropped."""
    joined = empirical(base, cells, "p0").join(empirical(target, cells, "p1"), cells, "full").na.fill(0.0, ["p0", "p1"])
    return joined.withColumn("rho", F.when(F.col("p0") > 0, F.col("p1") / F.col("p0"))).withColumn("uncovered", F.col("p0") == 0)


def expected_risk(df: DataFrame, loss: str, weight: str) -> DataFrame:
    """Weighted and plain mean loss, their gap, and the effective sample size of the weights: one aggregate."""
    w, x = F.col(weight), F.col(loss)
    out = df.agg(F.try_divide(F.sum(w * x), F.sum(w)).alias("risk"), F.avg(x).alias("biased"), F.try_divide(F.sum(w) * F.sum(w), F.sum(w * w)).alias("ess"))
    return out.select("risk", "biased", (F.col("risk") - F.col("biased")).alias("gap"), "ess")


def risk_contributors(df: DataFrame, cells: list[str], loss: str, weight: str) -> DataFrame:
    """Each cell's share of the weighted risk, ranked."""
    by = df.groupBy(*cells).agg(F.sum(F.col(weight) * F.col(loss)).alias("part"), F.avg(loss).alias("mean_loss"))
    total = F.broadcast(by.agg(F.sum("part").alias("_t")))
    shares = by.crossJoin(total).select(*cells, "mean_loss", F.try_divide("part", "_t").alias("share"))
    return shares.withColumn("rank", F.row_number().over(Window.orderBy(F.round("share", 9).desc(), *cells)))  # one row a cell


def tilt(df: DataFrame, beta: float, *, by: str, p: str = "p", advantage: str = "adv") -> DataFrame:
    """p' ∝ p·exp(beta·advantage) within ``by``, shifted by the greatest exponent."""
    own = Window.partitionBy(by)
    e = F.exp(beta * (F.col(advantage) - F.max(advantage).over(own))) if beta >= 0 else F.exp(beta * (F.col(advantage) - F.min(advantage).over(own)))
    raised = df.withColumn("_e", F.col(p) * e)
    return raised.withColumn("tilted", F.try_divide("_e", F.sum("_e").over(own))).drop("_e")


def mix(p0: DataFrame, p1: DataFrame, lam: float, key: str, p: str = "p") -> DataFrame:
    """lam·P0 + (1 - lam)·P1 over the union of both supports."""
    joined = p0.select(key, F.col(p).alias("_a")).join(p1.select(key, F.col(p).alias("_b")), key, "full").na.fill(0.0, ["_a", "_b"])
    return joined.select(key, (F.lit(lam) * F.col("_a") + F.lit(1 - lam) * F.col("_b")).alias(p))


def distances(p: DataFrame, q: DataFrame, key: list[str], a: str = "p0", b: str = "p1") -> DataFrame:
    """Total variation, and KL(p‖q) over the cells that q covers with the p-mass it does not."""
    joined = p.join(q, key, "full").na.fill(0.0, [a, b])
    x, y = F.col(a), F.col(b)
    kl = F.sum(F.when((x > 0) & (y > 0), x * F.log(F.when(x > 0, x) / F.when(y > 0, y))).otherwise(0.0))
    return joined.agg((F.sum(F.abs(x - y)) / 2).alias("tv"), kl.alias("kl"), F.sum(F.when(y == 0, x).otherwise(0.0)).alias("uncovered"))
