"""Reward parts and token-level quantities as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def length_score(length: Column, correct: Column, least: float, most: float) -> Column:
    """1 if right or long enough, 0 if wrong and too short, linear between; equal bounds make a step."""
    slope = F.lit(0.0) if most == least else (length - F.lit(float(least))) / F.lit(float(most - least))
    return F.when(correct | (length >= most), 1.0).when(length <= least, 0.0).otherwise(slope)


def repetition_factor(ratio: Column, floor: float = 0.1) -> Column:
    return F.greatest(F.lit(float(floor)), 1 - ratio)


def sequence_nll(logps: Column, mean: bool = False) -> Column:
    total = -F.aggregate(logps, F.lit(0.0), lambda a, x: a + x)
    return F.try_divide(total, F.size(logps).cast("double")) if mean else total


def policy_ratio(new: Column, old: Column) -> Column:
    return F.zip_with(new, old, lambda n, o: F.exp(n - o))


def clipped_terms(ratios: Column, advantage: Column, low: float, high: float) -> Column:
    """min(r·Â, clip(r, 1 - low, 1 + high)·Â) for each token."""
    return F.transform(ratios, lambda r: F.least(r * advantage, F.least(F.greatest(r, F.lit(1.0 - low)), F.lit(1.0 + high)) * advantage))


def total(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda a, x: a + x)


def cosine(a: Column, b: Column) -> Column:
    """Cosine in double precision; null for a zero vector or vectors of different length."""
    x, y = F.transform(a, lambda v: v.cast("double")), F.transform(b, lambda v: v.cast("double"))
    dot = total(F.zip_with(x, y, lambda p, q: p * q))
    norm = F.sqrt(total(F.transform(x, lambda v: v * v))) * F.sqrt(total(F.transform(y, lambda v: v * v)))
    return F.when(F.size(a) == F.size(b), F.try_divide(dot, norm))
