"""Annotation, validity and verifiability filters, retention priority."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cotengine.sources.providers import Provider


def annotate(df: DataFrame, provider: Provider) -> DataFrame:
    return provider(df)


def keep_valid(df: DataFrame, unknown: str = "keep") -> DataFrame:
    """Drop rows marked invalid; rows without a mark are kept or dropped as ``unknown`` says."""
    if unknown not in ("keep", "drop"):
        raise ValueError("unknown is 'keep' or 'drop'")
    return df.where(F.coalesce("is_valid", F.lit(unknown == "keep")))


def verifiable_subset(df: DataFrame, answer_types: list[str] | None = None) -> DataFrame:
    """Rows fit for training with verified rewards: valid, verifiable, and of the given answer types."""
    out = df.where(F.coalesce(F.col("is_valid") & F.col("verifiable"), F.lit(False)))
    return out.where(F.col("answer_type").isin(answer_types)) if answer_types else out


def priority(is_valid: str = "is_valid", verifiable: str = "verifiable"):
    """0 valid and verifiable, 1 valid only, 2 unmarked, 3 invalid: the smaller is retained."""
    valid = F.col(is_valid)
    return F.when(valid & F.coalesce(F.col(verifiable), F.lit(False)), 0).when(valid, 1).when(valid.isNull(), 2).otherwise(3)
