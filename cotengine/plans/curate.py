"""The whole first stage as one call, with a ledger of rows per step and source."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cotengine.operators.annotate import annotate, keep_valid, priority
from cotengine.operators.decontam import decontaminate
from cotengine.operators.dedup import cut_lineage, dedup_exact, dedup_near, shared_folder
from cotengine.operators.distill import distill_responses
from cotengine.operators.sampling import QUANTILES, RATES, stratified_by_length
from cotengine.sources.providers import Provider, materialized, reasoning_teacher


@dataclass(frozen=True)
class CurationConfig:
    unknown: str = "keep"
    near_mode: str = "bucket"
    gram: int = 13
    rep_n: int = 3
    rep_most: float = 0.2
    quantiles: tuple = QUANTILES
    rates: tuple = RATES
    seed: int = 42
    #: Disciplines that are sampled by length (the STEM ones); None: all. Rows of others all stay.
    scope: tuple | None = None
    #: What becomes of answers that are wrong after the retry: "keep" or "drop_incorrect".
    wrong: str = "keep"
    #: Names the run: provider outputs of a named run are kept and never asked for again.
    run: str | None = None


@dataclass
class CurationResult:
    curated: DataFrame
    stages: dict[str, DataFrame] = field(default_factory=dict)

    def ledger(self) -> DataFrame:
        """(step, stage, source, n): rows of each source after each step."""
        parts = [df.groupBy("source").agg(F.count("*").alias("n")).select(F.lit(i).alias("step"), F.lit(name).alias("stage"), "source", "n") for i, (name, df) in enumerate(self.stages.items())]
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out


def curate(docs: DataFrame, items: DataFrame, annotator: Provider, config: CurationConfig = CurationConfig(), *, teacher: Callable[[int], Provider] = reasoning_teacher, gold: Column | None = None) -> CurationResult:
    """Cheap steps first: validity, exact, near, decontamination; then responses, repetition, verification with one retry, sampling.

    ``gold`` is the verifiable answer of a row, null where there is none. Annotated ids, not
    texts, are what early steps move; a stage that later stages read more than once is written
    and reread, and a provider's output once for good.
    """
    run = config.run or uuid.uuid4().hex

    def call(df: DataFrame, provider: Provider, tag: str) -> DataFrame:
        return materialized(df, provider, f"{shared_folder(df.sparkSession)}/providers/{run}/{tag}")

    stages: dict[str, DataFrame] = {"raw": docs}
    marked = cut_lineage(annotate(docs, annotator), "annotated")
    stages["valid"] = keep_valid(marked, config.unknown)
    stages["exact"] = cut_lineage(dedup_exact(stages["valid"], prio=priority()), "exact")
    stages["near"] = cut_lineage(dedup_near(stages["exact"], priority(), mode=config.near_mode), "near")
    stages["decontaminated"] = cut_lineage(decontaminate(stages["near"], items, n=config.gram)[0], "clean")
    asked = stages["decontaminated"].withColumn("gold", gold if gold is not None else F.lit(None).cast("string"))
    done = distill_responses(asked, teacher, call, n=config.rep_n, most=config.rep_most, policy=config.wrong)
    stages["responded"], stages["repetition"] = done.responded, done.kept
    stages["verified"] = cut_lineage(done.verified, "verified")
    scope = F.col("discipline").isin(*config.scope) if config.scope is not None else None
    stages["sampled"] = stratified_by_length(stages["verified"], qs=config.quantiles, rates=config.rates, seed=config.seed, scope=scope)
    return CurationResult(stages["sampled"], stages)


def source_distribution(before: DataFrame, after: DataFrame) -> DataFrame:
    """Rows and share of each source before and after."""
    count = lambda df, n: df.groupBy("source").agg(F.count("*").alias(n))
    joined = count(before, "n_before").join(count(after, "n_after"), "source", "full").na.fill(0, ["n_before", "n_after"])
    total = joined.agg(F.sum("n_before").alias("tb"), F.sum("n_after").alias("ta"))
    share = lambda n, t: F.round(F.try_divide(F.col(n).cast("double"), F.col(t)), 6)
    return joined.crossJoin(F.broadcast(total)).select("source", "n_before", "n_after", share("n_before", "tb").alias("share_before"), share("n_after", "ta").alias("share_after"))
