"""Response distillation around a teacher: pairing, repetition filter, verification, one retry."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cotengine.functions.text import canonical_answer, repetition_ratio, token_count
from cotengine.sources.providers import Provider


def qa_pairs(conversations: DataFrame) -> DataFrame:
    """Each assistant turn as the response to the user turn right before it."""
    order = Window.partitionBy("conv_id").orderBy("turn")
    turned = conversations.withColumns({"q_role": F.lag("role").over(order), "question": F.lag("text").over(order)})
    return turned.where("role = 'assistant' AND q_role = 'user'").select("conv_id", "turn", "question", F.col("text").alias("response"), token_count(F.col("text")).alias("n_tokens"))


def drop_degenerate(df: DataFrame, text: str = "text", *, n: int = 3, most: float = 0.2) -> DataFrame:
    """Rows whose share of repeated token n-grams is at most ``most``."""
    return df.where(repetition_ratio(F.col(text), n) <= most)


def verify_answer(predicted: Column, gold: Column) -> Column:
    """Whether two final answers agree once normalised; null where there is no gold answer, false without a prediction."""
    return F.when(gold.isNotNull(), F.coalesce(canonical_answer(predicted) == canonical_answer(gold), F.lit(False)))


@dataclass
class Distilled:
    """Rows with a response each; those without degenerate repetition; those after verification and one retry."""

    responded: DataFrame
    kept: DataFrame
    verified: DataFrame


def distill_responses(df: DataFrame, teacher: Callable[[int], Provider], call: Callable[[DataFrame, Provider, str], DataFrame], *, gold: str = "gold", key: str = "doc_id", n: int = 3, most: float = 0.2, policy: str = "keep") -> Distilled:
    """A teacher's response to every row, filtered for repetition, verified, and asked for once more where it is wrong.

    ``teacher(i)`` gives ``response`` and ``answer`` of the i-th attempt; ``call`` runs a provider
    and keeps what it said, so no row is ever asked twice for one attempt. Only rows whose
    answer does not match their ``gold`` (null: nothing to verify) are asked again, and the
    second response counts whatever it says, unless it repeats itself. With ``keep`` wrong
    answers stay; ``drop_incorrect`` is the rejected alternative.
    """
    if policy not in ("keep", "drop_incorrect"):
        raise ValueError("policy is 'keep' or 'drop_incorrect'")
    responded = call(df, teacher(1), "responses-1")
    kept = drop_degenerate(responded, "response", n=n, most=most)
    missed = F.coalesce(~verify_answer(F.col("answer"), F.col(gold)), F.lit(False))
    again = drop_degenerate(call(kept.where(missed).drop("response", "answer"), teacher(2), "responses-2"), "response", n=n, most=most)
    final = kept.where(~missed).withColumn("retried", F.lit(False)).unionByName(again.withColumn("retried", F.lit(True)))
    final = final.withColumns({"correct": verify_answer(F.col("answer"), F.col(gold)), "n_tokens": token_count(F.col("response"))})
    return Distilled(responded, kept, final.where(F.coalesce("correct", F.lit(True))) if policy == "drop_incorrect" else final)


def select_with_retry(first: DataFrame, second: DataFrame, gold: DataFrame, *, key: str = "item_id", policy: str = "keep") -> DataFrame:
    """The response of each item after one retry of those that did not match.

    ``second`` needs rows of mismatched items only. With ``keep`` an answer that is wrong
    in the end stays; ``drop_incorrect`` is the rejected alternative.
    """
    one = first.select(key, F.col("answer").alias("a1")).join(gold.select(key, "gold"), key, "left")
    ok = verify_answer(F.col("a1"), F.col("gold"))
    both = one.withColumn("ok1", ok).join(second.select(key, F.col("answer").alias("a2")), key, "left")
    retried = F.col("ok1").isNotNull() & ~F.col("ok1") & F.col("a2").isNotNull()
    out = both.withColumn("retried", F.coalesce(retried, F.lit(False))).withColumn("answer", F.when(F.col("retried"), F.col("a2")).otherwise(F.col("a1")))
    out = out.withColumn("correct", verify_answer(F.col("answer"), F.col("gold"))).select(key, "answer", "gold", "retried", "correct")
    if policy == "drop_incorrect":
        return out.where(F.coalesce("correct", F.lit(True)))
    if policy != "keep":
        raise ValueError("policy is 'keep' or 'drop_incorrect'")
    return out
