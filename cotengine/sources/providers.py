"""The model boundary: batch providers with a declared contract, and deterministic stand-ins.

A provider is a function DataFrame → DataFrame that adds declared columns. Model calls are
paid for, so ``materialized`` writes a provider's output once per run key and rereads it: a
plan that Spark evaluates twice, or a task that is retried after a lost executor, never
calls a model twice for a finished batch. The stand-ins are column expressions; what they
produce says nothing about any model.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cotengine.functions.hashing import h8, unit
from cotengine.functions.text import tokens


@dataclass(frozen=True)
class Provider:
    name: str
    needs: tuple[str, ...]
    adds: tuple[str, ...]
    call: Callable[[DataFrame], DataFrame]

    def __call__(self, df: DataFrame) -> DataFrame:
        missing = [c for c in self.needs if c not in df.columns]
        if missing:
            raise ValueError(f"provider {self.name} needs {missing}")
        out = self.call(df)
        lacking = [c for c in self.adds if c not in out.columns]
        if lacking:
            raise ValueError(f"provider {self.name} did not add {lacking}")
        return out


def materialized(df: DataFrame, provider: Provider, path: str) -> DataFrame:
    """The provider's output, kept under ``path``: called only if that path holds no finished output."""
    spark = df.sparkSession
    there = spark._jvm.org.apache.hadoop.fs.Path(f"{path}/_SUCCESS")
    if not there.getFileSystem(spark._jsc.hadoopConfiguration()).exists(there):
        provider(df).write.mode("overwrite").parquet(path)
    return spark.read.parquet(path)


def lexical_annotator(labels: DataFrame) -> Provider:
    """Validity and verifiability from ``labels`` (unknown where unlabelled), discipline from lang, level and answer type from the text."""

    def call(df: DataFrame) -> DataFrame:
        marks = labels.groupBy("doc_id").agg(F.min("quality").alias("quality"), F.max("toxic").alias("toxic"))
        toks = tokens(F.col("text"))
        joined = df.join(marks, "doc_id", "left").withColumn("_t", toks)
        variety = F.when(F.size("_t") > 0, F.size(F.array_distinct("_t")) / F.size("_t")).otherwise(0.0)
        level = F.when(variety < 0.4, "primary").when(variety < 0.6, "secondary").when(variety < 0.8, "undergraduate").otherwise("graduate")
        kinds = F.array(*map(F.lit, ["numeric", "expression", "choice", "text"]))
        kind = F.element_at(kinds, (F.pmod(h8(F.col("text")), F.lit(4)) + 1).cast("int"))
        return joined.withColumns({"is_valid": F.col("quality") == 1, "verifiable": F.col("toxic") == 0, "discipline": F.col("lang"), "edu_level": level, "answer_type": kind}).drop("_t", "quality", "toxic")

    return Provider("annotator", ("doc_id", "text", "lang"), ("is_valid", "verifiable", "discipline", "edu_level", "answer_type"), call)


def option(key: Column, salt: str) -> Column:
    """One of five options from a hash of key and salt."""
    pick = F.pmod(h8(F.concat(key.cast("string"), F.lit(f":{salt}"))), F.lit(5))
    return F.element_at(F.array(*map(F.lit, "ABCDE")), (pick + 1).cast("int"))


def option_teacher(attempt: int, salt: str = "t") -> Provider:
    """An answer among five options from a hash of item, attempt and salt."""
    return Provider("teacher", ("item_id",), ("answer",), lambda df: df.withColumn("answer", option(F.col("item_id"), f"{attempt}:{salt}")))


def reasoning_teacher(attempt: int, key: str = "doc_id") -> Provider:
    """A response that ends in a boxed option, both from hashes of key and attempt; one of twelve repeats itself."""

    def call(df: DataFrame) -> DataFrame:
        degenerate = F.pmod(h8(F.concat(F.col(key).cast("string"), F.lit(f":{attempt}:d"))), F.lit(12)) == 0
        answer = option(F.col(key), f"{attempt}:t")
        steps = F.when(degenerate, F.repeat(F.lit("and so on "), 60)).otherwise(F.concat(F.coalesce(F.col("text"), F.lit("")), F.lit(" ")))
        return df.withColumns({"answer": answer, "response": F.concat(steps, F.lit("so the answer is \\boxed{"), answer, F.lit("}."))})

    return Provider("reasoning teacher", (key, "text"), ("answer", "response"), call)


def pair_synthesizer(per_doc: int = 2, agree: float = 0.6, extra: int = 3) -> Provider:
    """Candidates of each document: slot, two answers that agree at about the given rate, extra answers, trace length."""

    def call(df: DataFrame) -> DataFrame:
        slots = df.withColumn("slot", F.explode(F.sequence(F.lit(0), F.lit(per_doc - 1))))
        key = F.concat_ws(":", F.col("d_id").cast("string"), F.col("slot").cast("string"))
        options = F.array(*map(F.lit, "ABCDE"))
        said = lambda tag: F.element_at(options, (F.pmod(h8(F.concat(F.lit(tag + ":"), key)), F.lit(5)) + 1).cast("int"))
        second = F.when(unit(key, "agree") < agree, said("a1")).otherwise(said("a2"))
        return slots.withColumns({"question": F.concat(F.lit("q:"), key), "ans1": said("a1"), "ans2": second, "extra": F.array(*[said(f"x{i}") for i in range(extra)]), "trace_len": 100 + F.pmod(h8(F.concat(F.lit("len:"), key)), F.lit(9000))})

    return Provider("synthesizer", ("d_id",), ("slot", "question", "ans1", "ans2", "extra", "trace_len"), call)
