"""Corpus pipeline: quality, line dedup, near-duplicate join, benchmark decontamination, packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; ``run`` writes what a stage
returns as Parquet to the shared folder and gives it to the next as its documents. All but
the last return the columns of ``documents``, with ``n_chars`` of the text as it then is.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cotengine.llm import pu_quality
from cotengine.llm.bench_decontam import contaminated
from cotengine.llm.jaccard_join import near_duplicates
from cotengine.llm.line_dedup import dedup_lines
from cotengine.llm.queries import WORD_TOKENIZER, benchmark_items, table, tokenizer_path
from cotengine.llm.ss_packing import pack_documents
from cotengine.llm.store import drop_table, scratch

#: Documents that score below it are rejected.
LEAST_QUALITY = 0.3


#: Name of the added key column; no column of the documents may have it.
KEY = "__row_key"


def _keyed(docs: DataFrame) -> DataFrame:
    """The documents with the operators' key of (id, text)."""
    return docs.withColumn(KEY, F.xxhash64(F.col("doc_id").cast("long"), F.col("text").cast("string")))


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier, learned from the marks of these documents, does not reject."""
    return pu_quality.accepted(docs, pu_quality.fit(docs, table(spark, sf_dir, "labels")), LEAST_QUALITY)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without their repeated lines, null texts as empty; a document all of whose words went goes too."""
    kept = dedup_lines(docs, carry=[c for c in docs.columns if c != "text"])
    kept = kept.where((F.col("n_removed") == 0) | F.regexp_like("text", F.lit(r"[\p{L}\p{N}]")))
    own = {"text": F.col("text"), "n_chars": F.length("text").cast(docs.schema["n_chars"].dataType)}
    return kept.select([own.get(c, F.col(f"carried.`{c}`")).alias(c) for c in docs.columns])


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near duplicates: the one of least id; of repeated rows one."""
    chosen = near_duplicates(docs).where("first").select(F.col("rid").alias(KEY)).distinct()
    return _keyed(docs).join(chosen, KEY, "left_semi").dropDuplicates([KEY]).select(docs.columns)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item."""
    hits = contaminated(docs, benchmark_items(spark, sf_dir)).select(F.col("rid").alias(KEY)).distinct()
    return _keyed(docs).join(hits, KEY, "left_anti").select(docs.columns)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack_documents(docs, tokenizer=tokenizer_path(WORD_TOKENIZER))


STAGES = [("quality", quality), ("lines", lines), ("near", near), ("decontaminate", decontaminate), ("packing", packing)]

#: No SQL expresses the classifier or the tokenizer; tests compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages; what a stage wrote for itself goes with it, and its input once the next table is written."""
    docs, last = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES:
        with scratch(spark) as write:
            docs, path = write(stage(spark, docs, sf_dir), f"pipeline-{name}")
        if last is not None:
            drop_table(spark, last)
        last = path
    return docs
