"""Readers and writers around the methods: text formats, raw pages, idempotent partitioned output."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


_FREE = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def write_once(df: DataFrame, path: str) -> None:
    """Write Parquet and free the shuffle files that the write needed at its end, not when the driver happens to collect its garbage."""
    conf = df.sparkSession.conf
    before = conf.get(_FREE)
    conf.set(_FREE, "true")
    try:
        df.write.parquet(path)
    finally:
        conf.set(_FREE, before)


def write_stage(df: DataFrame, path: str, partition: str | None = None) -> None:
    """Write a stage's output so that a second run replaces it instead of adding to it.

    With ``partition`` only the partitions that ``df`` holds are replaced, after one
    shuffle by it so that each task writes few files.
    """
    if partition is None:
        df.write.mode("overwrite").parquet(path)
    else:
        df.repartition(F.col(partition)).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(partition).parquet(path)


def write_bucketed(df: DataFrame, name: str, key: str, buckets: int) -> None:
    """A table bucketed and sorted by ``key``: later joins and aggregates on it need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).format("parquet").saveAsTable(name)


def export_jsonl(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").option("compression", "gzip").json(path)


def round_trip(df: DataFrame, kind: str, path: str) -> DataFrame:
    """Write as ``kind`` (csv, json, orc, parquet) and read back under the declared schema."""
    options = {"header": "true", "escape": '"', "multiLine": "true"} if kind == "csv" else {}
    df.write.mode("overwrite").format(kind).options(**options).save(path)
    return df.sparkSession.read.schema(df.schema).format(kind).options(**options).load(path)


def raw_pages(spark: SparkSession, path: str) -> DataFrame:
    """Files of a folder as rows (path, length, content)."""
    return spark.read.format("binaryFile").load(path).select("path", "length", "content")
