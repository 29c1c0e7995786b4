"""Shared-folder tables: how these operators cut lineage so that a lost executor costs nothing.

Intermediate tables go as Parquet to the folder that the cluster names in
``spark.checkpoint.dir``; every executor and the driver see it. Where the session names
none (a local test session) a folder of the local machine is made and set.
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cotengine.sources.files import write_once


def shared_folder(spark: SparkSession) -> str:
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        if not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        folder = spark.sparkContext.getCheckpointDir() if spark.sparkContext.getCheckpointDir() else None
        if not folder:
            folder = "file://" + tempfile.mkdtemp(prefix="cotengine-")
            spark.sparkContext.setCheckpointDir(folder)
    return folder.rstrip("/")


def materialize(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` once to the shared folder and return the table read back."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/tables/{tag}-{uuid.uuid4().hex}"
    write_once(df, path)
    if _made is not None:
        _made.append(path)
    return spark.read.schema(df.schema).parquet(path)


_made: list[str] | None = None


@contextmanager
def scratch(spark: SparkSession) -> Iterator[Callable[[DataFrame, str], tuple[DataFrame, str]]]:
    """Delete at the end the tables that operators write meanwhile.

    Gives a ``materialize`` whose tables stay, with their paths: what is returned has to be written by it, as a
    result that is not yet computed still reads the operators' tables.
    """
    global _made
    outer, _made = _made, []
    stay: set[str] = set()

    def write(df: DataFrame, tag: str) -> tuple[DataFrame, str]:
        out = materialize(df, tag)
        stay.add(_made[-1])
        return out, _made[-1]

    try:
        yield write
    finally:
        made, _made = _made, outer
        for path in made:
            if path not in stay:
                drop_table(spark, path)
            elif outer is not None:
                outer.append(path)


def drop_table(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def small_side(df: DataFrame, most: int = 500_000) -> DataFrame:
    """``df`` with a broadcast hint if it has at most ``most`` (narrow) rows; else as it is, for a shuffled join."""
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df
