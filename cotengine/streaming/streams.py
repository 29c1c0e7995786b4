"""Streams of rollouts and documents: windowed curves, sessions, dedup, decontamination, groups.

Every twin takes a streaming DataFrame, so it runs the same over files, Kafka or a rate source.
State is bounded by a watermark wherever the method allows it.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cotengine.functions.text import ngrams, tokens
from cotengine.operators.decontam import MOST_BROADCAST, small
from cotengine.sources.tables import OPTIONS, PROPS


def file_stream(spark: SparkSession, folder: str, schema, files: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(folder)


def marked(events: DataFrame) -> DataFrame:
    """Rollout columns that need no order within a prompt: prompt, correct, len."""
    gold = F.element_at(F.array(*map(F.lit, OPTIONS)), (F.pmod("user_id", F.lit(5)) + 1).cast("int"))
    ok = (F.from_json("props", PROPS)["k"] < F.pmod(F.col("user_id") * 37, F.lit(101))) | (F.col("event_type") == gold)
    return events.select("event_id", F.col("ts").cast("timestamp").alias("ts"), F.col("user_id").alias("prompt"), ok.alias("correct"), F.round(F.col("value") * 100).cast("long").alias("len"))


def curve(events: DataFrame, width: str = "1 day", late: str = "2 days", slide: str | None = None) -> DataFrame:
    """Accuracy and mean length per (sliding) window; rows later than the watermark are dropped."""
    by = marked(events).withWatermark("ts", late).groupBy(F.window("ts", width, slide) if slide else F.window("ts", width))
    return by.agg(F.count("*").alias("n"), F.avg(F.col("correct").cast("double")).alias("accuracy"), F.avg("len").alias("mean_len")).select(F.col("window.start").alias("start"), "n", "accuracy", "mean_len")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 day") -> DataFrame:
    by = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap))
    return by.agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")


def dedup_exact(docs: DataFrame, at: str = "ts", late: str = "1 day") -> DataFrame:
    """The first row of each text digest within the watermark's reach; state older than it goes."""
    return docs.withColumn("fp", F.md5("text")).withColumn(at, F.col(at).cast("timestamp")).withWatermark(at, late).dropDuplicatesWithinWatermark(["fp"])


def decontaminate(docs: DataFrame, items: DataFrame, n: int = 13) -> DataFrame:
    """Rows that share a run of n tokens with a (static) item, marked: a stream-static join; the items are sent if they are few."""
    held = items.select(tokens(F.col("text")).alias("t")).where(F.size("t") >= n).select(F.explode(ngrams(F.col("t"), n)).alias("gram")).distinct()
    grams = docs.select("doc_id", tokens(F.col("text")).alias("t")).where(F.size("t") >= n).select("doc_id", F.explode(ngrams(F.col("t"), n)).alias("gram"))
    return grams.join(small(held, MOST_BROADCAST), "gram", "left_semi").select("doc_id")


def reward_join(rollouts_: DataFrame, rewards: DataFrame, within: str = "1 hour", late: str = "1 day") -> DataFrame:
    """Rollouts with their rewards that arrive within an interval: a stream-stream join with bounded state."""
    a, b = rollouts_.withWatermark("ts", late).alias("a"), rewards.withWatermark("rts", late).alias("b")
    return a.join(b, F.expr(f"a.event_id = b.rid AND b.rts >= a.ts AND b.rts <= a.ts + INTERVAL {within}")).select("event_id", "ts", "reward")


def full_groups(r: DataFrame, size: int) -> DataFrame:
    """A row (prompt, n, mean) for each ``size`` rollouts of a prompt, as soon as they are there; the rest waits as state."""
    from pyspark.sql.streaming.state import GroupStateTimeout

    def step(key, frames: Iterator[pd.DataFrame], state):
        n, ok = state.get if state.exists else (0, 0)
        done = []
        for frame in frames:
            for c in frame.sort_values("event_id")["correct"]:
                n, ok = n + 1, ok + int(c)
                if n == size:
                    done.append((key[0], n, ok / n))
                    n, ok = 0, 0
        state.update((n, ok))
        yield pd.DataFrame(done, columns=["prompt", "n", "mean"])

    return r.groupBy("prompt").applyInPandasWithState(step, "prompt long, n int, mean double", "n int, ok int", "append", GroupStateTimeout.NoTimeout)


def run_available(df: DataFrame, name: str, mode: str, checkpoint: str) -> DataFrame:
    """Run a stream over what is there now into an in-memory table (a test sink) and return it."""
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table(name)


def upsert_sink(df: DataFrame, path: str, checkpoint: str):
    """Write each micro-batch to its own folder, so that a replayed batch replaces itself."""

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return df.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
