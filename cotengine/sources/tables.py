"""The given tables, pools of several sources, and the rollout mapping on ``events``."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: Answer options of the rollout mapping, in order.
OPTIONS = ["click", "error", "purchase", "signup", "view"]
PROPS = "struct<k:int>"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register_views(spark: SparkSession, sf_dir: str) -> None:
    """Every given table as a temporary view, so each method is also reachable through ``spark.sql``."""
    for name in TABLES:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def collect_sources(sources: dict[str, DataFrame], exclude: tuple[str, ...] = ()) -> DataFrame:
    """One pool of several sources with a ``pool`` column; excluded ones are never read."""
    tagged = [df.withColumn("pool", F.lit(name)) for name, df in sources.items() if name not in exclude]
    if not tagged:
        raise ValueError("no source is left")
    return reduce(lambda a, b: a.unionByName(b, allowMissingColumns=True), tagged)


def rollouts(events: DataFrame, group: int | None = 16, salt: int = 0) -> DataFrame:
    """``events`` as rollout groups: prompt, i, answer, gold, correct, len, logp_old, logp_new, ts.

    A fixed, SQL-expressible mapping; ``salt`` gives another policy on the same prompts. The
    row number over a prompt stops early in the plan (window group limit), and only narrow
    columns cross the shuffle: the log-probability arrays are computed after it.
    """
    k = F.from_json("props", PROPS)["k"]
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    numbered = events.select("event_id", "ts", "user_id", "event_type", "value", k.alias("k")).withColumn("i", F.row_number().over(order))
    if group:
        numbered = numbered.where(F.col("i") <= group)
    gold = F.element_at(F.array(*map(F.lit, OPTIONS)), (F.pmod("user_id", F.lit(5)) + 1).cast("int"))
    answer = F.when(F.pmod(F.col("k") + salt, F.lit(100)) < F.pmod(F.col("user_id") * 37, F.lit(101)), gold).otherwise(F.col("event_type"))
    steps = F.sequence(F.lit(0), F.lit(7))
    old = F.transform(steps, lambda t: -(F.pmod(F.col("k") + 7 * t, F.lit(50)) + 1) / F.lit(50.0))
    shift = F.transform(steps, lambda t: 1 + (F.pmod(F.col("event_id") + 3 * t, F.lit(21)) - 10) / F.lit(20.0))
    return numbered.select("event_id", "ts", F.col("user_id").alias("prompt"), "i", gold.alias("gold"), answer.alias("answer"), F.round(F.col("value") * 100).cast("long").alias("len"), old.alias("logp_old"), shift.alias("shift")).select(
        "event_id", "ts", "prompt", "i", "gold", "answer", (F.col("answer") == F.col("gold")).alias("correct"), "len", "logp_old", F.zip_with("logp_old", "shift", lambda o, s: o * s).alias("logp_new")
    )


def spread(df: DataFrame) -> DataFrame:
    """``df`` dealt to all cores if it is a scan of fewer input splits than there are cores; a large table stays as it is.

    For maps that take long over few bytes, as signatures do. The plan's own size estimate decides, nothing runs.
    """
    session = df.sparkSession._jsparkSession.sessionState()
    cores = df.sparkSession.sparkContext.defaultParallelism
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return df.repartition(cores) if size < cores * session.conf().filesMaxPartitionBytes() else df
