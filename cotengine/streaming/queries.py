"""Registered queries that run the streaming twins over the given tables as file streams."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from cotengine.operators.dedup import shared_folder
from cotengine.plans.curation_queries import sql_hits13
from cotengine.sources.tables import table
from cotengine.streaming import streams

QUERIES: dict = {}
ORACLES: dict = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def _stream(spark, sf_dir, name):
    static = table(spark, sf_dir, name)
    return spark.readStream.schema(static.schema).parquet(f"{sf_dir}/{name}.parquet*")


def _run(df, mode="append"):
    name = "s" + uuid.uuid4().hex
    return streams.run_available(df, name, mode, f"{shared_folder(df.sparkSession)}/{name}")


@query("""WITH m AS (SELECT ts, CAST(json_extract(props, '$.k') AS BIGINT) < (user_id * 37) % 101 OR event_type = (['click', 'error', 'purchase', 'signup', 'view'])[user_id % 5 + 1] AS ok, round(value * 100) AS len FROM events)
        SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, count(*) AS n, round(avg(CAST(ok AS INTEGER)), 6) AS accuracy, round(avg(len), 6) AS mean_len FROM m GROUP BY ALL""")
def training_curve_stream(spark, sf_dir):
    out = _run(streams.curve(_stream(spark, sf_dir, "events")), "complete")
    return out.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "n", F.round("accuracy", 6).alias("accuracy"), F.round("mean_len", 6).alias("mean_len"))


@query(f"WITH {sql_hits13('documents', 'hits')} SELECT DISTINCT doc_id FROM hits")
def decontaminate_stream(spark, sf_dir):
    return _run(streams.decontaminate(_stream(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))).distinct()


@query("SELECT count(DISTINCT md5(event_type || user_id)) AS n FROM events")
def dedup_stream(spark, sf_dir):
    docs = _stream(spark, sf_dir, "events").select("ts", F.concat("event_type", F.col("user_id").cast("string")).alias("text"))
    return _run(streams.dedup_exact(docs, late="60 days")).agg(F.count("*").alias("n"))


@query("SELECT user_id AS prompt, count(*) // 16 AS groups FROM events GROUP BY user_id HAVING count(*) >= 16")
def full_groups_stream(spark, sf_dir):
    out = _run(streams.full_groups(streams.marked(_stream(spark, sf_dir, "events")), 16))
    return out.groupBy("prompt").agg(F.count("*").alias("groups"))


@query("""WITH g AS (SELECT user_id, ts, CASE WHEN lag(ts) OVER w IS NULL OR ts >= lag(ts) OVER w + INTERVAL 12 HOUR THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
        n AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT * FROM g ORDER BY user_id, ts, fresh DESC)), c AS (SELECT user_id, s, count(*) AS n FROM n GROUP BY ALL)
        SELECT user_id, count(*) AS sessions, CAST(sum(n) AS BIGINT) AS events, max(n) AS longest FROM c GROUP BY user_id""")
def sessions_stream(spark, sf_dir):
    out = _run(streams.sessions(_stream(spark, sf_dir, "events"), gap="12 hours"), "complete")
    return out.groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("events"), F.max("n").alias("longest"))


@query("SELECT event_id, round(value, 6) AS reward FROM events WHERE event_id % 120 <= 60")
def reward_join_stream(spark, sf_dir):
    """Rollouts meet rewards that arrive up to two hours later; those within one hour count."""
    said = streams.marked(_stream(spark, sf_dir, "events"))
    paid = _stream(spark, sf_dir, "events").select(F.col("event_id").alias("rid"), (F.col("ts").cast("timestamp") + F.make_dt_interval(mins=(F.col("event_id") % 120).cast("int"))).alias("rts"), F.col("value").alias("reward"))
    return _run(streams.reward_join(said, paid)).select("event_id", F.round("reward", 6).alias("reward"))
