"""The plain operators around the methods: joins, aggregates, windows, sets, subqueries, functions."""

from __future__ import annotations

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from cotengine.operators.dedup import shared_folder
from cotengine.sources.files import round_trip
from cotengine.sources.tables import register_views, table

QUERIES: dict = {}
ORACLES: dict = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def same(name: str, sql: str, spark_sql: str | None = None) -> None:
    """A query of the SQL surface: one text for both engines, or Spark's own form of it."""

    def f(spark, sf_dir):
        register_views(spark, sf_dir)
        return spark.sql(spark_sql or sql)

    f.__name__ = name
    query(sql)(f)


T = table

# --- scans, projection, filter ------------------------------------------------------------------


@query("SELECT doc_id, n_chars FROM documents WHERE n_chars > 2000")
def op_scan_parquet(spark, sf_dir):
    return T(spark, sf_dir, "documents").where("n_chars > 2000").select("doc_id", "n_chars")


@query("SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem")
def op_project(spark, sf_dir):
    return T(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"))


@query("SELECT l_orderkey, l_linenumber FROM lineitem WHERE (l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R')) OR (NOT l_linestatus = 'O' AND regexp_matches(l_returnflag, '^N')) OR l_returnflag IS NOT DISTINCT FROM NULL")
def op_filter_compound(spark, sf_dir):
    c = F.col
    return T(spark, sf_dir, "lineitem").where((c("l_quantity").between(10, 20) & c("l_returnflag").isin("A", "R")) | (~(c("l_linestatus") == "O") & c("l_returnflag").rlike("^N")) | c("l_returnflag").eqNullSafe(None)).select("l_orderkey", "l_linenumber")


for _kind in ("csv", "json", "orc"):

    def _trip(spark, sf_dir, kind=_kind):
        rows = T(spark, sf_dir, "benchmark")
        return round_trip(rows, kind, f"{_folder(spark)}/{kind}")

    QUERIES[f"op_round_trip_{_kind}"], ORACLES[f"op_round_trip_{_kind}"] = _trip, "SELECT item_id, text FROM benchmark"


def _folder(spark) -> str:
    return f"{shared_folder(spark)}/{uuid.uuid4().hex}"


# --- joins -----------------------------------------------------------------------------------------

for _how, _sql in (("inner", "JOIN"), ("left", "LEFT JOIN"), ("right", "RIGHT JOIN"), ("full", "FULL JOIN")):

    def _join(spark, sf_dir, how=_how):
        c = T(spark, sf_dir, "customer").where("c_acctbal > 0").select("c_custkey", "c_mktsegment")
        o = T(spark, sf_dir, "orders").where("o_totalprice > 100000").select("o_orderkey", F.col("o_custkey").alias("c_custkey"))
        return c.join(o, "c_custkey", how)

    QUERIES[f"op_join_{_how}"] = _join
    ORACLES[f"op_join_{_how}"] = f"SELECT c_custkey, c_mktsegment, o_orderkey FROM (SELECT c_custkey, c_mktsegment FROM customer WHERE c_acctbal > 0) {_sql} (SELECT o_orderkey, o_custkey AS c_custkey FROM orders WHERE o_totalprice > 100000) USING (c_custkey)"
for _how, _not in (("semi", ""), ("anti", "NOT")):

    def _half(spark, sf_dir, how=_how):
        return T(spark, sf_dir, "customer").select("c_custkey").join(T(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", f"left_{how}")

    QUERIES[f"op_join_{_how}"], ORACLES[f"op_join_{_how}"] = _half, f"SELECT c_custkey FROM customer WHERE {_not} EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)"
for _hint in ("broadcast", "merge", "shuffle_hash"):

    def _hinted(spark, sf_dir, hint=_hint):
        return T(spark, sf_dir, "customer").join(T(spark, sf_dir, "nation").hint(hint), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))

    QUERIES[f"op_join_{_hint}"], ORACLES[f"op_join_{_hint}"] = _hinted, "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name"


@query("SELECT r_name, n_name FROM region, nation")
def op_join_cross(spark, sf_dir):
    return T(spark, sf_dir, "region").select("r_name").crossJoin(T(spark, sf_dir, "nation").select("n_name"))  # two tables of fixed size


@query("SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey AND a.n_regionkey + b.n_regionkey > 6")
def op_join_theta(spark, sf_dir):
    n = T(spark, sf_dir, "nation")
    return n.alias("a").join(n.alias("b"), F.expr("a.n_nationkey < b.n_nationkey AND a.n_regionkey + b.n_regionkey > 6")).select(F.col("a.n_name").alias("a"), F.col("b.n_name").alias("b"))


@query("WITH b(lo, hi, band) AS (VALUES (0, 500, 'short'), (500, 2000, 'middle'), (2000, 1000000, 'long')) SELECT doc_id, band FROM documents JOIN b ON n_chars >= lo AND n_chars < hi")
def op_join_range(spark, sf_dir):
    bands = F.broadcast(spark.createDataFrame([(0, 500, "short"), (500, 2000, "middle"), (2000, 1_000_000, "long")], "lo long, hi long, band string"))
    return T(spark, sf_dir, "documents").select("doc_id", "n_chars").join(bands, F.expr("n_chars >= lo AND n_chars < hi")).select("doc_id", "band")


@query("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def op_join_interval(spark, sf_dir):
    """Events within an hour: an equi-join on user and hour bucket (own and next) before the exact test."""
    e = T(spark, sf_dir, "events").select("event_id", "user_id", "event_type", "ts", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 3_600_000_000).alias("h"))
    a = e.where("event_type = 'view'").select("user_id", F.col("event_id").alias("a"), F.col("ts").alias("ta"), F.explode(F.array("h", F.col("h") + 1)).alias("h"))
    b = e.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("b"), F.col("ts").alias("tb"), "h")
    return a.join(b, ["user_id", "h"]).where("tb > ta AND tb <= ta + INTERVAL 1 HOUR").select("a", "b")


@query("SELECT e.event_id, v.value AS last_view FROM (SELECT * FROM events WHERE event_type = 'purchase') e ASOF LEFT JOIN (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = 'view' GROUP BY user_id, ts) v ON e.user_id = v.user_id AND e.ts >= v.ts")
def op_join_asof(spark, sf_dir):
    """The latest earlier row by a union and a running last value: one shuffle, no inequality join."""
    e = T(spark, sf_dir, "events")
    left = e.where("event_type = 'purchase'").select("user_id", "ts", "event_id", F.lit(None).cast("double").alias("value"), F.lit(1).alias("side"))
    right = e.where("event_type = 'view'").groupBy("user_id", "ts").agg(F.max("value").alias("value")).select("user_id", "ts", F.lit(None).cast("long").alias("event_id"), "value", F.lit(0).alias("side"))
    order = Window.partitionBy("user_id").orderBy("ts", "side").rowsBetween(Window.unboundedPreceding, 0)
    return left.unionByName(right).withColumn("last_view", F.last("value", ignorenulls=True).over(order)).where("side = 1").select("event_id", "last_view")


@query("SELECT l_returnflag, count(*) AS n FROM lineitem JOIN (SELECT DISTINCT l_returnflag AS f FROM lineitem) ON l_returnflag = f GROUP BY l_returnflag")
def op_join_skewed(spark, sf_dir):
    """A join on three hot keys, salted: the small side is repeated for each salt."""
    rows = T(spark, sf_dir, "lineitem").select("l_returnflag", F.pmod(F.xxhash64("l_orderkey", "l_linenumber"), F.lit(8)).alias("salt"))
    flags = rows.select("l_returnflag").distinct().withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(7).cast("long"))))
    return rows.join(flags, ["l_returnflag", "salt"]).groupBy("l_returnflag").agg(F.count("*").alias("n"))


@query("WITH a AS (SELECT c_custkey AS k, CASE WHEN c_custkey % 3 <> 0 THEN c_nationkey END AS nk FROM customer) SELECT k, n_name FROM a LEFT JOIN nation ON nk = n_nationkey")
def op_join_null_key(spark, sf_dir):
    a = T(spark, sf_dir, "customer").select(F.col("c_custkey").alias("k"), F.when(F.col("c_custkey") % 3 != 0, F.col("c_nationkey")).alias("nk"))
    return a.join(F.broadcast(T(spark, sf_dir, "nation")), F.col("nk") == F.col("n_nationkey"), "left").select("k", "n_name")


# --- aggregation -----------------------------------------------------------------------------------

same("op_agg_hash", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty FROM lineitem GROUP BY l_returnflag, l_linestatus")
same("op_agg_sort", "SELECT o_orderpriority, min(o_orderstatus) AS lo, max(o_orderstatus) AS hi FROM orders GROUP BY o_orderpriority")
same("op_count_distinct", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY event_type")
same("op_grouping_sets", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
same("op_cube", "SELECT lang, source, count(*) AS n FROM documents GROUP BY CUBE (lang, source)")
same("op_rollup", "SELECT lang, source, count(*) AS n FROM documents GROUP BY ROLLUP (lang, source)")
same("op_filter_agg", "SELECT user_id, count(*) FILTER (WHERE event_type = 'error') AS errors, count(*) AS n FROM events GROUP BY user_id")
same("op_percentile", "SELECT event_type, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY event_type", "SELECT event_type, round(percentile(value, 0.9), 6) AS p90 FROM events GROUP BY event_type")
same("op_max_by", "SELECT user_id, max_by(event_type, event_id) AS last_type FROM events GROUP BY user_id")
same("op_collect", "SELECT user_id, string_agg(DISTINCT event_type, ',' ORDER BY event_type) AS types FROM events GROUP BY user_id", "SELECT user_id, array_join(array_sort(collect_set(event_type)), ',') AS types FROM events GROUP BY user_id")


@query("SELECT source, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'de') AS de FROM documents GROUP BY source")
def op_pivot(spark, sf_dir):
    return T(spark, sf_dir, "documents").groupBy("source").pivot("lang", ["en", "de"]).agg(F.count(F.lit(1))).na.fill(0)


@query("SELECT source, lang AS mode FROM (SELECT source, lang, count(*) AS n FROM documents GROUP BY ALL) QUALIFY row_number() OVER (PARTITION BY source ORDER BY n DESC, lang) = 1")
def op_mode(spark, sf_dir):
    c = T(spark, sf_dir, "documents").groupBy("source", "lang").agg(F.count("*").alias("n"))
    return c.groupBy("source").agg(F.min(F.struct((-F.col("n")).alias("n"), "lang")).alias("b")).select("source", F.col("b.lang").alias("mode"))


@query()
def op_approx_distinct(spark, sf_dir):
    e = T(spark, sf_dir, "events")
    return e.agg(F.approx_count_distinct("user_id").alias("acd"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("hll"))


@query()
def op_approx_top_k(spark, sf_dir):
    register_views(spark, sf_dir)
    return spark.sql("SELECT t.item AS event_type, t.count AS n FROM (SELECT explode(approx_top_k(event_type, 3)) AS t FROM events)")


# --- windows, sort, limit ---------------------------------------------------------------------------

same("op_rank_family", "SELECT event_id, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd, ntile(4) OVER w AS nt FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
same("op_lag_lead", "SELECT event_id, lag(event_type) OVER w AS before, lead(event_type) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
same("op_rows_frame", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS m FROM events")
same("op_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY value RANGE BETWEEN 5 PRECEDING AND 5 FOLLOWING) AS near FROM events")
same("op_first_last", "SELECT event_id, first_value(event_type) OVER w AS f, last_value(event_type) OVER w AS l FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
same("op_running_share", "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) / sum(o_totalprice) OVER (PARTITION BY o_custkey), 6) AS share FROM orders")
same("op_sort_multi", "SELECT l_orderkey, l_linenumber FROM lineitem ORDER BY l_shipdate DESC NULLS LAST, l_orderkey, l_linenumber")
same("op_limit", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 17")
same("op_topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 50")


@query("SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 3")
def op_topk_per_group(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy(F.col("o_totalprice").desc(), "o_orderkey")
    return T(spark, sf_dir, "orders").withColumn("r", F.row_number().over(w)).where("r <= 3").select("o_custkey", "o_orderkey")


# --- sets, subqueries ---------------------------------------------------------------------------------

_A, _B = "SELECT o_custkey AS k FROM orders WHERE o_orderstatus = 'F'", "SELECT o_custkey AS k FROM orders WHERE o_orderstatus = 'O'"
for _name, _op in (("union_all", "UNION ALL"), ("union", "UNION"), ("intersect", "INTERSECT"), ("intersect_all", "INTERSECT ALL"), ("except", "EXCEPT"), ("except_all", "EXCEPT ALL")):
    same(f"op_{_name}", f"{_A} {_op} {_B}")
same("op_exists", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 200000)")
same("op_not_in_nulls", "SELECT n_nationkey FROM nation WHERE n_nationkey NOT IN (SELECT CASE WHEN r_regionkey > 99 THEN NULL ELSE r_regionkey END FROM region)")
same("op_scalar_subquery", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM orders)")
same("op_lateral", "SELECT r_name, t.n_name FROM region, LATERAL (SELECT n_name FROM nation WHERE n_regionkey = r_regionkey ORDER BY n_name LIMIT 2) t")

# --- functions ----------------------------------------------------------------------------------------

same("op_string", r"SELECT doc_id, md5(trim(lower(text))) AS digest, length(text) AS n, substring(text, 1, 5) AS head, instr(text, 'the') AS at, translate(lang, 'ed', 'ab') AS tr, levenshtein(lang, source) AS lev FROM documents")
same("op_string_split", r"SELECT page_id, string_split(url, '/')[3] AS host, regexp_replace(url, '[0-9]+', '#', 'g') AS shape FROM pages", r"SELECT page_id, split(url, '/')[2] AS host, regexp_replace(url, '[0-9]+', '#') AS shape FROM pages")
same("op_date", "SELECT event_id, year(ts) AS y, month(ts) AS m, date_diff('day', DATE '2020-01-01', CAST(ts AS DATE)) AS days, epoch_us(date_trunc('hour', ts)) AS hour FROM events", "SELECT event_id, year(ts) AS y, month(ts) AS m, datediff(CAST(ts AS DATE), DATE '2020-01-01') AS days, unix_micros(date_trunc('hour', ts)) AS hour FROM events")
same("op_math", "SELECT l_orderkey, l_linenumber, round(exp(l_discount), 6) AS e, round(ln(l_quantity + 1), 6) AS l, round(pow(l_tax + 1, 3), 6) AS p, greatest(l_discount, l_tax) AS g, least(l_discount, l_tax) AS s FROM lineitem")
same("op_json", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events", "SELECT event_id, CAST(from_json(props, 'k INT').k AS BIGINT) AS k FROM events")


@query("SELECT vec_id, round(list_sum(list_transform(embedding::DOUBLE[], lambda x: x * x)), 5) AS norm2, len(list_filter(embedding, lambda x: x > 0)) AS positive, round(list_max(embedding)::DOUBLE, 5) AS top FROM embeddings")
def op_array(spark, sf_dir):
    d = F.transform("embedding", lambda x: x.cast("double"))
    total = F.aggregate(F.transform(d, lambda x: x * x), F.lit(0.0), lambda a, x: a + x)
    return T(spark, sf_dir, "embeddings").select("vec_id", F.round(total, 5).alias("norm2"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.round(F.array_max(d), 5).alias("top"))


@query("SELECT source, CAST(sum(n) AS BIGINT) AS total, max(n) FILTER (lang = 'en') AS en FROM (SELECT source, lang, count(*) AS n FROM documents GROUP BY ALL) GROUP BY source")
def op_map_struct(spark, sf_dir):
    c = T(spark, sf_dir, "documents").groupBy("source", "lang").agg(F.count("*").alias("n")).groupBy("source").agg(F.map_from_entries(F.collect_list(F.struct("lang", "n"))).alias("m"))
    return c.select("source", F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, x: a + x).alias("total"), F.col("m")["en"].alias("en"))


@query(r"SELECT doc_id, i, t[i + 1] || ' ' || t[i + 2] AS g FROM (SELECT doc_id, unnest(range(len(t) - 1)) AS i, t FROM (SELECT doc_id, list_slice(regexp_extract_all(lower(text), '[\p{L}\p{N}]+'), 1, 4) AS t FROM documents))")
def op_udtf_ngrams(spark, sf_dir):
    """The n-gram table function called from SQL over the first four tokens of each text."""
    from cotengine.functions.sqlapi import register

    register(spark)
    register_views(spark, sf_dir)
    spark.sql("SELECT doc_id, array_join(slice(regexp_extract_all(lower(text), '[\\\\p{L}\\\\p{N}]+', 0), 1, 4), ' ') AS head FROM documents").createOrReplaceTempView("heads")
    return spark.sql("SELECT doc_id, CAST(g.i AS BIGINT) AS i, g.gram AS g FROM heads, LATERAL ngrams(head, 2) g WHERE g.gram LIKE '% %'")


@query("SELECT event_id, round(CASE WHEN event_type = 'view' OR value >= 100 THEN 1.0 WHEN value <= 10 THEN 0.0 ELSE (value - 10) / 90.0 END, 6) AS s FROM events")
def op_sql_functions(spark, sf_dir):
    """Methods as SQL functions that inline into the plan."""
    from cotengine.functions.sqlapi import register

    register(spark)
    register_views(spark, sf_dir)
    return spark.sql("SELECT event_id, round(length_score(value, event_type = 'view', 10D, 100D), 6) AS s FROM events")


@query(r"SELECT doc_id, i, t[i + 1] || ' ' || t[i + 2] AS part FROM (SELECT doc_id, unnest(range(len(t) - 1)) AS i, t FROM (SELECT doc_id, list_slice(regexp_extract_all(lower(text), '[\p{L}\p{N}]+'), 1, 4) AS t FROM documents) WHERE len(t) >= 2)")
def op_udtf_windows(spark, sf_dir):
    """The window table function called from SQL: windows of two tokens at steps of one over the first four of each text."""
    from cotengine.functions.sqlapi import register

    register(spark)
    register_views(spark, sf_dir)
    spark.sql("SELECT doc_id, array_join(slice(regexp_extract_all(lower(text), '[\\\\p{L}\\\\p{N}]+', 0), 1, 4), ' ') AS head FROM documents").createOrReplaceTempView("heads")
    return spark.sql("SELECT doc_id, CAST(w.i AS BIGINT) AS i, w.part FROM heads, LATERAL windows(head, 2, 1) w WHERE w.part LIKE '% %'")


@query("SELECT user_id, event_type AS consensus FROM (SELECT user_id, event_type, count(*) AS v FROM events GROUP BY ALL) QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY v DESC, event_type) = 1")
def op_udaf_majority(spark, sf_dir):
    """The majority aggregate called from SQL."""
    from cotengine.functions.sqlapi import register

    register(spark)
    register_views(spark, sf_dir)
    return spark.sql("SELECT user_id, majority(event_type) AS consensus FROM events GROUP BY user_id")


@query("SELECT lang, count(*) AS n FROM documents GROUP BY lang")
def op_write_partitioned(spark, sf_dir):
    """A stage written by partition twice: the second run replaces the first."""
    from cotengine.sources.files import write_stage

    path = _folder(spark)
    for _ in range(2):
        write_stage(T(spark, sf_dir, "documents").select("doc_id", "lang"), path, "lang")
    return spark.read.parquet(path).groupBy("lang").agg(F.count("*").alias("n"))


@query("SELECT lang AS value, count(*) AS n FROM documents GROUP BY lang")
def op_round_trip_text(spark, sf_dir):
    path = _folder(spark)
    T(spark, sf_dir, "documents").select("lang").write.text(path)
    return spark.read.text(path).groupBy("value").agg(F.count("*").alias("n"))


@query("SELECT 1::BIGINT AS files, true AS filled")
def op_scan_binary(spark, sf_dir):
    from cotengine.sources.files import raw_pages

    return raw_pages(spark, f"{sf_dir}/benchmark.parquet").agg(F.count("*").alias("files"), F.bool_and((F.length("content") == F.col("length")) & (F.col("length") > 0)).alias("filled"))
