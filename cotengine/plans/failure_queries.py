"""Registered queries of distribution matching and of the failure-driven stage, each beside its SQL."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from cotengine.functions.rewards import sequence_nll
from cotengine.functions.text import token_count, tokens
from cotengine.operators import failure as fd
from cotengine.operators import knowledge, shift
from cotengine.operators.decontam import small
from cotengine.operators.dedup import cut_lineage
from cotengine.operators.sampling import top_share
from cotengine.plans.curation_queries import sql_h8, sql_tokens
from cotengine.plans.failure_round import RoundConfig, failure_driven_round, failure_loop, ledger
from cotengine.sources.tables import rollouts, table

QUERIES: dict = {}
ORACLES: dict = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return add


SQL_ROLLOUTS_ALL = """r0 AS (SELECT event_id, ts, user_id AS prompt, event_type, value, CAST(json_extract(props, '$.k') AS BIGINT) AS k, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS i FROM events),
        r1 AS (SELECT *, (['click', 'error', 'purchase', 'signup', 'view'])[prompt % 5 + 1] AS gold, CAST(round(value * 100) AS BIGINT) AS len FROM r0),
        rall AS (SELECT *, CASE WHEN k < (prompt * 37) % 101 THEN gold ELSE event_type END AS answer, list_transform(range(8), lambda t: -((k + 7 * t) % 50 + 1) / 50.0::DOUBLE) AS lo,
                 list_transform(range(8), lambda t: -((k + 7 * t) % 50 + 1) / 50.0::DOUBLE * (1 + ((event_id + 3 * t) % 21 - 10) / 20.0::DOUBLE)) AS ln FROM r1)"""
SQL_ROLLOUTS = SQL_ROLLOUTS_ALL + ", r AS (SELECT *, answer = gold AS correct, CASE WHEN answer = gold THEN 1.0::DOUBLE ELSE 0.0 END AS reward FROM rall WHERE i <= 16)"
TAU = 0.05
SQL_SIMS = """x AS (SELECT vec_id AS x_id, embedding::DOUBLE[] AS v, label FROM embeddings WHERE vec_id % 5 = 0), d AS (SELECT vec_id AS d_id, embedding::DOUBLE[] AS v FROM embeddings WHERE vec_id % 5 <> 0),
        sims AS (SELECT x_id, d_id, round(list_cosine_similarity(x.v, d.v), 9) AS sim FROM x, d),
        top AS (SELECT *, row_number() OVER (PARTITION BY x_id ORDER BY sim DESC, d_id) AS rank FROM sims QUALIFY rank <= 30),
        kern AS (SELECT *, exp((sim - max(sim) OVER p) / 0.05) / sum(exp((sim - m) / 0.05)) OVER p AS prob FROM (SELECT *, max(sim) OVER (PARTITION BY x_id) AS m FROM top) WINDOW p AS (PARTITION BY x_id)),
        w AS (SELECT x_id, CASE WHEN (x_id // 5) % 10 <> label THEN 1 ELSE 0 END AS w FROM x),
        qd AS (SELECT x_id, w / (SELECT sum(w) FROM w)::DOUBLE AS q FROM w WHERE w > 0)"""
_SAID = lambda tag: f"(['A', 'B', 'C', 'D', 'E'])[{sql_h8(f"'{tag}:' || key")} % 5 + 1]"
SQL_SYNTH = f"""{SQL_SIMS}, fk AS (SELECT kern.* FROM kern JOIN qd USING (x_id)), docs AS (SELECT DISTINCT d_id FROM fk), ck AS (SELECT d_id, CAST(s AS INTEGER) AS slot, d_id || ':' || s AS key FROM docs, range(2) g(s)),
        cand AS (SELECT d_id, slot, {_SAID('a1')} AS ans1, CASE WHEN {sql_h8("'agree:' || key")} / 4294967296.0::DOUBLE < 0.6 THEN {_SAID('a1')} ELSE {_SAID('a2')} END AS ans2, [{_SAID('x0')}, {_SAID('x1')}, {_SAID('x2')}] AS extra, 100 + {sql_h8("'len:' || key")} % 9000 AS trace_len FROM ck),
        acc AS (SELECT * FROM cand WHERE ans1 = ans2), mass AS (SELECT d_id, sum(q * prob) AS mass FROM fk JOIN qd USING (x_id) GROUP BY d_id),
        cnt AS (SELECT d_id, count(*) AS k FROM acc GROUP BY d_id), psyn AS (SELECT a.d_id, slot, mass / k / (SELECT sum(mass) FROM mass JOIN cnt USING (d_id)) AS p FROM acc a JOIN mass USING (d_id) JOIN cnt USING (d_id))"""


def vectors(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings")
    return e.where("vec_id % 5 = 0").select(F.col("vec_id").alias("x_id"), F.col("embedding").alias("vec"), "label"), e.where("vec_id % 5 <> 0").select(F.col("vec_id").alias("d_id"), F.col("embedding").alias("vec"))


def query_weights(spark, sf_dir):
    x, _ = vectors(spark, sf_dir)
    return x.select("x_id", (F.floor(F.col("x_id") / 5) % 10 != F.col("label")).cast("int").alias("w"))


def round_of(spark, sf_dir):
    x, d = vectors(spark, sf_dir)
    return failure_driven_round(query_weights(spark, sf_dir), x.select("x_id", "vec"), d, config=RoundConfig(tau=TAU))


R6 = lambda c: F.round(c, 6).alias(c)

# --- distribution matching --------------------------------------------------------------------

SQL_CELLS = """cells AS (SELECT o_orderpriority, c_nationkey, o_orderstatus FROM orders JOIN customer ON o_custkey = c_custkey),
        p0 AS (SELECT o_orderpriority, c_nationkey, count(*) / (SELECT count(*) FROM cells WHERE o_orderstatus = 'F')::DOUBLE AS p0 FROM cells WHERE o_orderstatus = 'F' GROUP BY ALL),
        p1 AS (SELECT o_orderpriority, c_nationkey, count(*) / (SELECT count(*) FROM cells WHERE o_orderstatus = 'O')::DOUBLE AS p1 FROM cells WHERE o_orderstatus = 'O' GROUP BY ALL),
        dr AS (SELECT o_orderpriority, c_nationkey, coalesce(p0, 0) AS p0, coalesce(p1, 0) AS p1 FROM p0 FULL JOIN p1 USING (o_orderpriority, c_nationkey))"""


def _cells(spark, sf_dir):
    o, c = table(spark, sf_dir, "orders").select("o_custkey", "o_orderpriority", "o_orderstatus", "o_totalprice"), table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    return o.join(c, F.col("o_custkey") == F.col("c_custkey"))


CELLS = ["o_orderpriority", "c_nationkey"]


def _ratio(spark, sf_dir):
    rows = _cells(spark, sf_dir)
    return shift.density_ratio(rows.where("o_orderstatus = 'F'"), rows.where("o_orderstatus = 'O'"), CELLS)


@query(f"WITH {SQL_CELLS} SELECT o_orderpriority, c_nationkey, round(p0, 6) AS p0, round(p1, 6) AS p1, round(CASE WHEN p0 > 0 THEN p1 / p0 END, 6) AS rho, p0 = 0 AS uncovered FROM dr")
def density_ratio_orders(spark, sf_dir):
    return _ratio(spark, sf_dir).select(*CELLS, R6("p0"), R6("p1"), R6("rho"), "uncovered")


@query("""WITH a AS (SELECT lang, count(*) / (SELECT count(*) FROM documents WHERE source < 'src2')::DOUBLE AS p0 FROM documents WHERE source < 'src2' GROUP BY lang), b AS (SELECT lang, count(*) / (SELECT count(*) FROM documents)::DOUBLE AS p1 FROM documents GROUP BY lang)
        SELECT lang, round(coalesce(p0, 0), 6) AS p0, round(coalesce(p1, 0), 6) AS p1, round(p1 / p0, 6) AS rho, p0 IS NULL AS uncovered FROM a FULL JOIN b USING (lang)""")
def density_ratio(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("lang", "source")
    return shift.density_ratio(docs.where("source < 'src2'"), docs, ["lang"]).select("lang", R6("p0"), R6("p1"), R6("rho"), "uncovered")


SQL_WEIGHTED = f"{SQL_CELLS}, wl AS (SELECT o_orderpriority, c_nationkey, CASE WHEN p0 > 0 THEN p1 / p0 ELSE 0 END AS rho, o_totalprice / 1000 AS loss FROM (SELECT o_orderpriority, c_nationkey, o_totalprice FROM orders JOIN customer ON o_custkey = c_custkey WHERE o_orderstatus = 'F') JOIN dr USING (o_orderpriority, c_nationkey))"


def _weighted(spark, sf_dir):
    rows = _cells(spark, sf_dir).where("o_orderstatus = 'F'").withColumn("loss", F.col("o_totalprice") / 1000)
    return rows.join(F.broadcast(_ratio(spark, sf_dir).select(*CELLS, F.coalesce("rho", F.lit(0.0)).alias("rho"))), CELLS)  # one row for each priority and nation


@query(f"WITH {SQL_WEIGHTED} SELECT round(sum(rho * loss) / sum(rho), 6) AS risk, round(avg(loss), 6) AS biased, round(sum(rho * loss) / sum(rho) - avg(loss), 6) AS gap, round(sum(rho) * sum(rho) / sum(rho * rho), 4) AS ess FROM wl")
def importance_risk(spark, sf_dir):
    return shift.expected_risk(_weighted(spark, sf_dir), "loss", "rho").select(R6("risk"), R6("biased"), R6("gap"), F.round("ess", 4).alias("ess"))


@query(f"WITH {SQL_WEIGHTED}, c AS (SELECT o_orderpriority, avg(loss) AS mean_loss, sum(rho * loss) / (SELECT sum(rho * loss) FROM wl) AS share FROM wl GROUP BY ALL) SELECT o_orderpriority, round(mean_loss, 6) AS mean_loss, round(share, 6) AS share, CAST(row_number() OVER (ORDER BY round(share, 9) DESC, o_orderpriority) AS INTEGER) AS rank FROM c")
def risk_contributors(spark, sf_dir):
    return shift.risk_contributors(_weighted(spark, sf_dir), ["o_orderpriority"], "loss", "rho").select("o_orderpriority", R6("mean_loss"), R6("share"), "rank")


@query(f"WITH {SQL_ROLLOUTS}, b(beta) AS (VALUES (0.0), (1.0), (4.0)), e AS (SELECT beta, prompt, i, exp(beta * reward) AS e FROM r, b) SELECT beta, prompt, i, round(e / sum(e) OVER (PARTITION BY beta, prompt), 6) AS p FROM e")
def advantage_tilt(spark, sf_dir):
    r = rollouts(table(spark, sf_dir, "events")).select("prompt", "i", F.col("correct").cast("double").alias("adv"), (F.lit(1.0) / 16).alias("p"))
    parts = [shift.tilt(r, b, by="prompt").select(F.lit(b).alias("beta"), "prompt", "i", F.round("tilted", 6).alias("p")) for b in (0.0, 1.0, 4.0)]
    return parts[0].union(parts[1]).union(parts[2])


@query(f"WITH {SQL_ROLLOUTS} SELECT event_id, round(-list_sum(ln), 6) AS nll, round(-list_sum(ln) / len(ln), 6) AS mean_nll FROM r", "sequence_nll")
def sequence_nll_query(spark, sf_dir):
    r = rollouts(table(spark, sf_dir, "events"))
    return r.select("event_id", F.round(sequence_nll(F.col("logp_new")), 6).alias("nll"), F.round(sequence_nll(F.col("logp_new"), mean=True), 6).alias("mean_nll"))


@query("""WITH a AS (SELECT lang, count(*) / (SELECT count(*) FROM documents WHERE doc_id % 2 = 0)::DOUBLE AS p FROM documents WHERE doc_id % 2 = 0 GROUP BY lang), b AS (SELECT lang, count(*) / (SELECT count(*) FROM documents WHERE doc_id % 2 = 1)::DOUBLE AS q FROM documents WHERE doc_id % 2 = 1 GROUP BY lang)
        SELECT round(sum(abs(coalesce(p, 0) - coalesce(q, 0))) / 2, 6) AS tv, round(sum(CASE WHEN p > 0 AND q > 0 THEN p * ln(p / q) ELSE 0 END), 6) AS kl, round(sum(CASE WHEN q IS NULL THEN p ELSE 0 END), 6) AS uncovered FROM a FULL JOIN b USING (lang)""")
def distribution_distance(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id", "lang")
    p, q = (shift.empirical(docs.where(f"doc_id % 2 = {i}"), ["lang"], f"p{i}") for i in (0, 1))
    return shift.distances(p, q, ["lang"]).select(R6("tv"), R6("kl"), R6("uncovered"))


# --- failures and retrieval ---------------------------------------------------------------------


@query(f"WITH {SQL_ROLLOUTS} SELECT prompt, CASE WHEN correct THEN 0 ELSE 1 END AS w FROM r WHERE i = 1")
def failure_weights(spark, sf_dir):
    return fd.failure_weights(rollouts(table(spark, sf_dir, "events")))


@query(f"WITH {SQL_ROLLOUTS} SELECT prompt, round(1 - avg(reward), 6) AS w FROM r GROUP BY prompt")
def failure_soft(spark, sf_dir):
    return fd.failure_weights(rollouts(table(spark, sf_dir, "events")), kind="soft").select("prompt", R6("w"))


@query(f"WITH {SQL_ROLLOUTS}, w AS (SELECT prompt, 1 - reward AS w FROM r WHERE i = 1) SELECT prompt, round(w / (SELECT sum(w) FROM w), 9) AS q FROM w WHERE w > 0")
def failure_distribution(spark, sf_dir):
    return fd.failure_distribution(fd.failure_weights(rollouts(table(spark, sf_dir, "events")))).select("prompt", F.round("q", 9).alias("q"))


@query(f"WITH {SQL_SIMS} SELECT x_id, d_id, round(sim, 6) AS sim FROM sims WHERE x_id % 50 = 0")
def cosine_pairs(spark, sf_dir):
    x, d = vectors(spark, sf_dir)
    return fd.retrieve(x.where("x_id % 50 = 0"), d, min_sim=-2.0).select("x_id", "d_id", R6("sim"))


@query("""WITH d AS (SELECT vec_id AS d_id, embedding::DOUBLE[] AS v FROM embeddings), sims AS (SELECT x.d_id AS x_id, d.d_id, round(list_cosine_similarity(x.v, d.v), 9) AS sim FROM d x, d WHERE x.d_id % 50 = 0 AND x.d_id <> d.d_id),
        m AS (SELECT *, max(sim) OVER (PARTITION BY x_id) AS m FROM sims) SELECT x_id, d_id, round(exp((sim - m) / 0.05) / sum(exp((sim - m) / 0.05)) OVER (PARTITION BY x_id), 6) AS prob FROM m""")
def kernel_full(spark, sf_dir):
    """The kernel of every fiftieth vector over all the others, each pair put out."""
    e = table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").alias("vec"))
    return fd.full_kernel(e.where("vec_id % 50 = 0").withColumnRenamed("vec_id", "x_id"), e.withColumnRenamed("vec_id", "d_id"), TAU, apart=True, digits=6)


@query(f"WITH {SQL_SIMS} SELECT x_id, d_id, round(sim, 6) AS sim, CAST(rank AS INTEGER) AS rank FROM top")
def retrieve_top30(spark, sf_dir):
    x, d = vectors(spark, sf_dir)
    return fd.retrieve(x, d).select("x_id", "d_id", R6("sim"), "rank")


@query(f"WITH {SQL_SIMS} SELECT x_id, d_id, round(prob, 6) AS prob FROM kern")
def kernel_topk(spark, sf_dir):
    x, d = vectors(spark, sf_dir)
    return fd.retrieval_kernel(fd.retrieve(x, d), TAU).select("x_id", "d_id", R6("prob"))


@query(f"WITH {SQL_SIMS} SELECT x_id, d_id, round(sim, 6) AS sim FROM sims WHERE sim >= 0.3")
def retrieve_threshold(spark, sf_dir):
    x, d = vectors(spark, sf_dir)
    return fd.retrieve(x, d, min_sim=0.3).select("x_id", "d_id", R6("sim"))


@query(f"WITH {SQL_SIMS}, t(t) AS (VALUES (0.2), (0.3), (0.4)) SELECT t AS min_sim, count(*) AS retrieved, count(DISTINCT d_id) AS documents FROM sims, t WHERE sim >= t GROUP BY t")
def relevance_sweep(spark, sf_dir):
    """How many documents looser relevance brings in."""
    x, d = vectors(spark, sf_dir)
    got = fd.retrieve(x, d, min_sim=0.2).withColumn("min_sim", F.explode(F.array(F.lit(0.2), F.lit(0.3), F.lit(0.4)))).where("sim >= min_sim")
    return got.groupBy("min_sim").agg(F.count("*").alias("retrieved"), F.countDistinct("d_id").alias("documents"))


@query(f"WITH {SQL_SIMS}, f AS (SELECT x_id, rank() OVER (PARTITION BY x_id ORDER BY sim DESC, d_id) AS rk, exp((sim - max(sim) OVER (PARTITION BY x_id)) / 0.05) AS e FROM sims) SELECT x_id, round(1 - sum(e) FILTER (rk <= 30) / sum(e), 6) AS tv FROM f GROUP BY x_id")
def kernel_truncation_gap(spark, sf_dir):
    """Total variation between full and truncated kernel: the mass outside the top k."""
    x, d = vectors(spark, sf_dir)
    return fd.truncation_gap(x, d, k=30, tau=TAU).select("x_id", R6("tv"))


def _screen(d, kind):
    if kind == "srp":
        return fd.sign_sketch(64)
    sample = d.orderBy(F.xxhash64("d_id")).limit(5000).collect()  # bound of the centroid sample
    m = np.array([r.vec for r in sample], float)
    return fd.cell_residuals(fd.sphere_centres(m / np.linalg.norm(m, axis=1, keepdims=True)))


def _approximate(spark, sf_dir, kind, k=30):
    x, d = vectors(spark, sf_dir)
    return fd.retrieve(x, d, k=k, screen=_screen(d, kind))


@query()
def retrieve_ivf(spark, sf_dir):
    """Shortlist of a fifth of the corpus by centre and 4-bit residual, then exact cosine."""
    return _approximate(spark, sf_dir, "ivf")


@query()
def retrieve_srp(spark, sf_dir):
    """Shortlist of three tenths of the corpus by 384 sign bits, then exact cosine."""
    return _approximate(spark, sf_dir, "srp")


@query()
def retrieval_recall(spark, sf_dir):
    """Share of the exact top 30 that each approximate way finds; every pair counts once."""
    x, d = vectors(spark, sf_dir)
    exact = fd.retrieve(x, d).select("x_id", "d_id")
    found = {"ivf": retrieve_ivf, "srp": retrieve_srp}
    parts = [exact.join(f(spark, sf_dir).select("x_id", "d_id").distinct().withColumn("hit", F.lit(1)), ["x_id", "d_id"], "left").agg(F.avg(F.coalesce("hit", F.lit(0))).alias("recall")).select(F.lit(kind).alias("method"), "recall") for kind, f in found.items()]
    return parts[0].union(parts[1])


@query(f"""WITH dt AS (SELECT doc_id AS d_id, w, count(*) AS tf FROM (SELECT doc_id, unnest({sql_tokens()}) AS w FROM documents) GROUP BY ALL), it AS (SELECT item_id AS x_id, w, count(*) AS tf FROM (SELECT item_id, unnest({sql_tokens()}) AS w FROM benchmark) GROUP BY ALL),
        df AS (SELECT w, ln((SELECT count(*) FROM documents)::DOUBLE / count(*)) AS idf FROM dt GROUP BY w),
        dv AS (SELECT d_id, w, tf * idf AS v FROM dt JOIN df USING (w)), iv AS (SELECT x_id, w, tf * idf AS v FROM it JOIN df USING (w)),
        s AS (SELECT x_id, d_id, round(sum(iv.v * dv.v) / sqrt(any_value(xn)) / sqrt(any_value(dn)), 9) AS sim FROM iv JOIN dv USING (w) JOIN (SELECT x_id, sum(v * v) AS xn FROM iv GROUP BY x_id) USING (x_id) JOIN (SELECT d_id, sum(v * v) AS dn FROM dv GROUP BY d_id) USING (d_id) GROUP BY x_id, d_id)
        SELECT x_id, d_id, round(sim, 6) AS sim FROM s QUALIFY row_number() OVER (PARTITION BY x_id ORDER BY sim DESC, d_id) <= 5""")
def retrieve_lexical(spark, sf_dir):
    """TF-IDF cosine over all shared terms. The item side is sent to the documents while it is small, so no common term gathers its documents."""
    from pyspark.sql import Window

    def counts(name, key, out):
        return table(spark, sf_dir, name).select(F.col(key).alias(out), F.explode(tokens(F.col("text"))).alias("w")).groupBy(out, "w").agg(F.count("*").alias("tf"))

    dt, it = counts("documents", "doc_id", "d_id"), counts("benchmark", "item_id", "x_id")
    n = F.broadcast(table(spark, sf_dir, "documents").agg(F.count("*").alias("n")))
    df = dt.groupBy("w").agg(F.count("*").alias("df")).crossJoin(n).select("w", F.log(F.col("n") / F.col("df")).alias("idf"))
    dv, iv = (x.join(df, "w").select(k, "w", (F.col("tf") * F.col("idf")).alias("v")) for x, k in ((dt, "d_id"), (it, "x_id")))
    dn, xn = dv.groupBy("d_id").agg(F.sum(F.col("v") * F.col("v")).alias("dn")), iv.groupBy("x_id").agg(F.sum(F.col("v") * F.col("v")).alias("xn"))
    dots = small(cut_lineage(iv.withColumnRenamed("v", "a"), "item-terms"), 500_000).join(dv.withColumnRenamed("v", "b"), "w").groupBy("x_id", "d_id").agg(F.sum(F.col("a") * F.col("b")).alias("dot"))
    sims = dots.join(xn, "x_id").join(dn, "d_id").select("x_id", "d_id", F.round(F.col("dot") / F.sqrt("xn") / F.sqrt("dn"), 9).alias("sim"))
    return sims.withColumn("r", F.row_number().over(Window.partitionBy("x_id").orderBy(F.col("sim").desc(), "d_id"))).where("r <= 5").select("x_id", "d_id", R6("sim"))


# --- synthesis and mixtures -----------------------------------------------------------------------


@query(f"WITH {SQL_SYNTH} SELECT d_id, round(mass, 9) AS mass FROM mass")
def activation_mass(spark, sf_dir):
    return round_of(spark, sf_dir).mass.select("d_id", F.round("mass", 9).alias("mass"))


@query(f"WITH {SQL_SYNTH} SELECT d_id, slot, ans1, ans2, trace_len FROM cand")
def synth_candidates(spark, sf_dir):
    return round_of(spark, sf_dir).candidates.select("d_id", "slot", "ans1", "ans2", "trace_len")


@query(f"WITH {SQL_SYNTH} SELECT d_id, slot FROM acc")
def synth_accepted(spark, sf_dir):
    return round_of(spark, sf_dir).accepted.select("d_id", "slot")


@query(f"""WITH {SQL_SYNTH}, v AS (SELECT d_id, slot, a, count(*) AS v FROM (SELECT d_id, slot, unnest(list_concat([ans1, ans2], extra)) AS a FROM cand WHERE ans1 <> ans2) GROUP BY ALL)
        SELECT d_id, slot, a AS consensus, v AS votes FROM v QUALIFY row_number() OVER (PARTITION BY d_id, slot ORDER BY v DESC, a) = 1""")
def synth_hard_majority(spark, sf_dir):
    return round_of(spark, sf_dir).hard.select("d_id", "slot", "consensus", "votes")


@query(f"WITH {SQL_SYNTH} SELECT d_id, slot, trace_len FROM acc QUALIFY percent_rank() OVER (ORDER BY trace_len DESC, d_id, slot) < 0.2")
def synth_difficult(spark, sf_dir):
    return top_share(round_of(spark, sf_dir).accepted, 0.2, [F.col("trace_len").desc(), F.col("d_id"), F.col("slot")]).select("d_id", "slot", "trace_len")


@query(f"WITH {SQL_SYNTH} SELECT d_id, slot, round(p, 9) AS p FROM psyn")
def p_syn(spark, sf_dir):
    return round_of(spark, sf_dir).p_syn.select("d_id", "slot", F.round("p", 9).alias("p"))


SQL_MIX = f"{SQL_SYNTH}, o AS (SELECT 'o:' || doc_id AS key, 1.0::DOUBLE / (SELECT count(*) FROM documents) AS p FROM documents), s AS (SELECT 's:' || d_id || ':' || slot AS key, p FROM psyn)"


def _sides(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id")
    o = shift.empirical(docs.select(F.concat(F.lit("o:"), F.col("doc_id").cast("string")).alias("key")), ["key"], "p")
    return o, round_of(spark, sf_dir).p_syn.select(F.concat_ws(":", F.lit("s"), F.col("d_id").cast("string"), F.col("slot").cast("string")).alias("key"), "p")


def _mixture(lam, name):
    def f(spark, sf_dir):
        o, s = _sides(spark, sf_dir)
        return shift.mix(o, s, lam, "key").where("p > 0").select("key", F.round("p", 9).alias("p"))

    query(f"WITH {SQL_MIX} SELECT key, round({lam} * p, 9) AS p FROM o WHERE {lam} > 0 UNION ALL SELECT key, round({1 - lam} * p, 9) FROM s WHERE {1 - lam} > 0", name)(f)


_mixture(0.5, "mixture_p1")
_mixture(1.0, "mixture_p0")


def _experiment(tenths, name):
    def f(spark, sf_dir):
        o, s = _sides(spark, sf_dir)
        n = s.count() * tenths // 34
        return fd.sample_mixture(o.select("key"), s.select("key"), n)

    query(f"WITH {SQL_MIX} SELECT key, 'synthetic' AS origin FROM s UNION ALL (SELECT key, 'original' FROM o QUALIFY row_number() OVER (ORDER BY {sql_h8("'42:' || key")}, key) <= (SELECT count(*) * {tenths} // 34 FROM s))", name)(f)


_experiment(0, "mixture_exp1")
_experiment(10, "mixture_exp2")
_experiment(30, "mixture_exp3")


@query(f"WITH {SQL_SYNTH}, b AS (SELECT DISTINCT (x_id // 5) % 2 AS suite, d_id FROM fk), n AS (SELECT suite, count(*) AS documents, CAST(sum(k) AS BIGINT) AS accepted FROM b LEFT JOIN cnt USING (d_id) GROUP BY suite) SELECT suite, documents, accepted, (SELECT count(*) FROM (SELECT d_id FROM b GROUP BY d_id HAVING count(*) = 2)) AS shared FROM n")
def synth_source_ablation(spark, sf_dir):
    """Synthetic sets of two suites of failures, and the documents they share."""
    r = round_of(spark, sf_dir)
    by = r.kernel.select((F.floor(F.col("x_id") / 5) % 2).alias("suite"), "d_id").distinct()
    shared = F.broadcast(by.groupBy("d_id").count().where("count = 2").agg(F.count("*").alias("shared")))
    k = r.accepted.groupBy("d_id").agg(F.count("*").alias("k"))
    return by.join(k, "d_id", "left").groupBy("suite").agg(F.count("*").alias("documents"), F.sum("k").alias("accepted")).crossJoin(shared)


@query(f"WITH {SQL_SYNTH} SELECT 'failures' AS step, count(*) AS n FROM qd UNION ALL SELECT 'retrieved', count(*) FROM fk UNION ALL SELECT 'documents', count(*) FROM docs UNION ALL SELECT 'candidates', count(*) FROM cand UNION ALL SELECT 'accepted', count(*) FROM acc UNION ALL SELECT 'hard', count(*) FROM cand WHERE ans1 <> ans2")
def failure_round(spark, sf_dir):
    return ledger(round_of(spark, sf_dir))


@query()
def failure_rounds(spark, sf_dir):
    """The loop run three times on the proxy learner: failures, accuracy and target risk before each round, and after the last."""
    return failure_loop(table(spark, sf_dir, "embeddings"), rounds=3)


# --- knowledge base ---------------------------------------------------------------------------

_ENT = "replace(replace(replace(replace(replace(replace({}, '&nbsp;', ' '), '&lt;', '<'), '&gt;', '>'), '&quot;', '\"'), '&#39;', ''''), '&amp;', '&')"
SQL_PAGES = r"""pt AS (SELECT page_id, url, trim(regexp_extract(html, '(?is)<title[^>]*>(.*?)</title>', 1)) AS title, trim(regexp_replace(""" + _ENT.format(r"""regexp_replace(regexp_replace(html, '(?is)<script\b.*?</script>|<style\b.*?</style>|<nav\b.*?</nav>|<!--.*?-->', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g')""") + r""", '\s+', ' ', 'g')) AS text FROM pages)"""
SQL_SHARES = ", ".join(f"len(list_filter(t, lambda w: w IN ({', '.join(repr(w) for w in ws)})))::DOUBLE / greatest(len(t), 1) AS {lang}" for lang, ws in sorted(knowledge.STOP.items()))
SQL_SCORED = f"""{SQL_PAGES}, tk AS (SELECT *, {sql_tokens()} AS t FROM pt), sh AS (SELECT *, {SQL_SHARES} FROM tk),
        lo AS (SELECT page_id, unnest([de, en, es, fr]) AS s, unnest(['de', 'en', 'es', 'fr']) AS l, unnest([0, 1, 2, 3]) AS o FROM sh), rk AS (SELECT *, row_number() OVER (PARTITION BY page_id ORDER BY s DESC, o) AS n FROM lo),
        sc AS (SELECT page_id, a.s AS fluency, a.l AS subject, a.s - b.s AS margin, CASE WHEN len(t) > 0 THEN len(list_distinct(t))::DOUBLE / len(t) ELSE 0 END AS usefulness FROM sh JOIN rk a USING (page_id) JOIN rk b USING (page_id) WHERE a.n = 1 AND b.n = 2)"""


@query(f"WITH {SQL_PAGES} SELECT page_id, title, md5(text) AS digest FROM pt")
def pages_text(spark, sf_dir):
    return knowledge.parse_pages(table(spark, sf_dir, "pages")).select("page_id", "title", F.md5("text").alias("digest"))


@query(f"WITH {SQL_SCORED} SELECT page_id, round(fluency, 6) AS fluency, round(usefulness, 6) AS usefulness FROM sc WHERE fluency >= 0.05 AND usefulness >= 0.2 AND margin >= 0.02")
def kb_quality(spark, sf_dir):
    return knowledge.quality_filter(knowledge.scored(knowledge.parse_pages(table(spark, sf_dir, "pages")))).select("page_id", R6("fluency"), R6("usefulness"))


@query(f"WITH {SQL_SCORED} SELECT page_id, subject, round(margin, 6) AS margin FROM sc")
def kb_subject(spark, sf_dir):
    return knowledge.scored(knowledge.parse_pages(table(spark, sf_dir, "pages"))).select("page_id", "subject", R6("margin"))


@query()
def kb_quality_model(spark, sf_dir):
    """A usefulness model: logistic regression on column scores, learned from ``labels``."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import VectorAssembler

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    toks = docs.withColumn("n", token_count(F.col("text")).cast("double"))
    x = knowledge.scored(toks).withColumn("symbols", F.length(F.regexp_replace("text", r"[\p{L}\p{N}\s]", "")) / F.greatest(F.length("text"), F.lit(1)))
    rows = VectorAssembler(inputCols=["fluency", "usefulness", "margin", "symbols"], outputCol="features").transform(x.select("doc_id", "fluency", "usefulness", "margin", "symbols"))
    marks = table(spark, sf_dir, "labels").select("doc_id", F.col("quality").cast("double").alias("label"))
    model = LogisticRegression(maxIter=20).fit(rows.join(marks, "doc_id"))
    return model.transform(rows).select("doc_id", F.col("prediction").cast("int").alias("useful"))


@query(f"WITH {SQL_PAGES}, q AS (SELECT page_id, text, unnest([0, 1]) AS s FROM pt WHERE length(text) > 0) SELECT page_id * 2 + s AS item_id, CASE WHEN s = 0 THEN 'Explain: ' || left(text, 80) ELSE 'Derive: ' || right(text, 80) END AS question, 'pages' AS origin FROM q")
def stage1_doc_questions(spark, sf_dir):
    """Two questions of each page's parsed text, tagged by origin (stand-in generator); pages without text give none."""
    read = knowledge.parse_pages(table(spark, sf_dir, "pages")).where(F.length("text") > 0)
    asked = read.select("page_id", F.posexplode(F.array(F.concat(F.lit("Explain: "), F.left("text", F.lit(80))), F.concat(F.lit("Derive: "), F.right("text", F.lit(80))))).alias("s", "question"))
    return asked.select((F.col("page_id") * 2 + F.col("s")).alias("item_id"), "question", F.lit("pages").alias("origin"))
