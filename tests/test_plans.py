"""Shapes of plans, and a few queries against their SQL on the smallest tables."""

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from cotengine.operators import rollout
from cotengine.sources.tables import rollouts, table

SF = "/root/testdata/sf0.001"


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_filter_and_advantage_share_one_exchange(spark):
    r = rollouts(table(spark, SF, "events")).withColumn("reward", F.col("correct").cast("double"))
    text = plan(rollout.group_advantage(rollout.filter_by_group_score(rollout.drop_overlong(r, 16_384))))
    assert text.count("Exchange hashpartitioning") == 1 and "WindowGroupLimit" in text


def test_id_only_paths_do_not_read_text(spark):
    text = plan(table(spark, SF, "documents").where("n_chars > 2000").select("doc_id"))
    assert "PushedFilters: [IsNotNull(n_chars), GreaterThan(n_chars,2000)]" in text and "text" not in text.split("ReadSchema")[1]


def test_entry_runs(spark):
    df = entry.entry(spark)
    assert df.count() > 0 and "stratum" in df.columns


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", ["dedup_md5", "pass_at_1", "obj_dapo", "decon_13gram_hits", "stratified_length", "p_syn", "op_join_asof", "kb_subject"])
def test_against_sql(spark, name):
    con = duckdb.connect()
    for t in ("documents", "events", "benchmark", "embeddings", "pages", "labels"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    got = con.execute(entry.oracle_sql()[name])
    cols = [d[0] for d in got.description]
    want = sorted(map(str, got.fetchall()))
    df = entry.queries()[name](spark, SF).select(*cols)
    assert sorted(str(tuple(r)) for r in df.collect()) == want


def test_approximate_retrieval_finds_nine_tenths(spark):
    got = {r.method: r.recall for r in entry.queries()["retrieval_recall"](spark, SF).collect()}
    assert set(got) == {"ivf", "srp"} and min(got.values()) >= 0.9


def test_failure_driven_mixture_is_better_aligned(spark):
    got = entry.queries()["gradient_alignment"](spark, SF).collect()
    assert len(got) == 6 and all(r.better_aligned and r.lower_risk for r in got)


def test_rounds_lower_the_target_risk(spark):
    got = sorted(entry.queries()["failure_rounds"](spark, SF).collect())
    assert [r.round for r in got] == [0, 1, 2, 3] and all(a.target_risk > b.target_risk for a, b in zip(got, got[1:])) and got[-1].failures < got[0].failures


def test_sketch_quantiles_are_close(spark):
    assert all(r.rank_error < 0.02 for r in entry.queries()["quantile_error"](spark, SF).collect())


def test_the_full_kernel_shuffles_no_pair(spark):
    text = entry.queries()["kernel_full"](spark, SF)._jdf.queryExecution().optimizedPlan().toString()
    assert "Window" not in text and "prob" in text


def test_the_binary_scan_reads_the_content(spark):
    text = plan(entry.queries()["op_scan_binary"](spark, SF))
    assert "content:binary" in text.split("ReadSchema")[1].split("\n")[0]


@pytest.mark.parametrize("name", ["kernel_full", "op_scan_binary", "published_rank"])
def test_moved_queries_against_sql(spark, name):
    assert "parquet" in plan(entry.queries()[name](spark, SF))
    test_against_sql(spark, name)


def test_the_full_kernel_over_several_blocks(spark, monkeypatch):
    from cotengine.operators import failure, vector_blocks

    monkeypatch.setattr(vector_blocks, "ROWS", 7)
    monkeypatch.setattr(vector_blocks, "QUERY_ROWS", 3)
    rows = [(i, [float((i * j) % 7 - 3) for j in (1, 2, 3)]) for i in range(1, 30)] + [(40, [0.0, 0.0, 0.0]), (41, [1.0, 2.0])]
    c = spark.createDataFrame(rows, "d_id long, vec array<double>").repartition(3)
    q = c.withColumnRenamed("d_id", "x_id")
    want = {(r.x_id, r.d_id): r.prob for r in failure.retrieval_kernel(failure.retrieve(q, c, min_sim=-2.0).where("x_id <> d_id"), 0.1).collect()}
    got = {(r.x_id, r.d_id): r.prob for r in failure.full_kernel(q, c, 0.1, apart=True).collect()}
    assert set(got) == set(want) and all(abs(got[k] - want[k]) < 1e-9 for k in want)


def test_verified_pairs_move_hashes_not_words(spark):
    from cotengine.operators import dedup

    docs = spark.createDataFrame([(1, "a b c d e"), (2, "a b c d f")], "doc_id long, text string")
    banded = dedup.cut_lineage(dedup.band_keys(dedup.minhash(docs)), "bands")
    found = dedup.verify_pairs(banded.withColumns({"band": F.lit(0), "bkey": F.lit("x")}), docs)
    assert [(r.a, r.b, r.jaccard) for r in found.collect()] == [(1, 2, 0.5)]
    assert "xxhash64" in found._jdf.queryExecution().optimizedPlan().toString()
