"""Worked values of the methods on hand-made rows."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from cotengine.functions import rewards, text
from cotengine.functions.hashing import BANDS, ROWS
from cotengine.operators import decontam, dedup, distill, rollout, sampling, shift
from cotengine.operators import failure as fd


def values(df, *cols):
    return [tuple(r[c] for c in cols) for r in df.collect()]


def test_kernel_and_truncation(spark):
    sims = spark.createDataFrame([(1, i, s) for i, s in enumerate([0.9, 0.8, 0.5, 0.1])], "x_id long, d_id long, sim double")
    full = sorted((r.d_id, r.prob) for r in fd.retrieval_kernel(sims, 0.1).collect())
    assert [round(p, 6) for _, p in full] == [0.721225, 0.265324, 0.01321, 0.000242]
    top = fd.retrieval_kernel(sims.where("d_id < 2"), 0.1)
    assert sorted(round(r.prob, 6) for r in top.collect()) == [0.268941, 0.731059]


def test_failure_distribution(spark):
    w = spark.createDataFrame([(1, 1), (2, 0), (3, 1), (4, 0)], "prompt long, w int")
    assert sorted(values(fd.failure_distribution(w), "prompt", "q")) == [(1, 0.5), (3, 0.5)]
    with pytest.raises(Exception, match="no failure"):
        fd.failure_distribution(w.withColumn("w", F.lit(0))).collect()
        fd.failure_distribution(w.withColumn("w", F.lit(0)).where("prompt > 0")).count()
        raise AssertionError("no failure was expected")


def test_activation_and_synthetic_mass(spark):
    q = spark.createDataFrame([(1, 0.5), (2, 0.5)], "x_id long, q double")
    k = spark.createDataFrame([(1, 1, 0.7), (1, 2, 0.3), (2, 2, 0.6), (2, 3, 0.4)], "x_id long, d_id long, prob double")
    mass = fd.activation_mass(q, k)
    assert {r.d_id: round(r.mass, 6) for r in mass.collect()} == {1: 0.35, 2: 0.45, 3: 0.2}
    accepted = spark.createDataFrame([(1, 0), (1, 1), (2, 0)], "d_id long, slot int")
    p, lost = fd.synthetic_distribution(mass, accepted)
    assert {(r.d_id, r.slot): round(r.p, 6) for r in p.collect()} == {(1, 0): 0.21875, (1, 1): 0.21875, (2, 0): 0.5625}
    assert round(lost.first().lost, 6) == 0.2


def test_tilt(spark):
    df = spark.createDataFrame([(0, 0.2, 1.0), (0, 0.3, 0.0), (0, 0.5, 0.0)], "g int, p double, adv double")
    assert sorted(round(r.tilted, 6) for r in shift.tilt(df, 2.0, by="g").collect()) == [0.131705, 0.219509, 0.648786]
    assert all(abs(r.tilted - r.p) < 1e-12 for r in shift.tilt(df, 0.0, by="g").collect())


def test_advantage_and_clipping(spark):
    r = spark.createDataFrame([(1, x) for x in (1.0, 0.0, 0.0, 1.0, 1.0)] + [(2, 1.0)] * 3, "prompt long, reward double")
    got = rollout.group_advantage(r).collect()
    assert sorted({round(x.advantage, 6) for x in got if x.prompt == 1}) == [-1.224745, 0.816497]
    assert {x.advantage for x in got if x.prompt == 2} == {0.0}
    df = spark.createDataFrame([([1.349859, 0.740818, 1.051271],)], "r array<double>")
    for a, want in ((1.0, [1.28, 0.740818, 1.051271]), (-1.0, [-1.349859, -0.8, -1.051271])):
        assert np.allclose(df.select(rewards.clipped_terms(F.col("r"), F.lit(a), 0.2, 0.28).alias("c")).first().c, want)


def test_length_score_and_repetition(spark):
    df = spark.createDataFrame([(50, False), (200, False), (300, False), (10, True)], "len int, ok boolean")
    assert [x[0] for x in df.select(rewards.length_score(F.col("len"), F.col("ok"), 100, 300)).collect()] == [0.0, 0.5, 1.0, 1.0]
    t = spark.createDataFrame([("a b a b a b",), ("",), (None,), ("one",)], "text string")
    assert [round(x[0], 6) for x in t.select(text.repetition_ratio(F.col("text"), 2)).collect()] == [0.6, 0.0, 0.0, 0.0]


def test_pass_at_k_and_votes(spark):
    rows = [(c, i, i < c) for c in (0, 1, 4, 13) for i in range(16)]
    r = spark.createDataFrame(rows, "prompt long, i int, correct boolean")
    for c, want in ((0, 0.0), (1, 0.25), (4, 0.728022), (13, 1.0)):
        assert round(rollout.pass_at_k(r.where(f"prompt = {c}"), [4]).first().pass_at_k, 6) == want
    v = spark.createDataFrame([(1, "A"), (1, "A"), (1, "B"), (2, "B"), (2, "A"), (3, "A"), (3, None)], "p long, answer string")
    assert {x.p: x.consensus for x in fd.majority(v, ["p"]).collect()} == {1: "A", 2: "A", 3: "A"}


def test_density_ratio_reports_uncovered(spark):
    base = spark.createDataFrame([("a",), ("b",)], "c string")
    target = spark.createDataFrame([("a",), ("b",), ("b",), ("c",)], "c string")
    got = {r.c: (r.rho, r.uncovered) for r in shift.density_ratio(base, target, ["c"]).collect()}
    assert got == {"a": (0.5, False), "b": (1.0, False), "c": (None, True)}


def test_two_passes_and_answers(spark):
    df = spark.createDataFrame([("42", "42.0"), ("A", "B"), ("x", None), ("\\boxed{1/2}", "0.5"), ("\\frac{1}{4}", "0.25")], "ans1 string, ans2 string")
    assert [r.accepted for r in fd.accept_consistent(df).collect()] == [True, False, False, True, True]
    assert df.select(distill.verify_answer(F.lit("a"), F.lit(None).cast("string")).alias("v")).first().v is None


def test_retention_prefers_valid_and_verifiable(spark):
    docs = spark.createDataFrame([(1, "one two three four five six"), (2, "one two three four five six"), (3, "One two three four five, six")], "doc_id long, text string")
    prio = F.element_at(F.array(F.lit(2), F.lit(0), F.lit(1)), F.col("doc_id").cast("int"))
    for mode in ("bucket", "component"):
        assert [r.doc_id for r in dedup.dedup_near(docs, prio, mode=mode).collect()] == [2]


def test_banding_follows_the_curve():
    rng = np.random.default_rng(5)
    for s, want in ((0.5, 0.0232), (0.7, 0.4973), (0.8, 0.9345)):
        hit = (rng.random((4000, BANDS, ROWS)) < s).all(2).any(1).mean()
        assert abs(hit - want) < 0.03 and abs(1 - (1 - s**ROWS) ** BANDS - want) < 1e-3


def test_group_bounds(spark):
    rows = [(p, i < n) for p, n in ((1, 1), (2, 2), (3, 10), (4, 19), (5, 20)) for i in range(20)]
    r = spark.createDataFrame(rows, "prompt long, correct boolean")
    assert {x.prompt for x in rollout.filter_by_group_score(r).select("prompt").distinct().collect()} == {2, 3, 4}


def test_decontamination_leaves_no_shared_run(spark):
    item = "w1 w2 w3 w4 w5 w6 w7 w8 w9 w10 w11 w12 w13 w14"
    train = spark.createDataFrame([(1, "x " + item + " y"), (2, "w1 w2 w3"), (3, None), (4, "")], "doc_id long, text string")
    items = spark.createDataFrame([(9, item)], "item_id long, text string")
    kept, hits = decontam.decontaminate(train, items)
    assert sorted(r.doc_id for r in kept.collect()) == [2, 3, 4] and [r.doc_id for r in hits.collect()] == [1]
    empty = items.where("false")
    assert decontam.decontaminate(train, empty)[0].count() == 4


def test_samples_are_nested_and_independent_of_partitions(spark):
    df = spark.range(2000).select(F.col("id").alias("doc_id"), (F.col("id") % 500).cast("int").alias("n_tokens"))
    low = {r.doc_id for r in sampling.stratified_by_length(df, rates=(0, 0.1, 0.5, 1)).collect()}
    high = {r.doc_id for r in sampling.stratified_by_length(df.repartition(7), rates=(0, 0.2, 0.5, 1)).collect()}
    assert low < high and len(low) < 1000
    assert low == {r.doc_id for r in sampling.stratified_by_length(df.repartition(3), rates=(0, 0.1, 0.5, 1)).collect()}


def test_components(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(30)] + [(100, 101), (5, 5)], "u long, v long")
    got = {r.node: r.root for r in dedup.components(edges).collect()}
    assert {got[i] for i in range(31)} == {0} and got[101] == 100


def test_approximate_pairs_are_unique_and_few_are_compared(spark):
    m = np.random.default_rng(3).standard_normal((640, 64))
    x, d = (spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(part)], f"{k} long, vec array<double>") for k, part in (("x_id", m[:40]), ("d_id", m[40:])))
    exact = {(r.x_id, r.d_id) for r in fd.retrieve(x, d).collect()}
    unit = m / np.linalg.norm(m, axis=1, keepdims=True)
    for screen in (fd.sign_sketch(64), fd.cell_residuals(fd.sphere_centres(unit[40:]))):
        assert screen(unit[:40], unit[40:]).mean() < 1 / 3
        got = [(r.x_id, r.d_id) for r in fd.retrieve(x, d, screen=screen).collect()]
        assert len(got) == len(set(got)) == 1200 and len(exact & set(got)) >= 0.9 * 1200


def test_retrieval_of_odd_vectors(spark):
    x = spark.createDataFrame([(1, [1.0, 0.0]), (2, [0.0, 0.0]), (3, [1.0, 0.0, 0.0])], "x_id long, vec array<double>")
    d = spark.createDataFrame([(1, [2.0, 0.0]), (2, [0.0, 0.0]), (3, [0.0, 1.0]), (4, [1.0, 1.0]), (4, [1.0, 1.0])], "d_id long, vec array<double>")
    assert sorted(values(fd.retrieve(x, d, k=2), "x_id", "d_id", "sim", "rank")) == [(1, 1, 1.0, 1), (1, 4, 0.707106781, 2)]
    assert sorted(values(fd.retrieve(x, d, min_sim=-1.0), "d_id", "sim")) == [(1, 1.0), (3, 0.0), (4, 0.707106781), (4, 0.707106781)]
    assert fd.retrieve(x.where("false"), d).count() == fd.retrieve(x, d.where("false")).count() == 0


def test_responses_are_filtered_verified_and_retried_once(spark):
    from cotengine.sources.providers import Provider, materialized

    rows = spark.createDataFrame([(1, "A"), (2, "A"), (3, None), (4, "A"), (5, "A")], "doc_id long, gold string")
    said = {1: {1: ("A", "fine"), 2: ("B", "fine"), 3: ("C", "fine"), 4: ("B", "no " * 50), 5: ("B", "fine")}, 2: {2: ("C", "other"), 5: ("A", "so " * 50)}}
    asked = []

    def teacher(i):
        table = spark.createDataFrame([(k, a, r) for k, (a, r) in said[i].items()], "doc_id long, answer string, response string")
        return Provider("t", ("doc_id",), ("answer", "response"), lambda df: (asked.append(i), df.join(table, "doc_id"))[1])

    done = distill.distill_responses(rows, teacher, lambda df, p, tag: p(df))
    assert done.responded.count() == 5 and sorted(r.doc_id for r in done.kept.collect()) == [1, 2, 3, 5]
    assert sorted(values(done.verified, "doc_id", "answer", "retried", "correct")) == [(1, "A", False, True), (2, "C", True, False), (3, "C", False, None)]
    dropped = distill.distill_responses(rows, teacher, lambda df, p, tag: p(df), policy="drop_incorrect").verified
    assert sorted(r.doc_id for r in dropped.collect()) == [1, 3]
    path = f"{dedup.shared_folder(spark)}/once"
    asked.clear()
    assert materialized(rows, teacher(1), path).count() == materialized(rows, teacher(1), path).count() == 5 and asked == [1]


def test_only_the_scope_is_sampled(spark):
    df = spark.range(400).select(F.col("id").alias("doc_id"), (F.col("id") % 100).cast("int").alias("n_tokens"), F.when(F.col("id") < 200, "en").alias("lang"))
    got = sampling.stratified_by_length(df, scope=F.col("lang") == "en").collect()
    assert sum(r.lang is None for r in got) == 200 and {r.doc_id for r in got if r.lang and r.n_tokens > 75} == {i for i in range(200) if i % 100 > 75}
    assert all(r.n_tokens > 19 for r in got if r.lang)


def test_top_share_is_the_relative_rank(spark):
    for n in (0, 1, 2, 7, 101):
        df = spark.range(n)
        want = [i for i in range(n) if (i / (n - 1) if n > 1 else 0) < 0.2]
        assert sorted(r.id for r in sampling.top_share(df, 0.2, [F.col("id")]).collect()) == want


def test_exact_pairs_and_banding_recall(spark):
    rng = np.random.default_rng(2)
    rows = []
    for i in range(30):
        base = [f"w{k}" for k in rng.integers(0, 300, 60)]
        rows += [(2 * i, " ".join(base)), (2 * i + 1, " ".join(base[: 60 - i % 20]))]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    sets = {d: {tuple(t.split()[k : k + 3]) for k in range(len(t.split()) - 2)} for d, t in rows}
    want = {(a, b) for a in sets for b in sets if a < b and len(sets[a] & sets[b]) / len(sets[a] | sets[b]) >= 0.7}
    assert {(r.a, r.b) for r in dedup.exact_pairs(df, 0.7).collect()} == want and len(want) >= 20


def test_many_items_are_joined_instead_of_probed(spark):
    docs = spark.createDataFrame([(1, "a b c d e f"), (2, "x y z"), (3, None), (4, "c d e"), (5, "")], "doc_id long, text string")
    items = spark.createDataFrame([(7, "B c d"), (8, "d e f g"), (9, None), (10, "y z")], "item_id long, text string")
    for most in (1000, 0):
        assert sorted(values(decontam.ngram_hits(docs, items, n=3, most_broadcast=most), "doc_id", "item_id")) == [(1, 7), (1, 8)]
    assert decontam.ngram_hits(docs, items.where("false"), n=3).count() == 0


def test_published_record(spark):
    from cotengine.sources.published import published_scores

    got = {(r.record, r.measure, r.setting): [] for r in published_scores(spark).collect()}
    for r in published_scores(spark).collect():
        got[r.record, r.measure, r.setting].append(r.score)
    assert max(got["T1", "AIME25", "64K"]) == 87.08 and len(got["T3", "AIME25 best", "64K"]) == 6
