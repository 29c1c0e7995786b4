"""Failure-driven data: weights, query distribution, retrieval kernel, acceptance, synthetic distribution."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cotengine.operators import vector_blocks
from cotengine.operators.dedup import cut_lineage

def failure_weights(answers: DataFrame, item: str = "prompt", *, kind: str = "binary") -> DataFrame:
    """(item, w): 1 if the item's first answer is wrong, or for ``soft`` 1 minus its pass rate."""
    if kind == "binary":
        return answers.where("i = 1").select(item, (~F.col("correct")).cast("int").alias("w"))
    if kind != "soft":
        raise ValueError("kind is 'binary' or 'soft'")
    return answers.groupBy(item).agg((1 - F.avg(F.col("correct").cast("double"))).alias("w"))


def failure_distribution(weights: DataFrame, item: str = "prompt", q: str | None = None) -> DataFrame:
    """q·w / E[w] over failures only; an error if nothing failed."""
    mass = (F.col(q) if q else F.lit(1.0)) * F.col("w")
    total = weights.agg(F.sum(mass).alias("_t")).select(F.when(F.col("_t") > 0, F.col("_t")).otherwise(F.raise_error(F.lit("no failure has mass")).cast("double")).alias("_t"))
    return weights.where("w > 0").crossJoin(F.broadcast(total)).select(item, (mass / F.col("_t")).alias("q"))


def _doubles(df: DataFrame, key: str) -> DataFrame:
    return df.select(F.col(key).cast("long").alias(key), F.transform("vec", lambda v: v.cast("double")).alias("vec"))


def _unit_rows(m: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rows at length one, and which rows have a length at all."""
    norm = np.linalg.norm(m, axis=1)
    return m / np.where(norm > 0, norm, 1)[:, None], norm > 0


def retrieve(queries: DataFrame, corpus: DataFrame, *, k: int = 30, min_sim: float | None = None, screen: Callable[[np.ndarray, np.ndarray], np.ndarray] | None = None) -> DataFrame:
    """(x_id, d_id, sim, rank): cosine top-k of each query over the whole corpus.

    Zero vectors and other lengths have no similarity. With ``min_sim`` all pairs at or above
    it are returned instead, without rank. ``screen(q, c)`` marks the pairs of two blocks that
    are compared at all (unit rows): with one, the search is approximate.
    """

    def score(q: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        (q, some), (c, any_) = _unit_rows(q), _unit_rows(c)
        counts = some[:, None] & any_[None, :]
        return np.round(q @ c.T, 9), counts if screen is None else counts & screen(q, c)

    asked = cut_lineage(vector_blocks.packed(_doubles(queries, "x_id"), "x_id", "vec", vector_blocks.QUERY_ROWS, "<f8"), "query-blocks")
    blocks = vector_blocks.packed(_doubles(corpus, "d_id"), "d_id", "vec", vector_blocks.ROWS, "<f8")
    if min_sim is None:
        found = vector_blocks.best_matches(asked, blocks, score, k=k, kind="<f8", ddl="double", apart=False)
        return found.select(F.col("x").alias("x_id"), F.col("d").alias("d_id"), F.col("score").alias("sim"), "rank")

    def above(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                x, d = np.frombuffer(r["q_ids"], np.int64), np.frombuffer(r["ids"], np.int64)
                sim, counts = score(np.frombuffer(r["q_data"], "<f8").reshape(len(x), -1), np.frombuffer(r["data"], "<f8").reshape(len(d), -1))
                i, j = np.nonzero(counts & (sim >= min_sim))
                yield pa.RecordBatch.from_arrays([pa.array(x[i]), pa.array(d[j]), pa.array(sim[i, j])], names=["x_id", "d_id", "sim"])

    pairs = blocks.crossJoin(asked.select(F.col("dim").alias("q_dim"), F.col("ids").alias("q_ids"), F.col("data").alias("q_data"))).where("dim = q_dim")  # blocks, bounded in size
    return pairs.select("q_ids", "q_data", "ids", "data").mapInArrow(above, "x_id long, d_id long, sim double")


def truncation_gap(queries: DataFrame, corpus: DataFrame, *, k: int, tau: float) -> DataFrame:
    """(x_id, tv): kernel mass outside the top k. One sum a query over all pairs (shifted by 1, the greatest cosine), one over the top k."""
    e = F.exp((F.col("sim") - 1) / tau)
    whole = retrieve(queries, corpus, min_sim=-2.0).groupBy("x_id").agg(F.sum(e).alias("whole"))
    top = retrieve(queries, corpus, k=k).groupBy("x_id").agg(F.sum(e).alias("top"))
    return whole.join(top, "x_id").select("x_id", (1 - F.col("top") / F.col("whole")).alias("tv"))


#: Pairs that a task hands over at once.
_PAIRS = 1 << 16


def full_kernel(queries: DataFrame, corpus: DataFrame, tau: float, *, apart: bool = False, digits: int | None = None) -> DataFrame:
    """(x_id, d_id, prob): ``retrieval_kernel`` of each query over the whole corpus, as two scans of blocks.

    With ``apart`` a query is no candidate of its own id; ``digits`` rounds the shares.

    The first gives each query's greatest similarity and its sum, which go with the query into the
    second. Pairs are only put out: none is shuffled, sorted or written on the way.
    """
    asked, blocks = _doubles(queries, "x_id"), vector_blocks.packed(_doubles(corpus, "d_id"), "d_id", "vec", vector_blocks.ROWS, "<f8")

    def met(blocks_of_queries: DataFrame, more: int) -> DataFrame:
        """Pairs of blocks; no equality is left to hash by, as all blocks of one length would be one task's."""
        other = blocks_of_queries.select(F.col("dim").alias("q_dim"), F.col("ids").alias("q_ids"), F.col("data").alias("q_data"))
        return blocks.crossJoin(other).where(F.col("q_dim") - F.col("dim") == more).select("q_ids", "q_data", "ids", "data")

    def cosines(r: dict, more: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        x, d = np.frombuffer(r["q_ids"], np.int64), np.frombuffer(r["ids"], np.int64)
        q = np.frombuffer(r["q_data"], "<f8").reshape(len(x), -1)
        (a, some), (b, any_) = _unit_rows(q[:, : q.shape[1] - more]), _unit_rows(np.frombuffer(r["data"], "<f8").reshape(len(d), -1))
        x, d, sim = x[some], d[any_], np.round(a[some] @ b[any_].T, 9)
        if apart:
            sim[x[:, None] == d[None, :]] = -np.inf
        return x, d, sim, q[some, q.shape[1] - more :]

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["x_id", "top", "mass"]
        for batch in batches:
            for r in batch.to_pylist():
                x, d, sim, _ = cosines(r, 0)
                if len(x) and len(d):
                    top = sim.max(1)
                    any_ = np.isfinite(top)
                    x, top, sim = x[any_], top[any_], sim[any_]
                    yield pa.RecordBatch.from_arrays([pa.array(x), pa.array(top), pa.array(np.exp((sim - top[:, None]) / tau).sum(1))], names=names)

    def shares(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                x, d, sim, own = cosines(r, 2)
                step = max(1, _PAIRS // max(1, len(d)))
                for low in range(0, len(x) if len(d) else 0, step):
                    part, near = own[low : low + step], sim[low : low + step]
                    i, j = np.nonzero(np.isfinite(near))
                    prob = (np.exp((near - part[:, :1]) / tau) / part[:, 1:])[i, j]
                    yield pa.RecordBatch.from_arrays([pa.array(x[low + i]), pa.array(d[j]), pa.array(prob if digits is None else np.round(prob, digits))], names=["x_id", "d_id", "prob"])

    first = cut_lineage(vector_blocks.packed(asked, "x_id", "vec", vector_blocks.QUERY_ROWS, "<f8"), "query-blocks")
    parts = met(first, 0).mapInArrow(sums, "x_id long, top double, mass double").groupBy("x_id").agg(F.max("top").alias("top"), F.collect_list(F.struct("top", "mass")).alias("parts"))
    mass = F.aggregate("parts", F.lit(0.0), lambda s, p: s + p["mass"] * F.exp((p["top"] - F.col("top")) / tau))
    weighed = asked.join(parts.select("x_id", F.array("top", mass).alias("own")), "x_id").select("x_id", F.concat("vec", "own").alias("vec"))
    second = cut_lineage(vector_blocks.packed(weighed, "x_id", "vec", vector_blocks.QUERY_ROWS, "<f8"), "weighed-query-blocks")
    return met(second, 2).mapInArrow(shares, "x_id long, d_id long, prob double")


def retrieval_kernel(sims: DataFrame, tau: float) -> DataFrame:
    """Softmax of similarities at temperature tau within each query, shifted by the greatest."""
    own = Window.partitionBy("x_id")
    return sims.withColumn("_e", F.exp((F.col("sim") - F.max("sim").over(own)) / tau)).withColumn("prob", F.col("_e") / F.sum("_e").over(own)).drop("_e")


def planes(dim: int, bits: int, seed: int) -> np.ndarray:
    return np.random.default_rng(seed).standard_normal((bits, dim))


def _nearest_share(rough: np.ndarray, share: float) -> np.ndarray:
    """The ``share`` of a block's candidates with the greatest rough score for each query."""
    keep = max(1, int(np.ceil(share * rough.shape[1])))
    out = np.zeros(rough.shape, bool)
    np.put_along_axis(out, np.argpartition(-rough, keep - 1, axis=1)[:, :keep] if keep < rough.shape[1] else np.broadcast_to(np.arange(rough.shape[1]), rough.shape), True, 1)
    return out


def sign_sketch(dim: int, bits: int = 384, share: float = 0.3, seed: int = 42):
    """Screen by sign sketches of random projections: the pairs of least Hamming distance go on to exact cosine."""
    p = planes(dim, bits, seed)
    words = lambda m: np.packbits((m @ p.T) > 0, axis=1).view(np.uint64)

    def screen(q: np.ndarray, c: np.ndarray) -> np.ndarray:
        a, b = words(q), words(c)
        apart = np.zeros((len(q), len(c)), np.int32)
        for i in range(a.shape[1]):
            apart += np.bitwise_count(a[:, i][:, None] ^ b[:, i][None, :])
        return _nearest_share(-apart, share)

    return screen


def cell_residuals(centres: np.ndarray, share: float = 0.2, levels: int = 7):
    """Screen by inverted-file codes: a candidate is its nearest centre plus a residual of 4-bit steps, scored without its exact vector."""

    def screen(q: np.ndarray, c: np.ndarray) -> np.ndarray:
        own = (c @ centres.T).argmax(1)
        rest = c - centres[own]
        step = np.maximum(np.abs(rest).max(1, keepdims=True), 1e-12) / levels
        return _nearest_share((q @ centres.T)[:, own] + (q @ np.rint(rest / step).T) * step.T, share)

    return screen


def sphere_centres(sample: np.ndarray, cells: int = 16, rounds: int = 10, seed: int = 42) -> np.ndarray:
    """k-means centres of unit length of a bounded sample."""
    rng = np.random.default_rng(seed)
    centres = sample[rng.choice(len(sample), min(cells, len(sample)), replace=False)]
    for _ in range(rounds):
        own = (sample @ centres.T).argmax(1)
        centres = np.stack([sample[own == c].mean(0) if (own == c).any() else centres[c] for c in range(len(centres))])
        centres /= np.maximum(np.linalg.norm(centres, axis=1, keepdims=True), 1e-12)
    return centres


def activation_mass(qdist: DataFrame, kernel: DataFrame) -> DataFrame:
    """Σ_x q(x)·K(d|x) of each document."""
    return kernel.join(qdist, "x_id").groupBy("d_id").agg(F.sum(F.col("q") * F.col("prob")).alias("mass"))


def accept_consistent(candidates: DataFrame) -> DataFrame:
    """Candidates whose two passes agree once normalised; a missing answer never agrees."""
    from cotengine.functions.text import canonical_answer

    same = canonical_answer(F.col("ans1")) == canonical_answer(F.col("ans2"))
    return candidates.withColumn("accepted", F.coalesce(same, F.lit(False)))


def majority(answers: DataFrame, keys: list[str], answer: str = "answer") -> DataFrame:
    """(keys, consensus, votes, n): most votes, then the smallest string; nulls do not vote. Pre-aggregated by answer."""
    votes = answers.where(F.col(answer).isNotNull()).groupBy(*keys, answer).agg(F.count("*").alias("v"))
    best = F.min(F.struct((-F.col("v")).alias("v"), F.col(answer).alias("a")))
    return votes.groupBy(*keys).agg(best.alias("b"), F.sum("v").alias("n")).select(*keys, F.col("b.a").alias("consensus"), (-F.col("b.v")).alias("votes"), "n")


def resolve_by_vote(candidates: DataFrame, *, strict: bool = False) -> DataFrame:
    """Hard candidates: where the passes disagree, the consensus of all answers (``strict``: over half of them)."""
    split = candidates.where(~F.col("accepted")).select("d_id", "slot", F.explode(F.concat(F.array("ans1", "ans2"), "extra")).alias("answer"))
    out = majority(split, ["d_id", "slot"])
    return out.where(F.col("votes") * 2 > F.col("n")) if strict else out


def synthetic_distribution(mass: DataFrame, accepted: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(p over candidates, lost mass): a document's mass is split among its accepted candidates,
    documents without one are reported as lost and the rest renormalised."""
    count = accepted.groupBy("d_id").agg(F.count("*").alias("k"))
    joined = mass.join(count, "d_id", "left")
    totals = joined.agg(F.sum(F.when(F.col("k").isNotNull(), F.col("mass")).otherwise(0.0)).alias("kept"), F.sum(F.when(F.col("k").isNull(), F.col("mass")).otherwise(0.0)).alias("lost"))
    p = accepted.select("d_id", "slot").join(joined.where("k IS NOT NULL"), "d_id").crossJoin(F.broadcast(totals.select("kept"))).select("d_id", "slot", (F.col("mass") / F.col("k") / F.col("kept")).alias("p"))
    return p, totals.select("lost")


def sample_mixture(original: DataFrame, synthetic: DataFrame, n_original: int, *, key: str = "key", seed: int = 42) -> DataFrame:
    """All synthetic rows and exactly ``n_original`` originals (all, if fewer), with their origin."""
    from cotengine.operators.sampling import uniform_n

    return synthetic.withColumn("origin", F.lit("synthetic")).unionByName(uniform_n(original, n_original, seed=seed, key=key).withColumn("origin", F.lit("original")))
