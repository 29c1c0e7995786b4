"""Quality classifier by positive-unlabelled learning with the non-negative risk estimator.

Trusted positives (texts marked as good) and unlabelled web text give an unbiased estimate of
the classification risk once the class prior is known:
prior·E_P[l(g)] + (E_U[l(-g)] - prior·E_P[l(-g)]). Its second part estimates a risk of
negatives and cannot be below zero; where it is, the step climbs that part alone, so a
flexible model cannot drive it negative by overfitting.

The prior is estimated first: a positive-against-unlabelled model is fitted on one half of
the sample; on the other half the share of unlabelled texts above a score, over the share of
positives above it, bounds the prior from above, and the least bound (with its sampling
error) is taken.

Features are cheap sums over the whole text: hashed character-shape trigrams, shares of
character kinds, and repetition of words, word pairs and lines.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cotengine.llm.blocks import blocks, rows, schema_of, utf8
from cotengine.llm.words import Words, mixed

#: Bound of the fitting sample: positives, and as many unlabelled texts.
SAMPLE = 6000
SHAPES, KINDS = 256, 8


def _shape_table() -> np.ndarray:
    """Shape of each byte: 0 blank, 1 small letter (or part of a letter beyond ASCII), 2 capital, 3 digit, 4 line end, others their own."""
    out = np.ones(256, np.uint8)
    out[:128] = [5 + i % 27 for i in range(128)]
    out[[9, 32]], out[[10, 13]] = 0, 4
    out[48:58], out[65:91], out[97:123] = 3, 2, 1
    return out


_SHAPE = _shape_table()


def features(texts: list[str]) -> np.ndarray:
    """One row of SHAPES + KINDS + 5 numbers for each text; zeros for an empty one."""
    data, starts = utf8(pa.array(texts, pa.large_string()))
    n, size = len(texts), np.diff(starts)
    own = np.repeat(np.arange(n), size)
    shape = _SHAPE[data]
    out = np.zeros((n, SHAPES + KINDS + 5), np.float32)
    many = np.maximum(size, 1)[:, None]
    if len(data) > 2:
        code = shape.astype(np.uint32)
        tri = (code[:-2] * np.uint32(1024) + code[1:-1] * np.uint32(32) + code[2:]) * np.uint32(0x9E3779B1) >> np.uint32(24)
        inside = own[:-2] == own[2:]
        out[:, :SHAPES] = np.sqrt(np.bincount((own[:-2] * SHAPES + tri)[inside], minlength=n * SHAPES).reshape(n, SHAPES) / many)
    kind = np.minimum(shape, 5) if len(data) else shape
    out[:, SHAPES : SHAPES + 6] = np.bincount(own * 6 + kind, minlength=6 * n).reshape(n, 6) / many
    words = Words(texts)
    first, h = words.first, words.hashes
    counts = np.diff(first)
    text = np.repeat(np.arange(n), counts)
    total = np.maximum(counts, 1)
    if len(h):
        same = np.zeros(len(h), bool)
        same[1:] = (h[1:] == h[:-1]) & (text[1:] == text[:-1])
        pair = mixed(h * np.uint64(3) + np.append(h[1:], h[:1])) + text.astype(np.uint64)
        seen = np.unique(mixed(pair), return_index=True)[1]
        out[:, SHAPES + KINDS] = np.bincount(text, same, n) / total
        out[:, SHAPES + KINDS + 1] = np.bincount(text[seen], minlength=n) / total
        out[:, SHAPES + KINDS + 2] = np.log1p(np.bincount(text, words.ends - words.opens, n) / total)
    out[:, SHAPES + KINDS + 3] = np.log1p(counts)
    out[:, SHAPES + KINDS + 4] = counts / np.maximum(1, size)
    return out


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * (1 + np.tanh(0.5 * x))


class QualityModel:
    """A linear score of standardised features: mean, spread, weights, bias."""

    def __init__(self, mean, spread, weights, bias, prior: float):
        self.mean, self.spread, self.weights, self.bias, self.prior = mean, spread, weights, bias, prior

    def score(self, x: np.ndarray) -> np.ndarray:
        return _sigmoid(np.clip(((x - self.mean) / self.spread).clip(-8, 8) @ self.weights + self.bias, -30, 30))


class _Adam:
    def __init__(self, n: int, rate: float):
        self.m, self.v, self.t, self.rate = np.zeros(n), np.zeros(n), 0, rate

    def step(self, g: np.ndarray) -> np.ndarray:
        self.t += 1
        self.m, self.v = 0.9 * self.m + 0.1 * g, 0.999 * self.v + 0.001 * g * g
        return self.rate * (self.m / (1 - 0.9**self.t)) / (np.sqrt(self.v / (1 - 0.999**self.t)) + 1e-8)


def minimise(positive: np.ndarray, unlabelled: np.ndarray, prior: float, *, steps: int = 400, rate: float = 0.02, decay: float = 1e-4) -> np.ndarray:
    """Weights (bias last) of least non-negative risk with the logistic loss, by full-batch steps."""
    p, u = (np.hstack([x, np.ones((len(x), 1))]) for x in (positive, unlabelled))
    w, adam = np.zeros(p.shape[1]), _Adam(p.shape[1], rate)
    for _ in range(steps):
        gp, gu = p @ w, u @ w
        negative = np.logaddexp(0, gu).mean() - prior * np.logaddexp(0, gp).mean()
        part = u.T @ _sigmoid(gu) / len(u) - prior * (p.T @ _sigmoid(gp)) / len(p)
        grad = -part if negative < 0 else part - prior * (p.T @ _sigmoid(-gp)) / len(p)
        w -= adam.step(grad + decay * np.append(w[:-1], 0))
    return w


def class_prior(positive: np.ndarray, unlabelled: np.ndarray) -> float:
    """Prior from features, by the least ratio of tail shares on held-back halves."""
    w = minimise(positive[::2], unlabelled[::2], 0.5, steps=200)
    p, u = (np.sort(x[1::2] @ w[:-1] + w[-1]) for x in (positive, unlabelled))
    at = np.unique(p)
    share_p = 1 - np.searchsorted(p, at, "left") / len(p)
    share_u = 1 - np.searchsorted(u, at, "left") / len(u)
    error = np.sqrt(np.log(20) / 2) * (len(p) ** -0.5 + len(u) ** -0.5)
    bound = (share_u + error) / np.maximum(share_p, 1e-9)
    best = int(bound.argmin())
    return float(np.clip(share_u[best] / share_p[best], 0.02, 0.98))


def learning_rows(doc_id: Column) -> Column:
    """Rows that may be learned from: crc32(id as text) mod 5 is not 0 (null ids may not)."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 != 0, F.lit(False))


def _numbers(df: DataFrame) -> np.ndarray:
    ddl = "x array<float>"
    schema = schema_of(ddl)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, "text"):
            x = features([t or "" for t in batch.column("text").to_pylist()])
            yield rows(schema, pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1]), pa.array(x.reshape(-1))))

    got = df.select("text").mapInArrow(work, ddl).toArrow().column("x").combine_chunks()
    return got.flatten().to_numpy().reshape(len(got), -1) if len(got) else np.zeros((0, SHAPES + KINDS + 5), np.float32)


def fit(docs: DataFrame, labels: DataFrame, *, sample: int = SAMPLE, doc_id: str = "doc_id", text: str = "text") -> QualityModel | None:
    """A model from up to ``sample`` positives and as many unlabelled texts, chosen by hash of their ids.

    labels: (doc_id, quality). Positives are texts marked 1; the unlabelled sample is drawn
    from all texts that may be learned from, whatever their mark. An id marked both ways is no
    positive. Of rows that share an id one text is taken. None where there are no positives or no texts.
    """
    ids = docs.select(F.col(doc_id).cast("long").alias("id")).where(learning_rows(F.col("id")))
    good = labels.where("doc_id IS NOT NULL AND quality IS NOT NULL").groupBy(F.col("doc_id").cast("long").alias("id")).agg(F.min("quality").alias("quality")).where("quality = 1").select("id")
    taken = {}
    for name, rows_ in (("positive", ids.join(good, "id", "left_semi")), ("unlabelled", ids)):
        chosen = [r.id for r in rows_.select("id", F.xxhash64("id", F.lit(name)).alias("h")).distinct().orderBy("h", "id").limit(sample).collect()]
        held = docs.sparkSession.createDataFrame([(i,) for i in chosen], "id long")
        picked = docs.select(F.col(doc_id).cast("long").alias("id"), F.col(text).cast("string").alias("text")).join(F.broadcast(held), "id", "left_semi")
        one = picked.groupBy("id").agg(F.min_by("text", F.xxhash64("text")).alias("text"))  # so that rows, too, are at most ``sample``
        taken[name] = _numbers(one.orderBy("id")).astype(np.float64)
    p, u = taken["positive"], taken["unlabelled"]
    if len(p) < 2 or len(u) < 2:
        return None
    mean, spread = u.mean(0), u.std(0)
    spread = np.where(spread > 1e-6, spread, 1.0)
    p, u = ((x - mean) / spread for x in (p, u))
    p, u = p.clip(-8, 8), u.clip(-8, 8)
    order = np.random.default_rng(7)
    p, u = p[order.permutation(len(p))], u[order.permutation(len(u))]
    prior = class_prior(p, u)
    w = minimise(p, u, prior)
    return QualityModel(mean, spread, w[:-1], float(w[-1]), prior)


def score(docs: DataFrame, model: QualityModel | None, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, rid, score (0 to 1, higher: good likelier) of every row.

    Null and empty texts are scored as texts without features. Without a model (no positives
    to learn from) all score 0.5. Repeated rows are scored alike. ``rid`` is a key of (id,
    text). Other columns are ignored. A map over rows: no shuffle.
    """
    ddl = "doc_id long, rid long, score double"
    schema = schema_of(ddl)

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, "text"):
            x = features([t or "" for t in batch.column("text").to_pylist()])
            s = model.score(x) if model else np.full(len(x), 0.5)
            yield rows(schema, batch.column("doc_id"), batch.column("rid"), s.astype(np.float64))

    keyed = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text")).withColumn("rid", F.xxhash64("doc_id", "text"))
    return keyed.mapInArrow(judge, ddl)


def accepted(docs: DataFrame, model: QualityModel | None, least: float, *, text: str = "text") -> DataFrame:
    """The rows of ``docs``, with all their columns, that score ``least`` at least: a map over rows, without shuffle."""

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, text):
            x = features([t or "" for t in batch.column(text).to_pylist()])
            yield batch.filter(pa.array((model.score(x) if model else np.full(len(x), 0.5)) >= least))

    return docs.mapInArrow(keep, docs.schema)
