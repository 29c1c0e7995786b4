"""A proxy learner (softmax regression) for the two-stage fit and the gradient-alignment report.

Gradients are sums over Arrow batches: each task returns one row of fixed size (classes ×
dimensions), so a step costs one scan and moves nothing but those rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def proxy_rows(embeddings: DataFrame) -> DataFrame:
    """(id, x, y, w): the target is the place of the greatest of the first ten coordinates."""
    ten = F.slice("embedding", 1, 10)
    return embeddings.select(F.col("vec_id").alias("id"), F.transform("embedding", lambda v: v.cast("double")).alias("x"), (F.array_position(ten, F.array_max(ten)) - 1).cast("int").alias("y"), F.lit(1.0).alias("w"))


class ProxyLearner:
    def __init__(self, dim: int, classes: int):
        self.theta = np.zeros((classes, dim))

    def loss_and_gradient(self, rows: DataFrame, theta: np.ndarray | None = None) -> tuple[float, np.ndarray]:
        theta = self.theta if theta is None else theta

        def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            grad, loss, weight = np.zeros_like(theta), 0.0, 0.0
            for b in batches:
                if not b.num_rows:
                    continue
                x = b.column("x").flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1)
                y, w = b.column("y").to_numpy(), b.column("w").to_numpy()
                z = x @ theta.T
                z -= z.max(1, keepdims=True)
                p = np.exp(z)
                p /= p.sum(1, keepdims=True)
                loss -= float((w * np.log(p[np.arange(len(y)), y])).sum())
                p[np.arange(len(y)), y] -= 1
                grad += (p * w[:, None]).T @ x
                weight += float(w.sum())
            yield pa.RecordBatch.from_arrays([pa.array([loss]), pa.array([weight]), pa.array([grad.reshape(-1).tolist()])], names=["loss", "weight", "grad"])

        got = rows.select("x", "y", "w").mapInArrow(sums, "loss double, weight double, grad array<double>").collect()  # one row a task
        weight = sum(r.weight for r in got)
        grad = np.sum([np.array(r.grad) for r in got], axis=0).reshape(theta.shape)
        return sum(r.loss for r in got) / weight, grad / weight

    def fit(self, rows: DataFrame, *, steps: int, rate: float) -> list[float]:
        losses = []
        for _ in range(steps):
            loss, grad = self.loss_and_gradient(rows)
            self.theta -= rate * grad
            losses.append(loss)
        return losses


    def predictions(self, rows: DataFrame) -> DataFrame:
        """(id, right): whether the greatest score is the target's; a map."""
        theta = self.theta.copy()

        def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                if b.num_rows:
                    x = b.column("x").flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1)
                    yield pa.RecordBatch.from_arrays([b.column("id"), pa.array((x @ theta.T).argmax(1) == b.column("y").to_numpy())], names=["id", "right"])

        return rows.select(F.col("id").cast("long"), "x", "y").mapInArrow(judge, "id long, right boolean")


def alignment_report(learner: ProxyLearner, target: DataFrame, p0: DataFrame, p1: DataFrame, etas=(0.1, 0.5)) -> list[tuple]:
    """(eta, align0, align1, risk0, risk1, better_aligned, lower_risk) of one step under P0 and under P1, gradients at equal norm."""
    _, g = learner.loss_and_gradient(target)
    (_, g0), (_, g1) = (learner.loss_and_gradient(p) for p in (p0, p1))
    g1 = g1 * np.linalg.norm(g0) / max(np.linalg.norm(g1), 1e-12)
    a0, a1 = float((g * g0).sum()), float((g * g1).sum())
    out = []
    for eta in etas:
        r0, r1 = (learner.loss_and_gradient(target, learner.theta - eta * x)[0] for x in (g0, g1))
        out.append((float(eta), a0, a1, r0, r1, a1 >= a0, r1 <= r0))
    return out
