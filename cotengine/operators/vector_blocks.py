"""Every query vector against every candidate vector, block by block, with the best kept as they are found.

Both sides are packed into rows of a bounded number of vectors. Pairs of blocks, not of
vectors, meet in the join: the engine broadcasts the query blocks while they are small and
deals out pairs of partitions when they are not. A task keeps each query's k best so far, so
the candidates are read once and what is shuffled are k rows a query and task.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Vectors of a query block and of a candidate block; queries whose best a task holds before it writes them out.
QUERY_ROWS, ROWS, HELD = 512, 4096, 100_000
_PACKED = "dim int, ids binary, data binary"
Score = Callable[[np.ndarray, np.ndarray], tuple[np.ndarray, np.ndarray | None]]


def packed(df: DataFrame, key: str, vector: str, size: int, kind: str) -> DataFrame:
    """Blocks of up to ``size`` vectors of one length: their ids (64-bit) and numbers (``kind``) as bytes."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[tuple[np.ndarray, np.ndarray]]] = {}

        def block(dim: int) -> pa.RecordBatch:
            ids, flat = (np.concatenate(x) for x in zip(*held.pop(dim)))
            return pa.RecordBatch.from_arrays([pa.array([dim], pa.int32()), pa.array([ids.tobytes()], pa.binary()), pa.array([flat.tobytes()], pa.binary())], names=["dim", "ids", "data"])

        for batch in batches:
            ids, vectors = batch.column(0).to_numpy(), batch.column(1)
            dims = pa.compute.list_value_length(vectors).to_numpy(zero_copy_only=False)
            for dim in np.unique(dims).tolist():
                own = np.flatnonzero(dims == dim)
                flat = vectors.take(pa.array(own)).flatten().to_numpy(zero_copy_only=False).astype(kind)
                for at in range(0, len(own), size):
                    held.setdefault(dim, []).append((ids[own[at : at + size]], flat[at * dim : (at + size) * dim]))
                    if sum(len(i) for i, _ in held[dim]) >= size:
                        yield block(dim)
        for dim in list(held):
            yield block(dim)

    return df.select(F.col(key).cast("long"), F.col(vector)).mapInArrow(pack, _PACKED)


def _kept(ids: np.ndarray, scores: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """The k best, ties to the smaller id; an id counts once, with its best score. Partition first, then sort what is left."""
    if len(scores) > 4 * k:
        near = scores >= np.partition(scores, len(scores) - 2 * k)[len(scores) - 2 * k]
        if len(np.unique(ids[near])) >= k:
            ids, scores = ids[near], scores[near]
    order = np.lexsort((ids, -scores))
    ids, scores = ids[order], scores[order]
    _, first = np.unique(ids, return_index=True)
    first = np.sort(first)[:k]
    return ids[first], scores[first]


def best_matches(queries: DataFrame, candidates: DataFrame, score: Score, *, k: int, kind: str, ddl: str, apart: bool) -> DataFrame:
    """(x, d, score, rank) of each query's k best candidates.

    ``queries``: blocks from ``packed`` as a written table, as they are read for every
    candidate partition; ``candidates``: blocks. ``score(q, c)`` gives a matrix of scores and
    a mask of the pairs that count (None: all). ``ddl`` is the type of a score, ``kind`` that
    of the vectors. With ``apart`` a query is no candidate of its own id.
    """
    out = pa.schema([("x", pa.int64()), ("d", pa.int64()), ("score", pa.int64() if ddl == "long" else pa.float64())])

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best: dict[int, tuple[np.ndarray, np.ndarray]] = {}

        def written() -> Iterator[pa.RecordBatch]:
            if best:
                x = np.repeat(np.fromiter(best, np.int64, len(best)), [len(i) for i, _ in best.values()])
                yield pa.RecordBatch.from_arrays([pa.array(x), pa.array(np.concatenate([i for i, _ in best.values()])), pa.array(np.concatenate([s for _, s in best.values()]), out.field(2).type)], schema=out)
                best.clear()

        for batch in batches:
            for r in batch.to_pylist():
                x, d = np.frombuffer(r["q_ids"], np.int64), np.frombuffer(r["ids"], np.int64)
                s, counts = score(np.frombuffer(r["q_data"], kind).reshape(len(x), -1), np.frombuffer(r["data"], kind).reshape(len(d), -1))
                for i, x_id in enumerate(x.tolist()):
                    ids, own = d, s[i]
                    if counts is not None:
                        ids, own = ids[counts[i]], own[counts[i]]
                    held = best.get(x_id)
                    if held is not None and len(held[0]) >= k:
                        near = own >= held[1][-1]
                        ids, own = ids[near], own[near]
                    if apart:
                        other = ids != x_id
                        ids, own = ids[other], own[other]
                    if len(ids):
                        if held is not None:
                            ids, own = np.concatenate([held[0], ids]), np.concatenate([held[1], own])
                        best[x_id] = _kept(ids, own, k)
                if len(best) > HELD:
                    yield from written()
        yield from written()

    pairs = candidates.crossJoin(queries.select(F.col("dim").alias("q_dim"), F.col("ids").alias("q_ids"), F.col("data").alias("q_data"))).where("dim = q_dim")  # blocks, bounded in size
    found = pairs.select("q_ids", "q_data", "ids", "data").mapInArrow(meet, f"x long, d long, score {ddl}")
    found = found.groupBy("x", "d").agg(F.max("score").alias("score"))
    order = Window.partitionBy("x").orderBy(F.col("score").desc(), "d")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
