"""Exact top-k inner products by exhaustive term-at-a-time accumulation.

A vector's component is a term and its quantised value the posting's weight. Candidates and
queries are packed in blocks; where two blocks meet, postings per term (the rows with a non-zero
weight) are scattered, query weight × posting weight, into a dense score array, one term after
the other. Partition selection keeps k per query and task; a window merges them. The candidates
are read once, however many queries there are, and no vector comes to the driver.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cotengine.llm.store import materialize
from cotengine.operators.vector_blocks import ROWS, best_matches, packed


def quantise(vector: Column, scale: int = 1024) -> Column:
    """floor(scale · x) of each component as double; null where a component is null or not finite."""
    x = F.transform(vector, lambda v: v.cast("double"))
    fine = F.size(vector) == F.size(F.filter(x, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < F.lit(float("inf")))))
    return F.when(fine & (F.size(vector) > 0), F.transform(x, lambda v: F.floor(v * scale).cast("long")))


def accumulate(queries: np.ndarray, block: np.ndarray) -> np.ndarray:
    """Dense scores (query × candidate): postings of one term after the other are scattered in."""
    scores = np.zeros((len(queries), len(block)), np.int64)
    for term in range(queries.shape[1]):
        weights = block[:, term]
        postings, asking = np.flatnonzero(weights), np.flatnonzero(queries[:, term])
        if not len(postings) or not len(asking):
            continue
        add = np.multiply.outer(queries[asking, term], weights[postings])
        if len(postings) == len(block) and len(asking) == len(queries):
            scores += add
        elif len(postings) == len(block):
            scores[asking] += add
        else:
            scores[np.ix_(asking, postings)] += add
    return scores


def top_k(vectors: DataFrame, queries: DataFrame, *, k: int = 10, vec_id: str = "vec_id", vector: str = "embedding", scale: int = 1024, query_block: int = 512) -> DataFrame:
    """Each query's k best of all other vectors: query_id, rank (from 1), vec_id, score.

    ``queries`` has the columns of ``vectors``; a candidate with the query's own id is left
    out. Vectors or ids that are null, or vectors holding null or non-finite components, take
    no part, on either side. Vectors of another length than a query's are no candidates of
    it. Rows repeated under one id compete as one (the best score counts). Fewer than k
    candidates give fewer rows; empty tables give none.
    """

    def ready(df: DataFrame) -> DataFrame:
        return df.select(F.col(vec_id).cast("long").alias("vec_id"), quantise(F.col(vector), scale).alias("w")).where("vec_id IS NOT NULL AND w IS NOT NULL")

    asked = materialize(ready(queries), "queries")
    n_blocks = max(1, -(-asked.count() // query_block))
    # Dealt out by number of blocks, so that a block is full: its rows meet a candidate block in one product.
    asked = materialize(packed(asked.repartition(n_blocks), "vec_id", "w", query_block, "<i8"), "query-blocks")
    found = best_matches(asked, packed(ready(vectors), "vec_id", "w", ROWS, "<i8"), lambda q, c: (accumulate(q, c), None), k=k, kind="<i8", ddl="long", apart=True)
    return found.select(F.col("x").alias("query_id"), F.col("rank").cast("int").alias("rank"), F.col("d").alias("vec_id"), "score")
