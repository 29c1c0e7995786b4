"""Near-duplicate join on word n-grams with Bayesian candidate pruning.

Texts with equal words are collapsed to one node. MinHash bands propose candidates; the
candidate groups are the connected parts of the bucket stars, so each node's shingles move
once. Within a group, a pair that shares a band is compared on MinHash values kept apart
from the bands, some at a time; it is dropped as soon as the posterior probability (flat
prior) that its similarity reaches the threshold falls below ``tolerance``. What is left is
verified on the exact shingle sets, by sparse counts for few pairs and block products for many.

A pair at the threshold 0.8 misses all 20 bands of 4 with probability 3·10⁻⁵, one at 0.9 with
10⁻⁹; pruning adds less than ``tolerance`` a step.
"""

from __future__ import annotations

from collections.abc import Iterator
from math import comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cotengine.llm.blocks import blocks, rows, schema_of
from cotengine.llm.components import components, least_connected, verified
from cotengine.llm.store import materialize
from cotengine.llm.words import Words, mixed, shingles

SHINGLE, THRESHOLD, TOLERANCE = 5, 0.8, 1e-6
BANDS, ROWS, EXTRA, STEP = 20, 4, 64, 16


def _parameters(n: int, seed: int = 1) -> tuple[np.ndarray, np.ndarray]:
    h = mixed(np.arange(1, 2 * n + 1, dtype=np.uint64) * np.uint64(seed * 2 + 1) + np.uint64(seed))
    return (h[:n] >> np.uint64(32)).astype(np.uint32) | np.uint32(1), (h[n:] >> np.uint64(32)).astype(np.uint32)


def minhash(hashes: np.ndarray, starts: np.ndarray, n: int, skip: int = 0) -> np.ndarray:
    """``n`` MinHash values (from the ``skip``-th on) of each set; every set has a member."""
    x = (hashes >> np.uint64(32)).astype(np.uint32)
    a, b = _parameters(BANDS * ROWS + EXTRA)
    out = np.empty((len(starts) - 1, n), np.uint32)
    for i in range(n):
        v = x * a[skip + i] + b[skip + i]
        v ^= v >> np.uint32(15)
        v *= np.uint32(0x2C1B3C6D)
        out[:, i] = np.minimum.reduceat(v, starts[:-1])
    return out


def band_keys(signature: np.ndarray) -> np.ndarray:
    """One 64-bit key of each band; the band's number is part of it."""
    s = signature[:, : BANDS * ROWS].reshape(-1, BANDS, ROWS).astype(np.uint64)
    key = np.broadcast_to(np.arange(1, BANDS + 1, dtype=np.uint64), s.shape[:2]).copy()
    for i in range(ROWS):
        key = mixed(key * np.uint64(0x9E3779B97F4A7C15) + s[:, :, i])
    return key.view(np.int64)


def least_matches(threshold: float, tolerance: float, most: int = EXTRA, step: int = STEP) -> dict[int, int]:
    """After n compared values, the fewest matches with posterior P(similarity ≥ threshold) ≥ tolerance.

    With a flat prior the posterior is Beta(m + 1, n - m + 1), whose upper tail at t is the
    chance of at most m successes among n + 1 trials of probability t.
    """
    out = {}
    for n in range(step, most + 1, step):
        tail = np.cumsum([comb(n + 1, k) * threshold**k * (1 - threshold) ** (n + 1 - k) for k in range(n + 1)])
        out[n] = int(np.argmax(tail >= tolerance))
    return out


def prune(signature: np.ndarray, a: np.ndarray, b: np.ndarray, least: dict[int, int]) -> tuple[np.ndarray, np.ndarray]:
    """Pairs whose matches never fall below ``least`` while values are compared step by step."""
    met, done = np.zeros(len(a), np.int64), 0
    for n, m in least.items():
        met += (signature[a, done:n] == signature[b, done:n]).sum(1)
        keep = met >= m
        a, b, met, done = a[keep], b[keep], met[keep], n
    return a, b


def overlaps(sets: list[np.ndarray], a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Exact size of the intersection of each pair of sets."""
    if len(a) <= 4 * len(sets):
        return np.array([len(np.intersect1d(sets[x], sets[y], assume_unique=True)) for x, y in zip(a.tolist(), b.tolist())], np.int64)
    flat, row = np.concatenate(sets), np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    _, column, many = np.unique(flat, return_inverse=True, return_counts=True)
    shared = many[column] > 1
    place = np.cumsum(many > 1) - 1
    row, column = row[shared], place[column[shared]]
    both = np.zeros((len(sets), len(sets)), np.float32)
    order = np.argsort(column, kind="stable")
    row, column = row[order], column[order]
    for low in range(0, int(column[-1]) + 1 if len(column) else 0, 4096):
        x, y = np.searchsorted(column, [low, low + 4096])
        block = np.zeros((len(sets), 4096), np.float32)
        block[row[x:y], column[x:y] - low] = 1
        both += block @ block.T
    return both[a, b].astype(np.int64)


def checker(threshold: float, tolerance: float):
    least = least_matches(threshold, tolerance)

    def check(table: pa.Table, left: np.ndarray, right: np.ndarray, group: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        n = table.num_rows
        signature = np.frombuffer(b"".join(table.column("signature").to_pylist()), np.uint32).reshape(n, -1)
        sets = [np.frombuffer(s, np.uint64) for s in table.column("shingles").to_pylist()]
        weight, nodes = table.column("weight").to_numpy(), table.column("node").to_numpy()
        keys = band_keys(signature)
        meet = np.zeros((n, n), bool)
        for i in range(BANDS):
            meet |= keys[:, i][:, None] == keys[:, i][None, :]
        meet &= group[:, None] == group[None, :]
        meet &= np.triu((left[:, None] & right[None, :]) | (right[:, None] & left[None, :]), 1)
        a, b = prune(signature[:, BANDS * ROWS :], *np.nonzero(meet), least)
        links = np.zeros(n, np.int64)
        if len(a):
            size = np.array([len(s) for s in sets])
            both = overlaps(sets, a, b)
            true = both / (size[a] + size[b] - both) >= threshold - 1e-12
            a, b = a[true], b[true]
            np.add.at(links, a, weight[b])
            np.add.at(links, b, weight[a])
        return links, least_connected(nodes, a, b)

    return check


def near_duplicates(docs: DataFrame, *, shingle: int = SHINGLE, threshold: float = THRESHOLD, tolerance: float = TOLERANCE, chunk: int = 256, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, rid, class_id, n_links, first of every row.

    Two texts are linked if the Jaccard similarity of their word ``shingle``-gram sets is
    ``threshold`` at least; a class is a connected group of links, its id the least doc_id in
    it; n_links counts the other rows a row is linked with, copies included. A text with
    fewer words has one shingle of all its words; one without any word (null or empty, say)
    is alone: class_id is its own id, n_links 0. Repeated rows are copies of each other.
    ``rid`` is a key of (id, text); ``first`` marks the row of least (id, rid) of a class, or
    equal rows of it. Null ids come last; a class of none but null ids has class_id null.
    Other columns are ignored.
    """
    ddl = "doc_id long, rid long, dg binary, bands array<long>"
    schema = schema_of(ddl)

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, "text"):
            words = Words([t or "" for t in batch.column("text").to_pylist()])
            hashes, starts = shingles(words, shingle)
            some = np.flatnonzero(np.diff(starts) > 0)
            keys = band_keys(minhash(hashes, starts[np.append(some, len(starts) - 1)], BANDS * ROWS)) if len(some) else np.zeros((0, BANDS), np.int64)
            raw = memoryview(words.hashes.tobytes())
            dg: list = [None] * batch.num_rows
            for i in some.tolist():
                dg[i] = xxhash.xxh3_128_digest(raw[8 * words.first[i] : 8 * words.first[i + 1]])
            bounds = np.zeros(batch.num_rows + 1, np.int32)
            bounds[1:] = np.cumsum(np.diff(starts) > 0) * BANDS
            yield rows(schema, batch.column("doc_id"), batch.column("rid"), pa.array(dg, pa.binary()), pa.ListArray.from_arrays(pa.array(bounds), pa.array(keys.reshape(-1))))

    keyed = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text")).withColumn("rid", F.xxhash64("doc_id", "text"))
    signed = materialize(keyed.mapInArrow(sign, ddl), "signed")
    nodes = materialize(signed.where("dg IS NOT NULL").groupBy("dg").agg(F.count("*").alias("weight"), F.min("rid").alias("node"), F.min(F.struct(F.col("doc_id").isNull().alias("nameless"), "doc_id", "rid")).alias("least"), F.any_value("bands").alias("bands")), "nodes")
    banded = nodes.select("node", F.explode("bands").alias("band"))
    stars = banded.groupBy("band").agg(F.min("node").alias("centre"), F.count("*").alias("k")).where("k > 1").select("band", "centre")
    edges = banded.join(stars, "band").where(F.col("node") != F.col("centre")).select(F.col("node").alias("u"), F.col("centre").alias("v"))
    comp = components(edges).withColumnsRenamed({"root": "comp"})
    asked = nodes.join(comp, "node").select("node", "comp", "weight")
    members_ddl = "node long, comp long, weight long, signature binary, shingles binary"
    members_schema = schema_of(members_ddl)

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, "text"):
            hashes, starts = shingles(Words([t or "" for t in batch.column("text").to_pylist()]), shingle)
            signature = minhash(hashes, starts, BANDS * ROWS + EXTRA)
            sets = [np.unique(hashes[x:y]).tobytes() for x, y in zip(starts[:-1].tolist(), starts[1:].tolist())]
            yield rows(members_schema, *(batch.column(c) for c in ("node", "comp", "weight")), pa.array([s.tobytes() for s in signature], pa.binary()), pa.array(sets, pa.binary()))

    members = keyed.select("text", F.col("rid").alias("node")).join(asked, "node").select("node", "comp", "weight", "text").mapInArrow(gather, members_ddl)
    found = materialize(verified(members, checker(threshold, tolerance), members_ddl, chunk=chunk), "links")
    rooted = nodes.select("dg", "node", "weight", "least").join(found, "node", "left").select("dg", "weight", "least", F.coalesce("root", "node").alias("root"), F.coalesce("links", F.lit(0)).alias("links"))
    classes = rooted.groupBy("root").agg(F.min("least").alias("one"))
    by_text = rooted.join(classes, "root").select("dg", "one", (F.col("links") + F.col("weight") - 1).alias("n_links"))
    with_words = signed.where("dg IS NOT NULL").select("doc_id", "rid", "dg").join(by_text, "dg").select("doc_id", "rid", F.col("one.doc_id").alias("class_id"), "n_links", (F.col("rid") == F.col("one.rid")).alias("first"))
    return with_words.unionByName(signed.where("dg IS NULL").select("doc_id", "rid", F.col("doc_id").alias("class_id"), F.lit(0).cast("long").alias("n_links"), F.lit(True).alias("first")))
