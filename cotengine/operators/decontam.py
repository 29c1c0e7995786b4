"""Decontamination against evaluation items: identical n-grams, shared MinHash buckets, both.

The evaluation side is broadcast only while it is small (counted first, ``most_broadcast``
keys); beyond that the same joins run as shuffles. Training texts are never shuffled: hits are
ids, and the survivors an anti join on them.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cotengine.functions.text import ngrams, tokens
from cotengine.operators.dedup import band_keys, cut_lineage, minhash
from cotengine.sources.tables import spread

MOST_BROADCAST = 2_000_000


def small(df: DataFrame, most: int) -> DataFrame:
    """``df`` with a broadcast hint if it has at most ``most`` rows."""
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df


def _full_grams(df: DataFrame, key: str, text: str, n: int) -> DataFrame:
    toks = df.select(F.col(key), tokens(F.col(text)).alias("t")).where(F.size("t") >= n)
    return toks.select(key, F.explode(ngrams(F.col("t"), n)).alias("gram"))


def run_hashes(column: pa.ListArray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Rolling 64-bit hash of every run of n tokens of every row, and its place among all tokens of the column."""
    size = pa.compute.list_value_length(column).to_numpy(zero_copy_only=False).astype(np.int64)
    coded = column.flatten().dictionary_encode()
    own = np.array([xxhash.xxh64_intdigest(w) for w in coded.dictionary.to_pylist()], np.uint64)
    h = own[coded.indices.to_numpy()] if len(own) else own
    many = len(h) - n + 1
    if many <= 0:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    rolled = np.zeros(many, np.uint64)
    for i in range(n):
        rolled = rolled * np.uint64(0x9E3779B97F4A7C15) + h[i : i + many]
    row = np.repeat(np.arange(len(size)), size)
    place = np.flatnonzero(row[:many] == row[n - 1 :])
    return rolled[place], place


def _probed_grams(train: DataFrame, known: np.ndarray, key: str, text: str, n: int) -> DataFrame:
    """(key, gram): the runs of n tokens whose hash is in ``known`` (sorted); a map that writes out hits only."""
    sent = train.sparkSession.sparkContext.broadcast(known)

    def probe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for low in range(0, whole.num_rows, 512):
                batch = whole.slice(low, 512)
                h, place = run_hashes(batch.column(1), n)
                at = np.minimum(np.searchsorted(sent.value, h), len(sent.value) - 1)
                place = place[sent.value[at] == h]
                if len(place):
                    words = batch.column(1).flatten()
                    ends = np.cumsum(pa.compute.list_value_length(batch.column(1)).to_numpy(zero_copy_only=False))
                    grams = [" ".join(words.slice(p, n).to_pylist()) for p in place.tolist()]
                    yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(np.searchsorted(ends, place, "right"))), pa.array(grams, pa.string())], names=[key, "gram"])

    own = spread(train.select(F.col(key).cast("long").alias(key), F.col(text).alias("_text")))
    return own.select(key, tokens(F.col("_text")).alias("t")).mapInArrow(probe, f"{key} long, gram string")


def ngram_hits(train: DataFrame, items: DataFrame, *, n: int = 13, key: str = "doc_id", text: str = "text", most_broadcast: int = MOST_BROADCAST) -> DataFrame:
    """(key, item_id): each training row and item that share a run of n tokens.

    The items' hashed runs, while there are at most ``most_broadcast``, are probed within the
    map that cuts the texts, so only hits become rows; beyond that the runs are joined by hash as
    a shuffle. The strings decide in both.
    """
    keyed = cut_lineage(_full_grams(items, "item_id", "text", n).distinct(), "item-grams")
    if keyed.limit(most_broadcast + 1).count() <= most_broadcast:
        got = keyed.select("gram").distinct().toArrow().column("gram")  # counted above
        words = pa.compute.split_pattern(got, " ").combine_chunks() if len(got) else pa.array([], pa.list_(pa.string()))
        known = np.unique(run_hashes(words, n)[0])
        grams = _probed_grams(train, known if len(known) else np.zeros(1, np.uint64), key, text, n).distinct()
        return grams.join(F.broadcast(keyed), "gram").select(key, "item_id").distinct()
    hashed = keyed.withColumn("h", F.xxhash64("gram")).withColumnRenamed("gram", "item_gram")
    grams = _full_grams(train, key, text, n).withColumn("h", F.xxhash64("gram"))
    return grams.join(hashed, "h").where(F.col("gram") == F.col("item_gram")).select(key, "item_id").distinct()


def windows(df: DataFrame, size: int, step: int, *, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, wid, text): windows of ``size`` tokens every ``step`` tokens; a shorter text is one window."""
    toks = df.select(F.col(key), tokens(F.col(text)).alias("t")).where(F.size("t") > 0)
    many = F.greatest(F.lit(1), F.ceil((F.size("t") - size) / F.lit(float(step))).cast("int") + 1)
    return toks.select(key, "t", F.explode(F.sequence(F.lit(0), many - 1)).alias("w")).select(key, F.col("w").alias("wid"), F.array_join(F.slice("t", F.col("w") * step + 1, size), " ").alias("text"))


def minhash_hits(train: DataFrame, items: DataFrame, *, unit: str = "document", size: int = 40, step: int = 20, key: str = "doc_id", text: str = "text", most_broadcast: int = MOST_BROADCAST) -> DataFrame:
    """Keys of training rows that share a MinHash bucket with an item, as whole texts or as windows."""
    eval_bands = band_keys(minhash(items, key="item_id"), key="item_id").select("band", "bkey").distinct()
    if unit == "document":
        banded = band_keys(minhash(train, key=key, text=text), key=key)
        return banded.join(small(eval_bands, most_broadcast), ["band", "bkey"], "left_semi").select(key).distinct()
    if unit != "window":
        raise ValueError("unit is 'document' or 'window'")
    cut = windows(train, size, step, key=key, text=text)
    banded = band_keys(minhash(cut, key=key), key=key)
    return banded.join(small(eval_bands, most_broadcast), ["band", "bkey"], "left_semi").select(key).distinct()


def decontaminate(train: DataFrame, items: DataFrame, *, n: int = 13, unit: str = "document", key: str = "doc_id", text: str = "text") -> tuple[DataFrame, DataFrame]:
    """(survivors, hits with a reason): what either detector finds goes."""
    by_gram = ngram_hits(train, items, n=n, key=key, text=text).select(key).distinct().withColumn("reason", F.lit("ngram"))
    by_bucket = minhash_hits(train, items, unit=unit, key=key, text=text).withColumn("reason", F.lit("minhash"))
    hits = by_gram.union(by_bucket).groupBy(key).agg(F.array_join(F.array_sort(F.collect_set("reason")), "+").alias("reason"))
    return train.join(hits, key, "left_anti"), hits
