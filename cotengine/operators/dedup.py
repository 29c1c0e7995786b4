"""Exact and near deduplication.

Texts stay where they are: what is shuffled are ids, digests, band keys and priorities. Exact
dedup and bucket retention are partial aggregates (a minimum per key), so a bucket that holds a
third of all rows costs each map task one row; joins back to buckets have written tables on
both sides, which adaptive execution splits where a bucket is hot. Shingles, signatures and band
keys are Arrow batches with exact 64-bit arithmetic.
"""

from __future__ import annotations

import hashlib
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cotengine.functions.hashing import BANDS, PRIME, ROWS, SEED, family
from cotengine.functions.text import TOKEN, ngrams, normalize, tokens
from cotengine.sources.files import write_once
from cotengine.sources.tables import spread


def shared_folder(spark: SparkSession) -> str:
    """The folder that ``spark.checkpoint.dir`` names; in a local session without one, a temporary folder."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not folder:
        if not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        folder = "file://" + tempfile.mkdtemp(prefix="cotengine-")
        spark.sparkContext.setCheckpointDir(folder)
        folder = spark.sparkContext.getCheckpointDir()
    return folder.rstrip("/")


def cut_lineage(df: DataFrame, tag: str) -> DataFrame:
    """``df`` written to the shared folder and reread."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/cut/{tag}-{uuid.uuid4().hex}"
    write_once(df, path)
    return spark.read.schema(df.schema).parquet(path)


def _best(prio: Column | None, key: str) -> Column:
    return F.struct((prio if prio is not None else F.lit(0)).alias("p"), F.col(key).alias("id"))


def dedup_exact(df: DataFrame, text: str = "text", *, key: str = "doc_id", normalized: bool = False, prio: Column | None = None) -> DataFrame:
    """One row per md5 of the text: the best (priority, key). Null texts have no digest and all stay."""
    body = normalize(F.col(text)) if normalized else F.col(text)
    digest = F.md5(body)
    best = df.where(F.col(text).isNotNull()).groupBy(digest.alias("fp")).agg(F.min(_best(prio, key)).alias("best")).select(F.col("best.id").alias(key))
    nulls = df.where(F.col(text).isNull()).select(key)
    return df.join(best.union(nulls), key, "left_semi")


def shingle_hashes(toks: list[str], n: int) -> np.ndarray:
    """Base hashes (first eight hex digits of the md5, mod PRIME) of the distinct runs of n tokens; a shorter text is one run."""
    runs = {" ".join(toks)} if len(toks) < n else set(map(" ".join, zip(*(toks[i:] for i in range(n)))))
    raw = b"".join([hashlib.md5(r.encode()).digest()[:4] for r in runs])
    return np.frombuffer(raw, ">u4").astype(np.int64) % PRIME


def least_hashes(hashes: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Least value of each universal hash a·h + b mod PRIME; the modulus of a Mersenne prime by shifts."""
    best, prime = np.full(len(a), PRIME, np.uint64), np.uint64(PRIME)
    a, b, hashes = a.astype(np.uint64), b.astype(np.uint64), hashes.astype(np.uint64)
    for low in range(0, len(hashes), 256):  # blocks that stay in cache; a very long text costs no more memory than one
        x = a * hashes[low : low + 256]
        x += b
        high = x >> np.uint64(31)
        x &= prime
        x += high
        np.subtract(x, prime, out=high)  # wraps where x is below the prime, so the lesser of both is the rest
        np.minimum(best, np.minimum(x, high, out=x).min(1), out=best)
    return best.astype(np.int64)


def minhash(df: DataFrame, *, key: str = "doc_id", text: str = "text", n: int = 3, bands: int = BANDS, rows: int = ROWS, seed: int = SEED, carry: list[str] = []) -> DataFrame:
    """(key, carried columns, sig array<long>) of every row whose text has a token; a narrow map. ``carry``: int or long columns."""
    a, b = (np.array(x, np.int64)[:, None] for x in family(bands * rows, seed))

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for low in range(0, whole.num_rows, 256):
                batch = whole.slice(low, 256)
                out = np.empty((batch.num_rows, bands * rows), np.int64)
                for i, toks in enumerate(batch.column(batch.num_columns - 1).to_pylist()):
                    out[i] = least_hashes(shingle_hashes(toks, n), a, b)
                sig = pa.ListArray.from_arrays(pa.array(np.arange(batch.num_rows + 1, dtype=np.int32) * (bands * rows)), pa.array(out.reshape(-1)))
                yield pa.RecordBatch.from_arrays([*batch.columns[:-1], sig], names=[key, *carry, "sig"])

    own = spread(df.select(F.col(key).cast("long").alias(key), *[F.col(c).cast("long").alias(c) for c in carry], F.col(text).alias("_text")).where(F.col(text).rlike(TOKEN)))
    cut = own.select(key, *carry, tokens(F.col("_text")).alias("t"))
    return cut.mapInArrow(sign, ", ".join([f"{c} long" for c in (key, *carry)] + ["sig array<long>"]))


def band_keys(signed: DataFrame, *, key: str = "doc_id", bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """(key, carried columns, band, bkey): 24 narrow rows per text; keys are comparable within a band only."""
    names = [c for c in signed.columns if c != "sig"]

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for low in range(0, whole.num_rows, 1024):
                batch = whole.slice(low, 1024)
                keys = [hashlib.md5(",".join(map(str, s[i * rows : i * rows + rows])).encode()).hexdigest() for s in batch.column("sig").to_pylist() for i in range(bands)]
                place = pa.array(np.repeat(np.arange(batch.num_rows), bands))
                band = pa.array(np.tile(np.arange(bands, dtype=np.int32), batch.num_rows))
                yield pa.RecordBatch.from_arrays([*(batch.column(c).take(place) for c in names), band, pa.array(keys, pa.string())], names=[*names, "band", "bkey"])

    return signed.select(*names, "sig").mapInArrow(cut, ", ".join([f"{c} long" for c in names] + ["band int", "bkey string"]))


def bucket_losers(banded: DataFrame, *, key: str = "doc_id") -> DataFrame:
    """Keys that are not the best by (prio, key) of some bucket. ``banded``: a written table of key, prio, band, bkey."""
    best = banded.groupBy("band", "bkey").agg(F.min(F.struct("prio", key)).alias("best"), F.count("*").alias("n")).where("n > 1").drop("n")
    met = cut_lineage(banded.join(cut_lineage(best, "best-of-buckets"), ["band", "bkey"]).where(F.struct("prio", key) != F.col("best")).select(key), "bucket-losers")
    return met.distinct()


def components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(u, v) → (node, root) with the least node of each component.

    Each round a node hooks to the least root among its neighbours and pointers are jumped; the
    edges are then drawn between roots, so what is settled leaves the table. Raises if
    ``most_rounds`` did not suffice, rather than return a part.
    """
    now = cut_lineage(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "links")
    labels = cut_lineage(now.select(F.col("u").alias("node")).union(now.select("v")).distinct().withColumn("root", F.col("node")), "roots")
    for _ in range(most_rounds):
        if now.isEmpty():
            return labels
        both = now.union(now.select("v", "u"))
        hooked = cut_lineage(both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("to")), "hooks")
        jumped = hooked.join(hooked.select(F.col("u").alias("to"), F.col("to").alias("top")), "to").select("u", "top")
        jumped = cut_lineage(jumped.join(jumped.select(F.col("u").alias("top"), F.col("top").alias("last")), "top").select("u", F.col("last").alias("top")), "jumps")
        labels = cut_lineage(labels.join(jumped, F.col("root") == F.col("u"), "left").select("node", F.coalesce("top", "root").alias("root")), "roots")
        ends = now.join(jumped, "u").select("v", F.col("top").alias("a")).join(jumped.select(F.col("u").alias("v"), F.col("top").alias("b")), "v").where("a <> b")
        now = cut_lineage(ends.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "links")
    raise RuntimeError(f"components did not settle within {most_rounds} rounds")


def near_components(banded: DataFrame, *, key: str = "doc_id") -> DataFrame:
    """(node, root) of the transitive closure of shared buckets, by star edges to each bucket's least key."""
    heads = banded.groupBy("band", "bkey").agg(F.min(key).alias("v"), F.count("*").alias("n")).where("n > 1").drop("n")
    edges = banded.join(heads, ["band", "bkey"]).where(F.col(key) != F.col("v")).select(F.col(key).alias("u"), "v").distinct()
    return components(edges)


def dedup_near(df: DataFrame, prio: Column, *, mode: str = "bucket", key: str = "doc_id", text: str = "text", **sizes) -> DataFrame:
    """Near dedup by banded MinHash. ``bucket``: a row goes if some bucket has a better one.
    ``component``: of each connected group of buckets the best row stays."""
    ranks = df.select(key, prio.alias("prio"))
    banded = cut_lineage(band_keys(minhash(df.select(key, text, prio.alias("prio")), key=key, text=text, carry=["prio"], **sizes), key=key), "bands")
    if mode == "bucket":
        return df.join(bucket_losers(banded, key=key), key, "left_anti")
    if mode != "component":
        raise ValueError("mode is 'bucket' or 'component'")
    roots = near_components(banded, key=key)
    best = roots.join(ranks, roots["node"] == ranks[key]).groupBy("root").agg(F.min(F.struct("prio", "node")).alias("best"))
    losers = roots.join(best, "root").where(F.col("node") != F.col("best.node")).select(F.col("node").alias(key))
    return df.join(losers, key, "left_anti")


def verify_pairs(banded: DataFrame, df: DataFrame, *, theta: float = 0.0, n: int = 3, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(a, b, jaccard): exact similarity of the pairs that share a bucket; a measure, for bucket sizes of a test corpus."""
    left, right = banded.alias("l"), banded.alias("r")
    pairs = left.join(right, (F.col("l.band") == F.col("r.band")) & (F.col("l.bkey") == F.col("r.bkey")) & (F.col(f"l.{key}") < F.col(f"r.{key}"))).select(F.col(f"l.{key}").alias("a"), F.col(f"r.{key}").alias("b")).distinct()
    grams = df.select(F.col(key), F.array_distinct(F.transform(ngrams(tokens(F.col(text)), n), lambda x: F.xxhash64(x))).alias("g"))  # eight bytes a run, not its words, are what a shuffle moves
    joined = pairs.join(grams.select(F.col(key).alias("a"), F.col("g").alias("ga")), "a").join(grams.select(F.col(key).alias("b"), F.col("g").alias("gb")), "b")
    both = F.size(F.array_intersect("ga", "gb"))
    return joined.select("a", "b", (both / (F.size("ga") + F.size("gb") - both)).alias("jaccard")).where(F.col("jaccard") >= theta)


def exact_pairs(df: DataFrame, theta: float, *, n: int = 3, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(a, b, jaccard) of all pairs at least ``theta`` similar on word n-grams: the reference that banding is measured against.

    Exact by prefixes: with n-grams in order of rarity, similar texts share one of their first
    size - ceil(theta * size) + 1, so common n-grams join nothing.
    """
    grams = df.select(F.col(key), F.array_distinct(ngrams(tokens(F.col(text)), n)).alias("g")).where(F.size("g") > 0)
    rows = cut_lineage(grams.select(key, F.size("g").alias("size"), F.explode(F.transform("g", lambda x: F.xxhash64(x))).alias("h")), "grams")
    rare = rows.join(rows.groupBy("h").agg(F.count("*").alias("df")), "h")
    sets = cut_lineage(rare.groupBy(key, "size").agg(F.array_sort(F.collect_list(F.struct("df", "h"))).alias("s")).select(key, F.col("s.h").alias("s")), "gram-sets")
    first = F.slice("s", 1, (F.size("s") - F.ceil(F.size("s") * F.lit(theta) - F.lit(1e-9)) + 1).cast("int"))
    prefix = sets.select(key, F.explode(first).alias("h"))
    pairs = prefix.select(F.col(key).alias("a"), "h").join(prefix.select(F.col(key).alias("b"), "h"), "h").where("a < b").select("a", "b").distinct()
    joined = pairs.join(sets.select(F.col(key).alias("a"), F.col("s").alias("ga")), "a").join(sets.select(F.col(key).alias("b"), F.col("s").alias("gb")), "b")
    both = F.size(F.array_intersect("ga", "gb"))
    return joined.select("a", "b", (both / (F.size("ga") + F.size("gb") - both)).alias("jaccard")).where(F.col("jaccard") >= theta)
