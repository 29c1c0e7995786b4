"""Exact substring dedup: every byte covered by a ``length``-byte string that also starts elsewhere.

1. Screening (exact). The anchor of a ``length``-byte window is the place of its least
   ``gram``-byte hash (the leftmost of equals): a function of the window's bytes alone, so equal
   windows have equal anchors. Neighbouring windows with one anchor form a segment; only
   segments whose anchor hash occurs twice in the corpus can hold a repeated window. All that
   moves here are narrow rows. Equal segments (128-bit digest) are wholly repeated at once.
2. Suffix arrays. One copy of each different segment whose anchor other segments share goes to
   a shard by its anchor. A shard sorts its suffixes by Larsson-Sadakane refinement in numpy
   and takes Kasai's common prefixes; runs with common prefixes of ``length`` are repeats.
3. Merging across shards. An anchor with more than ``hot`` different segments is spread over
   several shards. Each of them sends the windows that it saw once, and one of each repeat, as
   a run of sorted digests, cut by binary search at fixed bounds; each range of digests is
   merged by binary search of the shards' runs.

The covered places return to their documents as spans, grouped by a key of (id, text).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cotengine.llm.blocks import blocks, per_group, rows, schema_of, utf8
from cotengine.llm.store import materialize

_SEGMENT = "rid long, at int, n int, v long, dg binary"
_SPAN = "rid long, a long, b long"
_WINDOW = "rid long, a long, b long, part int, digests binary, rids binary, starts binary"


def anchors(data: np.ndarray, starts: np.ndarray, length: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Segments of texts end to end: first window, number of windows, anchor hash.

    ``starts``: offset of each text and the end. ``gram`` is a power of two, 8 at least.
    """
    n = len(data)
    ends = starts[1:]
    if n < length or not (ends - starts[:-1] >= length).any():
        return (np.zeros(0, np.int64),) * 3
    h = np.ndarray((n - 7,), "<u8", data.tobytes(), strides=(1,)).copy()
    h *= np.uint64(0x9E3779B97F4A7C15)
    h ^= h >> np.uint64(29)
    m = 8
    while m < gram:
        h = h[:-m] * np.uint64(0xBF58476D1CE4E5B9) + h[m:]
        h ^= h >> np.uint64(31)
        h *= np.uint64(0x94D049BB133111EB)
        m *= 2
    place = np.uint64((1 << 26) - 1)
    if n > int(place):
        raise ValueError("a block holds at most 64 MB of text")
    low = (h & ~place) | np.arange(len(h), dtype=np.uint64)
    width, span = length - gram + 1, 1
    while span * 2 <= width:
        low = np.minimum(low[:-span], low[span:])
        span *= 2
    if width > span:
        low = np.minimum(low[: -(width - span)], low[width - span :])
    at = (low & place).astype(np.int64)  # anchor of each window of the block
    fits = np.zeros(n + 1, np.int32)
    good = ends - starts[:-1] >= length
    np.add.at(fits, starts[:-1][good], 1)
    np.add.at(fits, ends[good] - length + 1, -1)
    fits = np.cumsum(fits)[: len(at)] > 0
    new = fits.copy()
    new[1:] &= (at[1:] != at[:-1]) | ~fits[:-1]
    first = np.flatnonzero(new)
    stop = fits.copy()
    stop[:-1] &= (at[1:] != at[:-1]) | ~fits[1:]
    return first, np.flatnonzero(stop) - first + 1, h[at[first]].view(np.int64)


def suffix_array(data: np.ndarray) -> np.ndarray:
    """Suffixes in full order by Larsson-Sadakane refinement: each round doubles the sorted depth of what is not yet single."""
    n = len(data)
    padded = np.concatenate([data, np.zeros(8, np.uint8)]).tobytes()
    key = np.ndarray((n,), ">u8", padded, strides=(1,)).astype(np.uint64)
    sa = np.argsort(key, kind="stable")
    ordered = key[sa]
    head = np.ones(n, bool)
    head[1:] = ordered[1:] != ordered[:-1]
    group = np.empty(n, np.int64)  # number of a group: place of its head
    where = np.maximum.accumulate(np.where(head, np.arange(n), 0))
    group[sa] = where
    h = 8
    while True:
        single = head.copy()
        single[:-1] &= head[1:]
        todo = np.flatnonzero(~single)  # only groups that are not yet single are refined
        if not len(todo):
            return sa
        own = sa[todo]
        # A suffix that ends within h bytes comes before all it is a prefix of, the shortest first.
        then = np.where(own + h < n, group[np.minimum(own + h, n - 1)], n - 1 - (own + h))
        mine = where[todo]
        order = np.argsort(mine * np.int64(n + h + 1) + (then + h), kind="stable")
        sa[todo] = own[order]
        mine, then = mine[order], then[order]
        fresh = np.ones(len(todo), bool)
        fresh[1:] = (mine[1:] != mine[:-1]) | (then[1:] != then[:-1])
        head[todo] = fresh
        where = np.maximum.accumulate(np.where(head, np.arange(n), 0))
        group[sa] = where
        h *= 2


def common_prefixes(data: np.ndarray, sa: np.ndarray, most: int, lanes: int = 4096) -> np.ndarray:
    """Kasai: the common prefix of each suffix with the one before it in order, counted up to ``most``.

    The text is cut in up to ``lanes`` stretches that go ahead in step; each carries its own
    prefix from place to place, and eight bytes are compared at once. ``sa`` is in full order,
    without which a carried prefix would not hold.
    """
    n = len(sa)
    out = np.zeros(n, np.int64)
    if not n:
        return out
    before = np.full(n, -1, np.int64)
    before[sa[1:]] = sa[:-1]
    words = np.ndarray((n,), "<u8", np.concatenate([data, np.zeros(8, np.uint8)]).tobytes(), strides=(1,)).copy()
    step = -(-n // max(1, min(lanes, n // 64)))
    starts = np.arange(0, n, step)
    carried = np.zeros(len(starts), np.int64)
    for k in range(step):
        i = starts + k
        i = i[: np.searchsorted(i, n)]
        j = before[i]
        end = np.where(j < 0, 0, np.minimum(most, n - np.maximum(i, j)))
        h = np.minimum(carried[: len(i)], end)
        live = np.flatnonzero(h < end)
        while len(live):
            at = h[live]
            x = words[i[live] + at] ^ words[j[live] + at]
            equal = (np.bitwise_count((x & -x) - np.uint64(1)) >> 3).astype(np.int64)  # equal low bytes of the two words
            h[live] = np.minimum(at + equal, end[live])
            live = live[(equal == 8) & (h[live] < end[live])]
        out[i] = h
        carried = np.maximum(h - 1, 0)
    return out[sa]


def _joined(rid: np.ndarray, a: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Window starts as spans, neighbours of one text in one."""
    order = np.lexsort((a, rid))
    rid, a = rid[order], a[order]
    new = np.ones(len(a), bool)
    new[1:] = (rid[1:] != rid[:-1]) | (a[1:] > a[:-1] + length)
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(a))[: len(first)] - 1
    return rid[first], a[first], a[last] + length


def _shard(table: pa.Table, length: int, parts: int, schema: pa.Schema) -> Iterator[pa.RecordBatch]:
    """One shard's different segments → spans of what repeats, and what merging has to see."""
    data, starts = utf8(table.column("body"))
    rid, at, n, c = (table.column(x).to_numpy() for x in ("rid", "at", "n", "c"))
    spread = bool(table.column("spread")[0].as_py())
    sa = suffix_array(data)
    lcp = common_prefixes(data, sa, length)
    segment = np.repeat(np.arange(len(n)), np.diff(starts))[sa]
    within = sa - starts[segment]
    window = within < n[segment]  # a start that the segment owns, with all its bytes
    run = np.cumsum(lcp < length)[window]
    segment, within, sa = segment[window], within[window], sa[window]
    _, group, size = np.unique(run, return_inverse=True, return_counts=True)
    several = (size > 1) | (np.bincount(group, c[segment] > 1, len(size)) > 0)
    hit = several[group] & (c[segment] == 1)
    s_rid, a, b = _joined(rid[segment[hit]], at[segment[hit]].astype(np.int64) + within[hit], length)
    k = len(a)
    none = pa.nulls(len(a), pa.binary())
    yield rows(schema, s_rid, a, b, pa.nulls(len(a), pa.int32()), none, none, none)
    if spread:
        _, one = np.unique(group, return_index=True)
        raw = data.tobytes()
        run = np.frombuffer(b"".join(xxhash.xxh3_128_digest(raw[p : p + length]) for p in sa[one].tolist()), _DIGEST)
        order = np.argsort(run, order=("hi", "lo"))
        run, one, alone = run[order], one[order], ~several[order]
        own = segment[one]
        begin = at[own].astype(np.int64) + within[one]
        cuts = np.searchsorted(run["hi"] >> np.uint64(32), np.arange(1, parts, dtype=np.uint64) * np.uint64((1 << 32) // parts))
        cuts = [0, *cuts.tolist(), len(run)]
        # A window that this shard itself saw again is settled; it only answers for others (start -1).
        full = [(i, x, y) for i, (x, y) in enumerate(zip(cuts[:-1], cuts[1:])) if y > x]
        begin = np.where(alone, begin, -1)
        packed = [pa.array([v[x:y].tobytes() for _, x, y in full], pa.binary()) for v in (run, rid[own], begin)]
        empty = pa.nulls(len(full), pa.int64())
        yield rows(schema, empty, empty, empty, [i for i, _, _ in full], *packed)


_DIGEST = np.dtype([("hi", "<u8"), ("lo", "<u8")])


def _merge(table: pa.Table, length: int, schema: pa.Schema) -> Iterator[pa.RecordBatch]:
    """One range of digests: what another shard's run holds too, by binary search in the merged runs."""
    runs = [np.frombuffer(b, _DIGEST) for b in table.column("digests").to_pylist()]
    rid, start = (np.concatenate([np.frombuffer(b, np.int64) for b in table.column(c).to_pylist()]) for c in ("rids", "starts"))
    _, code = np.unique(np.concatenate(runs), return_inverse=True)
    merged = np.sort(code, kind="stable")  # a shard's run holds each window once, so a second entry is another shard's
    met = np.searchsorted(merged, code, "right") - np.searchsorted(merged, code, "left") > 1
    hit = met & (start >= 0)
    yield rows(schema, *_joined(rid[hit], start[hit], length))


def repeated_spans(texts: DataFrame, *, length: int = 400, gram: int = 128, hot: int = 256, shard_bytes: int = 1 << 20) -> DataFrame:
    """(rid, text) → (rid, a, b): byte spans of ``text`` that repeated strings cover; they may overlap and come again.

    ``rid`` is a key of the text's row; rows that share it hold one text, and each counts as a copy.
    """
    seg, span, window = schema_of(_SEGMENT), schema_of(_SPAN), schema_of(_WINDOW)

    def screen(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, "text"):
            data, starts = utf8(batch.column("text"))
            first, n, v = anchors(data, starts, length, gram)
            raw = data.tobytes()
            dg = [xxhash.xxh3_128_digest(raw[p : p + k + length - 1]) for p, k in zip(first.tolist(), n.tolist())]
            doc = np.searchsorted(starts, first, "right") - 1
            yield rows(seg, batch.column("rid").take(pa.array(doc)), first - starts[doc], n, v, pa.array(dg, pa.binary()))

    segments = materialize(texts.select("rid", "text").mapInArrow(screen, _SEGMENT), "segments")
    # Both sides of each join below are written tables, so that a hot anchor or digest is split at run time.
    twice = materialize(segments.groupBy("v").agg(F.count("*").alias("k")).where("k > 1").select("v"), "shared-anchors")
    shared = materialize(segments.join(twice, "v").select(*seg.names), "shared-segments")
    each = shared.groupBy("v", "dg").agg(F.count("*").alias("c"), F.min(F.struct("rid", "at", "n")).alias("one"))
    each = materialize(each.select("v", "dg", "c", "one.rid", "one.at", "one.n"), "different-segments")
    copied = materialize(each.where("c > 1").select("dg").distinct(), "copied-segments")
    whole = shared.join(copied, "dg", "left_semi").select("rid", F.col("at").cast("long").alias("a"), (F.col("at") + F.col("n") + (length - 1)).cast("long").alias("b"))
    kinds = each.groupBy("v").agg(F.count("*").alias("kinds"), F.sum(F.col("n") + length).alias("bytes"), F.sum("n").alias("windows")).where("kinds > 1")
    kinds = materialize(kinds, "several-segments")
    total, spread = kinds.agg(F.sum("bytes"), F.coalesce(F.sum(F.when(F.col("kinds") > hot, F.col("windows"))), F.lit(0))).first()
    if not total:
        return whole
    ranges = max(64, -(-int(spread) // 50_000))
    shards = max(64, -(-int(total) // shard_bytes))
    parts = F.ceil(F.col("kinds") / hot).cast("long")
    asked = each.join(kinds.select("v", "kinds"), "v").select("c", "rid", "at", "n", (parts > 1).alias("spread"), F.pmod(F.xxhash64("v", F.pmod(F.xxhash64("dg"), parts)), F.when(parts > 1, F.lit(1 << 62)).otherwise(F.lit(shards))).alias("shard"))

    def sort(table: pa.Table) -> Iterator[pa.RecordBatch]:
        yield from _shard(table, length, ranges, window)

    def merge(table: pa.Table) -> Iterator[pa.RecordBatch]:
        yield from _merge(table, length, span)

    body = F.substring(F.col("text").cast("binary"), F.col("at") + 1, F.col("n") + (length - 1))
    carried = texts.select("rid", "text").join(materialize(asked, "asked"), "rid").select("rid", "at", "n", "c", "shard", "spread", body.alias("body"))
    seen = materialize(carried.repartition(F.col("shard")).sortWithinPartitions("shard").mapInArrow(per_group(["shard"], sort), _WINDOW), "windows")
    found = seen.where("part IS NULL").select("rid", "a", "b")
    if spread:
        merged = seen.where("part IS NOT NULL").select("part", "digests", "rids", "starts").repartition("part").sortWithinPartitions("part").mapInArrow(per_group(["part"], merge), _SPAN)
        found = found.union(merged)
    return whole.union(found)


def dedup_substrings(docs: DataFrame, *, length: int = 400, gram: int = 128, hot: int = 256, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, ``kept`` (binary: the remaining bytes) and n_chars (characters that begin in them) of every row.

    A byte goes if a string of ``length`` bytes that covers it starts anywhere else too, in
    another row or the same; overlaps count, and all is judged on the input, so no copy stays.
    Matches never cross rows. A null text counts as empty. Repeated rows are copies of each
    other, and a null id is an id like others. Other columns are ignored. ``hot`` places the
    limit above which an anchor's segments are spread over shards; no setting changes results.
    """
    keyed = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.coalesce(F.col(text).cast("string"), F.lit("")).alias("text")).withColumn("rid", F.xxhash64("doc_id", "text"))
    spans = repeated_spans(keyed, length=length, gram=gram, hot=hot)
    by_row = spans.groupBy("rid").agg(F.collect_set(F.struct("a", "b")).alias("spans")).select("rid", F.col("spans.a").alias("a"), F.col("spans.b").alias("b"))
    ddl = "doc_id long, n_bytes long, n_removed long, n_spans long, kept binary, n_chars long"
    schema = schema_of(ddl)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, "text"):
            data, starts = utf8(batch.column("text"))
            raw = memoryview(data)
            kept, gone, runs, chars = [], [], [], []
            for at, end, a, b in zip(starts[:-1].tolist(), starts[1:].tolist(), batch.column("a").to_pylist(), batch.column("b").to_pylist()):
                parts, last, removed, k = [], at, 0, 0
                upto = -1
                for x, y in sorted(zip(a or (), b or ())):
                    if x > upto:
                        k += 1
                        parts.append(raw[last : at + x])
                    removed += max(0, y - max(x, upto))
                    upto = max(upto, y)
                    last = at + upto
                parts.append(raw[last:end])
                kept.append(b"".join(parts))
                chars.append(int(np.count_nonzero(np.frombuffer(kept[-1], np.uint8) & 0xC0 != 0x80)))
                gone.append(removed)
                runs.append(k)
            yield rows(schema, batch.column("doc_id"), np.diff(starts), gone, runs, pa.array(kept, pa.binary()), chars)

    return keyed.join(by_row, "rid", "left").select("doc_id", "text", "a", "b").mapInArrow(cut, ddl)
