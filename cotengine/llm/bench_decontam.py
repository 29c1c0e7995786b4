"""Benchmark decontamination: BM25 over an inverted index of test items, block-max WAND, verified overlaps.

Test items are cut in even chunks of at most ``CHUNK`` words; a chunk's BM25 impacts are
divided by its score of itself, so one threshold holds for all. Every training text is cut in
passages of twice that size at half steps, so each chunk-sized stretch lies whole in one.
Each passage queries the index for all chunks that reach the threshold. The block-max test of
WAND (no chunk of a range can reach the threshold if the sum of the terms' greatest impacts
in that range does not) is taken for all passages of a block of text and all ranges at once;
passages with a range that passes walk their posting lists by pivots, with block maxima to
skip. What is retrieved is verified on word n-grams of the item's question and answer
around the passage.

The index holds at most ``shard`` items and is sent to the executors; more items are taken
shard by shard, with document frequencies of all of them. Texts never move.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cotengine.llm.blocks import blocks, rows, schema_of
from cotengine.llm.words import Words, mixed

CHUNK, K1, B, GRAM = 48, 1.2, 0.75, 5
_BLOCK, _RANGES = 32, 128
_OUT = "doc_id long, rid long, item_id long, score double, question_overlap double, answer_overlap double"


def question_and_answer(text: Column) -> tuple[Column, Column]:
    """The last sentence of a text as its answer, what is before it as its question (one sentence: no answer)."""
    two = r"(?s)^(.*[.?!])\s+([^.?!]+[.?!]*)\s*$"
    return F.when(F.regexp_like(text, F.lit(two)), F.regexp_extract(text, two, 1)).otherwise(text), F.regexp_extract(text, two, 2)


def grams(h: np.ndarray, n: int) -> np.ndarray:
    out = np.zeros(max(0, len(h) - n + 1), np.uint64)
    for i in range(n):
        out = out * np.uint64(0x9E3779B97F4A7C15) + h[i : i + len(out)]
    return mixed(out)


class BlockMaxIndex:
    """Posting lists of normalised BM25 impacts, with the greatest of each list and of each block."""

    def __init__(self, items: list[tuple[int, np.ndarray, np.ndarray]], df: dict[int, int], chunks: int, words: int):
        """items: id, question's and answer's word hashes; df: chunks with a term; chunks, words: of all items."""
        self.items = items
        self.chunk_item, lists, n = [], {}, 0
        for i, (_, q, a) in enumerate(items):
            h = np.concatenate([q, a])
            for part in chunk_words(h):
                terms, tf = np.unique(part, return_counts=True)
                own = np.array([df.get(int(t), 1) for t in terms], float)
                idf = np.log1p((chunks - own + 0.5) / (own + 0.5))
                impact = idf * tf * (K1 + 1) / (tf + K1 * (1 - B + B * len(part) * chunks / max(words, 1)))
                impact /= impact.sum()
                for t, w in zip(terms.tolist(), impact.tolist()):
                    lists.setdefault(t, []).append((n, w))
                self.chunk_item.append(i)
                n += 1
        self.terms = np.array(sorted(lists), np.uint64)
        self.lists = [lists[int(t)] for t in self.terms]
        self.most = np.array([max(w for _, w in x) for x in self.lists] + [0.0])
        self.block_most = [[max(w for _, w in x[i : i + _BLOCK]) for i in range(0, len(x), _BLOCK)] for x in self.lists]
        self.block_last = [[x[min(i + _BLOCK, len(x)) - 1][0] for i in range(0, len(x), _BLOCK)] for x in self.lists]

        # Greatest impact of each term in each range of chunks.
        span = max(2, -(-n // _RANGES))
        self.ranges = max(1, -(-n // span))
        begin, which, greatest = [0], [], []
        for x in self.lists:
            held: dict[int, float] = {}
            for c, w in x:
                held[c // span] = max(held.get(c // span, 0.0), w)
            which += held
            greatest += held.values()
            begin.append(len(which))
        self.range_begin, self.range_of, self.range_most = np.array(begin, np.int64), np.array(which, np.int64), np.array(greatest, float)

    def bounds(self, term: np.ndarray, first: np.ndarray, passages: np.ndarray, step: int) -> np.ndarray:
        """Upper bound of the score of any chunk, over the ranges, for each passage of two steps' words."""
        many, base = np.diff(first), np.cumsum(passages) - passages
        text = np.repeat(np.arange(len(many)), many)
        own = (np.arange(len(term)) - first[text]) // step
        total, terms = int(passages.sum()), len(self.terms)
        known = np.flatnonzero(term < terms)
        text, own, term = text[known], own[known], term[known]
        pairs = []
        for back in (0, 1):
            k = own - back
            fits = (k >= 0) & (k < passages[text])
            pairs.append((base[text] + k)[fits] * max(terms, 1) + term[fits])
        at, t = np.divmod(np.unique(np.concatenate(pairs)), max(terms, 1))  # a passage asks for a term once
        reps = self.range_begin[t + 1] - self.range_begin[t]
        upto = np.cumsum(reps)
        place = np.repeat(self.range_begin[t] - (upto - reps), reps) + np.arange(upto[-1] if len(upto) else 0)
        cells = np.bincount(np.repeat(at, reps) * self.ranges + self.range_of[place], self.range_most[place], total * self.ranges)
        return cells.reshape(total, self.ranges).max(1, initial=0.0)

    def term_numbers(self, hashes: np.ndarray) -> np.ndarray:
        """Number of each word's term; the number after the last for words that no item has."""
        if not len(self.terms):
            return np.zeros(len(hashes), np.int64)
        at = np.searchsorted(self.terms, hashes)
        return np.where(self.terms[np.minimum(at, len(self.terms) - 1)] == hashes, at, len(self.terms))

    def reach(self, terms: list[int], threshold: float) -> list[tuple[int, float]]:
        """All chunks that score ``threshold`` at least for a set of terms: WAND with block maxima."""
        end = 1 << 60
        threshold -= 1e-9
        cursors = [[self.lists[t][0][0], 0, t] for t in terms]  # current chunk, place in the list, term
        out = []

        def move(c: list, to: int) -> None:
            x, at = self.lists[c[2]], c[1]
            last, b = self.block_last[c[2]], at // _BLOCK
            while b < len(last) and last[b] < to:
                b += 1
            at = max(at, b * _BLOCK)
            while at < len(x) and x[at][0] < to:
                at += 1
            c[0], c[1] = (x[at][0] if at < len(x) else end), at

        while True:
            cursors = sorted(c for c in cursors if c[0] != end)
            total, pivot = 0.0, -1
            for i, c in enumerate(cursors):
                total += self.most[c[2]]
                if total >= threshold:
                    pivot = i
                    break
            if pivot < 0:
                return out
            chunk = cursors[pivot][0]
            while pivot + 1 < len(cursors) and cursors[pivot + 1][0] == chunk:
                pivot += 1
            bound, stop = 0.0, end
            for c in cursors[: pivot + 1]:
                last, b = self.block_last[c[2]], c[1] // _BLOCK
                while b < len(last) and last[b] < chunk:
                    b += 1
                if b < len(last):
                    bound += self.block_most[c[2]][b]
                    stop = min(stop, last[b] + 1)
            if bound < threshold:
                to = max(chunk + 1, min(stop, cursors[pivot + 1][0] if pivot + 1 < len(cursors) else end))
                if stop == end:
                    to = max(chunk + 1, cursors[pivot + 1][0] if pivot + 1 < len(cursors) else end)
                for c in cursors[: pivot + 1]:
                    move(c, to)
            elif cursors[0][0] == chunk:
                score = sum(self.lists[c[2]][c[1]][1] for c in cursors[: pivot + 1])
                if score >= threshold:
                    out.append((chunk, score))
                for c in cursors[: pivot + 1]:
                    move(c, chunk + 1)
            else:
                for c in cursors[: pivot + 1]:
                    if c[0] < chunk:
                        move(c, chunk)

    def overlap(self, own: np.ndarray, around: np.ndarray) -> float:
        """Share of an item part's word n-grams that are among those of the words around the passage."""
        n = min(GRAM, len(own))
        if not n:
            return 0.0
        want = np.unique(grams(own, n))
        return float(np.isin(want, grams(around, n)).mean())


def chunk_words(h: np.ndarray) -> list[np.ndarray]:
    return np.array_split(h, -(-len(h) // CHUNK)) if len(h) else []


def _scan(sent, threshold: float, question: float, answer: float, schema: pa.Schema):
    window, step = 2 * CHUNK, CHUNK

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index: BlockMaxIndex = sent.value
        for batch in blocks(batches, "text"):
            words = Words([t or "" for t in batch.column("text").to_pylist()])
            term = index.term_numbers(words.hashes)
            many = np.diff(words.first)
            passages = np.where(many > 0, np.maximum(1, -(-(many - (window - step)) // step)), 0)
            text = np.repeat(np.arange(len(many)), passages)
            low = words.first[:-1][text] + step * (np.arange(len(text)) - np.repeat(np.cumsum(passages) - passages, passages))
            high = np.minimum(low + window, words.first[1:][text])
            best: dict[tuple[int, int], tuple] = {}
            for p in np.flatnonzero(index.bounds(term, words.first, passages, step) >= threshold - 1e-6).tolist():
                a, b, t = int(low[p]), int(high[p]), int(text[p])
                own = np.unique(term[a:b])
                own = own[own < len(index.terms)].tolist()
                for chunk, score in index.reach(own, threshold):
                    i = index.chunk_item[chunk]
                    _, q, r = index.items[i]
                    reach = len(q) + len(r)
                    around = words.hashes[max(int(words.first[t]), a - reach) : min(int(words.first[t + 1]), b + reach)]
                    qo, ao = index.overlap(q, around), index.overlap(r, around)
                    if qo >= question and (not len(r) or ao >= answer) or qo >= max(question, 0.8):
                        best[t, i] = max(best.get((t, i), (0.0,)), (score, qo, ao))
            keys = list(best)
            at = pa.array([t for t, _ in keys], pa.int64())
            found = [best[k] for k in keys]
            yield rows(schema, batch.column("doc_id").take(at), batch.column("rid").take(at), [index.items[i][0] for _, i in keys], *([x[c] for x in found] for c in range(3)))

    return scan


def contaminated(docs: DataFrame, items: DataFrame, *, threshold: float = 0.5, question: float = 0.5, answer: float = 0.5, shard: int = 20_000, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """docs × items (item_id, question, answer) → doc_id, rid, item_id, score, question_overlap, answer_overlap.

    One row for each text and test item that it holds: some passage reaches ``threshold`` of
    the BM25 score that a chunk of the item has for itself, and around it the n-grams (5 words,
    or all of a shorter part) of the question overlap by ``question`` and those of the answer
    by ``answer`` at least; four fifths of the question are enough alone, and an item without
    an answer needs its question only. Scores are the best over the text's passages. Null or
    wordless texts and items have no rows; repeated rows have one each; repeated items as well.
    ``rid`` is a key of (id, text). Other columns are ignored.
    """
    spark = docs.sparkSession
    schema = schema_of(_OUT)
    keyed = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text")).withColumn("rid", F.xxhash64("doc_id", "text"))
    ready = items.select(F.col("item_id").cast("long").alias("item_id"), F.coalesce("question", F.lit("")).alias("question"), F.coalesce("answer", F.lit("")).alias("answer"))

    def terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = schema_of("term long, words long")
        for b in batches:
            q, a = Words(b.column("question").to_pylist()), Words(b.column("answer").to_pylist())
            for i in range(b.num_rows):
                h = np.concatenate([q.hashes[q.first[i] : q.first[i + 1]], a.hashes[a.first[i] : a.first[i + 1]]])
                for part in chunk_words(h):
                    found = np.unique(part).view(np.int64)
                    yield rows(own, pa.array([None, *found.tolist()], pa.int64()), np.append(len(part), np.zeros(len(found), np.int64)))

    counted = ready.mapInArrow(terms, "term long, words long")
    whole = counted.where("term IS NULL").agg(F.count("*").alias("chunks"), F.coalesce(F.sum("words"), F.lit(0)).alias("words"), ).first()
    shards = max(1, -(-ready.count() // shard))
    dealt = ready.withColumn("s", F.pmod(F.xxhash64("item_id", "question"), F.lit(shards)))
    found = None
    for s in range(shards):
        own = dealt.where(F.col("s") == s)
        held = own.select("item_id", "question", "answer").orderBy("item_id", "question", "answer").collect()  # about ``shard`` items
        used = own.select("item_id", "question", "answer").mapInArrow(terms, "term long, words long").where("term IS NOT NULL").select("term").distinct()
        df = {r.term & (1 << 64) - 1: r.n for r in counted.where("term IS NOT NULL").join(used, "term").groupBy("term").agg(F.count("*").alias("n")).collect()}
        q, a = Words([r.question for r in held]), Words([r.answer for r in held])
        index = BlockMaxIndex([(r.item_id, q.hashes[q.first[i] : q.first[i + 1]], a.hashes[a.first[i] : a.first[i + 1]]) for i, r in enumerate(held)], df, whole.chunks, whole.words)
        part = keyed.mapInArrow(_scan(spark.sparkContext.broadcast(index), threshold, question, answer, schema), _OUT)
        found = part if found is None else found.union(part)
    return found
