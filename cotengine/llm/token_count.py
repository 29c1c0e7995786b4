"""Token counts by a compiled finite-state transducer.

Layer 1 is the pre-tokeniser as a local rule over character kinds, so word starts come from
array comparisons. Layer 2 is a deterministic transducer compiled from the tokenizer's merges
(``merge_rules``): a state is the prefix of a word and knows the prefix's tokens, a transition
within a word emits the difference, one that leaves a word emits what its end adds. The sum over
a word telescopes to the count at its end. States are compiled lazily, for words that come up,
up to a fixed number; a word without states runs into a dead state, and its count comes from the
worker's memory of words or the tokenizer library, which also checks each word that is
compiled. So results never depend on what was compiled.

A block of text is cut in chunks of fixed length that run in step, one array gather for each
symbol place. A chunk's state map sends an entry state to its exit state: the same one for all
entries if a word starts in it, else the dead state of the run that goes through, as no compiled
word is as long as a chunk. The maps are composed in a parallel prefix scan of doubling steps,
which gives each chunk's entry state; from it the chunk's head, up to its first word start, is
run again.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cotengine.llm.blocks import blocks, rows, schema_of
from cotengine.llm.merge_rules import MergeRules
from cotengine.llm.word_bpe import KIND, LETTER, NUMBER, OTHER, Spans, WordBPE, byte_symbols, kept

_OUT = "doc_id long, n_bytes long, n_tokens long"
CHUNK, WIDTH, LONGEST = 512, 128, 48
#: States of the transducer in each Python worker, 0.5 kB each.
STATES = 100_000
_ROOT, _DEAD_LETTERS, _DEAD_OTHERS = range(3)
_UNKNOWN = -1 << 20
_SOLE, _RARE_NUMBER, _RARE_LETTER, _RARE_OTHER = 124, 125, 126, 127


class CountingTransducer:
    def __init__(self, bpe: WordBPE, states: int = STATES):
        self.bpe, self.most = bpe, states
        self.symbol = np.array([0, _RARE_LETTER, _RARE_NUMBER, _RARE_OTHER], np.uint8)[KIND]
        own = [c for c in map(chr, range(0x21, 0x100)) if c.lower() == c and not 0x7F <= ord(c) <= 0xA0 and c != "\u00ad"]
        own.sort(key=lambda c: (ord(c) >= 0x80 and KIND[ord(c)] != LETTER, ord(c)))
        self.symbol_kind = np.zeros(WIDTH, np.uint8)
        self.symbol_kind[[_SOLE, _RARE_NUMBER, _RARE_LETTER, _RARE_OTHER]] = NUMBER, NUMBER, LETTER, OTHER
        for i, c in enumerate(own[: _SOLE - 1], 1):
            self.symbol[ord(c)], self.symbol_kind[i] = i, KIND[ord(c)]
        self.next = np.zeros((states, WIDTH), np.int32)
        self.rules = MergeRules(bpe.path)
        self.inside = np.zeros(states, np.int32)  # tokens of the prefix; a transition emits the difference of two states
        self.leave = np.full(states, _UNKNOWN, np.int32)  # what leaving the word here emits; unknown: the word has to be looked up
        self.run_of = np.full(states, 2, np.int8)  # run that a state is within: letters, other signs, none that goes on
        self.run_of[[_DEAD_LETTERS, _DEAD_OTHERS]] = 0, 1
        self.n, self.made = 3, Counter()
        start = np.zeros(WIDTH, np.int32)
        for s in range(1, WIDTH):
            if s in (_RARE_LETTER, _RARE_OTHER, _RARE_NUMBER, _SOLE) or not self.symbol_kind[s]:
                start[s] = _DEAD_LETTERS if self.symbol_kind[s] == LETTER else _DEAD_OTHERS if self.symbol_kind[s] == OTHER else _ROOT
            else:
                start[s], self.n = self.n, self.n + 1
        self.start = start
        self.next[_ROOT] = start
        for state, kind in ((_DEAD_LETTERS, LETTER), (_DEAD_OTHERS, OTHER), *((int(start[s]), int(self.symbol_kind[s])) for s in range(1, WIDTH) if start[s] > 2)):
            self._row(state, kind)

    def _row(self, state: int, kind: int) -> None:
        """A state's transitions before any word goes on from it: within its kind to the dead state, else a new word."""
        self.next[state] = self.start
        self.run_of[state] = 0 if kind == LETTER else 1 if kind == OTHER else 2
        if kind != NUMBER:
            self.next[state, self.symbol_kind == kind] = _DEAD_LETTERS if kind == LETTER else _DEAD_OTHERS

    def compile(self, word: str, check: int) -> None:
        """Add the states of a word, annotated from the merges; ``check``: the library's count of the word."""
        if len(word) > LONGEST or self.n + len(word) > self.most:
            return
        symbols = self.symbol[np.array([*map(ord, word)])].tolist()
        if any(s >= _SOLE for s in symbols):
            return
        counted = self.rules.counts(byte_symbols(word))
        if counted is None or counted[1] != check:
            return
        many, whole = counted
        at, kind, place = int(self.start[symbols[0]]), int(self.symbol_kind[symbols[0]]), len(word[0].encode())
        self.inside[at] = many[place]
        for s, c in zip(symbols[1:], word[1:]):
            then = int(self.next[at, s])
            if then <= 2:
                then, self.n = self.n, self.n + 1
                self._row(then, kind)
                self.next[at, s] = then
            at, place = then, place + len(c.encode())
            self.inside[at] = many[place]
        self.leave[at] = whole - many[place]

    def run(self, symbols: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """The state after each symbol. starts: where a word or a blank begins."""
        n = len(symbols)
        chunks = -(-n // CHUNK)
        grid = np.zeros(chunks * CHUNK, np.int64)
        grid[:n] = symbols
        grid = np.ascontiguousarray(grid.reshape(chunks, CHUNK).T)
        fresh = np.ones(chunks * CHUNK, bool)
        fresh[:n] = starts
        fresh = fresh.reshape(chunks, CHUNK)
        first = np.where(fresh.any(1), fresh.argmax(1), CHUNK)
        table, seen = self.next.reshape(-1), np.empty((CHUNK, chunks), np.int32)
        state = np.zeros(chunks, np.int64)
        for place in range(CHUNK):
            state = table[(state << 7) | grid[place]]
            seen[place] = state
            state = state.astype(np.int64)
        leaves = seen[-1].astype(np.int64)
        maps = np.repeat(leaves[:, None], 3, 1)  # exit state of each chunk by the run that it is entered within
        maps[first == CHUNK, :2] = _DEAD_LETTERS, _DEAD_OTHERS
        leaves = self.composed(maps)[:, 2]  # the first chunk is entered within no run
        again = np.flatnonzero(first > 0)
        again = again[again > 0]
        again = again[np.argsort(-first[again], kind="stable")]
        state, lengths = leaves[again - 1], first[again]
        for place in range(int(lengths[0]) if len(again) else 0):
            live = int(np.searchsorted(-lengths, -place, "left"))
            state = table[(state[:live] << 7) | grid[place, again[:live]]].astype(np.int64)
            seen[place, again[:live]] = state
        return seen.T.reshape(-1)[:n]

    def composed(self, maps: np.ndarray) -> np.ndarray:
        """Row i: all maps up to the i-th, one after the other. Composition is associative, so a scan of doubling steps gives all."""
        out, d = maps.copy(), 1
        while d < len(out):
            out[d:] = np.take_along_axis(out[d:], self.run_of[out[:-d]].astype(np.int64), 1)
            d *= 2
        return out

    def totals(self, texts: list[str]) -> np.ndarray:
        """Tokens of each plain text."""
        spans = Spans([t.lower() for t in texts])
        symbols = self.symbol[spans.code]
        for at, word in spans.short:
            symbols[at : at + len(word)] = _SOLE  # a word of its own, looked up below
        state = self.run(symbols, spans.starts)
        last = state[spans.ends - 1]
        counts, left = self.inside[last], self.leave[last]
        missed = np.flatnonzero(left == _UNKNOWN)
        counts += left
        if len(missed):
            words = spans.words(missed)
            try:
                counts[missed] = [len(self.bpe.memo[w]) >> 2 for w in words]
            except KeyError:
                self.bpe.learn(words)
                counts[missed] = [len(self.bpe.memo[w]) >> 2 for w in words]
            self._grow(words)
        return np.diff(np.concatenate([[0], np.cumsum(counts, dtype=np.int64)])[spans.upto], prepend=0)

    def _grow(self, words: list[str]) -> None:
        if self.n + LONGEST >= self.most:
            return
        self.made.update(words)
        for w, c in self.made.most_common(4000):
            if c < 3 or self.n + LONGEST >= self.most:
                break
            self.compile(w, len(self.bpe.memo[w]) >> 2) if w in self.bpe.memo else None
        self.made.clear()


def count_tokens(docs: DataFrame, *, tokenizer: str, doc_id: str = "doc_id", text: str = "text", limit: int = 2048, states: int = STATES) -> DataFrame:
    """doc_id, n_bytes (UTF-8), n_tokens, over_limit (n_tokens > limit) of every row.

    Counts equal the tokenizer library's, without begin, end or other added tokens. A null
    text counts as empty: 0 bytes, 0 tokens. One row out for each row in, repeated or with a
    null id alike; other columns are ignored. A map over rows: no shuffle, and work arrays
    are bounded by block whatever a text's length.
    """
    schema = schema_of(_OUT)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine = kept(CountingTransducer, tokenizer, states)
        bpe = machine.bpe
        for batch in blocks(batches, "text"):
            texts = [t or "" for t in batch.column("text").to_pylist()]
            plain = [bpe.plain(t) for t in texts]
            tokens = np.zeros(len(texts), np.int64)
            tokens[np.flatnonzero(plain)] = machine.totals([t for t, p in zip(texts, plain) if p])
            for i in np.flatnonzero(~np.array(plain, bool)).tolist():
                tokens[i] = len(bpe.whole(texts[i]))
            yield rows(schema, batch.column("doc_id"), pa.compute.fill_null(pa.compute.binary_length(batch.column("text")), 0).cast(pa.int64()), tokens)

    counted = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text")).mapInArrow(count, _OUT)
    return counted.withColumn("over_limit", F.col("n_tokens") > limit)
