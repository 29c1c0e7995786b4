"""What token counting and packing share: a word-ended BPE applied word by word.

The tokenizer file's own library stays the authority: every word met for the first time is
encoded by it, and any text that holds a special string, or a character outside a set whose
normalisation is known to be plain lower-casing, is given to it whole.
"""

from __future__ import annotations

import os
import re
import unicodedata
from struct import pack

import numpy as np

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # a task has one core

#: Characters whose normalisation by the tokenizer (NFC, blanks to a space, lower case) is ``str.lower`` alone.
SAFE = "\t\n\r" + "".join(map(chr, [*range(0x20, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x250), 0x2013, 0x2014, 0x2018, 0x2019, 0x201C, 0x201D, 0x2026, 0x20AC]))
_UNSAFE = re.compile("[^" + re.escape(SAFE) + "]")
_LOWERED = sorted(set(SAFE) | set(SAFE.lower()))
LETTERS = [c for c in _LOWERED if unicodedata.category(c)[0] == "L"]
NUMBERS = [c for c in _LOWERED if unicodedata.category(c)[0] == "N"]
BLANKS = "\t\n\r "
#: The tokenizer's contractions.
CONTRACTIONS = ("'s", "'t", "'re", "'ve", "'m", "'ll", "'d")
WORDS = re.compile(f"'(?:s|t|re|ve|m|ll|d)|[{''.join(LETTERS)}]+|[{''.join(NUMBERS)}]|[^{BLANKS}{''.join(LETTERS + NUMBERS)}]+")
#: Words whose encoding a Python worker remembers before a new generation starts (two are held).
REMEMBERED = 300_000


SPACE, LETTER, NUMBER, OTHER = range(4)
#: Kind of each character, by code point.
KIND = np.full(max(map(ord, _LOWERED)) + 1, OTHER, np.uint8)
for _chars, _kind in ((BLANKS, SPACE), (LETTERS, LETTER), (NUMBERS, NUMBER)):
    KIND[[*map(ord, _chars)]] = _kind


class Spans:
    """Words of lowered plain texts, found by comparing the kinds of neighbouring characters."""

    def __init__(self, texts: list[str]):
        self.joined = "\n".join(texts) + "\n"
        self.code = np.frombuffer(self.joined.encode("utf-32-le"), "<u4")
        self.kind = kind = KIND[self.code]
        self.starts = np.ones(len(kind), bool)  # where a word or a blank begins
        self.starts[1:] = (kind[1:] != kind[:-1]) | (kind[1:] == NUMBER) | (kind[1:] == SPACE)
        self.short: list[tuple[int, str]] = []  # contractions: place, string
        if "'" in self.joined:
            for i in np.flatnonzero((self.code == 39) & self.starts).tolist():
                tail = self.joined[i + 1 : i + 3]
                found = "'" + (tail[0] if tail[0] in "stmd" else tail)
                if found in CONTRACTIONS:
                    self.short.append((i, found))
                    self.starts[i + 1 : i + len(found)] = False
                    self.starts[i + len(found)] = True
        bounds = np.flatnonzero(self.starts)
        word = kind[bounds] != SPACE
        self.opens, self.ends = bounds[word], np.append(bounds[1:], len(kind))[word]
        stops = np.cumsum([len(t) + 1 for t in texts]) if texts else np.zeros(0, np.int64)
        self.upto = np.searchsorted(self.opens, stops)  # words up to the end of each text

    def words(self, which: np.ndarray) -> list[str]:
        return [self.joined[a:b] for a, b in zip(self.opens[which].tolist(), self.ends[which].tolist())]


def _byte_alphabet() -> dict[int, int]:
    """The byte-level alphabet: printable bytes stand for themselves, the others for code points from 256 on."""
    printable = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    rest = iter(range(256, 512))
    return {b: b if b in printable else next(rest) for b in range(256)}


_BYTES = _byte_alphabet()


def byte_symbols(word: str) -> str:
    """A word in the byte alphabet, one character for each of its bytes."""
    return word if word.isascii() else word.encode().decode("latin-1").translate(_BYTES)


class WordBPE:
    """One per Python worker. ``path``: a tokenizers file of the kind described above."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.path = path
        self.library = Tokenizer.from_file(path)
        self.model = self.library.model
        self.library.no_truncation()
        self.library.no_padding()
        self.special = [t.content for t in self.library.get_added_tokens_decoder().values()]
        self.memo: dict[str, bytes] = {}
        self.before: dict[str, bytes] = {}

    def plain(self, text: str) -> bool:
        """Whether the text can be taken word by word."""
        return not _UNSAFE.search(text) and not any(s in text for s in self.special)

    def whole(self, text: str) -> np.ndarray:
        return np.array(self.library.encode(text, add_special_tokens=False).ids, np.uint32)

    def learn(self, words) -> None:
        """Remember the ids of all ``words`` (little-endian unsigned 32-bit) that are new."""
        new = [w for w in set(words) if w not in self.memo]
        if len(self.memo) + len(new) > REMEMBERED:
            self.before, self.memo = self.memo, {}
            new = list(set(words))
        fresh = []
        for w in new:
            known = self.before.get(w)
            if known is None:
                fresh.append(w)
            else:
                self.memo[w] = known
        tokenize = self.model.tokenize
        for w in fresh:
            self.memo[w] = pack("<%dI" % len(found := tokenize(byte_symbols(w))), *[t.id for t in found])

    def ids(self, text: str) -> bytes:
        """All ids of a text as little-endian unsigned 32-bit values, word by word."""
        if not self.plain(text):
            return self.whole(text).astype("<u4").tobytes()
        words = WORDS.findall(text.lower())
        try:
            return b"".join(map(self.memo.__getitem__, words))
        except KeyError:
            self.learn(words)
            return b"".join(map(self.memo.__getitem__, words))


_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 1 << 64)
#: Words the hashed table holds, and the longest word it takes (others go through the memory of words).
TABLE_BITS, TABLE_LONGEST = 21, 32


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    out[0] = 1
    return np.cumprod(out, dtype=np.uint64)


class WordTable:
    """Ids of many words at once: 64-bit polynomial word hashes looked up in an open-addressed table."""

    def __init__(self, bpe: WordBPE):
        self.bpe = bpe
        self.up, self.down = _powers(_BASE, 1 << 16), _powers(_INVERSE, 1 << 16)
        self._empty()

    def _empty(self) -> None:
        self.keys = np.zeros(1 << TABLE_BITS, np.uint64)
        self.slot = np.zeros(1 << TABLE_BITS, np.int32)
        self.n = 0
        self.at, self.length = np.zeros(1 << 16, np.int64), np.zeros(1 << 16, np.int32)
        self.store = np.zeros(1 << 18, np.uint32)
        self.used = 0

    def _hashes(self, spans: Spans) -> np.ndarray:
        n = len(spans.code)
        if n + 1 > len(self.up):
            self.up, self.down = _powers(_BASE, 2 * n), _powers(_INVERSE, 2 * n)
        sums = np.zeros(n + 1, np.uint64)
        np.cumsum((spans.code.astype(np.uint64) + np.uint64(1)) * self.up[:n], out=sums[1:])
        h = (sums[spans.ends] - sums[spans.opens]) * self.down[spans.opens]
        h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9) + (spans.ends - spans.opens).astype(np.uint64)
        h ^= h >> np.uint64(32)
        return np.where(h == 0, np.uint64(1), h)

    def _find(self, h: np.ndarray) -> np.ndarray:
        """Slot of each hash, -1 where it isn't held."""
        mask = np.int64((1 << TABLE_BITS) - 1)
        place = (h >> np.uint64(64 - TABLE_BITS)).astype(np.int64)
        held = self.keys[place]
        out = np.where(held == h, self.slot[place], -1)
        go = np.flatnonzero((held != h) & (held != 0))
        while len(go):
            place[go] = (place[go] + 1) & mask
            held = self.keys[place[go]]
            same = held == h[go]
            out[go[same]] = self.slot[place[go[same]]]
            go = go[~same & (held != 0)]
        return out

    def _insert(self, h: np.ndarray, words: list[str]) -> None:
        self.bpe.learn(words)
        raw = [self.bpe.memo[w] for w in words]
        length = np.array([len(r) >> 2 for r in raw], np.int32)
        new = np.frombuffer(b"".join(raw), "<u4")
        while self.n + len(h) > len(self.at):
            self.at, self.length = np.resize(self.at, 2 * len(self.at)), np.resize(self.length, 2 * len(self.length))
        while self.used + len(new) > len(self.store):
            self.store = np.resize(self.store, 2 * len(self.store))
        self.at[self.n : self.n + len(h)] = self.used + np.cumsum(length) - length
        self.length[self.n : self.n + len(h)] = length
        self.store[self.used : self.used + len(new)] = new
        mask = (1 << TABLE_BITS) - 1
        place = (h >> np.uint64(64 - TABLE_BITS)).astype(np.int64)
        todo = np.arange(len(h))
        while len(todo):
            free = todo[self.keys[place[todo]] == 0]
            _, one = np.unique(place[free], return_index=True)
            put = free[one]
            self.keys[place[put]], self.slot[place[put]] = h[put], self.n + put
            left = np.ones(len(h), bool)
            left[put] = False
            todo = todo[left[todo]]
            place[todo] = np.where(self.keys[place[todo]] != 0, (place[todo] + 1) & mask, place[todo])
        self.n += len(h)
        self.used += len(new)

    def ids(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of plain texts end to end, and how many each has."""
        spans = Spans([t.lower() for t in texts])
        long = np.flatnonzero(spans.ends - spans.opens > TABLE_LONGEST)
        h = self._hashes(spans)
        slot = self._find(h)
        slot[long] = -2
        missed = np.flatnonzero(slot == -1)
        if len(missed):
            new, first = np.unique(h[missed], return_index=True)
            if self.n + len(new) > 3 << (TABLE_BITS - 2):
                self._empty()
                missed = np.flatnonzero(slot != -2)
                new, first = np.unique(h[missed], return_index=True)
            self._insert(new, spans.words(missed[first]))
            slot[missed] = self._find(h[missed])
        length, at, store = self.length[slot], self.at[slot], self.store
        if len(long):
            words = spans.words(long)
            self.bpe.learn(words)
            raw = [np.frombuffer(self.bpe.memo[w], "<u4") for w in words]
            length[long] = [len(r) for r in raw]
            at[long] = self.used + np.cumsum(length[long]) - length[long]
            store = np.concatenate([self.store[: self.used], *raw])
        upto = np.concatenate([[0], np.cumsum(length, dtype=np.int64)])
        ids = store[np.repeat(at - upto[:-1], length) + np.arange(upto[-1])]
        return ids, np.diff(upto[spans.upto], prepend=0)


_KEPT: dict = {}


def kept(kind, path: str, *more):
    """One object of a kind and tokenizer in each Python worker, kept over its tasks."""
    key = (kind, path, *more)
    if key not in _KEPT:
        _KEPT[key] = kind(WordBPE(path), *more)
    return _KEPT[key]
