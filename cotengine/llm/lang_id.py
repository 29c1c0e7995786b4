"""Language identification by bit-sliced Bloom filters of byte n-grams.

All languages share the filter's places; a place holds one bit per language, so the AND of
an n-gram's places is the set of languages whose filter holds it. A text's count for a
language is the number of its n-grams with that bit, corrected for the false positives that
the filter's fill makes likely, and the greatest corrected share decides.

Training takes a bounded sample of labelled texts for each language, chosen by hash, and puts
in the n-grams that at least ``least`` of its texts hold, the commonest first, up to a fixed
number. Scoring reads every whole text and moves nothing.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cotengine.llm.blocks import blocks, rows, schema_of, utf8
from cotengine.llm.store import materialize
from cotengine.llm.words import mixed

#: Bounds of the fitted model: texts and n-grams of each language, languages of a filter word, places of the filter.
SAMPLE, GRAMS, LANGUAGES, PLACES_BITS = 2000, 40_000, 64, 20
SIZE, HASHES = 5, 3
_LETTERS = np.zeros(256, bool)
_LETTERS[[*range(65, 91), *range(97, 123), *range(128, 256)]] = True


def text_grams(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of the ``SIZE``-byte n-grams of each lowered text, and where each text's begin.

    What is no letter counts as a blank, runs of blanks as one; n-grams span words but not texts.
    """
    data, starts = utf8(pa.array([" " + t.lower() + " " for t in texts], pa.large_string()))
    letter = _LETTERS[data]
    byte = np.where(letter, data, 32).astype(np.uint64)
    text = np.repeat(np.arange(len(texts)), np.diff(starts))
    keep = letter.copy()
    keep[1:] |= letter[:-1] | (text[1:] != text[:-1])
    keep[:1] = True
    byte, text = byte[keep], text[keep]
    n = max(0, len(byte) - SIZE + 1)
    h = np.zeros(n, np.uint64)
    for i in range(SIZE):
        h = h << np.uint64(8) | byte[i : i + n]
    inside = text[:n] == text[SIZE - 1 :] if n else np.zeros(0, bool)
    return mixed(h[inside]), np.searchsorted(text[:n][inside], np.arange(len(texts) + 1))


def _places(h: np.ndarray, bits: int) -> list[np.ndarray]:
    return [(h >> np.uint64(i * 21) & np.uint64((1 << bits) - 1)).astype(np.int64) for i in range(HASHES)]


class BitSlicedFilters:
    def __init__(self, grams: dict[str, np.ndarray], bits: int = PLACES_BITS):
        """grams: the n-gram hashes of each language. A place has one word per ``LANGUAGES`` languages."""
        self.languages = sorted(grams)
        self.bits = bits
        wide = next(t for n, t in ((8, np.uint8), (16, np.uint16), (32, np.uint32), (64, np.uint64)) if n >= min(LANGUAGES, len(self.languages)))
        self.masks = [np.zeros(1 << bits, wide) for _ in range(0, len(self.languages), LANGUAGES)]
        for i, lang in enumerate(self.languages):
            for place in _places(grams[lang], bits):
                self.masks[i // LANGUAGES][place] |= wide(1 << i % LANGUAGES)
        self.false = np.array([self._bit(self.masks[i // LANGUAGES], i).mean() ** HASHES for i in range(len(self.languages))])

    @staticmethod
    def _bit(words: np.ndarray, i: int) -> np.ndarray:
        return (words >> words.dtype.type(i % LANGUAGES)) & words.dtype.type(1)

    def holding(self, h: np.ndarray) -> list[np.ndarray]:
        """Masks of the languages whose filter holds each n-gram."""
        places, out = _places(h, self.bits), []
        for masks in self.masks:
            found = masks[places[0]]
            for place in places[1:]:
                found &= masks[place]
            out.append(found)
        return out

    def shares(self, h: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """Corrected share of each text's n-grams in each language."""
        masks, many = self.holding(h), np.maximum(1, np.diff(starts))
        out = np.zeros((len(starts) - 1, len(self.languages)))
        for i in range(len(self.languages)):
            hits = np.concatenate([[0], np.cumsum(self._bit(masks[i // LANGUAGES], i), dtype=np.int64)])
            raw = (hits[starts[1:]] - hits[starts[:-1]]) / many
            out[:, i] = np.clip((raw - self.false[i]) / max(1e-9, 1 - self.false[i]), 0, 1)
        return out


def fit(docs: DataFrame, *, sample: int = SAMPLE, grams: int = GRAMS, least: int = 2, lang: str = "lang", text: str = "text") -> BitSlicedFilters | None:
    """Filters from labelled rows (null languages and texts left out); None where there are none."""
    known = docs.where(F.col(lang).isNotNull() & F.col(text).isNotNull()).select(F.col(lang).alias("lang"), F.col(text).alias("text"))
    place = F.shiftrightunsigned("h", 1)
    texts = materialize(known.select("lang", F.xxhash64("text").alias("h")).distinct(), "labelled-texts")
    # Counts first: a hash threshold lets about the sample through, and only that little is ranked.
    many = texts.groupBy("lang").agg(F.count("*").alias("n")).withColumn("most", F.lit(float(1 << 63)) * F.least(F.lit(1.0), (1.2 * sample + 100) / F.col("n"))).drop("n")
    many = materialize(many, "languages")
    names = sorted(r.lang for r in many.select("lang").collect())
    if not names:
        return None
    near = texts.join(F.broadcast(many), "lang").where(place < F.col("most"))  # a row for each language
    chosen = near.withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy(place, "h"))).where(F.col("r") <= sample).select("lang", "h")
    by = F.broadcast(materialize(chosen, "sampled-texts"))  # at most ``sample`` rows of 64-bit hashes a language
    picked = known.withColumn("h", F.xxhash64("text")).join(by, ["lang", "h"], "left_semi").dropDuplicates(["lang", "h"])
    ddl = "lang string, gram long, n long"
    schema = schema_of(ddl)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, "text"):
            h, starts = text_grams(batch.column("text").to_pylist())
            langs = np.array(batch.column("lang").to_pylist(), object)
            own = np.repeat(np.arange(len(langs)), np.diff(starts))
            order = np.lexsort((h, own))
            own, h = own[order], h[order]
            once = np.ones(len(h), bool)
            once[1:] = (h[1:] != h[:-1]) | (own[1:] != own[:-1])
            own, h = own[once], h[once]
            for lang in sorted(set(langs.tolist())):
                found, n = np.unique(h[(langs == lang)[own]], return_counts=True)
                yield rows(schema, [lang] * len(found), found.view(np.int64), n)

    counted = materialize(picked.select("lang", "text").mapInArrow(count, ddl).groupBy("lang", "gram").agg(F.sum("n").alias("n")).where(F.col("n") >= least), "gram-counts")
    # The count that the least common n-gram taken has, from each language's histogram of counts (at most ``sample`` rows).
    histogram = counted.groupBy("lang", "n").agg(F.count("*").alias("k")).withColumn("above", F.sum("k").over(Window.partitionBy("lang").orderBy(F.col("n").desc())) - F.col("k"))
    last = histogram.where(F.col("above") < grams).groupBy("lang").agg(F.min("n").alias("last"), F.max_by("k", -F.col("n")).alias("k"), F.max("above").alias("above"))
    part = F.least(F.lit(1.0), (1.2 * (grams - F.col("above")) + 100) / F.col("k"))
    kept = counted.join(F.broadcast(materialize(last, "least-counts")), "lang").where((F.col("n") > F.col("last")) | ((F.col("n") == F.col("last")) & (F.shiftrightunsigned("gram", 1) < F.lit(float(1 << 63)) * part)))
    top = kept.select("lang", "gram", "n").toArrow()  # about ``grams`` rows a language
    lang_of, values, counts = np.array(top.column("lang").to_pylist(), object), top.column("gram").to_numpy().view(np.uint64), top.column("n").to_numpy()
    model = {}
    for name in names:
        mine = np.flatnonzero(lang_of == name)
        model[name] = values[mine[np.lexsort((values[mine], -counts[mine]))[:grams]]]
    return BitSlicedFilters(model)


def training_rows(docs: DataFrame, *, doc_id: str = "doc_id") -> Column:
    """Which rows may be learned from: those whose crc32(id as text) mod 4 is not 2 (null ids may not)."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 4 != 2, F.lit(False))


def identify(docs: DataFrame, model: BitSlicedFilters | None, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, lang_pred, score of every row.

    ``und`` with score 0 for texts that are null or have no letter, and where there is no
    model. The score is the best language's part of the sum of all corrected shares; with no
    known n-gram at all the first language by name is given, at 1 / number of languages. Ties
    go to the first language by name. Repeated rows are judged alike; other columns are ignored.
    """
    ddl = "doc_id long, lang_pred string, score double"
    schema = schema_of(ddl)

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, "text"):
            texts = [t or "" for t in batch.column("text").to_pylist()]
            if model is None:
                yield rows(schema, batch.column("doc_id"), ["und"] * len(texts), [0.0] * len(texts))
                continue
            shares = model.shares(*text_grams(texts))
            best = shares.argmax(1)
            total = shares.sum(1)
            score = np.where(total > 0, shares[np.arange(len(best)), best] / np.where(total > 0, total, 1), 1 / len(model.languages))
            letters = np.array([any(map(str.isalpha, t)) for t in texts], bool)
            names = [model.languages[i] if x else "und" for i, x in zip(best.tolist(), letters.tolist())]
            yield rows(schema, batch.column("doc_id"), names, np.where(letters, score, 0.0))

    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text")).mapInArrow(judge, ddl)
