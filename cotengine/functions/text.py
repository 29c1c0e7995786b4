"""Tokens, n-grams, repetition, boxed answers, answer normalisation as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

TOKEN = r"[\p{L}\p{N}]+"


def let(value: Column, body) -> Column:
    """``body`` of a value that is computed once a row, however often ``body`` names it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def normalize(text: Column) -> Column:
    """Lower case, runs of blanks as one, ends trimmed."""
    return F.trim(F.regexp_replace(F.lower(text), r"\s+", " "))


def tokens(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit(TOKEN), F.lit(0))


def token_count(text: Column) -> Column:
    return F.size(tokens(text))


def ngrams(toks: Column, n: int) -> Column:
    """Runs of n tokens joined by blanks; a shorter text has one of all its tokens, an empty one none."""
    return let(toks, lambda t: _runs(t, n))


def _runs(toks: Column, n: int) -> Column:
    runs = F.transform(F.sequence(F.lit(1), F.size(toks) - (n - 1)), lambda i: F.array_join(F.slice(toks, i, n), " "))
    return F.when(F.size(toks) >= n, runs).when(F.size(toks) > 0, F.array(F.array_join(toks, " "))).otherwise(F.array().cast("array<string>"))


def duplicate_ratio(grams: Column) -> Column:
    """Share of n-grams that repeat an earlier one; 0 without n-grams."""
    return let(grams, lambda g: F.when(F.size(g) > 0, 1 - F.size(F.array_distinct(g)) / F.size(g)).otherwise(0.0))


def repetition_ratio(text: Column, n: int = 3) -> Column:
    return duplicate_ratio(ngrams(tokens(text), n))


def boxed(text: Column) -> Column:
    """Content of the last ``\\boxed{…}`` without inner braces; null if there is none."""
    got = F.regexp_extract(text, r"(?s).*\\boxed\{([^{}]*)\}", 1)
    return F.when(F.length(got) > 0, got)


def boxes(text: Column) -> Column:
    return F.size(F.regexp_extract_all(text, F.lit(r"\\boxed\{[^{}]*\}"), F.lit(0)))


def option_letter(text: Column) -> Column:
    """The option A to J in the box, with or without brackets or a full stop."""
    got = F.upper(F.regexp_extract(boxed(text), r"^\s*\(?([A-Ja-j])\)?\.?\s*$", 1))
    return F.when(F.length(got) > 0, got)


def canonical_answer(answer: Column) -> Column:
    """Answers as compared: box stripped, blanks, commas and dollars gone, plain numbers and fractions as numbers."""
    inner = F.coalesce(boxed(answer), answer)
    bare = F.lower(F.regexp_replace(inner, r"[\s,$]", ""))
    return let(F.regexp_replace(bare, r"^\\frac\{(-?\d+)\}\{(\d+)\}$", "$1/$2"), _number_or_text)


def _number_or_text(bare: Column) -> Column:
    top, bottom = F.regexp_extract(bare, r"^(-?\d+)/(\d+)$", 1), F.regexp_extract(bare, r"^(-?\d+)/(\d+)$", 2)
    number = F.when(F.length(top) > 0, F.try_divide(top.try_cast("double"), bottom.try_cast("double"))).when(bare.rlike(r"^-?\d+(\.\d+)?$"), bare.try_cast("double"))
    return let(number, lambda x: F.when(x.isNotNull(), F.format_string("%.6f", x)).otherwise(bare))
