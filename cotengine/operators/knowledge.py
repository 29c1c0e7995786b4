"""Knowledge base: pages to text, and the fluency, usefulness and subject filter."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cotengine.functions.text import let, tokens

#: Some of the commonest words of each language.
STOP = {"en": ["the", "of", "and", "to", "in", "is", "that", "for", "with", "was"], "fr": ["le", "la", "de", "et", "les", "des", "du", "un", "que", "dans"], "de": ["der", "die", "und", "das", "den", "von", "zu", "mit", "ist", "ein"], "es": ["el", "de", "que", "los", "se", "las", "por", "con", "para", "del"]}
DROPPED = r"(?is)<script\b.*?</script>|<style\b.*?</style>|<nav\b.*?</nav>|<!--.*?-->"


def page_text(html: Column) -> Column:
    """Text of a page: scripts, styles, navigation and comments dropped, tags to blanks, common entities decoded."""
    out = F.regexp_replace(html, DROPPED, " ")
    out = F.regexp_replace(out, r"(?s)<[^>]*>", " ")
    for entity, char in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&")):
        out = F.replace(out, F.lit(entity), F.lit(char))
    return F.trim(F.regexp_replace(out, r"\s+", " "))


def parse_pages(pages: DataFrame) -> DataFrame:
    title = F.trim(F.regexp_extract("html", r"(?is)<title[^>]*>(.*?)</title>", 1))
    return pages.select("page_id", "url", title.alias("title"), page_text(F.col("html")).alias("text"))


def _among(words: list[str]):
    return lambda w: w.isin(words)


def scored(docs: DataFrame) -> DataFrame:
    """fluency (share of stop words of the best language), usefulness (distinct share of tokens), subject (that language), margin."""
    toks = docs.select("*", tokens(F.col("text")).alias("_t"))
    n = F.greatest(F.size("_t"), F.lit(1))
    hits = [(F.size(F.filter("_t", _among(s))) / n).alias(f"_{lang}") for lang, s in sorted(STOP.items())]
    counted = toks.select("*", *hits)
    named = F.array(*[F.struct(F.col(f"_{lang}").alias("share"), (-F.lit(i)).alias("order"), F.lit(lang).alias("lang")) for i, lang in enumerate(sorted(STOP))])
    ranked = counted.withColumn("_r", F.sort_array(named, asc=False))
    out = ranked.withColumns({"fluency": F.col("_r")[0]["share"], "subject": F.col("_r")[0]["lang"], "margin": F.col("_r")[0]["share"] - F.col("_r")[1]["share"], "usefulness": let(F.col("_t"), lambda t: F.when(F.size(t) > 0, F.size(F.array_distinct(t)) / F.size(t)).otherwise(0.0))})
    return out.drop("_t", "_r", *[f"_{x}" for x in STOP])


def quality_filter(docs: DataFrame, *, fluency: float = 0.05, usefulness: float = 0.2, margin: float = 0.02) -> DataFrame:
    return docs.where((F.col("fluency") >= fluency) & (F.col("usefulness") >= usefulness) & (F.col("margin") >= margin))
