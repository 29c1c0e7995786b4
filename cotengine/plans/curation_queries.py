"""Registered queries of the curation stage, each beside its SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cotengine.functions.text import canonical_answer, repetition_ratio, token_count
from cotengine.operators import annotate as an
from cotengine.operators import decontam, dedup, distill, sampling
from cotengine.plans.curate import CurationConfig, curate, source_distribution
from cotengine.sources.providers import lexical_annotator, option, option_teacher
from cotengine.sources.tables import collect_sources, spread, table

QUERIES: dict = {}
ORACLES: dict = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


# --- SQL parts -----------------------------------------------------------------------------


def sql_tokens(c: str = "text") -> str:
    return f"regexp_extract_all(lower(coalesce({c}, '')), '[\\p{{L}}\\p{{N}}]+')"


def sql_grams(n: int, t: str = "t") -> str:
    return f"CASE WHEN len({t}) >= {n} THEN list_transform(range(1, len({t}) - {n} + 2), lambda i: array_to_string(list_slice({t}, i, i + {n} - 1), ' ')) WHEN len({t}) > 0 THEN [array_to_string({t}, ' ')] ELSE []::VARCHAR[] END"


def sql_h8(s: str) -> str:
    return f"('0x' || substr(md5({s}), 1, 8))::BIGINT"


def sql_unit(key: str, seed) -> str:
    return f"({sql_h8(f"'{seed}:' || {key}")} / 4294967296.0::DOUBLE)"


def sql_ratio() -> str:
    """Share of repeated n-grams of a column ``g`` of n-grams."""
    return "(CASE WHEN len(g) > 0 THEN 1 - len(list_distinct(g))::DOUBLE / len(g) ELSE 0.0 END)"


def sql_with_grams(source: str, n: int = 3, c: str = "text") -> str:
    """A relation with its tokens ``t`` and n-grams ``g``."""
    return f"(SELECT *, {sql_grams(n)} AS g FROM (SELECT *, {sql_tokens(c)} AS t FROM {source}))"


def sql_bands(source: str, key: str = "doc_id", text: str = "text", tag: str = "") -> str:
    """CTEs sig<tag>(key, i, v) and bands<tag>(key, band, bkey) of a source relation."""
    return f"""sh{tag} AS (SELECT {key}, unnest(list_distinct({sql_grams(3)})) AS g FROM (SELECT {key}, {sql_tokens(text)} AS t FROM {source})),
        gh{tag} AS (SELECT g, {sql_h8('g')} % 2147483647 AS h FROM (SELECT DISTINCT g FROM sh{tag})),
        seeds{tag} AS (SELECT i, 1 + {sql_h8("'42:' || i || ':a'")} % 2147483646 AS a, {sql_h8("'42:' || i || ':b'")} % 2147483647 AS b FROM range(240) r(i)),
        sig{tag} AS (SELECT {key}, i, min((a * h + b) % 2147483647) AS v FROM sh{tag} JOIN gh{tag} USING (g), seeds{tag} GROUP BY ALL),
        bands{tag} AS (SELECT {key}, CAST(i // 10 AS INTEGER) AS band, md5(string_agg(v::VARCHAR, ',' ORDER BY i)) AS bkey FROM sig{tag} GROUP BY {key}, i // 10)"""


SQL_MARKS = "marks AS (SELECT doc_id, min(quality) AS q, max(toxic) AS x FROM labels GROUP BY doc_id)"
SQL_PRIO = "CASE WHEN q = 1 AND x = 0 THEN 0 WHEN q = 1 THEN 1 WHEN q IS NULL THEN 2 ELSE 3 END"
SQL_POOL = f"{SQL_MARKS}, pool AS (SELECT d.*, q, x, {SQL_PRIO} AS prio FROM documents d LEFT JOIN marks USING (doc_id))"
SQL_LEVEL = f"""CASE WHEN v < 0.4 THEN 'primary' WHEN v < 0.6 THEN 'secondary' WHEN v < 0.8 THEN 'undergraduate' ELSE 'graduate' END"""
SQL_ANNOTATED = f"""{SQL_MARKS}, annotated AS (SELECT doc_id, text, source, lang, q = 1 AS is_valid, x = 0 AS verifiable, lang AS discipline, {SQL_LEVEL} AS edu_level,
        (['numeric', 'expression', 'choice', 'text'])[CAST({sql_h8('text')} % 4 + 1 AS INTEGER)] AS answer_type
        FROM (SELECT *, CASE WHEN len(t) > 0 THEN len(list_distinct(t))::DOUBLE / len(t) ELSE 0.0 END AS v FROM (SELECT *, {sql_tokens()} AS t FROM documents LEFT JOIN marks USING (doc_id))))"""


def sql_exact(source: str, out: str) -> str:
    return f"{out} AS (SELECT * FROM {source} QUALIFY row_number() OVER (PARTITION BY md5(text) ORDER BY prio, doc_id) = 1)"


def sql_near(source: str, out: str, tag: str = "") -> str:
    return f"""{sql_bands(source, tag=tag)},
        ranked{tag} AS (SELECT b.doc_id, band, bkey, p.prio, first_value(b.doc_id) OVER (PARTITION BY band, bkey ORDER BY p.prio, b.doc_id) AS best FROM bands{tag} b JOIN {source} p USING (doc_id)),
        {out} AS (SELECT * FROM {source} WHERE doc_id NOT IN (SELECT doc_id FROM ranked{tag} WHERE doc_id <> best))"""


def sql_hits13(source: str, out: str, tag: str = "") -> str:
    return f"""bg{tag} AS (SELECT DISTINCT item_id, unnest({sql_grams(13)}) AS g FROM (SELECT item_id, {sql_tokens()} AS t FROM benchmark) WHERE len(t) >= 13),
        tg{tag} AS (SELECT doc_id, unnest({sql_grams(13)}) AS g FROM (SELECT doc_id, {sql_tokens()} AS t FROM {source}) WHERE len(t) >= 13),
        {out} AS (SELECT DISTINCT doc_id, item_id FROM tg{tag} JOIN bg{tag} USING (g))"""


def sql_option(salt: str) -> str:
    return f"(['A', 'B', 'C', 'D', 'E'])[CAST({sql_h8(f"doc_id || ':{salt}'")} % 5 + 1 AS INTEGER)]"


def sql_response(attempt: int) -> str:
    degenerate = sql_h8(f"doc_id || ':{attempt}:d'")
    return f"(CASE WHEN {degenerate} % 12 = 0 THEN repeat('and so on ', 60) ELSE text || ' ' END || 'so the answer is \\boxed{{' || {sql_option(f'{attempt}:t')} || '}}.')"


SQL_CHAIN = f"""{SQL_POOL}, valid AS (SELECT * FROM pool WHERE q IS NULL OR q = 1), {sql_exact('valid', 'exact')}, {sql_near('exact', 'nearest')},
        {sql_hits13('nearest', 'hits')}, {sql_bands('benchmark', 'item_id', tag='_e')},
        bucket_hits AS (SELECT DISTINCT doc_id FROM bands JOIN bands_e USING (band, bkey)),
        clean AS (SELECT * FROM nearest WHERE doc_id NOT IN (SELECT doc_id FROM hits) AND doc_id NOT IN (SELECT doc_id FROM bucket_hits)),
        responded AS (SELECT *, {sql_option('1:t')} AS answer, {sql_response(1)} AS response, CASE WHEN x = 0 THEN {sql_option('0:gold')} END AS gold FROM clean),
        kept AS (SELECT * EXCLUDE (t, g) FROM {sql_with_grams("responded", c='response')} WHERE {sql_ratio()} <= 0.2),
        final AS (SELECT * REPLACE ({sql_option('2:t')} AS answer, {sql_response(2)} AS response), true AS retried FROM kept WHERE answer <> gold UNION ALL SELECT *, false FROM kept WHERE coalesce(answer = gold, true)),
        verified AS (SELECT * EXCLUDE (t, g), CAST(len(t) AS INTEGER) AS n_tokens FROM {sql_with_grams("final", c='response')} WHERE {sql_ratio()} <= 0.2),
        th AS (SELECT quantile_cont(n_tokens, [0.2, 0.5, 0.75]) AS th FROM verified WHERE lang IN ('de', 'en', 'fr')),
        sampled AS (SELECT verified.* FROM verified, th WHERE lang NOT IN ('de', 'en', 'fr') OR {sql_unit('doc_id', 42)} < CASE WHEN n_tokens > th[3] THEN 1.0 WHEN n_tokens > th[2] THEN 0.5 WHEN n_tokens > th[1] THEN 0.1 ELSE 0.0 END)"""


SQL_CHAIN = SQL_CHAIN.replace(" AS (SELECT", " AS MATERIALIZED (SELECT")


def sql_rates(rates, t: str = "th") -> str:
    return f"CASE WHEN n_tokens > {t}[3] THEN {rates[3]} WHEN n_tokens > {t}[2] THEN {rates[2]} WHEN n_tokens > {t}[1] THEN {rates[1]} ELSE {rates[0]} END"


SQL_LENGTHS = f"lengths AS (SELECT doc_id, lang, source, CAST(len({sql_tokens()}) AS INTEGER) AS n_tokens FROM documents), th AS (SELECT quantile_cont(n_tokens, [0.2, 0.5, 0.75]) AS th FROM lengths)"

# --- collection and annotation ----------------------------------------------------------------


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spread(table(spark, sf_dir, "documents"))


def annotated(spark: SparkSession, sf_dir: str) -> DataFrame:
    return an.annotate(documents(spark, sf_dir), lexical_annotator(table(spark, sf_dir, "labels")))


def lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    return documents(spark, sf_dir).select("doc_id", "lang", "source", token_count(F.col("text")).alias("n_tokens"))


@query("SELECT pool, source, count(*) AS n FROM (SELECT 'web' AS pool, source FROM documents WHERE source NOT IN ('src3', 'src7') UNION ALL SELECT 'chat', role FROM conversations) GROUP BY ALL")
def collect_pool(spark, sf_dir):
    docs = documents(spark, sf_dir).where(~F.col("source").isin("src3", "src7")).select(F.col("doc_id").alias("sample_id"), "text", "source")
    chat = table(spark, sf_dir, "conversations").select(F.col("conv_id").alias("sample_id"), "text", F.col("role").alias("source"))
    pool = collect_sources({"web": docs, "chat": chat, "skipped": chat}, exclude=("skipped",))
    return pool.groupBy("pool", "source").agg(F.count("*").alias("n"))


@query(f"WITH {SQL_ANNOTATED} SELECT doc_id, is_valid, verifiable, discipline, edu_level, answer_type FROM annotated")
def annotate_lexical(spark, sf_dir):
    return annotated(spark, sf_dir).select("doc_id", "is_valid", "verifiable", "discipline", "edu_level", "answer_type")


@query(f"WITH {SQL_POOL} SELECT doc_id FROM pool WHERE q IS NULL OR q = 1")
def valid_only(spark, sf_dir):
    return an.keep_valid(annotated(spark, sf_dir)).select("doc_id")


@query(f"WITH {SQL_POOL} SELECT doc_id FROM pool WHERE q = 1 AND x = 0")
def rl_eligible(spark, sf_dir):
    return an.verifiable_subset(annotated(spark, sf_dir)).select("doc_id")


@query(f"WITH {SQL_ANNOTATED} SELECT doc_id FROM annotated WHERE is_valid AND verifiable AND answer_type = 'numeric'")
def numeric_only_pool(spark, sf_dir):
    return an.verifiable_subset(annotated(spark, sf_dir), ["numeric"]).select("doc_id")


# --- deduplication -----------------------------------------------------------------------------


@query("SELECT doc_id FROM documents QUALIFY row_number() OVER (PARTITION BY md5(text) ORDER BY doc_id) = 1")
def dedup_md5(spark, sf_dir):
    return dedup.dedup_exact(documents(spark, sf_dir).select("doc_id", "text")).select("doc_id")


@query(r"SELECT doc_id FROM documents QUALIFY row_number() OVER (PARTITION BY md5(trim(regexp_replace(lower(text), '\s+', ' ', 'g'))) ORDER BY doc_id) = 1")
def dedup_md5_normalized(spark, sf_dir):
    return dedup.dedup_exact(documents(spark, sf_dir).select("doc_id", "text"), normalized=True).select("doc_id")


@query(f"WITH {sql_bands('documents')} SELECT doc_id, md5(string_agg(v::VARCHAR, ',' ORDER BY i)) AS sig FROM sig GROUP BY doc_id")
def minhash_signature(spark, sf_dir):
    signed = dedup.minhash(documents(spark, sf_dir))
    return signed.select("doc_id", F.md5(F.array_join(F.transform("sig", lambda v: v.cast("string")), ",")).alias("sig"))


@query(f"WITH {SQL_POOL}, {sql_exact('(SELECT * REPLACE (0 AS prio) FROM pool)', 'exact')}, {sql_bands('exact')} SELECT doc_id, band, bkey FROM bands")
def minhash_bands(spark, sf_dir):
    exact = dedup.dedup_exact(documents(spark, sf_dir))
    return dedup.band_keys(dedup.minhash(exact))


def _exact(spark, sf_dir):
    return dedup.cut_lineage(dedup.dedup_exact(annotated(spark, sf_dir), prio=an.priority()), "exact")


@query(f"WITH {SQL_POOL}, {sql_exact('pool', 'exact')}, {sql_near('exact', 'nearest')} SELECT doc_id FROM nearest")
def dedup_near_bucket(spark, sf_dir):
    return dedup.dedup_near(_exact(spark, sf_dir), an.priority()).select("doc_id")


@query(f"""WITH RECURSIVE {SQL_POOL}, {sql_exact('pool', 'exact')}, {sql_bands('exact')},
        edges AS (SELECT DISTINCT a.doc_id AS u, b.doc_id AS v FROM bands a JOIN bands b USING (band, bkey) WHERE a.doc_id <> b.doc_id),
        reach AS (SELECT doc_id AS u, doc_id AS v FROM exact UNION SELECT r.u, e.v FROM reach r JOIN edges e ON r.v = e.u),
        roots AS (SELECT u AS doc_id, min(v) AS root FROM reach GROUP BY u)
        SELECT doc_id FROM exact JOIN roots USING (doc_id) QUALIFY row_number() OVER (PARTITION BY root ORDER BY prio, doc_id) = 1""")
def dedup_near_component(spark, sf_dir):
    return dedup.dedup_near(_exact(spark, sf_dir), an.priority(), mode="component").select("doc_id")


SQL_PAIRS = f"""WITH {SQL_POOL}, {sql_exact('pool', 'exact')}, {sql_bands('exact')},
        pairs AS (SELECT DISTINCT x.doc_id AS a, y.doc_id AS b FROM bands x JOIN bands y USING (band, bkey) WHERE x.doc_id < y.doc_id),
        gs AS (SELECT doc_id, list(g) AS g FROM sh GROUP BY doc_id),
        jac AS (SELECT a, b, len(list_intersect(p.g, q.g))::DOUBLE AS i, len(p.g) + len(q.g) AS s FROM pairs JOIN gs p ON a = p.doc_id JOIN gs q ON b = q.doc_id)"""


@query(f"{SQL_PAIRS} SELECT a, b, round(i / (s - i), 6) AS jaccard FROM jac")
def near_dup_jaccard(spark, sf_dir):
    exact = _exact(spark, sf_dir)
    banded = dedup.cut_lineage(dedup.band_keys(dedup.minhash(exact)), "bands")
    return dedup.verify_pairs(banded, exact).select("a", "b", F.round("jaccard", 6).alias("jaccard"))


SQL_ALL_PAIRS = """shared AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*)::DOUBLE AS i FROM sh x JOIN sh y USING (g) WHERE x.doc_id < y.doc_id GROUP BY ALL),
        sizes AS (SELECT doc_id, len(g) AS n FROM gs), every AS (SELECT a, b FROM shared JOIN sizes p ON a = p.doc_id JOIN sizes q ON b = q.doc_id WHERE i / (p.n + q.n - i) >= 0.7)"""


@query(f"""{SQL_PAIRS}, {SQL_ALL_PAIRS}, found AS (SELECT a, b FROM jac WHERE i / (s - i) >= 0.7)
        SELECT (SELECT count(*) FROM jac) AS proposed, (SELECT count(*) FROM found) AS true_pairs, (SELECT count(*) FROM every) AS all_pairs, round((SELECT count(*) FROM found) / (SELECT count(*) FROM jac)::DOUBLE, 6) AS precision, round((SELECT count(*) FROM found) / (SELECT count(*) FROM every)::DOUBLE, 6) AS recall""")
def minhash_quality(spark, sf_dir):
    """Precision of banding at similarity 0.7 among proposed pairs, and recall against all pairs that similar, found exactly."""
    exact = _exact(spark, sf_dir)
    banded = dedup.cut_lineage(dedup.band_keys(dedup.minhash(exact)), "bands")
    true = F.count_if(F.col("jaccard") >= 0.7)
    found = dedup.verify_pairs(banded, exact).agg(F.count("*").alias("proposed"), true.alias("true_pairs"))
    every = dedup.exact_pairs(exact, 0.7).agg(F.count("*").alias("all_pairs"))
    share = lambda n: F.round(F.try_divide(F.col("true_pairs").cast("double"), F.col(n)), 6)
    return found.crossJoin(every).select("proposed", "true_pairs", "all_pairs", share("proposed").alias("precision"), share("all_pairs").alias("recall"))


@query(f"""WITH {SQL_POOL}, {sql_exact('pool', 'exact')}, {sql_near('exact', 'nearest')}
        SELECT doc_id, CASE WHEN doc_id NOT IN (SELECT doc_id FROM exact) THEN 'exact' WHEN doc_id NOT IN (SELECT doc_id FROM nearest) THEN 'near' END AS drop_reason FROM documents""")
def dedup_chain(spark, sf_dir):
    """Exact, then near dedup, with the reason for each dropped row."""
    docs = documents(spark, sf_dir).select("doc_id")
    exact = _exact(spark, sf_dir)
    nearest = dedup.dedup_near(exact, an.priority()).select("doc_id", F.lit(True).alias("n"))
    flagged = docs.join(exact.select("doc_id", F.lit(True).alias("e")), "doc_id", "left").join(nearest, "doc_id", "left")
    return flagged.select("doc_id", F.when(F.col("e").isNull(), "exact").when(F.col("n").isNull(), "near").alias("drop_reason"))


# --- decontamination ---------------------------------------------------------------------------


@query(f"WITH {sql_bands('documents')}, {sql_bands('benchmark', 'item_id', tag='_e')} SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM bands JOIN bands_e USING (band, bkey))")
def decon_minhash(spark, sf_dir):
    docs = documents(spark, sf_dir)
    return docs.join(decontam.minhash_hits(docs, table(spark, sf_dir, "benchmark")), "doc_id", "left_anti").select("doc_id")


@query(f"""WITH toks AS (SELECT doc_id, {sql_tokens()} AS t FROM documents),
        cut AS (SELECT doc_id * 100000 + w AS wid, array_to_string(list_slice(t, w * 20 + 1, w * 20 + 40), ' ') AS text FROM (SELECT doc_id, t, unnest(range(0, CAST(greatest(1, ceil((len(t) - 40) / 20.0) + 1) AS BIGINT))) AS w FROM toks WHERE len(t) > 0)),
        {sql_bands('cut', 'wid')}, {sql_bands('benchmark', 'item_id', tag='_e')} SELECT DISTINCT wid // 100000 AS doc_id FROM bands JOIN bands_e USING (band, bkey)""")
def decon_minhash_window(spark, sf_dir):
    return decontam.minhash_hits(documents(spark, sf_dir), table(spark, sf_dir, "benchmark"), unit="window")


@query(f"WITH {sql_hits13('documents', 'hits')} SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM hits)")
def decon_13gram(spark, sf_dir):
    docs = documents(spark, sf_dir)
    return docs.join(decontam.ngram_hits(docs, table(spark, sf_dir, "benchmark")), "doc_id", "left_anti").select("doc_id")


@query(f"WITH {sql_hits13('documents', 'hits')} SELECT doc_id, item_id FROM hits")
def decon_13gram_hits(spark, sf_dir):
    return decontam.ngram_hits(documents(spark, sf_dir), table(spark, sf_dir, "benchmark"))


@query(f"""WITH {sql_hits13('documents', 'hits')}, {sql_bands('documents')}, {sql_bands('benchmark', 'item_id', tag='_e')},
        g AS (SELECT DISTINCT doc_id FROM hits), m AS (SELECT DISTINCT doc_id FROM bands JOIN bands_e USING (band, bkey))
        SELECT d.doc_id, CASE WHEN g.doc_id IS NOT NULL AND m.doc_id IS NOT NULL THEN 'minhash+ngram' WHEN m.doc_id IS NOT NULL THEN 'minhash' WHEN g.doc_id IS NOT NULL THEN 'ngram' END AS reason
        FROM documents d LEFT JOIN g USING (doc_id) LEFT JOIN m USING (doc_id)""")
def decontaminate(spark, sf_dir):
    docs = documents(spark, sf_dir)
    _, hits = decontam.decontaminate(docs, table(spark, sf_dir, "benchmark"))
    return docs.select("doc_id").join(hits, "doc_id", "left")


# --- responses ---------------------------------------------------------------------------------


@query(f"""SELECT conv_id, turn, question, response, CAST(len({sql_tokens('response')}) AS INTEGER) AS n_tokens FROM (
        SELECT conv_id, turn, role, text AS response, lag(role) OVER w AS q_role, lag(text) OVER w AS question FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)) WHERE role = 'assistant' AND q_role = 'user'""")
def qa_pairs(spark, sf_dir):
    return distill.qa_pairs(table(spark, sf_dir, "conversations"))


@query(f"SELECT doc_id, round({sql_ratio()}, 6) AS ratio FROM {sql_with_grams('documents')}")
def repetition_ratio_by_doc(spark, sf_dir):
    return documents(spark, sf_dir).select("doc_id", F.round(repetition_ratio(F.col("text")), 6).alias("ratio"))


QUERIES["repetition_ratio"], ORACLES["repetition_ratio"] = QUERIES.pop("repetition_ratio_by_doc"), ORACLES.pop("repetition_ratio_by_doc")


@query(f"SELECT doc_id FROM {sql_with_grams('documents')} WHERE {sql_ratio()} <= 0.2")
def drop_degenerate(spark, sf_dir):
    return distill.drop_degenerate(documents(spark, sf_dir)).select("doc_id")


def _attempt_sql(a: int) -> str:
    return f"(['A', 'B', 'C', 'D', 'E'])[CAST({sql_h8(f"item_id || ':{a}:t'")} % 5 + 1 AS INTEGER)]"


SQL_ATTEMPTS = f"""att AS (SELECT item_id, {_attempt_sql(1)} AS a1, {_attempt_sql(2)} AS a2, CASE WHEN item_id % 7 <> 0 THEN (['A', 'B', 'C', 'D', 'E'])[CAST({sql_h8("item_id || ':0:gold'")} % 5 + 1 AS INTEGER)] END AS gold FROM benchmark),
        tried AS (SELECT *, coalesce(a1 <> gold, false) AS retried FROM att), final AS (SELECT item_id, CASE WHEN retried THEN a2 ELSE a1 END AS answer, gold, retried FROM tried)"""


def _gold(spark, sf_dir):
    items = option_teacher(0, "gold")(table(spark, sf_dir, "benchmark").select("item_id"))
    return items.select("item_id", F.when(F.col("item_id") % 7 != 0, F.col("answer")).alias("gold"))


@query(f"WITH {SQL_ATTEMPTS} SELECT item_id, CASE WHEN gold IS NOT NULL THEN a1 = gold END AS correct FROM att")
def verify_answers(spark, sf_dir):
    tried = option_teacher(1)(table(spark, sf_dir, "benchmark").select("item_id")).join(_gold(spark, sf_dir), "item_id")
    boxed = F.concat(F.lit("thus \\boxed{"), F.col("answer"), F.lit("}."))
    return tried.select("item_id", distill.verify_answer(boxed, F.col("gold")).alias("correct"))


def _retry(spark, sf_dir, policy):
    items, gold = table(spark, sf_dir, "benchmark").select("item_id"), _gold(spark, sf_dir)
    first = option_teacher(1)(items)
    missed = first.join(gold, "item_id").where(canonical_answer(F.col("answer")) != canonical_answer(F.col("gold"))).select("item_id")
    return distill.select_with_retry(first, option_teacher(2)(missed), gold, policy=policy)


@query(f"WITH {SQL_ATTEMPTS} SELECT *, CASE WHEN gold IS NOT NULL THEN answer = gold END AS correct FROM final")
def retry_once(spark, sf_dir):
    return _retry(spark, sf_dir, "keep")


@query(f"WITH {SQL_ATTEMPTS} SELECT item_id FROM final WHERE coalesce(answer = gold, true)")
def drop_incorrect(spark, sf_dir):
    return _retry(spark, sf_dir, "drop_incorrect").select("item_id")


# --- sampling ----------------------------------------------------------------------------------


def _sampled(rates) -> str:
    return f"WITH {SQL_LENGTHS} SELECT doc_id, n_tokens FROM lengths, th WHERE {sql_unit('doc_id', 42)} < {sql_rates(rates)}"


@query(_sampled((0.0, 0.1, 0.5, 1.0)))
def stratified_length(spark, sf_dir):
    return sampling.stratified_by_length(lengths(spark, sf_dir)).select("doc_id", "n_tokens")


@query(_sampled((0.0, 0.9, 0.5, 1.0)))
def stratified_length_alt(spark, sf_dir):
    return sampling.stratified_by_length(lengths(spark, sf_dir), rates=sampling.OTHER_RATES).select("doc_id", "n_tokens")


@query(f"WITH {SQL_LENGTHS}, tl AS (SELECT lang, quantile_cont(n_tokens, [0.2, 0.5, 0.75]) AS tq FROM lengths GROUP BY lang) SELECT doc_id, n_tokens FROM lengths JOIN tl USING (lang) WHERE {sql_unit('doc_id', 42)} < {sql_rates((0.0, 0.1, 0.5, 1.0), 'tq')}")
def stratified_length_by_lang(spark, sf_dir):
    return sampling.stratified_by_length(lengths(spark, sf_dir), by=["lang"]).select("doc_id", "n_tokens")


@query()
def stratified_length_kll(spark, sf_dir):
    return sampling.stratified_by_length(lengths(spark, sf_dir), method="kll").select("doc_id", "n_tokens")


@query()
def quantile_error(spark, sf_dir):
    return sampling.rank_error(lengths(spark, sf_dir), "n_tokens")


@query(f"SELECT doc_id FROM documents ORDER BY {sql_unit('doc_id', 42)}, doc_id LIMIT 200")
def uniform_budget(spark, sf_dir):
    return sampling.uniform_n(documents(spark, sf_dir).select("doc_id"), 200)


@query(f"WITH {SQL_LENGTHS} SELECT doc_id, n_tokens FROM lengths ORDER BY n_tokens DESC, doc_id LIMIT 200")
def baseline_longest(spark, sf_dir):
    return sampling.longest_n(lengths(spark, sf_dir), 200).select("doc_id", "n_tokens")


LEVELS = ["primary", "secondary", "undergraduate", "graduate"]
SQL_BY_LEVEL = f"{sql_unit('doc_id', 42)} < CASE edu_level WHEN 'primary' THEN 0.0 WHEN 'secondary' THEN 0.1 WHEN 'undergraduate' THEN 0.5 ELSE 1.0 END"


@query(f"WITH {SQL_ANNOTATED} SELECT doc_id, edu_level FROM annotated WHERE {SQL_BY_LEVEL}")
def baseline_annotation(spark, sf_dir):
    return sampling.stratified_by_level(annotated(spark, sf_dir), LEVELS).select("doc_id", "edu_level")


@query(f"WITH {SQL_LENGTHS} SELECT count(*) AS n, CAST(sum(n_tokens) AS BIGINT) AS total, max(n_tokens) AS longest, round(avg(n_tokens), 6) AS mean FROM lengths")
def token_stats(spark, sf_dir):
    return lengths(spark, sf_dir).agg(F.count("*").alias("n"), F.sum("n_tokens").alias("total"), F.max("n_tokens").alias("longest"), F.round(F.avg("n_tokens"), 6).alias("mean"))


@query(f"""WITH {SQL_ANNOTATED}, {SQL_LENGTHS}, cand AS (
          SELECT 'length' AS arm, doc_id FROM lengths, th WHERE {sql_unit('doc_id', 42)} < {sql_rates((0.0, 0.1, 0.5, 1.0))} UNION ALL
          SELECT 'annotation', doc_id FROM annotated WHERE {SQL_BY_LEVEL} UNION ALL
          (SELECT 'longest', doc_id FROM lengths ORDER BY n_tokens DESC, doc_id LIMIT 100)),
        arms AS (SELECT * FROM cand QUALIFY row_number() OVER (PARTITION BY arm ORDER BY {sql_unit('doc_id', 42)}, doc_id) <= 100)
        SELECT arm, count(*) AS n, count(DISTINCT lang) AS langs, count(DISTINCT source) AS sources, round(quantile_cont(n_tokens, 0.5), 6) AS p50, round(avg(n_tokens), 6) AS mean,
               count(*) FILTER (doc_id IN (SELECT doc_id FROM arms WHERE arm = 'length')) AS shared FROM arms JOIN lengths USING (doc_id) GROUP BY arm""")
def sampling_ablation(spark, sf_dir):
    """Equal budgets of three strategies: lengths and coverage of what each picks, and the rows it shares with the length arm."""
    long = lengths(spark, sf_dir)
    arms = {"length": sampling.stratified_by_length(long), "annotation": sampling.stratified_by_level(annotated(spark, sf_dir), LEVELS), "longest": sampling.longest_n(long, 100)}
    parts = [sampling.uniform_n(df.select("doc_id"), 100).select(F.lit(arm).alias("arm"), "doc_id") for arm, df in arms.items()]
    drawn = parts[0].union(parts[1]).union(parts[2]).join(long, "doc_id").join(parts[0].select("doc_id", F.lit(1).alias("too")), "doc_id", "left")
    return drawn.groupBy("arm").agg(F.count("*").alias("n"), F.countDistinct("lang").alias("langs"), F.countDistinct("source").alias("sources"), F.round(F.percentile("n_tokens", F.lit(0.5)), 6).alias("p50"), F.round(F.avg("n_tokens"), 6).alias("mean"), F.count("too").alias("shared"))


@query(f"""WITH th AS (SELECT quantile_cont(l_extendedprice, [0.2, 0.5, 0.75]) AS th FROM lineitem)
        SELECT l_orderkey, l_linenumber FROM lineitem, th WHERE {sql_unit("(l_orderkey * 100 + l_linenumber)", 42)} < CASE WHEN l_extendedprice > th[3] THEN 1.0 WHEN l_extendedprice > th[2] THEN 0.5 WHEN l_extendedprice > th[1] THEN 0.1 ELSE 0.0 END""")
def stratified_lineitem(spark, sf_dir):
    """The sampling operator at the size of the largest given table."""
    items = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_extendedprice", (F.col("l_orderkey") * 100 + F.col("l_linenumber")).alias("key"))
    return sampling.stratified_by_length(items, "l_extendedprice", key="key").select("l_orderkey", "l_linenumber")


# --- whole curation ----------------------------------------------------------------------------


def _curated(spark, sf_dir):
    """Three of the four disciplines count as STEM; the verifiable rows have an answer to match."""
    gold = F.when(F.col("verifiable"), option(F.col("doc_id"), "0:gold"))
    return curate(documents(spark, sf_dir), table(spark, sf_dir, "benchmark"), lexical_annotator(table(spark, sf_dir, "labels")), CurationConfig(scope=("de", "en", "fr")), gold=gold)


@query(f"WITH {SQL_CHAIN} SELECT doc_id, n_tokens, answer, retried, CASE WHEN gold IS NOT NULL THEN answer = gold END AS correct FROM sampled")
def curated(spark, sf_dir):
    """The chain to the sampled set: every row with the length of its response, its answer and whether it was asked twice."""
    return _curated(spark, sf_dir).curated.select("doc_id", "n_tokens", "answer", "retried", "correct")


@query(f"""WITH {SQL_CHAIN}, c(step, stage, n) AS (SELECT 0, 'raw', count(*) FROM documents UNION ALL SELECT 1, 'valid', count(*) FROM valid UNION ALL SELECT 2, 'exact', count(*) FROM exact UNION ALL
        SELECT 3, 'near', count(*) FROM nearest UNION ALL SELECT 4, 'decontaminated', count(*) FROM clean UNION ALL SELECT 5, 'responded', count(*) FROM responded
        UNION ALL SELECT 6, 'repetition', count(*) FROM kept UNION ALL SELECT 7, 'verified', count(*) FROM verified UNION ALL SELECT 8, 'sampled', count(*) FROM sampled)
        SELECT step, stage, n, round(n / (SELECT max(n) FROM c)::DOUBLE, 6) AS retained FROM c""")
def curation_ledger(spark, sf_dir):
    ledger = _curated(spark, sf_dir).ledger().groupBy("step", "stage").agg(F.sum("n").alias("n"))
    return ledger.select("step", "stage", "n", F.round(F.col("n") / F.max("n").over(Window.partitionBy()).cast("double"), 6).alias("retained"))


@query(f"""WITH {SQL_CHAIN}, b AS (SELECT source, count(*) AS n_before FROM documents GROUP BY source), a AS (SELECT source, count(*) AS n_after FROM sampled GROUP BY source),
        j AS (SELECT source, n_before, coalesce(n_after, 0) AS n_after FROM b LEFT JOIN a USING (source))
        SELECT source, n_before, n_after, round(n_before / (SELECT sum(n_before) FROM j)::DOUBLE, 6) AS share_before, round(n_after / (SELECT sum(n_after) FROM j)::DOUBLE, 6) AS share_after FROM j""")
def source_distribution_query(spark, sf_dir):
    return source_distribution(documents(spark, sf_dir), _curated(spark, sf_dir).curated)


QUERIES["source_distribution"], ORACLES["source_distribution"] = QUERIES.pop("source_distribution_query"), ORACLES.pop("source_distribution_query")


@query(f"""WITH {SQL_LENGTHS} SELECT lang, source, count(*) AS n, CAST(sum(n_tokens) AS BIGINT) AS tokens, round(quantile_cont(n_tokens, 0.5), 6) AS p50 FROM lengths GROUP BY CUBE (lang, source)""")
def corpus_stats(spark, sf_dir):
    return lengths(spark, sf_dir).cube("lang", "source").agg(F.count("*").alias("n"), F.sum("n_tokens").alias("tokens"), F.round(F.percentile("n_tokens", F.lit(0.5)), 6).alias("p50"))


@query(f"WITH {SQL_LENGTHS} SELECT lang, count(*) AS n FROM lengths WHERE lang IN ('en', 'de') GROUP BY lang")
def suite_subset(spark, sf_dir):
    """Items of chosen subjects only."""
    return lengths(spark, sf_dir).where(F.col("lang").isin("en", "de")).groupBy("lang").agg(F.count("*").alias("n"))


