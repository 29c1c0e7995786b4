"""The pipeline stage by stage against brute force on a small table, the registered queries on the given ones."""

import re
import zlib
from pathlib import Path

import numpy as np
import pytest

import __spark_entry__ as entry
import corpus_pipeline
from cotengine.llm.bench_decontam import contaminated
from cotengine.llm.line_dedup import alike, normal
from cotengine.llm.queries import WORD_TOKENIZER, tokenizer_path
from cotengine.llm.store import materialize, shared_folder
from cotengine.llm.word_bpe import WordBPE

SF = "/root/testdata/sf0.001"
QUESTION = "which of the seven lakes of the northern plateau was first drained by the old canal company"
ANSWER = "it was the long grey lake beside the abandoned copper mine."


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    rng = np.random.default_rng(5)
    few = ["".join(rng.choice(list("etaoinshrdlucm"), rng.integers(2, 9))) for _ in range(700)]
    line = lambda n: " ".join(rng.choice(few, n)).capitalize() + "."
    text = lambda: "\n".join(line(rng.integers(12, 30)) for _ in range(rng.integers(4, 9)))
    rows = [[i, text()] for i in range(120)]
    rows += [[200 + i, rows[i][1]] for i in range(4)]  # exact copies
    for i in range(4):  # near copies within one line
        words = rows[10 + i][1].split(" ")
        words[len(words) // 2] = "changed"
        rows.append([210 + i, " ".join(words)])
    shared = line(20)
    for i in range(20, 26):
        rows[i][1] += "\n" + shared
    rows[30][1] += "\n" + (QUESTION + "? " + ANSWER).capitalize()
    rows += [[300 + i, " ".join("@@" + "".join(rng.choice(list("#$%&*0123"), 9)) for _ in range(60))] for i in range(40)]  # junk
    rows += [[400, None], [401, ""], [402, "\n \n"], [None, text()], [410, rows[40][1]], [410, rows[40][1]]]
    at = str(tmp_path_factory.mktemp("corpus"))
    spark.createDataFrame([(i, t, "en", "s", len(t or ""), 1) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long, rid int").write.parquet(f"{at}/documents.parquet")
    spark.createDataFrame([(i, 1) for i in range(80)] + [(300 + i, 0) for i in range(20)], "doc_id long, quality int").write.parquet(f"{at}/labels.parquet")
    spark.createDataFrame([(1, QUESTION.capitalize() + "? " + ANSWER), (2, None)], "item_id long, text string").write.parquet(f"{at}/benchmark.parquet")
    return at


def lines_left(rows):
    """Brute force: lines of equal or similar words are one group, and its first by (id, line) stays."""
    all_lines = sorted(((i is None, i, n, normal(x)) for i, t in rows for n, x in enumerate((t or "").split("\n")) if normal(x)), key=lambda r: (r[0], r[1] or 0, r[2]))
    kept, gone = [], set()
    for nameless, i, n, words in all_lines:
        if any(w == words or abs(len(w) - len(words)) <= 0.2 * max(len(w), len(words)) and alike(w, words, 0.8) for w in kept):
            gone.add((i, n))
        kept.append(words)
    return {i: "\n".join(x for n, x in enumerate((t or "").split("\n")) if (i, n) not in gone) for i, t in rows}


def test_stages(spark, folder):
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    stages, got = dict(corpus_pipeline.STAGES), {}
    assert list(stages) == ["quality", "lines", "near", "decontaminate", "packing"]
    for name, stage in corpus_pipeline.STAGES:
        out = materialize(stage(spark, docs, folder), "test")
        assert name == "packing" or out.schema == docs.schema
        got[name] = (docs.collect(), out.collect())
        docs = out
    before, after = got["quality"]
    ids = {r.doc_id for r in after}
    assert not any(300 <= (i or 0) < 340 for i in ids) and len([i for i in ids if i is not None and i < 120]) >= 114
    before, after = got["lines"]
    once = {(r.doc_id, r.text) for r in before}
    want = {i: t for i, t in lines_left(sorted(once, key=lambda r: (r[0] is None, r[0] or 0))).items() if any(c.isalnum() for c in t) or not any(c.isalnum() for c in dict(once)[i] or "")}
    left = {r.doc_id: r.text for r in after}
    assert left == want and all(r.n_chars == len(r.text) for r in after)
    before, after = got["near"]
    assert {r.doc_id for r in after} <= {r.doc_id for r in before} and len({r.doc_id for r in after}) == len(after)
    worded = [r.text for r in after if any(c.isalnum() for c in r.text)]
    assert len(worded) == len(set(worded))
    sets = {r.doc_id: {tuple(w[i : i + 5]) for w in [re.findall(r"[^\W_]+", r.text.lower())] for i in range(max(1, len(w) - 4)) if w} for r in before}
    kept = {r.doc_id for r in after}
    for i in set(sets) - kept:
        assert any(j in kept and sets[i] and len(sets[i] & sets[j]) / len(sets[i] | sets[j]) >= 0.8 for j in sets if j != i)
    before, after = got["decontaminate"]
    assert {r.doc_id for r in before} - {r.doc_id for r in after} == {30}
    before, after = got["packing"]
    bpe = WordBPE(tokenizer_path(WORD_TOKENIZER))
    want = []
    for r in before:
        all_ids = np.append(np.frombuffer(bpe.ids(r.text or ""), "<u4"), np.uint32(1)).astype("<u4")
        want += [(r.doc_id or 0, i // 4096, zlib.crc32(all_ids[i : i + 4096].tobytes())) for i in range(0, len(all_ids), 4096)]
    assert sorted((r.doc_id or 0, r.piece, r.ids_crc32) for r in after) == sorted(want)


def test_run_of_empty_tables(spark, folder, tmp_path):
    for name in ("documents", "labels", "benchmark"):
        spark.read.parquet(f"{folder}/{name}.parquet").where("false").write.parquet(f"{tmp_path}/{name}.parquet")
    tables = Path(shared_folder(spark).removeprefix("file:")) / "tables"
    before = set(tables.glob("*")) if tables.exists() else set()
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
    assert [p.name.rsplit("-", 1)[0] for p in set(tables.glob("*")) - before] == ["pipeline-packing"]


def test_contamination_by_brute_force(spark):
    rng = np.random.default_rng(11)
    words = ["".join(rng.choice(list("bcdfglmnprst"), 2)) + str(i) for i in range(900)]
    text = lambda n: " ".join(rng.choice(words, n))
    items = [(i, text(rng.integers(12, 90)), text(rng.integers(4, 12))) for i in range(40)]
    rows = []
    for d in range(160):
        own, i = text(rng.integers(0, 400)), items[d % 40]
        rows.append((d, own + " " + i[1] + " " + i[2] + " " + text(rng.integers(0, 300)) if d % 2 else own))
    docs = spark.createDataFrame([*rows, (900, None), (901, "")], "doc_id long, text string")
    bench = spark.createDataFrame(items, "item_id long, question string, answer string")
    want = {(d, i) for d, t in rows for i, q, a in items if f"{q} {a}" in t}
    for shard in (1000, 7):
        assert {(r.doc_id, r.item_id) for r in contaminated(docs, bench, shard=shard).collect()} == want and len(want) == 80


@pytest.mark.parametrize("name, columns, table", [
    ("op1_url_rules", "page_id host path rule verdict", "pages"), ("op3_line_dedup", "doc_id n_lines n_removed kept_sha256", "documents"),
    ("op4_suffix_dedup", "doc_id n_bytes n_removed n_spans kept_sha256", "documents"), ("op6_jaccard_join", "doc_id class_id n_links", "documents"),
    ("op8_token_counts", "doc_id n_bytes n_tokens over_limit", "documents"),
])
def test_queries_give_a_row_for_each_row(spark, name, columns, table):
    df = entry.queries()[name](spark, SF)
    assert df.columns[: len(columns.split())] == columns.split()
    assert df.count() == spark.read.parquet(f"{SF}/{table}.parquet").count()


def test_quality_and_language_of_held_out_documents(spark):
    sf = "/root/testdata/sf0.01"
    marks = {r.doc_id: r.quality for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    got = entry.queries()["op5_quality_classifier"](spark, sf).collect()
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) and r.predicted == (r.score >= 0.3) and 0 <= r.score <= 1 for r in got)
    held = [(r.score, marks[r.doc_id]) for r in got if r.held_out and r.doc_id in marks]
    good, bad = ([s for s, m in held if m == x] for x in (1, 0))
    assert np.mean([a > b for a in good for b in bad]) >= 0.95
    lang = {r.doc_id: r.lang for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    got = entry.queries()["op7_language_id"](spark, sf).collect()
    held = [r for r in got if r.held_out]
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in got) and np.mean([r.lang_pred == lang[r.doc_id] for r in held]) >= 0.98


def test_packed_query_is_gapless(spark):
    by: dict[int, list] = {}
    for r in entry.queries()["op9_best_fit_packing"](spark, SF).collect():
        by.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in by.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 4096


def test_lines_meet_their_rows_once(spark, folder):
    """The columns beside the text come along with the rows: the texts are not joined to the documents again."""
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    plan = corpus_pipeline.lines(spark, docs, folder)._jdf.queryExecution().optimizedPlan().toString()
    assert len(re.findall(r"\bJoin ", plan)) == 1 and "Aggregate" not in plan
