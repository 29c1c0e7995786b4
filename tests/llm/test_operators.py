"""The pipeline operators against brute force on small tables, with the odd rows each has to take."""

import hashlib
import re
import time
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from cotengine.llm import lang_id, pu_quality
from cotengine.llm.bench_decontam import BlockMaxIndex, chunk_words, contaminated
from cotengine.llm.components import components
from cotengine.llm.jaccard_join import least_matches, near_duplicates
from cotengine.llm.line_dedup import alike, dedup_lines, distinct_words, edit_distance, most_edits, normal, settled, settled_by_common, simhash
from cotengine.llm.queries import WORD_TOKENIZER, tokenizer_path
from cotengine.llm.ss_packing import pack, pack_documents
from cotengine.llm.store import materialize
from cotengine.llm.suffix_dedup import common_prefixes, dedup_substrings, suffix_array
from cotengine.llm.token_count import count_tokens
from cotengine.llm.topk_search import top_k
from cotengine.llm.url_rules import filter_urls
from cotengine.llm.word_bpe import WordBPE, WordTable
from cotengine.llm.words import Words

DOCS = "doc_id long, text string, lang string, source string, n_chars long, rid long, score double"


def docs(spark, rows):
    """Documents with extra columns whose names clash with the operators' own."""
    return spark.createDataFrame([(i, t, "en", "s", len(t or ""), 7, 0.5) for i, t in rows], DOCS)


LONG = " ".join(f"word{i % 977}x{i}" for i in range(6000))
ODD = [(1, None), (2, ""), (3, "   \n\n"), (4, "a"), (None, "null id with a few words here"), (5, LONG), (6, LONG), (6, LONG), (7, "!!! ???"), (8, "日本語 text ñandú")]


# --- url rules ---------------------------------------------------------------------------------


def test_url_rules_local_and_by_range(spark):
    rng = np.random.default_rng(3)
    hosts = ["a.b.org", "b.org", "xb.org", "c.b.org", "org", "com", "q.com", ""]
    urls = [f"http://{hosts[rng.integers(8)]}/{'ab'[rng.integers(2)]}{'/cd'[rng.integers(3)]}{rng.integers(5)}" for _ in range(300)] + [None, "", "no scheme", "http://B.ORG", "ftp://b.org?x=/a", "http://b.org/a?q#f", "x://a.b.org/a/x"] * 2
    rules = [("org", "/", "allow"), ("b.org", "/a", "block"), ("b.org", "/a/c", "allow"), ("a.b.org", "/", "block"), ("com", "/b", "block"), (None, "/", "block"), ("b.org", "/a", "allow")]
    pages = spark.createDataFrame([(i, u, "x") for i, u in enumerate(urls)], "page_id long, url string, rule string")
    table = spark.createDataFrame(rules, "host string, path string, verdict string")

    def brute(u):
        rest = u.split("://", 1)[1] if u and "://" in u else ""
        host = re.match(r"[^/?#]*", rest)[0]
        path = re.match(r"[^?#]*", rest[len(host) :])[0]
        host = host.lower()
        fit = [(len(h + p), h + p, v == "block", v) for h, p, v in rules if h and (host == h or host.endswith("." + h)) and path.startswith(p)]
        best = max(fit, default=None)
        return (host, path, best[1] if best else None, best[3] if best else "allow")

    for limit in (1000, 1):
        got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in filter_urls(pages, table, local_rules=limit, ranges=5).collect()}
        assert got == {i: brute(u) for i, u in enumerate(urls)}
    assert filter_urls(pages.where("false"), table).count() == 0 and filter_urls(pages, table.where("false")).where("verdict <> 'allow'").count() == 0


# --- benchmark decontamination --------------------------------------------------------------------


def test_block_max_wand_finds_all(spark):
    rng = np.random.default_rng(1)
    vocab = np.arange(1, 60, dtype=np.uint64)
    items = [(i, rng.choice(vocab, rng.integers(5, 60)), rng.choice(vocab, 4)) for i in range(80)]
    df, n, total = Counter(), 0, 0
    for _, q, a in items:
        for part in chunk_words(np.concatenate([q, a])):
            df.update(np.unique(part).tolist())
            n, total = n + 1, total + len(part)
    index = BlockMaxIndex(items, df, n, total)
    for _ in range(60):
        query = sorted(rng.choice(len(index.terms), 25, replace=False).tolist())
        scores = Counter()
        for t in query:
            for c, w in index.lists[t]:
                scores[c] += w
        for threshold in (0.3, 0.5, 0.8):
            assert sorted(c for c, _ in index.reach(query, threshold)) == sorted(c for c, s in scores.items() if s >= threshold - 1e-9)


def test_contaminated(spark):
    question, answer = "what is the third moon of the ringed planet called by sailors", "it is called the silver lantern"
    items = spark.createDataFrame([(1, question, answer), (2, "short", ""), (3, None, None)], "item_id long, question string, answer string")
    rows = ODD + [(20, LONG + " " + question + "? " + answer + ". " + LONG), (21, question.replace("moon", "star")), (22, answer)]
    for shard in (100, 1):
        got = {(r.doc_id, r.item_id) for r in contaminated(docs(spark, rows), items, shard=shard).collect()}
        assert got == {(20, 1)}
    assert contaminated(docs(spark, rows), items.where("false")).count() == 0
    assert contaminated(docs(spark, []), items).count() == 0


# --- lines ------------------------------------------------------------------------------------------


def test_edit_distance():
    def plain(a, b):
        row = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            new = [i]
            for j, y in enumerate(b, 1):
                new.append(min(new[-1] + 1, row[j] + 1, row[j - 1] + (x != y)))
            row = new
        return row[-1]

    rng = np.random.default_rng(2)
    for _ in range(500):
        a, b = ("".join(rng.choice(list("abc"), rng.integers(0, 14))) for _ in "ab")
        assert edit_distance(a, b, 99) == plain(a, b)


def test_settled_only_says_what_edit_distance_says():
    rng = np.random.default_rng(21)
    words, seen = ["a", "bb", "abc", "dab", ""], set()
    for _ in range(3000):
        a = " ".join(rng.choice(words, rng.integers(0, 9)))
        b = " ".join(rng.choice(words, rng.integers(0, 9))) if rng.random() < 0.3 else a
        for _ in range(int(rng.integers(0, 4))):
            at = int(rng.integers(0, len(b) + 1))
            b = b[:at] + str(rng.choice(["", "x", " ", "abc"])) + b[at + int(rng.integers(0, 3)) :]
        most = most_edits(a, b, 0.8)
        said, truth = settled(a, b, most), edit_distance(a, b, most) <= most
        assert said is None or said == truth
        seen.add(said)
    assert seen == {True, False, None}


def test_common_subsequence_only_says_what_edit_distance_says():
    rng = np.random.default_rng(8)
    said = {True: 0, False: 0, None: 0}
    for _ in range(600):
        a = "".join(rng.choice(list("abcdefgh "), rng.integers(0, 150)))
        b = list(a)
        for _ in range(int(rng.integers(0, 60))):
            at = int(rng.integers(0, len(b) + 1))
            b[at : at + int(rng.integers(0, 2))] = rng.choice(list("abcdefgh "), int(rng.integers(0, 2))).tolist()
        b = "".join(b)
        most = most_edits(a, b, 0.8)
        known = settled_by_common(a, b, most)
        said[known] += 1
        assert known is None or known == (edit_distance(a, b, most) <= most)
    assert said[True] > 20 and said[False] > 20


def test_simhash_counts_in_lanes_of_any_width():
    rng = np.random.default_rng(22)
    for longest in (1, 255, 256, 70_000):
        starts = np.concatenate([[0], np.cumsum([longest, 3, 1])])
        hashes = rng.integers(0, 1 << 64, starts[-1], dtype=np.uint64)
        hashes[: longest // 2 + 1] |= np.uint64(1 << 63 | 1)
        bits = (hashes[:, None] >> np.arange(64, dtype=np.uint64)) & np.uint64(1)
        want = [sum(1 << b for b in range(64) if 2 * int(bits[x:y, b].sum()) > y - x) for x, y in zip(starts[:-1], starts[1:])]
        assert simhash(hashes, starts).tolist() == want


def test_lines(spark):
    base = "the quick brown fox jumps over the lazy dog while forty two grey geese fly south across seven frozen lakes and then rest near a quiet mill until the first light of the early spring morning comes"
    near = base.replace("geese", "goose")
    rows = ODD + [(10, base + "\nonly here\n\nBASE"), (11, "other start\n" + base.upper() + "!"), (12, near), (13, "only  here\nonly here")]
    out = {r.doc_id: r for r in dedup_lines(docs(spark, rows), distance=3).collect() if r.doc_id}
    assert out[10].n_removed == 0 and out[11].text == "other start" and out[13].text == ""
    assert out[5].n_removed == 0 and out[6].text == "" and out[3].text == "   \n\n" and out[1].n_removed == 0
    w = Words([normal(base), normal(near)])
    bits = int(np.bitwise_count(np.bitwise_xor(*simhash(*distinct_words(w.hashes, w.first)))))
    for bucket in (1, 4096):  # buckets dealt out in parts give the same lines
        got = {r.doc_id: r.n_removed for r in dedup_lines(docs(spark, rows), distance=6, bucket=bucket).collect()}
        assert got[12] == int(bits <= 6) and got[13] == 2
    with pytest.raises(ValueError):
        dedup_lines(docs(spark, rows), distance=9)
    assert dedup_lines(docs(spark, [])).count() == 0


def changed_lines(seed, words, common, n=60):
    """Lines of ``words`` words, ``common`` of ten from a few; each with a copy that has a tenth of its words changed."""
    rng = np.random.default_rng(seed)
    word = lambda: "".join(rng.choice(list("etaoinshrdlu"), rng.integers(2, 9)))
    few, out = [word() for _ in range(12)], []
    for _ in range(n):
        line = [few[rng.integers(12)] if rng.random() < common / 10 else word() for _ in range(words)]
        copy = list(line)
        for p in rng.choice(words, max(1, words // 10), replace=False):
            copy[p] = word()
        out.append((" ".join(line), " ".join(copy)))
    return out


@pytest.mark.parametrize("words", [12, 60])
def test_similar_lines_are_found(spark, words):
    made = changed_lines(words, words, 3)
    flat = [x for pair in made for x in pair]
    near = [(i, j) for j in range(len(flat)) for i in range(j) if alike(flat[i], flat[j], 0.8)]
    assert len(near) >= 50
    gone = {r.doc_id for r in dedup_lines(docs(spark, list(enumerate(flat)))).where("n_removed = 1").collect()}
    assert gone <= {j for _, j in near} and len(gone) >= 0.9 * len({j for _, j in near})


def test_lines_alike_by_all_words_are_found(spark):
    made = changed_lines(5, 60, 8)
    w = Words([x for pair in made for x in pair])
    by_all, by_different = simhash(w.hashes, w.first), simhash(*distinct_words(w.hashes, w.first))
    bits = lambda s: np.bitwise_count(s[0::2] ^ s[1::2])
    want = {2 * i + 1 for i in np.flatnonzero((bits(by_all) <= 3) & (bits(by_different) > 3)).tolist() if alike(*made[i], 0.8)}
    gone = {r.doc_id for r in dedup_lines(docs(spark, [(i, x) for i, x in enumerate(x for pair in made for x in pair)])).where("n_removed = 1").collect()}
    assert len(want) >= 5 and want <= gone


# --- substrings ---------------------------------------------------------------------------------------


def test_suffix_array_and_prefixes():
    rng = np.random.default_rng(0)
    for k in range(60):
        data = rng.integers(97, 99 + rng.integers(3), rng.integers(1, 300)).astype(np.uint8)
        if k % 3 == 0:  # shared runs longer than the counted prefix, and zero bytes at the end
            run = rng.integers(0, 2, rng.integers(500, 900)).astype(np.uint8)
            data = np.concatenate([run, data, run, run[100:], data, np.zeros(9, np.uint8)])
        raw = data.tobytes()
        sa = suffix_array(data)
        assert sa.tolist() == sorted(range(len(raw)), key=lambda i: raw[i:])
        for most, lanes in ((40, 4096), (400, 3)):
            lcp = common_prefixes(data, sa, most, lanes)
            for k in range(1, len(sa)):
                a, b = raw[sa[k - 1] :][:most], raw[sa[k] :][:most]
                assert lcp[k] == next((i for i, (x, y) in enumerate(zip(a, b)) if x != y), min(len(a), len(b)))


def brute_substrings(rows, size):
    """(id, bytes, removed, runs, digest of what stays) of each row, by counting every window."""
    enc = [(t or "").encode() for _, t in rows]
    count = Counter(b[i : i + size] for b in enc for i in range(len(b) - size + 1))
    out = []
    for (d, _), b in zip(rows, enc):
        gone = np.zeros(len(b), bool)
        for i in range(len(b) - size + 1):
            if count[b[i : i + size]] > 1:
                gone[i : i + size] = True
        runs = int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum())
        kept = bytes(x for x, g in zip(b, gone) if not g)
        out.append((d or 0, len(b), int(gone.sum()), runs, hashlib.sha256(kept).hexdigest(), sum(x & 0xC0 != 0x80 for x in kept)))
    return sorted(out)


def substrings(spark, rows, size, **settings):
    got = dedup_substrings(docs(spark, rows), length=size, **settings).withColumn("s", F.sha2("kept", 256)).collect()
    return sorted((r.doc_id or 0, r.n_bytes, r.n_removed, r.n_spans, r.s, r.n_chars) for r in got)


def test_long_shared_runs(spark):
    rng = np.random.default_rng(14)
    text = lambda n: "".join(rng.choice(list("ab "), n))
    runs, rows = [text(n) for n in (430, 700, 1900, 5000)], []
    for i in range(24):
        a, b = runs[i % 4], runs[(i + 1) % 4]
        cut = int(rng.integers(0, 300))
        rows.append((i, text(rng.integers(0, 300)) + a[cut:] + text(rng.integers(0, 40)) + b[: len(b) - cut] + text(rng.integers(0, 300))))
    rows += [(50, runs[2][:1000] + "c" + runs[2][1001:]), (51, "xy" * 2000)]
    assert substrings(spark, rows, 400) == substrings(spark, rows, 400, hot=1) == brute_substrings(rows, 400)


def test_many_equal_rows(spark):
    rows = [(7, LONG[:3000])] * 700 + [(8, LONG[:2500])]
    got = substrings(spark, rows, 400)
    assert len(got) == 701 and {r[2:4] for r in got} == {(3000, 1), (2500, 1)}


@pytest.mark.parametrize("hot", [256, 1])
def test_substrings(spark, hot):
    rng = np.random.default_rng(4)
    word = lambda n: "".join(rng.choice(list("abcdé "), n))
    shared = [word(90), word(45)]
    rows = ODD + [(20 + i, word(rng.integers(0, 80)) + shared[i % 2] + word(rng.integers(0, 80))) for i in range(30)] + [(90, "ab" * 100), (91, None)]
    assert substrings(spark, rows, 40, gram=8, hot=hot) == brute_substrings(rows, 40)
    assert dedup_substrings(docs(spark, []), length=40, gram=8).count() == 0


# --- near duplicates -------------------------------------------------------------------------------------


@pytest.mark.parametrize("chunk", [256, 2])
def test_near_duplicates(spark, chunk):
    rng = np.random.default_rng(6)
    rows = list(ODD)
    for f in range(4):
        base = [f"w{f}_{i}" for i in rng.integers(0, 4000, 150)]
        for c in range(6):
            copy = list(base)
            for p in rng.integers(0, 150, c):
                copy[p] = f"new{f}{c}{p}"
            rows.append((100 + 10 * f + c, " ".join(copy)))
    sets = []
    for _, t in rows:
        w = re.findall(r"[^\W_]+", (t or "").lower())
        sets.append({tuple(w[i : i + 5]) for i in range(len(w) - 4)} or ({tuple(w)} if w else set()))
    links, parent = Counter(), list(range(len(rows)))

    def top(x):
        return x if parent[x] == x else top(parent[x])

    for i in range(len(rows)):
        for j in range(i):
            if sets[i] and sets[j] and len(sets[i] & sets[j]) / len(sets[i] | sets[j]) >= 0.8:
                links[i] += 1
                links[j] += 1
                parent[top(i)] = top(j)
    want = sorted((d or 0, min((rows[k][0] or 0) for k in range(len(rows)) if top(k) == top(i)), links[i]) for i, (d, _) in enumerate(rows))
    got = near_duplicates(docs(spark, rows), chunk=chunk).collect()
    assert sorted((r.doc_id or 0, r.class_id or 0, r.n_links) for r in got) == want
    assert near_duplicates(docs(spark, [])).count() == 0


def test_pruning_bounds():
    least = least_matches(0.8, 1e-6)
    assert list(least) == [16, 32, 48, 64] and all(0 < least[n] < n for n in list(least)[1:]) and sorted(least.values()) == list(least.values())


def test_components(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(90, 91), (91, 92), (5, 5)], "u long, v long")
    got = {r.node: r.root for r in components(edges).collect()}
    assert {got[i] for i in range(41)} == {0} and {got[i] for i in (90, 91, 92)} == {90}


# --- models ------------------------------------------------------------------------------------------------


def test_quality(spark):
    rng = np.random.default_rng(8)
    word = lambda: "".join(rng.choice(list("etaoinshr"), rng.integers(2, 8)))
    good = [" ".join(word() for _ in range(60)).capitalize() + "." for _ in range(400)]
    junk = [" ".join(word() + "$$$ ###" for _ in range(60)) for _ in range(60)]
    rows = list(enumerate(good + junk))
    labels = spark.createDataFrame([(i, 1) for i in range(200)], "doc_id long, quality int")
    table = docs(spark, rows)
    model = pu_quality.fit(table, labels)
    assert 0.6 < model.prior <= 0.98
    got = {r.doc_id: r.score for r in pu_quality.score(table, model).collect()}
    right = np.mean([(got[i] >= 0.3) == (i < 400) for i, _ in rows])
    assert right > 0.97 and all(0 <= s <= 1 for s in got.values())
    assert pu_quality.score(docs(spark, ODD), model).count() == len(ODD)
    assert pu_quality.fit(table, labels.where("false")) is None
    assert {r.score for r in pu_quality.score(docs(spark, ODD), None).collect()} == {0.5}
    assert pu_quality.accepted(table, model, 0.3).columns == table.columns


def test_languages(spark):
    rng = np.random.default_rng(9)
    sound = {"aa": "bkd", "bb": "lmr", "cc": "szx"}
    rows = []
    for i in range(120):
        lang = sorted(sound)[i % 3]
        rows.append((i, " ".join("".join(rng.choice(list(sound[lang])) + rng.choice(list("aeiou")) for _ in range(4)) for _ in range(40)), lang))
    table = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = lang_id.fit(table.where("doc_id % 2 = 0"), grams=2000)
    got = {r.doc_id: r.lang_pred for r in lang_id.identify(table, model).collect()}
    assert np.mean([got[i] == lang for i, _, lang in rows]) > 0.98
    odd = {r.doc_id: (r.lang_pred, r.score) for r in lang_id.identify(docs(spark, ODD), model).collect()}
    assert odd[1] == odd[2] == odd[3] == odd[7] == ("und", 0.0) and odd[4][0] in sound
    assert lang_id.fit(table.where("false")) is None and lang_id.identify(docs(spark, ODD), None).where("lang_pred <> 'und'").count() == 0


# --- tokens ---------------------------------------------------------------------------------------------------

TEXTS = ["don't they'll ''s x're,'s I'M 12²3 ½", "a" * 3000, "!" * 2000 + "'s", "<|endoftext|> hi <|startoftext|>", "x" * 511 + " " + "y" * 513, "ÀÉ ß ŉ ǅ İstanbul ΟΔΟΣ", "\r\n\t", " . " * 700, "日本語 e\u0301", "'", "the the the " * 2000, "\x1c\u00a0\u2028 z"]


def test_token_counts_equal_the_library(spark):
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(tokenizer_path(WORD_TOKENIZER))
    rows = ODD + [(100 + i, t) for i, t in enumerate(TEXTS)]
    for states in (100_000, 1_000):
        got = count_tokens(docs(spark, rows), tokenizer=tokenizer_path(WORD_TOKENIZER), states=states).collect()
        want = [(d or 0, len((t or "").encode()), len(library.encode(t or "", add_special_tokens=False).ids)) for d, t in rows]
        assert sorted((r.doc_id or 0, r.n_bytes, r.n_tokens) for r in got) == sorted(want)
        assert all(r.over_limit == (r.n_tokens > 2048) for r in got)
    assert count_tokens(docs(spark, []), tokenizer=tokenizer_path(WORD_TOKENIZER)).count() == 0


def test_word_table_gives_the_library_ids():
    bpe = WordBPE(tokenizer_path(WORD_TOKENIZER))
    plain = [t for t in TEXTS + [LONG] if bpe.plain(t)]
    ids, many = WordTable(bpe).ids(plain)
    want = [bpe.library.encode(t, add_special_tokens=False).ids for t in plain]
    assert many.tolist() == [len(w) for w in want] and ids.tolist() == [x for w in want for x in w]
    assert [np.frombuffer(bpe.ids(t), "<u4").tolist() for t in plain] == want


def test_packing(spark):
    import zlib

    rows = ODD + [(100 + i, "word " * (37 * i % 900)) for i in range(200)]
    got = pack_documents(docs(spark, rows), tokenizer=tokenizer_path(WORD_TOKENIZER), size=512, group=1000).collect()
    bpe = WordBPE(tokenizer_path(WORD_TOKENIZER))
    want = []
    for d, t in rows:
        ids = np.append(np.frombuffer(bpe.ids(t or ""), "<u4"), np.uint32(1)).astype("<u4")
        want += [(d or 0, i // 512, i, min(512, len(ids) - i), zlib.crc32(ids[i : i + 512].tobytes())) for i in range(0, len(ids), 512)]
    assert sorted((r.doc_id or 0, r.piece, r.start, r.length, r.ids_crc32) for r in got) == sorted(want)
    used: dict[int, list] = {}
    for r in got:
        used.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in used.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 512
    assert len(used) <= 1.05 * sum(w[3] for w in want) / 512 + 2


def test_repeated_long_rows_have_sequences_of_their_own(spark):
    got = pack_documents(docs(spark, ODD), tokenizer=tokenizer_path(WORD_TOKENIZER), size=512).collect()
    full = [r for r in got if r.length == 512]
    once = sum(r.doc_id == 5 for r in full)
    assert once > 0 and sum(r.doc_id == 6 for r in full) == 2 * once
    assert len({r.sequence_id for r in full}) == len(full) and all(r.offset == 0 and r.sequence_id < 0 for r in full)


def test_pack_needs_few_sequences():
    lengths = np.random.default_rng(1).integers(1, 700, 3000)
    number, offset = pack(lengths, 1000)
    assert number.max() + 1 <= 1.02 * lengths.sum() / 1000 + 1 and (offset + lengths <= 1000).all()


# --- search -----------------------------------------------------------------------------------------------------


def test_top_k(spark):
    rng = np.random.default_rng(7)
    rows = [(i, rng.normal(size=8).round(2).tolist()) for i in range(60)] + [(100, None), (101, [1.0, None] + [0.0] * 6), (102, [float("nan")] * 8), (103, [0.0] * 8), (104, [1.0, 2.0])] + [(200 + i, [0.5] * 8) for i in range(20)]
    table = spark.createDataFrame([(i, v, 1) for i, v in rows], "vec_id long, embedding array<double>, score int")
    fine = {i: np.floor(1024 * np.array(v)).astype(int) for i, v in rows if v and None not in v and np.isfinite(v).all()}
    want = []
    for q in (i for i in fine if i % 4 == 0):
        scored = sorted((-int(fine[q] @ fine[c]), c) for c in fine if c != q and len(fine[c]) == len(fine[q]))[:10]
        want += [(q, k + 1, c, -s) for k, (s, c) in enumerate(scored)]
    for block in (512, 5):
        got = top_k(table, table.where("vec_id % 4 = 0"), query_block=block).collect()
        assert sorted((r.query_id, r.rank, r.vec_id, r.score) for r in got) == sorted(want)
    assert top_k(table, table.where("false")).count() == 0


def test_word_hashes_do_not_depend_on_neighbours():
    a, b = Words(["alpha beta", "beta"]), Words(["x", "beta", "ALPHA"])
    assert a.hashes[1] == a.hashes[2] == b.hashes[1] and a.hashes[0] == b.hashes[2]


def test_a_written_table_leaves_no_shuffle_files(spark):
    disk = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()
    held = lambda: {x for x in disk.getAllFiles().mkString("\n").split("\n") if "shuffle_" in x}
    before = held()
    table = materialize(spark.range(1000).repartition(3, "id").groupBy((F.col("id") % 7).alias("k")).agg(F.count("*").alias("n")), "test")
    for _ in range(100):  # executors are told, not waited for
        if not (left := [x for x in held() - before if x.endswith(".data")]):
            break
        time.sleep(0.1)
    assert not left
    assert sum(r.n for r in table.collect()) == 1000
