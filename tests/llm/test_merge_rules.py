"""Counts annotated from the merges against the library, word by word."""

import numpy as np

from cotengine.llm.queries import WORD_TOKENIZER, tokenizer_path
from cotengine.llm.token_count import CountingTransducer
from cotengine.llm.word_bpe import WordBPE, byte_symbols

WORDS = ["the", "tokenization", "a" * 45, "aaa", "antidisestablishmentarianism", "ñandú", "éèêë", "straße", "!!!", "...?!", "'s", "'re", "7", "x", "zzzzyyyyxxxx", "wörterbücher", "¿¡", "inininin", "thththan"]


def test_counts_of_words_and_prefixes():
    bpe = WordBPE(tokenizer_path(WORD_TOKENIZER))
    rules = CountingTransducer(bpe).rules
    rng = np.random.default_rng(0)
    words = WORDS + ["".join(rng.choice(list("etaoinshrdéß"), rng.integers(1, 14))) for _ in range(400)]
    bpe.learn(words)
    for w in words:
        many, whole = rules.counts(byte_symbols(w))
        assert whole == len(bpe.memo[w]) >> 2
        s = list(byte_symbols(w))
        assert many == [len(rules.merged(s[:i])) for i in range(len(s) + 1)]


def test_transitions_emit_the_differences():
    machine = CountingTransducer(WordBPE(tokenizer_path(WORD_TOKENIZER)))
    words = ["retrieval", "retrieve", "retry", "re"]
    machine.bpe.learn(words)
    for w in words:
        machine.compile(w, len(machine.bpe.memo[w]) >> 2)
    for w in words:
        at, total = int(machine.start[machine.symbol[ord(w[0])]]), 0
        total += machine.inside[at]
        for c in w[1:]:
            then = int(machine.next[at, machine.symbol[ord(c)]])
            total += machine.inside[then] - machine.inside[at]
            at = then
        assert total + machine.leave[at] == len(machine.bpe.memo[w]) >> 2


def test_state_maps_compose_like_a_fold():
    machine = CountingTransducer(WordBPE(tokenizer_path(WORD_TOKENIZER)))
    rng = np.random.default_rng(1)
    for n in (1, 2, 3, 7, 64, 65):
        maps = rng.integers(0, 8, (n, 3))
        want, now = [], np.arange(3)
        for i, m in enumerate(maps):
            now = m if i == 0 else m[machine.run_of[now]]
            want.append(now)
        assert (machine.composed(maps) == np.array(want)).all()
