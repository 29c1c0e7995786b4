"""A word-ended BPE as merge rules: what a word's prefixes are tokenised to, without running merges over whole words.

A sequence of tokens is what the merges make of a word exactly if every token stands for
itself and every two neighbours stay apart when merged alone. So the tokens of a prefix are
those of a shorter prefix and one more token, and there is one such way only: a left-to-right
machine, whose state is a prefix and whose transitions emit differences of token counts.
"""

from __future__ import annotations

import json


class MergeRules:
    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            model = json.load(f)["model"]
        if model["type"] != "BPE" or not model["end_of_word_suffix"] or model["continuing_subword_prefix"] or model["dropout"]:
            raise ValueError("a BPE with a suffix at word ends is needed")
        self.ending = model["end_of_word_suffix"]
        self.rank = {tuple(m if isinstance(m, list) else m.split(" ")): i for i, m in enumerate(model["merges"])}
        self.vocab = model["vocab"]
        self.longest = max(len(self.symbols(t)) for t in self.vocab)
        self.own: dict[str, bool] = {}
        self.apart: dict[tuple[str, str], bool] = {}

    def symbols(self, token: str) -> list[str]:
        """The characters that merges start from; the last one of a word carries the suffix."""
        if token.endswith(self.ending) and len(token) > len(self.ending):
            token = token[: -len(self.ending)]
            return [*token[:-1], token[-1] + self.ending]
        return list(token)

    def merged(self, parts: list[str]) -> list[str]:
        """What merging, best rank and leftmost first, leaves of a few symbols."""
        parts = list(parts)
        while len(parts) > 1:
            rank, i = min((self.rank.get(pair, len(self.rank)), i) for i, pair in enumerate(zip(parts, parts[1:])))
            if rank == len(self.rank):
                break
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
        return parts

    def _may_follow(self, before: str | None, token: str) -> bool:
        if token not in self.vocab:
            return False
        if (fine := self.own.get(token)) is None:
            fine = self.own[token] = self.merged(self.symbols(token)) == [token]
        if not fine or before is None:
            return fine
        if (apart := self.apart.get((before, token))) is None:
            apart = self.apart[before, token] = self.merged(self.symbols(before) + self.symbols(token)) == [before, token]
        return apart

    def counts(self, word: str) -> tuple[list[int], int] | None:
        """Of a word in the byte alphabet: tokens of each prefix (from the empty one) as if the word went on, and of the whole word."""
        last: list[str | None] = [None]
        many = [0]

        def further(end: int, tail: str) -> int:
            """The start of the one token that ends a prefix; -1 if the vocabulary lacks a symbol."""
            for start in range(max(0, end - self.longest), end):
                if (start == 0 or last[start] is not None) and self._may_follow(last[start], word[start:end] + tail):
                    return start
            return -1

        for end in range(1, len(word) + 1):
            start = further(end, "")
            last.append(word[start:end] if start >= 0 else None)
            many.append(many[start] + 1 if start >= 0 else 0)
        start = further(len(word), self.ending)
        return (many, many[start] + 1) if start >= 0 else None
