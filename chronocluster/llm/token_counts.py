"""Token counts of a unigram segmentation, by dynamic programming over a trie of pre-tokens.

The distinct pre-tokens of a batch form a trie.  Its nodes are visited in the order of their
sorted keys; a node's forward score (the best sum of piece scores of any segmentation of the
prefix, and the number of pieces of it) depends on the prefix alone, so a shared prefix is
computed once.  A terminal node's count is stored and reused for every later occurrence.
"""

from __future__ import annotations

import base64
import math
from functools import lru_cache

import regex
from pyspark.sql import DataFrame

from .bpe import PIECES
from .common import map_texts

#: Terminal counts that one worker keeps; when there are more it forgets them and starts anew.
TERMINALS = 500_000
#: Pre-tokens over this many bytes are counted without being kept.
KEPT_BYTES = 64


class UnigramCounter:
    """Scores of pieces follow Zipf's law on the rank of the piece in the vocabulary file: log p = -log(rank + 2)."""

    def __init__(self, path: str):
        with open(path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.score = {p: -math.log(r + 2) for p, r in ranks.items()}
        self.endings = {p[i:] for p in self.score for i in range(len(p))}
        self.pieces = regex.compile(PIECES)
        self.counts: dict[str, int] = {}

    def forward(self, new: list[bytes]) -> list[int]:
        """Counts of sorted distinct keys."""
        out, last, best, pieces = [], b"", [0.0], [0]
        score, endings = self.score, self.endings
        for key in new:
            shared, most = 0, min(len(last), len(key))
            while shared < most and last[shared] == key[shared]:
                shared += 1
            del best[shared + 1 :], pieces[shared + 1 :]
            for j in range(shared + 1, len(key) + 1):
                top, n, i = -math.inf, 0, j - 1
                while i >= 0 and (x := key[i:j]) in endings:
                    if (s := score.get(x)) is not None and ((s := s + best[i]) > top or s == top and pieces[i] + 1 < n):
                        top, n = s, pieces[i] + 1
                    i -= 1
                best.append(top)
                pieces.append(n)
            out.append(pieces[len(key)])
            last = key
        return out

    def count_all(self, texts: list[str | None]) -> tuple[list[int], list[int]]:
        """Tokens and pre-tokens of each text."""
        split = [self.pieces.findall(t) if t else [] for t in texts]
        distinct = {p for ps in split for p in ps}
        if len(self.counts) + len(distinct) > TERMINALS:
            self.counts.clear()
        keyed = sorted((p.encode(), p) for p in distinct - self.counts.keys())
        made = dict(zip((p for _, p in keyed), self.forward([k for k, _ in keyed]), strict=True))
        long = {p: made.pop(p) for k, p in keyed if len(k) > KEPT_BYTES}
        self.counts.update(made)
        get = self.counts.__getitem__ if not long else lambda p: long[p] if p in long else self.counts[p]
        return [sum(map(get, ps)) for ps in split], [len(ps) for ps in split]


@lru_cache(maxsize=2)
def counter(path: str) -> UnigramCounter:
    return UnigramCounter(path)


def token_counts(df: DataFrame, key: str, text: str, path: str) -> DataFrame:
    """Per row: key, n_tokens, n_pretokens, n_bytes.  A null or empty text has 0 of each; nothing is shuffled."""

    def kernel():
        c = counter(path)

        def run(texts):
            tokens, pretokens = c.count_all(texts)
            return [tokens, pretokens, [len(t.encode()) if t else 0 for t in texts]]

        return run

    return map_texts(df, [key], text, kernel, [("n_tokens", "bigint"), ("n_pretokens", "bigint"), ("n_bytes", "bigint")])
