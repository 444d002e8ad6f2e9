"""Language identification of words in code-switched text by a linear-chain conditional random field.

A word's features are its affixes, its letter n-grams (with word borders) and whether it is in the
lexicon of frequent training words.  State and transition weights are learned together by gradient
ascent on the conditional likelihood of sequences in which the language switches; words are labelled by their
forward-backward marginals, and a document by the sum of its words' marginals.
"""

from __future__ import annotations

import random
import re
from collections import Counter, defaultdict

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import map_texts

#: Documents of each language that training reads at most, and features it keeps at most.
TRAIN_DOCUMENTS, TRAIN_FEATURES = 150, 60_000
#: Training sequences, words of each, and the chance that a word begins another language's run.
SEQUENCES, LENGTH, SWITCH = 4000, 24, 0.12
#: Words whose scores one task keeps; when there are more it forgets them and starts anew.
KEPT_WORDS = 320_000
UNKNOWN = "und"
WORD = re.compile(r"[^\W\d_]+")


def words_of(text: str | None) -> list[str]:
    return WORD.findall(text.lower()) if text else []


def word_features(w: str) -> list[str]:
    """The word itself, its affixes, and all n-grams of two and three letters with its borders."""
    b = f"^{w}$"
    n = len(b)
    return ["L" + w, "p" + w[:2], "p" + w[:3], "s" + w[-2:], "s" + w[-3:], "s" + w[-4:], *(b[i : i + 2] for i in range(n - 1)), *(b[i : i + 3] for i in range(n - 2))]


class LanguageField:
    def __init__(self, labels: list[str]):
        self.labels = labels
        self.index: dict[str, int] = {}
        k = len(labels)
        self.states, self.transitions, self.start = np.zeros((1, k)), np.zeros((k, k)), np.zeros(k)
        self._rows: dict[str, int] = {}
        self._scores = np.zeros((0, k))

    def fresh(self) -> LanguageField:
        """The same model without kept words."""
        made = LanguageField(self.labels)
        made.__setstate__(self.__getstate__())
        return made

    def __getstate__(self):
        return {"labels": self.labels, "index": self.index, "states": self.states, "transitions": self.transitions, "start": self.start}

    def __setstate__(self, kept):
        self.__dict__.update(kept)
        self._rows, self._scores = {}, np.zeros((0, len(self.labels)))

    # Training.

    def fit(self, texts: list[tuple[str, str]], seed: int = 3, epochs: int = 4) -> LanguageField:
        """texts: (text, language)."""
        rng = random.Random(seed)
        docs: dict[int, list[list[str]]] = defaultdict(list)
        for text, lang in texts:
            if w := words_of(text):
                docs[self.labels.index(lang)].append(w)
        if not docs:
            return self
        seen = Counter(f for ws in docs.values() for d in ws for w in set(d) for f in word_features(w))
        self.index = {f: i + 1 for i, (f, n) in enumerate(sorted(seen.items(), key=lambda x: (-x[1], x[0]))[:TRAIN_FEATURES]) if n > 1}
        k, langs = len(self.labels), sorted(docs)
        sequences, labels = [], []
        for _ in range(SEQUENCES):
            ws, ys, lang = [], [], rng.choice(langs)
            while len(ws) < LENGTH:
                d = rng.choice(docs[lang])
                at = rng.randrange(len(d))
                run = 1
                while rng.random() > SWITCH:
                    run += 1
                part = d[at : at + run]
                ws += part
                ys += [lang] * len(part)
                lang = rng.choice(langs)
            sequences.append(ws[:LENGTH])
            labels.append(ys[:LENGTH])
        words = {w: i for i, w in enumerate(sorted({w for ws in sequences for w in ws}))}
        each = [self._ids(w) or [0] for w in words]
        features = np.array([i for x in each for i in x], dtype=np.int64), np.array([len(x) for x in each])
        ids = np.array([[words[w] for w in ws] for ws in sequences])
        y = np.array(labels)
        self.states = np.zeros((len(self.index) + 1, k))
        squares = [np.full_like(p, 1e-8) for p in (self.states, self.transitions, self.start)]
        order = np.random.default_rng(seed)
        for _ in range(epochs):
            for rows in np.array_split(order.permutation(SEQUENCES), max(1, SEQUENCES // 250)):
                gradients = self._gradient(ids[rows], y[rows], *features)
                for p, g, q in zip((self.states, self.transitions, self.start), gradients, squares, strict=True):
                    q += g * g
                    p += 0.5 * g / np.sqrt(q)
                self.states[0] = 0
        return self

    def _ids(self, word: str) -> list[int]:
        return [i for f in word_features(word) if (i := self.index.get(f))]

    def _emissions(self, flat: np.ndarray, sizes: np.ndarray) -> np.ndarray:
        """Per word, given by its features one after the other and their number: the weight of each label, 1 at most."""
        owner = np.repeat(np.arange(len(sizes)), sizes)
        sums = np.stack([np.bincount(owner, self.states[flat, c], minlength=len(sizes)) for c in range(len(self.labels))], axis=1)
        return np.exp(np.maximum(sums - sums.max(1, keepdims=True), -60))

    def _gradient(self, ids: np.ndarray, y: np.ndarray, flat: np.ndarray, sizes: np.ndarray):
        n, length, k = len(ids), ids.shape[1], len(self.labels)
        emit = self._emissions(flat, sizes)[ids]
        step, alpha, scale = np.exp(self.transitions), np.zeros((n, length, k)), np.zeros((n, length))
        a = np.exp(self.start) * emit[:, 0]
        for t in range(length):
            if t:
                a = (alpha[:, t - 1] @ step) * emit[:, t]
            scale[:, t] = a.sum(1)
            alpha[:, t] = a / scale[:, t, None]
        beta, pairs = np.ones((n, k)), np.zeros((k, k))
        marginal = np.zeros((n, length, k))
        marginal[:, -1] = alpha[:, -1]
        for t in range(length - 1, 0, -1):
            ahead = emit[:, t] * beta / scale[:, t, None]
            pairs += (alpha[:, t - 1].T @ ahead) * step
            beta = ahead @ step.T
            marginal[:, t - 1] = alpha[:, t - 1] * beta
        truth = np.eye(k)[y]
        seen = np.zeros((k, k))
        np.add.at(seen, (y[:, :-1].ravel(), y[:, 1:].ravel()), 1)
        diff = truth - marginal
        gradient = np.zeros_like(self.states)
        for c in range(k):
            owed = np.bincount(ids.ravel(), diff[..., c].ravel(), minlength=len(sizes))
            gradient[:, c] = np.bincount(flat, np.repeat(owed, sizes), minlength=len(self.states))
        return gradient / n - 1e-5 * self.states, (seen - pairs) / n, diff[:, 0].sum(0) / n

    # Labelling.

    def _number(self, docs: list[list[str]]) -> list[np.ndarray]:
        """Rows of self._scores for the words of each document."""
        distinct = {w for d in docs for w in d}
        if len(self._rows) + len(distinct) > KEPT_WORDS:
            self._rows, self._scores = {}, np.zeros((0, len(self.labels)))
        new = sorted(distinct - self._rows.keys())
        if new:
            ids = [self._ids(w) or [0] for w in new]
            scores = self._emissions(np.array([i for x in ids for i in x], dtype=np.int64), np.array([len(x) for x in ids]))
            base = len(self._rows)
            self._rows.update((w, base + i) for i, w in enumerate(new))
            held = np.zeros((max(len(self._rows), 2 * len(self._scores)), len(self.labels))) if len(self._rows) > len(self._scores) else self._scores
            if held is not self._scores:
                held[:base] = self._scores[:base]
            held[base : base + len(new)] = scores
            self._scores = held
        get = self._rows.__getitem__
        return [np.fromiter(map(get, d), dtype=np.int64, count=len(d)) for d in docs]

    def _forward_backward(self, docs: list[list[str]]) -> tuple[list[int], np.ndarray, np.ndarray, np.ndarray]:
        """Marginals of every word, documents side by side: their order (longest first), the number of words
        before each step, and for each row of the marginals the place of its document in that order."""
        numbers = self._number(docs)
        order = sorted((i for i in range(len(docs)) if len(docs[i])), key=lambda i: -len(docs[i]))
        k = len(self.labels)
        if not order:
            return order, np.zeros(1, dtype=np.int64), np.zeros((0, k)), np.zeros(0, dtype=np.int64)
        sizes = np.array([len(docs[i]) for i in order])
        longest = int(sizes[0])
        active = np.searchsorted(-sizes, -np.arange(longest), side="left")
        offset = np.concatenate([[0], np.cumsum(active)])
        flat = np.empty(offset[-1], dtype=np.int64)
        for r, i in enumerate(order):
            flat[offset[: sizes[r]] + r] = numbers[i]
        del numbers
        emit = self._scores[flat]
        step = np.exp(self.transitions)
        alpha, back = np.empty_like(emit), step.T.copy()
        a = np.exp(self.start)[None, :]
        for t in range(longest):
            lo, hi = offset[t], offset[t + 1]
            a = emit[lo:hi] * (a[: hi - lo] @ step if t else a)
            a /= a.sum(1, keepdims=True)
            alpha[lo:hi] = a
        beta = np.ones((0, k))
        for t in range(longest - 1, -1, -1):
            lo, hi = offset[t], offset[t + 1]
            if len(beta) < hi - lo:
                beta = np.concatenate([beta, np.ones((hi - lo - len(beta), k))])
            m = alpha[lo:hi] * beta
            m /= m.sum(1, keepdims=True)
            beta = (emit[lo:hi] * beta) @ back
            beta /= beta.sum(1, keepdims=True)
            alpha[lo:hi] = m
        return order, offset, alpha, np.arange(offset[-1]) - np.repeat(offset[:-1], active)

    def marginals(self, docs: list[list[str]]) -> list[np.ndarray]:
        """Forward-backward marginals of every word, one matrix per document."""
        order, offset, m, _ = self._forward_backward(docs)
        out = [np.zeros((len(d), len(self.labels))) for d in docs]
        for r, i in enumerate(order):
            out[i] = m[offset[: len(docs[i])] + r]
        return out

    def predict(self, texts: list[str | None]) -> tuple[list[str], list[float]]:
        """The language with the largest sum of marginals, and its share of the words."""
        docs = [words_of(t) for t in texts]
        labels, scores = [UNKNOWN] * len(docs), [0.0] * len(docs)
        if not self.index:
            return labels, scores
        order, _, m, owner = self._forward_backward(docs)
        totals = np.stack([np.bincount(owner, m[:, c], minlength=len(order)) for c in range(len(self.labels))], axis=1)
        for r, i in enumerate(order):
            if any(c.isalpha() for w in docs[i] for c in w):
                best = int(np.argmax(totals[r]))
                labels[i] = self.labels[best]
                scores[i] = float(min(1.0, totals[r, best] / totals[r].sum()))
        return labels, scores


def held_out(key: str):
    return F.coalesce(F.crc32(F.col(f"`{key}`").cast("string").cast("binary")) % 4 == 2, F.lit(False))


def train(docs: DataFrame, key: str = "doc_id", text: str = "text", lang: str = "lang", per_language: int = TRAIN_DOCUMENTS) -> LanguageField:
    """Learn from at most per_language documents of each language, those whose hash is smallest, outside the held-out fold.

    Rows that repeat key and text are one document, so a key that fills the table is held to the bound too.
    """
    named = docs.select(F.col(f"`{key}`").alias("k"), F.col(f"`{lang}`").alias("y"), F.col(f"`{text}`").alias("t"))
    labelled = named.withColumn("h", F.xxhash64("t")).filter(F.col("y").isNotNull() & F.col("k").isNotNull() & ~held_out("k"))
    order = Window.partitionBy("y").orderBy(F.xxhash64("k"), "k", "h")
    chosen = labelled.select("k", "y", "h").distinct().withColumn("n", F.row_number().over(order)).filter(F.col("n") <= per_language)
    some = chosen.select("k", "h").distinct().collect()
    picked = labelled.filter(F.col("k").isin([r.k for r in some]) & F.col("h").isin([r.h for r in some])) if some else None
    rows = picked.dropDuplicates(["k", "h", "y"]).orderBy("k", "y", "h").collect() if some else []
    field = LanguageField(sorted({r.y for r in rows}))
    return field.fit([(r.t, r.y) for r in rows])


def identify(docs: DataFrame, keys: list[str], text: str, field: LanguageField) -> DataFrame:
    """Per row: keys, lang_pred and score.

    A text that is null or has no letter, and every text if nothing could be learned, gets `und`
    with score 0; ties go to the first language in order; repeated rows each give a row.
    """
    shared = docs.sparkSession.sparkContext.broadcast(field)

    def kernel():
        model = shared.value.fresh()

        def run(texts):
            return list(model.predict(texts))

        return run

    return map_texts(docs, keys, text, kernel, [("lang_pred", "string"), ("score", "double")])
