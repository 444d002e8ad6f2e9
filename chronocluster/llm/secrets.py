"""Secret scanning: patterns propose candidates, a random forest removes the false positives.

The forest is trained from labelled findings (:func:`labelled_findings` builds a set by rule, or a
table of them is passed in) on the candidate's length and character classes, its character
transitions against ordinary words, the share of it that dictionary words cover, the path it
stands in and the words beside it.
"""

from __future__ import annotations

import math
import random
import re
from collections import Counter
from functools import lru_cache

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_texts

# The forms of well-known credentials.
KNOWN = {
    "aws_key": r"\b(?:AKIA|ASIA)[0-9A-Z]{16}\b",
    "github_token": r"\bgh[pousr]_[A-Za-z0-9]{36}\b",
    "gitlab_token": r"\bglpat-[A-Za-z0-9_\-]{20}\b",
    "slack_token": r"\bxox[abprs]-[A-Za-z0-9\-]{10,}",
    "google_key": r"\bAIza[0-9A-Za-z_\-]{35}",
    "payment_key": r"\b[sr]k_(?:live|test)_[0-9A-Za-z]{16,}",
    "jwt": r"(?<![\w\-])eyJ[A-Za-z0-9_\-]{8,}\.eyJ[A-Za-z0-9_\-]{8,}\.[A-Za-z0-9_\-]{8,}",
    "private_key": r"-----BEGIN [A-Z ]*PRIVATE KEY-----(?:(?:(?!-----)[\s\S])*+-----END [A-Z ]*PRIVATE KEY-----|(?:\s*+[A-Za-z0-9+/=]{16,}+)*+)",
}
KEYWORDS = "password passwd pwd secret token apikey api_key api-key access_key accesskey auth_key authorization bearer private_key client_secret credential credentials passphrase".split()
HARMLESS = "example sample dummy placeholder test fake md5 sha1 sha256 sha512 checksum digest hash commit revision uuid guid etag integrity build version id isbn doi".split()
ASSIGNED = rf"(?i:(?<![A-Za-z])(?:{'|'.join(sorted(KEYWORDS, key=len, reverse=True))})[\"']?[ \t]*(?:[:=]|=>|:=)[ \t]*[\"']?)(?P<value>[A-Za-z0-9+/_.~\-]{{8,}}={{0,2}})"
BARE = r"(?<![A-Za-z0-9+/_\-])(?=[A-Za-z+/_\-]*+[0-9])[A-Za-z0-9+/_\-]{20,}={0,2}"
CANDIDATE = re.compile("|".join([*(f"(?P<{k}>{p})" for k, p in KNOWN.items()), f"(?P<assigned>{ASSIGNED})", f"(?P<bare>{BARE})"]))
WORD = re.compile(r"[^\W\d_]+")
#: Paths whose files seldom hold real credentials, and paths that often do.
QUIET_PATH = re.compile(r"(?i)(?:^|[/_\-.])(?:tests?|spec|examples?|docs?|fixtures?|samples?|mocks?|locales?|vendor|lock)(?:[/_\-.]|$)")
LOUD_PATH = re.compile(r"(?i)(?:^|[/_\-.])(?:env|config|conf|settings|credentials|secrets?|deploy|prod|ini|pem|key)(?:[/_\-.]|$)")
FEATURES = ("length", "digits", "upper", "symbols", "entropy", "hex", "transition", "coverage", "slashes", "path", "keyword", "harmless", "assigned", "known", "quoted", "repeats")
#: What a finding is replaced with.
MASK = "<SECRET>"


@lru_cache(maxsize=2)
def word_list(path: str) -> frozenset[str]:
    """The lower-case words of four letters or more in a vocabulary file of the tokenizers library."""
    import json

    with open(path, encoding="utf-8") as f:
        vocabulary = json.load(f)["model"]["vocab"]
    return frozenset(w.lower() for t in vocabulary if len(w := t.lstrip("Ġ")) >= 4 and w.isascii() and w.isalpha() and w[1:].islower())


@lru_cache(maxsize=2)
def transitions(path: str) -> dict[str, float]:
    """Log share of each pair of letters within dictionary words."""
    pairs = Counter(a + b for w in word_list(path) for a, b in zip(w, w[1:], strict=False))
    total = sum(pairs.values())
    return {p: math.log(n / total) for p, n in pairs.items()}


def candidates(text: str) -> list[tuple[int, int, str]]:
    """Start, end and kind of each candidate, in text order and without overlap."""
    out = []
    for m in CANDIDATE.finditer(text):
        kind = m.lastgroup if m.lastgroup != "value" else "assigned"
        start, end = m.span("value") if m.group("value") is not None else m.span()
        while end > start and kind in ("assigned", "bare") and text[end - 1] in ".-/":
            end -= 1
        if end - start >= 8:
            out.append((start, end, kind))
    return out


def features(text: str, start: int, end: int, kind: str, dictionary: str, path: str | None = "") -> list[float]:
    path = path or ""
    s = text[start:end]
    n = len(s)
    counts = Counter(s)
    low = s.lower()
    words, pairs = word_list(dictionary), transitions(dictionary)
    covered, i = 0, 0
    while i < n - 3:
        for k in range(min(12, n - i), 3, -1):
            if low[i : i + k] in words:
                covered, i = covered + k, i + k
                break
        else:
            i += 1
    steps = [pairs.get(low[i : i + 2], -12.0) for i in range(n - 1)]
    before = text[max(0, start - 48) : start]
    near = [w.lower() for w in WORD.findall(before)[-4:]] + [w.lower() for w in WORD.findall(text[end : end + 24])[:2]]
    gap = before.rstrip("\"'` ")
    return [
        min(n, 200),
        sum(c.isdigit() for c in s) / n,
        sum(c.isupper() for c in s) / n,
        sum(not c.isalnum() for c in s) / n,
        -sum(k / n * math.log2(k / n) for k in counts.values()),
        float(all(c in "0123456789abcdefABCDEF" for c in s)),
        sum(steps) / max(1, len(steps)),
        covered / n,
        float("/" in before[-2:] or s.count("/") >= 2),
        float(bool(LOUD_PATH.search(path))) - float(bool(QUIET_PATH.search(path))),
        float(any(k.replace("_", " ").replace("-", " ").split()[-1] in near for k in KEYWORDS)),
        float(any(w in HARMLESS for w in near)),
        float(gap.endswith(("=", ":", ">"))),
        float(kind in KNOWN),
        float(before[-1:] in "\"'`" and before[-1:] != ""),
        max(counts.values()) / n,
    ]


def labelled_findings(n: int = 1500, seed: int = 7, dictionary: str = "") -> list[tuple[str, int, int, str, int, str]]:
    """Labelled findings by rule: text, start, end, kind, 1 for a secret, and a path or none; about as many of each label.

    Half have no path, as texts without one are scanned too.
    """
    r = random.Random(seed)
    words = sorted(word_list(dictionary))
    hexa, alnum, b64 = "0123456789abcdef", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/"
    some = lambda letters, k: "".join(r.choice(letters) for _ in range(k))
    plain = lambda k: " ".join(r.choice(words) for _ in range(k))
    name = lambda k: r.choice("-_/").join(r.choice(words) for _ in range(k))
    yes = [
        lambda: "AKIA" + some(alnum[:26] + "0123456789", 16),
        lambda: "ghp_" + some(alnum, 36),
        lambda: "sk_live_" + some(alnum, 24),
        lambda: f"eyJ{some(alnum, 20)}.eyJ{some(alnum, 30)}.{some(alnum, 30)}",
        lambda: f"{r.choice(KEYWORDS)}{r.choice(['=', ' = ', ': '])}{r.choice(['', chr(34)])}{some(hexa, r.choice([16, 18, 24, 32, 40, 64]))}",
        lambda: f"{r.choice(KEYWORDS)}{r.choice(['=', ' = ', ': '])}{r.choice(['', chr(34)])}{some(alnum, r.randint(10, 44))}",
        lambda: f"{r.choice(KEYWORDS)}{r.choice(['=', ' = '])}{some(b64, r.randint(20, 60))}",
    ]
    no = [
        lambda: f"{r.choice(['sha256', 'md5', 'commit', 'checksum', 'digest', 'revision', 'integrity'])}{r.choice([' ', ': ', '='])}{some(hexa, r.choice([32, 40, 64]))}",
        lambda: f"{r.choice(['uuid', 'guid', 'id', ''])} {some(hexa, 8)}-{some(hexa, 4)}-{some(hexa, 4)}-{some(hexa, 4)}-{some(hexa, 12)}",
        lambda: f"https://{r.choice(words)}.example.org/{name(3)}/{r.randint(1, 9999)}-{name(2)}",
        lambda: f"{name(r.randint(2, 4))}_{r.randint(1, 99)}_{name(2)}",
        lambda: f"{r.choice(KEYWORDS)} = {r.choice(['your', 'my', 'some', 'the'])}_{name(2)}",
        lambda: f"{r.choice(KEYWORDS)}: {r.choice(words)}{r.choice(words)}",
        lambda: f"{r.choice(KEYWORDS)}={r.choice('x*0a')* r.randint(8, 24)}",
        lambda: f"{r.choice(words)}{some('0123456789', r.randint(18, 30))}",
        lambda: f"/{name(3)}/{some('0123456789', 8)}/{name(2)}",
        lambda: f"{r.choice(['example', 'placeholder', 'sample', 'dummy'])} {r.choice(KEYWORDS)} = {some(alnum, 12)}",
    ]
    out, k = [], 0
    while len(out) < n:
        label = k % 2
        head, body = plain(r.randint(2, 5)) + " ", r.choice(yes if label else no)()
        text = f"{head}{body}{r.choice(['', chr(34) if chr(34) in body else ''])} {plain(3)}"
        path = f"{r.choice(words)}/{r.choice(['.env', 'config.ini', 'deploy/settings.py', 'app.py', 'README.md'] if label else ['tests/data.py', 'docs/index.md', 'fixtures/a.json', 'app.py', 'README.md', 'package-lock.json'])}" if r.random() < 0.5 else ""
        out += [(text, a, b, kind, label, path) for a, b, kind in candidates(text) if a >= len(head) - 1 and b <= len(head) + len(body)]
        k += 1
    return out[:n]


class Forest:
    """A random forest of Gini trees on a dense matrix; trees are flat arrays."""

    def __init__(self, trees: int = 25, depth: int = 8, least: int = 3, seed: int = 11):
        self.n, self.depth, self.least, self.seed = trees, depth, least, seed
        self.trees: list[tuple[np.ndarray, ...]] = []

    def fit(self, x: np.ndarray, y: np.ndarray) -> Forest:
        rng = np.random.default_rng(self.seed)
        for _ in range(self.n):
            rows = rng.integers(0, len(x), len(x))
            nodes: list[list[float]] = []
            self._grow(x[rows], y[rows], 0, rng, nodes)
            self.trees.append(tuple(np.array(c) for c in zip(*nodes, strict=True)))
        return self

    def _grow(self, x, y, depth, rng, nodes) -> int:
        at = len(nodes)
        nodes.append([-1, 0.0, -1, -1, float(y.mean())])
        if depth == self.depth or len(y) < 2 * self.least or y.min() == y.max():
            return at
        best = (0.0, -1, 0.0)
        for f in rng.choice(x.shape[1], max(1, math.isqrt(x.shape[1])) + 1, replace=False):
            order = np.argsort(x[:, f], kind="stable")
            v, t = x[order, f], y[order]
            left = np.arange(1, len(t))
            ones = np.cumsum(t)[:-1]
            total = t.sum()
            p, q = ones / left, (total - ones) / (len(t) - left)
            gain = 2 * total / len(t) * (1 - total / len(t)) - (left * 2 * p * (1 - p) + (len(t) - left) * 2 * q * (1 - q)) / len(t)
            gain[(v[1:] <= v[:-1]) | (left < self.least) | (len(t) - left < self.least)] = -1
            k = int(np.argmax(gain))
            if gain[k] > best[0] + 1e-12:
                best = (float(gain[k]), int(f), float((v[k] + v[k + 1]) / 2))
        if best[1] < 0:
            return at
        go = x[:, best[1]] <= best[2]
        low = self._grow(x[go], y[go], depth + 1, rng, nodes)
        high = self._grow(x[~go], y[~go], depth + 1, rng, nodes)
        nodes[at] = [best[1], best[2], low, high, nodes[at][4]]
        return at

    def predict(self, x: np.ndarray) -> np.ndarray:
        total = np.zeros(len(x))
        for feature, cut, low, high, value in self.trees:
            at = np.zeros(len(x), dtype=np.int64)
            for _ in range(self.depth):
                f = feature[at].astype(np.int64)
                inner = f >= 0
                go = x[np.arange(len(x)), np.maximum(f, 0)] <= cut[at]
                at = np.where(inner, np.where(go, low[at], high[at]).astype(np.int64), at)
            total += value[at]
        return total / len(self.trees)


def train(dictionary: str, findings: list[tuple[str, int, int, str, int, str]] | None = None) -> Forest:
    findings = labelled_findings(dictionary=dictionary) if findings is None else findings
    x = np.array([features(t, a, b, k, dictionary, p) for t, a, b, k, _, p in findings])
    return Forest().fit(x, np.array([f[4] for f in findings], dtype=float))


def scan(df: DataFrame, keys: list[str], text: str, dictionary: str, path: str | None = None, threshold: float = 0.5, forest: Forest | None = None) -> DataFrame:
    """Per row: keys, n_candidates, findings (start, stop, kind, score) and clean, the text with findings masked.

    A null text stays null and has no candidates; rows with null keys and repeated rows each give a row;
    candidates never overlap (the leftmost wins).  Nothing is shuffled.  path names a column with the
    text's path; without one, or where it is null, the path says nothing.
    """
    model = df.sparkSession.sparkContext.broadcast(forest or train(dictionary))

    def kernel():
        f = model.value

        def run(texts, paths=None):
            paths = paths or [None] * len(texts)
            found = [[(i, *c) for c in candidates(t)] if t else [] for i, t in enumerate(texts)]
            flat = [c for cs in found for c in cs]
            scores = f.predict(np.array([features(texts[i], a, b, k, dictionary, paths[i]) for i, a, b, k in flat])) if flat else []
            out = [[len(c) for c in found], [[] for _ in texts], list(texts)]
            for (i, a, b, k), s in zip(flat, scores, strict=True):
                if s >= threshold:
                    out[1][i].append({"start": a, "stop": b, "kind": k, "score": float(s)})
            for i, hits in enumerate(out[1]):
                if hits:
                    parts, at = [], 0
                    for h in hits:
                        parts += [texts[i][at : h["start"]], MASK]
                        at = h["stop"]
                    out[2][i] = "".join([*parts, texts[i][at:]])
            return out

        return run

    fields = [("n_candidates", "bigint"), ("findings", "array<struct<start:int,stop:int,kind:string,score:double>>"), ("clean", "string")]
    return map_texts(df, keys, text, kernel, fields, path)


def digest(scanned: DataFrame, key: str = "doc_id") -> DataFrame:
    return scanned.select(
        key,
        "n_candidates",
        F.size("findings").cast("bigint").alias("n_secrets"),
        F.array_join(F.transform("findings", lambda x: F.concat_ws(":", x.kind, x.start.cast("string"), x.stop.cast("string"))), ",").alias("secrets"),
        F.sha2(F.coalesce("clean", F.lit("")).cast("binary"), 256).alias("clean_sha256"),
    )
