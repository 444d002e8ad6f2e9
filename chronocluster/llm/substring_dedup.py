"""Substring deduplication by sliding sentence spans.

From every sentence a span starts, and at every sentence one ends, that runs over several consecutive
sentences as far as it needs to hold MIN_WORDS words; a sentence with twice as many is a span alone,
besides.  Spans are hashed and joined globally; of a span that occurs more than once the first
occurrence stays, and sentences that any other occurrence covers are removed: all those in any
repeated run of several sentences with MIN_WORDS words.
"""

from __future__ import annotations

import re

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_texts, materialise

#: Words and sentences that a span has at least.
MIN_WORDS, MIN_SENTENCES = 16, 2
#: A sentence ends at its mark, with any other signs right after it, or at a line break.
BORDER = re.compile(r"[.!?…。][^\w\s]*\s+|\s*\n\s*")


def sentences(text: str) -> list[tuple[int, int]]:
    """Start and end of each sentence with the white space after it; together they cover the text."""
    ends = [m.end() for m in BORDER.finditer(text)]
    edges = [0, *(e for e in ends if 0 < e < len(text)), len(text)]
    return [(a, b) for a, b in zip(edges, edges[1:], strict=False) if b > a]


def span_arrays(text: str, min_words: int = MIN_WORDS) -> tuple[int, list[np.ndarray]]:
    """The number of sentences, and by span: two halves of its hash, first and last sentence, start, end.

    A passage of several sentences with min_words holds, around each of its sentences, the shortest
    such span from there on or else the shortest one that ends with the passage.
    """
    import xxhash

    cut = sentences(text)
    words = [text[a:b].lower().split() for a, b in cut]
    full = np.array([i for i, w in enumerate(words) if w], dtype=np.int64)  # white space alone is no sentence of a span
    sizes = np.array([len(words[i]) for i in full.tolist()], dtype=np.int64)
    hashes = b"".join(xxhash.xxh3_128_digest(" ".join(words[i])) for i in full.tolist())
    n, at = len(full), np.arange(len(full))
    total = np.concatenate([[0], np.cumsum(sizes)])
    stops = np.maximum(np.searchsorted(total, total[:-1] + min_words), at + MIN_SENTENCES)
    starts = np.minimum(np.searchsorted(total, total[1:] - min_words, side="right") - 1, at + 1 - MIN_SENTENCES)
    fits, mirrored, alone = stops <= n, starts >= 0, sizes >= 2 * min_words
    first = np.concatenate([at[fits], starts[mirrored], at[alone]])
    last = np.concatenate([stops[fits], at[mirrored] + 1, at[alone] + 1])
    first, last = np.divmod(np.unique(first * (n + 1) + last), n + 1)
    found = b"".join(xxhash.xxh3_128_digest(hashes[16 * i : 16 * j]) for i, j in zip(first.tolist(), last.tolist(), strict=True))
    halves = np.frombuffer(found, dtype="<i8").reshape(-1, 2)
    edges = np.array(cut, dtype=np.int64).reshape(-1, 2)
    i, j = full[first], full[last - 1] + 1
    places = (x.astype(np.int32) for x in (i, j, edges[i, 0], edges[j - 1, 1]))
    return len(cut), [halves[:, 0], halves[:, 1], *places]


def spans(text: str, min_words: int = MIN_WORDS) -> tuple[int, list[tuple[int, int, int, int, int, int]]]:
    """The same, a tuple for each span."""
    n, found = span_arrays(text, min_words)
    return n, list(zip(*(x.tolist() for x in found), strict=True))


def span_table(docs: DataFrame, key: str, text: str, min_words: int) -> DataFrame:
    """k, th (hash of the text), n (its sentences) and the spans of each row of docs."""
    names = ["h1", "h2", "i", "j", "s", "e"]

    def kernel():
        def run(texts):
            found = [span_arrays(t or "", min_words) for t in texts]
            return [[n for n, _ in found], *([x[c] for _, x in found] for c in range(len(names)))]

        return run

    picked = docs.select(F.col(f"`{key}`").alias("k"), F.xxhash64(f"`{text}`").alias("th"), F.col(f"`{text}`").alias("t"))
    return map_texts(picked, ["k", "th"], "t", kernel, [("n", "bigint"), *((x, "array<bigint>" if x in ("h1", "h2") else "array<int>") for x in names)])


def repeats(table: DataFrame) -> DataFrame:
    """k, th, runs: the covered ranges of each document of a span table with a repeated span that is not the first.

    The first occurrence is the one with the smallest key, then text hash, then place.
    """
    each = table.select("k", "th", F.explode(F.arrays_zip("h1", "h2", "i", "j", "s", "e")).alias("x")).select("k", "th", "x.*")
    # A row given twice counts as repeated here; none of its spans differs from the first below.
    first = each.groupBy("h1", "h2").agg(F.min(F.struct("k", "th", "i")).alias("first"), F.count("*").alias("times")).filter("times > 1")
    again = materialise(first.drop("times"), "repeated")
    hit = each.join(again, ["h1", "h2"]).filter(~F.struct("k", "th", "i").eqNullSafe(F.col("first")))
    return hit.groupBy("k", "th").agg(F.array_sort(F.collect_set(F.struct("s", "e", "i", "j"))).alias("runs"))


def deduplicate(docs: DataFrame, key: str = "doc_id", text: str = "text", min_words: int = MIN_WORDS) -> DataFrame:
    """Per row: key, n_sentences, n_removed, n_chars_removed and clean (the text without them).

    Texts are read once; their spans are written to the shared folder, some 40 bytes for each sentence.
    A null text stays null and has no sentences; rows that repeat both key and text are one
    document and keep the same; white space after a removed sentence goes with it.  A span that comes
    again in its own document is a repeated one as well.
    """
    table = materialise(span_table(docs, key, text, min_words), "spans")
    runs = materialise(repeats(table), "runs").withColumnsRenamed({"k": "ck", "th": "cth"})
    per = table.groupBy(F.col("k").alias("rk"), F.col("th").alias("rth")).agg(F.max("n").alias("n_sentences"))
    other = per.join(runs, F.col("rk").eqNullSafe(F.col("ck")) & (F.col("rth") == F.col("cth")), "left").drop("ck", "cth")
    rows = docs.select(F.col(f"`{key}`").alias("k"), F.col(f"`{text}`").alias("t"), F.xxhash64(f"`{text}`").alias("th"))
    both = rows.join(other, F.col("k").eqNullSafe(F.col("rk")) & (F.col("th") == F.col("rth")), "left")
    removed = "aggregate(runs, named_struct('n', 0L, 'e', 0), (a, x) -> named_struct('n', a.n + greatest(0, x.{1} - greatest(x.{0}, a.e)), 'e', greatest(a.e, x.{1})), a -> a.n)"
    kept = "aggregate(runs, named_struct('out', '', 'at', 0), (a, x) -> named_struct('out', a.out || substring(t, a.at + 1, greatest(0, x.s - a.at)), 'at', greatest(a.at, x.e)), a -> a.out || substring(t, a.at + 1))"
    return both.select(
        F.col("k").alias(key),
        "n_sentences",
        F.coalesce(F.expr(removed.format("i", "j")), F.lit(0)).cast("bigint").alias("n_removed"),
        F.coalesce(F.expr(removed.format("s", "e")), F.lit(0)).cast("bigint").alias("n_chars_removed"),
        F.when(F.col("runs").isNull(), F.col("t")).otherwise(F.expr(kept)).alias("clean"),
    )


def digest(cleaned: DataFrame, key: str = "doc_id") -> DataFrame:
    return cleaned.select(key, "n_sentences", "n_removed", "n_chars_removed", F.sha2(F.coalesce("clean", F.lit("")).cast("binary"), 256).alias("clean_sha256"))
