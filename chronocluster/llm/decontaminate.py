"""Benchmark decontamination as a prefix-filtered set join.

Each benchmark item is cut into windows of ``width`` consecutive words.  A window is a set of
5-word shingles (all its words where it has fewer); to contain it, a document must hold every one
of them, so its rarest shingle is the whole necessary prefix.  Rarity is counted over all documents.
A document position that holds the prefix shingle fixes the only place where the window can start;
the length and positional bounds discard places outside the text and the words are then compared.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WordHashes, map_texts, materialise, ready_workers, slices

#: Words of a shingle, unless a window has fewer.
SHINGLE = 5
#: Benchmark words of a block; its arrays take some 70 bytes for each, on the driver and in every worker.
BLOCK_WORDS = 2_000_000
#: Windows that are ranked at once.
RANKED = 100_000
#: Words are runs of 0-9, a-z and bytes over 7F, after A-Z has become a-z.
WORD_BYTES = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b > 127 else 32 for b in range(256))
WORD_PATTERN = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
PRIME = np.uint64(0x9E3779B97F4A7C15)
NONE = np.zeros(0, dtype=np.int64)


def words_of(text: str | None) -> list[bytes]:
    return (text or "").encode().translate(WORD_BYTES).split()


def codes(words: np.ndarray, m: int, salt: int = 29) -> np.ndarray:
    """One code for each run of m word hashes."""
    n = len(words) - m + 1
    if n <= 0:
        return np.zeros(0, dtype=np.uint64)
    out = np.zeros(n, dtype=np.uint64)
    for k in range(m):
        out = (out ^ (out >> np.uint64(salt))) * PRIME + words[k : k + n]
    return out ^ (out >> np.uint64(salt))


class Codes:
    """A sorted table of codes behind a sieve on their leading bits, which most strangers do not pass."""

    def __init__(self, codes: np.ndarray):
        self.codes = codes
        bits = max(10, (8 * len(codes)).bit_length())
        self.shift = np.uint64(64 - bits)
        self.sieve = np.zeros(1 << bits, dtype=bool)
        self.sieve[codes >> self.shift] = True

    def among(self, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Positions of the values that are in the table, and their places there."""
        some = np.flatnonzero(self.sieve[values >> self.shift])
        if not len(some) or not len(self.codes):
            return NONE, NONE
        at = np.minimum(np.searchsorted(self.codes, values[some]), len(self.codes) - 1)
        found = np.flatnonzero(self.codes[at] == values[some])
        return some[found], at[found]


def _spread(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The numbers from each start on, as many as its size, one run after the other."""
    ends = np.cumsum(sizes)
    return np.arange(ends[-1] if len(ends) else 0) - np.repeat(ends - sizes, sizes) + np.repeat(starts, sizes)


class Windows:
    """The distinct windows of a block of items, as arrays over the items' word hashes.

    start and size place a window in words; the items that have it are owner[first[k] : first[k + 1]].
    After rank(), prefix[m] holds the codes of the prefixes of m words, where the entries of
    each begin, and for each entry its window and the prefix's place in that.
    """

    def __init__(self, items: list[tuple[str | None, str | None]], width: int):
        hashes = WordHashes()
        texts = [np.fromiter(map(hashes.__getitem__, words_of(t)), dtype=np.uint64) for _, t in items]
        self.width, self.ids = width, [i for i, _ in items]
        self.words = np.concatenate([*texts, np.zeros(0, dtype=np.uint64)])
        lengths = np.array([len(t) for t in texts], dtype=np.int64)
        per = np.where(lengths > 0, np.maximum(1, lengths - width + 1), 0)
        start = _spread(np.cumsum(lengths) - lengths, per)
        owner = np.repeat(np.arange(len(items), dtype=np.int32), per)
        size = np.minimum(np.repeat(lengths, per), width).astype(np.int16)
        order, fresh = self._alike(start, size)
        firsts = np.flatnonzero(fresh)
        self.start, self.size = start[order][firsts], size[order][firsts]
        self.owner, self.first = owner[order], np.append(firsts, len(order))
        self.prefix: dict[int, tuple[Codes, np.ndarray, np.ndarray, np.ndarray]] = {}

    def __len__(self) -> int:
        return len(self.start)

    def _alike(self, start: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """An order of the windows that puts equal ones together, and which of them differ from the one before."""
        keys = np.zeros((2, len(start)), dtype=np.uint64)
        for n in np.unique(size).tolist():
            some = np.flatnonzero(size == n)
            for row, salt in zip(keys, (29, 31), strict=True):
                row[some] = codes(self.words, n, salt)[start[some]]
        order = np.lexsort((keys[1], keys[0], size))
        fresh = np.ones(len(order), dtype=bool)
        same = (size[order][1:] == size[order][:-1]) & (keys[:, order][:, 1:] == keys[:, order][:, :-1]).all(0)
        fresh[1:] = ~same
        return order, fresh

    def _by_size(self) -> Iterator[tuple[int, int, np.ndarray]]:
        """Words of a shingle, shingles of a window, and the windows of one size."""
        for n in np.unique(self.size).tolist():
            m = min(SHINGLE, n)
            yield m, n - m + 1, np.flatnonzero(self.size == n)

    def all_codes(self) -> dict[int, Codes]:
        got: dict[int, list[np.ndarray]] = {}
        for m, n, some in self._by_size():
            c = codes(self.words, m)
            got.setdefault(m, []).extend(np.unique(c[self.start[some] + k]) for k in range(n))
        return {m: Codes(np.unique(np.concatenate(c))) for m, c in got.items()}

    def rank(self, frequency: dict[int, tuple[Codes, np.ndarray]]) -> None:
        """Choose each window's rarest shingle, given codes and their counts; ties go to the smallest code."""
        entries: dict[int, list[tuple[np.ndarray, np.ndarray, np.ndarray]]] = {}
        for m, n, every in self._by_size():
            c = codes(self.words, m)
            table, counts = frequency.get(m, (Codes(np.zeros(0, dtype=np.uint64)), NONE))
            for lo in range(0, len(every), RANKED):
                some = every[lo : lo + RANKED]
                here = c[self.start[some][:, None] + np.arange(n)]
                seen = np.zeros(here.size, dtype=np.int64)
                at, where = table.among(here.ravel())
                seen[at] = counts[where]
                seen = seen.reshape(here.shape)
                place = np.where(seen == seen.min(1, keepdims=True), here, np.uint64(0xFFFFFFFFFFFFFFFF)).argmin(1)
                entries.setdefault(m, []).append((here[np.arange(len(some)), place], some.astype(np.int32), place.astype(np.int16)))
        for m, parts in entries.items():
            code, window, place = (np.concatenate(x) for x in zip(*parts, strict=True))
            order = np.argsort(code, kind="stable")
            table, first = np.unique(code[order], return_index=True)
            self.prefix[m] = Codes(table), np.append(first, len(order)), window[order], place[order]

    def find(self, words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where windows begin in a text's word hashes, and which windows."""
        n, at, which = len(words), [NONE], [NONE]
        for m, (table, first, window, place) in self.prefix.items():
            positions, where = table.among(codes(words, m))
            if not len(positions):
                continue
            sizes = first[where + 1] - first[where]
            entry = _spread(first[where], sizes)
            k = window[entry].astype(np.int64)
            begin = np.repeat(positions, sizes) - place[entry]
            inside = (begin >= 0) & (begin + self.size[k] <= n)
            k, begin = k[inside], begin[inside]
            for t in range(self.width):
                if not len(k):
                    break
                longer = np.flatnonzero(self.size[k] > t)
                same = np.ones(len(k), dtype=bool)
                same[longer] = words[begin[longer] + t] == self.words[self.start[k[longer]] + t]
                k, begin = k[same], begin[same]
            at.append(begin)
            which.append(k)
        return np.concatenate(at), np.concatenate(which)

    def items_of(self, windows: np.ndarray) -> list[str]:
        """The ids of the items that have any of the windows, sorted as strings."""
        k = np.unique(windows)
        owners = np.unique(self.owner[_spread(self.first[k], self.first[k + 1] - self.first[k])])
        return sorted({str(i) for o in owners.tolist() if (i := self.ids[o]) is not None})


def _frequencies(docs: DataFrame, text: str, block) -> dict[int, tuple[Codes, np.ndarray]]:
    """In how many documents each shingle of the block occurs; as many rows as the block has shingles."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w, hashes = block.value, WordHashes()
        tables = w.all_codes()
        totals = {m: np.zeros(len(t.codes), dtype=np.int64) for m, t in tables.items()}
        for whole in batches:
            for b in slices(whole, "t"):
                for t in b.column("t").to_pylist():
                    words = hashes.of(words_of(t))
                    for m, table in tables.items():
                        if len(places := table.among(codes(words, m))[1]):
                            totals[m][np.unique(places)] += 1
        for m, total in totals.items():
            some = np.flatnonzero(total)
            for lo in range(0, len(some), RANKED):
                at = some[lo : lo + RANKED]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), m, dtype=np.int32)), pa.array(tables[m].codes[at].view(np.int64)), pa.array(total[at])], names=["m", "code", "n"])

    ready_workers(docs.sparkSession)
    found = docs.select(F.col(f"`{text}`").alias("t")).mapInArrow(count, "m int, code bigint, n bigint").groupBy("m", "code").agg(F.sum("n").alias("n")).toArrow()
    m, code, n = (found.column(c).to_numpy() for c in ("m", "code", "n"))
    code = code.astype(np.int64).view(np.uint64)
    out = {}
    for k in np.unique(m).tolist():
        some = np.flatnonzero(m == k)
        some = some[np.argsort(code[some])]
        out[k] = Codes(code[some]), n[some]
    return out


def _marks(docs: DataFrame, keys: list[str], text: str, block) -> DataFrame:
    def kernel():
        w, hashes = block.value, WordHashes()

        def run(texts: list[str | None]) -> list[list]:
            out: list[list] = [[], [], []]
            for t in texts:
                words = hashes.of(words_of(t))
                begin, which = w.find(words)
                out[0].append(len(words))
                if not len(which):
                    out[1].append([])
                    out[2].append([])
                    continue
                out[1].append([{"s": s, "e": e} for s, e in np.unique(np.stack([begin, begin + w.size[which]], axis=1), axis=0).tolist()])
                out[2].append(w.items_of(which))
            return out

        return run

    return map_texts(docs, keys, text, kernel, [("n_words", "bigint"), ("spans", "array<struct<s:int,e:int>>"), ("items", "array<string>")])


def contamination(docs: DataFrame, benchmark: DataFrame, key: str = "doc_id", text: str = "text", item: str = "item_id", item_text: str = "text", width: int = 10, block_words: int = BLOCK_WORDS, carried: list[str] | None = None) -> DataFrame:
    """Per row of docs: key (or the carried columns), n_words, spans (word ranges of found windows), items (sorted ids, as strings).

    A null text has no words; an item without words is never found; an item without an id marks
    words but is not listed; repeated rows each give a row.  Words are compared by 64-bit hashes.  The
    benchmark is shipped in blocks of about block_words words (an item is not cut): its words are counted
    first, and a larger one takes two passes over docs for each block.
    """
    marks = benchmark.select(F.col(f"`{item}`").cast("string").alias("i"), F.col(f"`{item_text}`").alias("t"))
    total = marks.agg(F.sum(F.regexp_count("t", F.lit(WORD_PATTERN)))).first()[0] or 0
    n = int(total // block_words) + 1
    carried = carried or [key]
    picked = docs.select(*(F.col(f"`{c}`") for c in carried), *([] if text in carried else [F.col(f"`{text}`")]), F.xxhash64(f"`{text}`").alias("__h"))
    found = []
    for k in range(n):
        rows = marks.filter(F.pmod(F.xxhash64("t", "i"), F.lit(n)) == k).collect()
        windows = Windows([(r.i, r.t) for r in rows], width)
        sc = docs.sparkSession.sparkContext
        if len(windows):
            unranked = sc.broadcast(windows)
            frequency = _frequencies(picked, text, unranked)
            unranked.destroy()
            windows.rank(frequency)
        found.append(_marks(picked, [*carried, "__h"], text, sc.broadcast(windows)))
    if n == 1:
        return found[0].drop("__h")
    some = [materialise(f.filter(F.size("spans") > 0).select(F.col(f"`{key}`").alias("k"), F.col("__h").alias("h"), "spans", "items"), "contamination") for f in found]
    merged = some[0]
    for f in some[1:]:
        merged = merged.union(f)
    merged = merged.distinct().groupBy("k", "h").agg(F.flatten(F.collect_list("spans")).alias("spans"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"))
    words = F.regexp_count(F.coalesce(F.col(f"`{text}`"), F.lit("")), F.lit(WORD_PATTERN)).cast("bigint").alias("n_words")
    base = picked.select(*(F.col(f"`{c}`") for c in carried), "__h", words)
    empty = F.array().cast("array<struct<s:int,e:int>>")
    return base.join(merged, F.col(f"`{key}`").eqNullSafe(F.col("k")) & (F.col("__h") == F.col("h")), "left").select(*carried, "n_words", F.coalesce("spans", empty).alias("spans"), F.coalesce("items", F.array().cast("array<string>")).alias("items"))


def hit_words(spans: str = "spans"):
    """How many words lie in any of the spans."""
    return F.expr(
        f"aggregate(array_sort({spans}), named_struct('n', 0L, 'e', 0), "
        "(a, x) -> named_struct('n', a.n + greatest(0, x.e - greatest(x.s, a.e)), 'e', greatest(a.e, x.e)), a -> a.n)"
    )


def digest(marked: DataFrame, key: str = "doc_id") -> DataFrame:
    return marked.select(
        key,
        "n_words",
        hit_words().alias("n_hit"),
        F.size("items").cast("bigint").alias("n_items"),
        F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("items_sha256"),
        (hit_words() > 0).alias("contaminated"),
    )


def items_digest(ids: list[str]) -> str:
    return hashlib.sha256(",".join(sorted(ids)).encode()).hexdigest()
