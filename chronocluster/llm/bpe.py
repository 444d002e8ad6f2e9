"""Byte-level BPE encoding and decoding by tree concatenation.

A long text is cut into leaves at its halves, without regard to words.  Leaves are encoded on
their own; neighbours are then joined bottom-up: a window around the join is encoded again and
grows until it starts and ends at token boundaries on which both sides agree.  Two kinds of
agreement are exact:

* a *safe cut*: one space between two characters that are no space.  Every scan of the
  pre-tokeniser starts a piece there, wherever it began;
* inside one unsplit piece, where merges alone decide: the window repeats a token of the left
  side and one of the right side.  A sequence of tokens is the encoding of its text if and only
  if each pair of neighbours is the encoding of the pair's text, and with such overlap every pair
  lies in one of three encodings.

The leaves of a text beyond SPREAD_CHARS are rows of their own, which many tasks encode; one task
then joins them.
"""

from __future__ import annotations

import hashlib
import json
import re
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from .common import map_texts, ready_workers

#: Characters of a leaf, and bytes of a leaf inside one unsplit piece.
LEAF_CHARS, LEAF_BYTES = 4096, 256
#: A run of this many characters without a safe cut is handled piece by piece.
UNSPLIT_CHARS = 2048
#: Characters of a text that one task encodes, and of a leaf of a longer one that is a row.
SPREAD_CHARS, ROW_CHARS = 1 << 20, 1 << 16
#: How the leaves of a part are joined: at safe cuts, inside one unsplit piece, or not at all.
PROSE, PIECE, PLAIN = 0, 1, 2
#: The pattern of the byte-level pre-tokeniser.
PIECES = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


def byte_alphabet() -> dict[str, int]:
    """The character that stands for each byte in a byte-level vocabulary file."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    other = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(other)}


class TreeCodec:
    """Encodes and decodes with the vocabulary of a tokenizers JSON file."""

    def __init__(self, path: str, leaf_chars: int = LEAF_CHARS, leaf_bytes: int = LEAF_BYTES, unsplit: int = UNSPLIT_CHARS):
        import tiktoken

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model, alphabet = spec["model"], byte_alphabet()
        own = {t["content"] for t in spec["added_tokens"]}
        ranks = {bytes(alphabet[c] for c in t): i for t, i in model["vocab"].items() if t not in own}
        made = [model["vocab"]["".join(m) if isinstance(m, list) else m.replace(" ", "", 1)] for m in model["merges"]]
        plain = spec["normalizer"] is None and spec["pre_tokenizer"]["type"] == "ByteLevel" and not spec["pre_tokenizer"]["add_prefix_space"]
        if made != sorted(made) or not plain:
            raise ValueError(f"{path} is no byte-level BPE whose ids follow the order of its merges")
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.core = tiktoken.Encoding("tree", pat_str=PIECES, mergeable_ranks=ranks, special_tokens={})
        self.bytes = {i: b for b, i in ranks.items()} | {i: s.encode() for s, i in self.special.items()}
        self.sizes = np.zeros(max(self.bytes) + 1, dtype=np.int64)
        for i, b in self.bytes.items():
            self.sizes[i] = len(b)
        self.leaf_chars, self.leaf_bytes = leaf_chars, leaf_bytes
        self.pieces = regex.compile(PIECES)
        self.unsplit = re.compile(rf"(?:(?!(?<=\S) (?=\S))[\s\S]){{{unsplit},}}") if unsplit < 64 else re.compile(rf"\S{{{unsplit},}}|\s{{{unsplit},}}")
        self.at_special = re.compile("(" + "|".join(map(re.escape, self.special)) + ")") if self.special else None

    def encode(self, text: str) -> np.ndarray:
        """The ids of a whole text; literals of special tokens become their ids."""
        if self.at_special and any(s in text for s in self.special):
            parts = self.at_special.split(text)
            return np.concatenate([np.array([self.special[p]], dtype=np.uint32) if p in self.special else self._ordinary(p) for p in parts])
        return self._ordinary(text)

    def decode(self, ids) -> str:
        return b"".join(map(self.bytes.__getitem__, ids.tolist())).decode("utf-8", "replace")

    def _ordinary(self, text: str) -> np.ndarray:
        if len(text) <= self.leaf_chars and len(text) <= 4 * self.leaf_bytes:
            return self.core.encode_to_numpy(text)
        if self.unsplit.search(text):
            return np.concatenate([self._piece(m.group().encode()) for m in self.pieces.finditer(text)])
        return self._tree(text, 0, len(text)) if len(text) > self.leaf_chars else self.core.encode_to_numpy(text)

    # Long text: leaves at arbitrary places, joined at safe cuts.

    def _tree(self, text: str, lo: int, hi: int) -> np.ndarray:
        if hi - lo <= self.leaf_chars:
            return self.core.encode_to_numpy(text[lo:hi])
        mid = (lo + hi) // 2
        return self._join(text, lo, mid, hi, self._tree(text, lo, mid), self._tree(text, mid, hi))

    @staticmethod
    def _cut(text: str, at: int, step: int, stop: int) -> int:
        """The next safe cut from at, backwards or forwards, or stop."""
        while at != stop:
            if text[at] == " " and not text[at - 1].isspace() and not text[at + 1].isspace():
                return at
            at += step
        return stop

    def _join(self, text: str, lo: int, mid: int, hi: int, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        reach = 8
        while True:
            a = self._cut(text, mid - reach, -1, lo) if mid - reach > lo else lo
            b = self._cut(text, mid + reach, 1, hi - 1) if mid + reach < hi - 1 else hi - 1
            b = hi if b == hi - 1 else b
            i = self._index(left, len(text[a:mid].encode()), from_end=True)
            j = self._index(right, len(text[mid:b].encode()), from_end=False)
            if i is not None and j is not None:
                return np.concatenate([left[:i], self.core.encode_to_numpy(text[a:b]), right[j:]])
            reach *= 2

    def _index(self, ids: np.ndarray, n: int, from_end: bool) -> int | None:
        """How many tokens lie before the boundary n bytes from one end; None if none starts there."""
        sizes = np.cumsum(self.sizes[ids[::-1]] if from_end else self.sizes[ids])
        if n == 0:
            return len(ids) if from_end else 0
        k = int(np.searchsorted(sizes, n))
        if k == len(sizes) or sizes[k] != n:
            return None
        return len(ids) - k - 1 if from_end else k + 1

    # One unsplit piece: merges alone, joined where tokens repeat.

    def _piece(self, piece: bytes) -> np.ndarray:
        if len(piece) <= self.leaf_bytes:
            return np.array(self.core._encode_single_piece(piece), dtype=np.uint32)
        mid = len(piece) // 2
        return self._splice(self._piece(piece[:mid]), self._piece(piece[mid:]))

    def _splice(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        n = 2
        while True:
            a, b = max(0, len(left) - n), min(len(right), n)
            window = np.array(self.core._encode_single_piece(b"".join(self.bytes[int(i)] for i in [*left[a:], *right[:b]])), dtype=np.uint32)
            if (a == 0 or window[0] == left[a]) and (b == len(right) or window[-1] == right[b - 1]):
                return np.concatenate([left[:a], window, right[b:]])
            n *= 2

    # Leaves as rows: (part of the text, how its leaves are joined, strings of the leaf).

    def leaves(self, text: str, size: int) -> Iterator[tuple[int, int, list[str]]]:
        """The leaves of a text in order; each is at most size characters long, but for a literal of a special token."""
        part = 0
        for stretch in self.at_special.split(text) if self.at_special else [text]:
            if stretch in self.special:
                yield part, PLAIN, [stretch]
            elif not self.unsplit.search(stretch):
                yield from ((part, PROSE, [stretch[i : i + size]]) for i in range(0, len(stretch), size))
            else:
                held, n = [], 0
                for m in self.pieces.finditer(stretch):
                    piece = m.group()
                    if held and n + len(piece) > size:
                        yield part, PLAIN, held
                        held, n, part = [], 0, part + 1
                    if len(piece) > size:
                        yield from ((part, PIECE, [piece[i : i + size]]) for i in range(0, len(piece), size))
                        part += 1
                    else:
                        held.append(piece)
                        n += len(piece)
                if held:
                    yield part, PLAIN, held
            part += 1

    def encode_leaf(self, how: int, strings: list[str]) -> np.ndarray:
        if how == PROSE:
            return self._tree(strings[0], 0, len(strings[0]))
        return np.concatenate([np.array([self.special[s]], dtype=np.uint32) if how == PLAIN and s in self.special else self._piece(s.encode()) for s in strings])

    def join_leaves(self, how: int, texts: list[str], ids: list[np.ndarray]) -> np.ndarray:
        """The ids of a part from those of its leaves, joined as a tree."""
        if len(ids) == 1:
            return ids[0]
        text, at = "".join(texts), np.cumsum([0, *map(len, texts)]).tolist()

        def fold(lo: int, hi: int) -> np.ndarray:
            if hi - lo == 1:
                return ids[lo]
            mid = (lo + hi) // 2
            left, right = fold(lo, mid), fold(mid, hi)
            return self._join(text, at[lo], at[mid], at[hi], left, right) if how == PROSE else self._splice(left, right)

        return fold(0, len(ids))


@lru_cache(maxsize=4)
def codec(path: str) -> TreeCodec:
    return TreeCodec(path)


def _described(c: TreeCodec, ids: np.ndarray, with_ids: bool) -> list:
    ids = ids.astype("<u4")
    return [len(ids), hashlib.sha256(ids.tobytes()).hexdigest(), hashlib.sha256(c.decode(ids).encode()).hexdigest(), *([ids.tolist()] if with_ids else [])]


def _rows(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
    """One row after the other, so that no second copy of a batch of long texts is made."""
    for b in batches:
        for i in range(b.num_rows):
            yield b.slice(i, 1).to_pylist()[0]


def _by_leaves(texts: DataFrame, path: str, size: int, with_ids: bool, fields: list[tuple[str, str]]) -> DataFrame:
    """__sha and fields of each row of texts (__sha, t): leaves are rows, encoded by many tasks, joined by one for each text."""
    ready_workers(texts.sparkSession)
    row = "__sha string, place int, part int, how int, strings array<string>"
    as_arrow = pa.schema([("__sha", pa.string()), ("place", pa.int32()), ("part", pa.int32()), ("how", pa.int32()), ("strings", pa.list_(pa.string()))])
    made = ", ".join(f"{n} {t}" for n, t in fields)
    result = to_arrow_schema(StructType.fromDDL(f"__sha string, {made}"))

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path)
        for r in _rows(batches):
            for place, (part, how, strings) in enumerate(c.leaves(r["t"], size)):
                yield pa.RecordBatch.from_pylist([{"__sha": r["__sha"], "place": place, "part": part, "how": how, "strings": strings}], schema=as_arrow)

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path)
        for r in _rows(batches):
            r["ids"] = c.encode_leaf(r["how"], r["strings"]).astype("<u4").tobytes()
            r["strings"] = r["strings"] if r["how"] == PROSE else []
            yield pa.RecordBatch.from_pylist([r], schema=as_arrow.append(pa.field("ids", pa.binary())))

    def join(table: pa.Table) -> pa.Table:
        c, parts = codec(path), {}
        for r in sorted(table.to_pylist(), key=lambda r: r["place"]):
            parts.setdefault(r["part"], []).append(r)
        ids = [c.join_leaves(p[0]["how"], ["".join(r["strings"]) for r in p], [np.frombuffer(r["ids"], dtype="<u4") for r in p]) for p in parts.values()]
        values = [table.column("__sha")[0].as_py(), *_described(c, np.concatenate(ids), with_ids)]
        return pa.Table.from_arrays([pa.array([v], type=f.type) for v, f in zip(values, result, strict=True)], schema=result)

    tasks = int(texts.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    leaves = texts.mapInArrow(cut, row).repartition(tasks, "__sha", "place")
    return leaves.mapInArrow(encode, f"{row}, ids binary").groupBy("__sha").applyInArrow(join, f"__sha string, {made}")


def encode_decode(df: DataFrame, keys: list[str], text: str, path: str, with_ids: bool = False, spread: int = SPREAD_CHARS, size: int = ROW_CHARS) -> DataFrame:
    """Per row: keys, n_tokens, ids_sha256 and decoded_sha256, and with with_ids the ids too.

    A null or empty text has no ids; repeated rows each give a row.  Texts of at most spread characters
    are encoded where they lie; a longer one, once for all its rows, by leaves of size characters.
    """

    def kernel() -> Callable[[list[str | None]], list[list]]:
        c = codec(path)

        def run(texts: list[str | None]) -> list[list]:
            rows = [_described(c, c.encode(t or ""), with_ids) for t in texts]
            return [[r[i] for r in rows] for i in range(3 + with_ids)]

        return run

    fields = [("n_tokens", "bigint"), ("ids_sha256", "string"), ("decoded_sha256", "string"), ("ids", "array<int>")][: 3 + with_ids]
    whole = F.col(f"`{text}`")
    beyond = F.coalesce(F.length(whole) > spread, F.lit(False))
    near = map_texts(df.filter(~beyond), keys, text, kernel, fields)
    far = df.filter(beyond).select(*[F.col(f"`{k}`") for k in keys], F.sha2(whole.cast("binary"), 256).alias("__sha"))
    texts = df.filter(beyond).select(F.sha2(whole.cast("binary"), 256).alias("__sha"), whole.alias("t")).dropDuplicates(["__sha"])
    found = _by_leaves(texts, path, size, with_ids, fields)
    return near.union(far.join(found, "__sha").select(*[F.col(f"`{k}`") for k in keys], *[n for n, _ in fields]))
