"""Size-aware heavy-light set similarity join on word shingles, and the components of its links.

Documents are sets of distinct 5-word shingles; two link if their Jaccard similarity reaches the
threshold.  Small sets are *light*: each lists, for every size a partner may have, its subsets of
the overlap that this size asks for, so two light sets link exactly if they list a common one.
Large sets are *heavy*: they scan the inverted lists of their rarest shingles.  A size is light
if its subsets cost less than its scans, with both costs measured on the data.

How rare a shingle is comes from all documents.  Hashes are dealt to buckets, each bucket counts
its own, and answers with its part of two bit tables of bounded size: shingles in at least two
documents, and in at least COMMON.  The order (unique, shared, common; then by hash) is a function
of the shingle, so prefixes of it are exact however full the tables get; they get longer lists only.

Equal sets are one class and never meet.  A subset's list is for one pair of sizes; the smaller sets
in it link with all of it, the larger ones need not link with each other, so its centre is always a
smallest set and the links to it join what the list joins.  In the first turn each set meets one
centre, in the second every centre of its lists that is of another component.  Only inverted lists
that then still hold several components compare the rest, across components alone.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import forget
from .common import WordHashes, materialise, ready_workers, slices

#: Words of a shingle; the similarity asked for, in hundredths; documents that make a shingle common.
SHINGLE, PERCENT, COMMON = 5, 75, 32
#: Shingle hashes that one bucket counts, and bits of the larger bit table at most.
BUCKET_HASHES, MOST_BITS = 2_000_000, 1 << 28
#: Hashes that a task holds before it deals them to the buckets.
HELD_HASHES = 1_000_000
A_TO_Z = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
MIX = np.uint64(0x9E3779B97F4A7C15)
LIST = 'array<bigint>'


def overlap(n, m, percent: int = PERCENT):
    """The least intersection of linked sets of sizes n and m: ceil(t (n + m) / (1 + t))."""
    return -(-percent * (n + m) // (100 + percent))


def partner_sizes(n: int, percent: int = PERCENT) -> range:
    return range(-(-percent * n // 100), 100 * n // percent + 1)


def prefix_size(n: int, percent: int = PERCENT) -> int:
    return n - -(-percent * n // 100) + 1


def subset_count(n: int, percent: int = PERCENT) -> int:
    return sum(comb(n, overlap(n, m, percent)) for m in partner_sizes(n, percent) if overlap(n, m, percent) <= min(n, m))


def boundary(list_length: float, percent: int = PERCENT) -> int:
    """The largest size up to which listing subsets costs less than scanning lists and comparing sets."""
    n = 1
    while subset_count(n + 1, percent) <= prefix_size(n + 1, percent) * list_length * 2 * (n + 1):
        n += 1
    return n


class Shingler:
    """Sorted distinct shingle hashes of whole texts."""

    def __init__(self):
        self.words = WordHashes()

    def __call__(self, text: str | None) -> np.ndarray:
        words = (text or "").encode().translate(A_TO_Z).split()
        if not words:
            return np.zeros(0, dtype=np.uint64)
        h = self.words.of(words)
        k = min(SHINGLE, len(h))
        n = len(h) - k + 1
        s = np.full(n, k, dtype=np.uint64)
        for i in range(k):
            s = (s ^ h[i : i + n]) * MIX
            s ^= s >> np.uint64(32)
        return np.unique(s)


def set_id(s: np.ndarray) -> int:
    import xxhash

    h = xxhash.xxh3_64_intdigest(s.tobytes())
    return h - (1 << 64) if h >> 63 else h


def _texts(docs: DataFrame, key: str, text: str) -> DataFrame:
    ready_workers(docs.sparkSession)
    return docs.select(F.col(f"`{key}`").alias("k"), F.col(f"`{text}`").alias("t"))


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, list[np.ndarray]]]:
    make = Shingler()
    for whole in batches:
        for b in slices(whole, "t"):
            yield b, [make(t) for t in b.column("t").to_pylist()]


def set_sizes(docs: DataFrame, key: str, text: str) -> DataFrame:
    """k, n and sid (the class of equal sets; null for an empty set) of each row."""
    kind = dict(_texts(docs, key, text).dtypes)["k"]

    def run(batches):
        for b, sets in _sets(batches):
            ids = [set_id(s) if len(s) else None for s in sets]
            yield pa.RecordBatch.from_arrays([b.column("k"), pa.array([len(s) for s in sets], pa.int32()), pa.array(ids, pa.int64())], names=["k", "n", "sid"])

    return _texts(docs, key, text).mapInArrow(run, f"k {kind}, n int, sid bigint")


class Rarity:
    """Which shingles are shared and which are common, as two bit tables cut by bucket."""

    def __init__(self, buckets: int, bits: int):
        self.buckets = buckets
        self.shared = np.zeros((buckets, max(64, bits // buckets) // 8), dtype=np.uint8)
        self.common = np.zeros((buckets, max(64, bits // buckets // 8) // 8), dtype=np.uint8)

    def split(self, s: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The bucket of each hash and what it is counted by there."""
        return ((s >> np.uint64(48)) * np.uint64(self.buckets) >> np.uint64(16)).astype(np.int64), (s >> np.uint64(16)).astype(np.uint32)

    @staticmethod
    def places(short: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
        """Two bits of a row of size bytes for each."""
        x = short.astype(np.uint64) * MIX
        return (x >> np.uint64(34)).astype(np.int64) % (8 * size), ((x >> np.uint64(3)) & np.uint64(0x3FFFFFFF)).astype(np.int64) % (8 * size)

    @staticmethod
    def row(short: np.ndarray, size: int) -> bytes:
        """A bucket's part of a table of which these are members."""
        row = np.zeros(size, dtype=np.uint8)
        for p in Rarity.places(short, size):
            np.bitwise_or.at(row, p >> 3, (1 << (p & 7)).astype(np.uint8))
        return row.tobytes()

    def classes(self, s: np.ndarray) -> np.ndarray:
        """0 for a shingle of one document, 1 for a shared and 2 for a common one."""
        bucket, short = self.split(s)

        def held(table: np.ndarray) -> np.ndarray:
            p, q = self.places(short, table.shape[1])
            return (table[bucket, p >> 3] >> (p & 7) & 1) & (table[bucket, q >> 3] >> (q & 7) & 1)

        return held(self.shared).astype(np.int64) + held(self.common)


def rarity(docs: DataFrame, key: str, text: str, hashes: int) -> tuple[Rarity, float]:
    """The bit tables, and the mean length of the lists of shared shingles that are not common."""
    buckets = max(16, -(-hashes // BUCKET_HASHES))
    made = Rarity(buckets, min(MOST_BITS, 1 << max(14, hashes.bit_length())))
    sizes = made.shared.shape[1], made.common.shape[1]

    split = Rarity(buckets, 0).split

    def dealt_out(once: dict[int, np.ndarray]) -> pa.RecordBatch:
        values, n = np.unique(np.concatenate(list(once.values())), return_counts=True)
        bucket, short = split(np.repeat(values, np.minimum(n, COMMON)))
        ends = np.searchsorted(bucket, np.arange(buckets + 1))
        some = np.flatnonzero(ends[:-1] < ends[1:]).tolist()
        return pa.RecordBatch.from_arrays([pa.array(some, pa.int32()), pa.array([short[ends[b] : ends[b + 1]].tobytes() for b in some], pa.binary())], names=["bucket", "hashes"])

    def deal(batches):
        once: dict[int, np.ndarray] = {}
        held = 0
        for _, sets in _sets(batches):
            for s in sets:
                if len(s) and (sid := set_id(s)) not in once:
                    once[sid] = s
                    held += len(s)
            if held > HELD_HASHES:
                yield dealt_out(once)
                once, held = {}, 0
        if once:
            yield dealt_out(once)

    def count(table: pa.Table) -> pa.Table:
        values, n = np.unique(np.concatenate([np.frombuffer(x.as_py(), dtype=np.uint32) for x in table.column("hashes")]), return_counts=True)
        light = n[(n >= 2) & (n < COMMON)].astype(np.float64)
        return pa.table({"bucket": table.column("bucket").slice(0, 1), "shared": pa.array([Rarity.row(values[n >= 2], sizes[0])], pa.binary()), "common": pa.array([Rarity.row(values[n >= COMMON], sizes[1])], pa.binary()), "lists": pa.array([float(light.sum())]), "squares": pa.array([float((light**2).sum())])})

    dealt = _texts(docs, key, text).mapInArrow(deal, "bucket int, hashes binary")
    lists = squares = 0.0
    for r in dealt.groupBy("bucket").applyInArrow(count, "bucket int, shared binary, common binary, lists double, squares double").collect():
        made.shared[r.bucket] = np.frombuffer(r.shared, dtype=np.uint8)
        made.common[r.bucket] = np.frombuffer(r.common, dtype=np.uint8)
        lists, squares = lists + r.lists, squares + r.squares
    return made, squares / lists if lists else 2.0


def signatures(docs: DataFrame, key: str, text: str, table, light: int, percent: int) -> DataFrame:
    """Of each class that may link: sid, n, its hashes, its subsets if it is light, and its inverted-list entries."""

    def run(batches):
        r: Rarity = table.value
        least = -(-percent * (light + 1) // 100)
        done: set[int] = set()
        for _, sets in _sets(batches):
            out: list[list] = [[], [], [], [], [], []]
            for s in sets:
                n = len(s)
                if not n or (sid := set_id(s)) in done:
                    continue
                if len(done) < 1_000_000:
                    done.add(sid)
                subsets, hashes, places = [], [], []
                if 1 < n <= light:
                    for m in partner_sizes(n, percent):
                        c = overlap(n, m, percent)
                        if c <= min(n, m):
                            head = np.array([min(n, m), max(n, m)], dtype=np.uint64)
                            subsets += [set_id(np.concatenate([head, s[list(x)]])) for x in combinations(range(n), c)]
                if n >= least:
                    kind = r.classes(s)
                    order = np.lexsort((s, kind))[: prefix_size(n, percent)]
                    shared = np.flatnonzero(kind[order] > 0)
                    hashes, places = s[order[shared]].view(np.int64), shared.astype(np.int32)
                if subsets or len(hashes):
                    for column, x in zip(out, (sid, n, s.view(np.int64), subsets, hashes, places), strict=True):
                        column.append(x)
            kinds = (pa.int64(), pa.int32(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.list_(pa.int32()))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, kinds, strict=True)], names=["sid", "n", "hashes", "subsets", "entries", "places"])

    return _texts(docs, key, text).mapInArrow(run, f"sid bigint, n int, hashes {LIST}, subsets {LIST}, entries {LIST}, places array<int>")


def verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose sets reach the similarity."""
    own = sets.select("sid", "n", "hashes")
    with_a = pairs.join(own.toDF("a", "na", "x"), "a")
    both = with_a.join(own.toDF("b", "nb", "y"), "b")
    common = both.select("a", "b", "na", "nb", F.size(F.array_intersect("x", "y")).alias("both"))
    return common.filter(100 * F.col("both") >= percent * (F.col("na") + F.col("nb") - F.col("both"))).select("a", "b")


def components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """sid and comp, the smallest sid that links reach, for every sid with a link.

    Labels fall to the smallest neighbour's and then to their label's label, so the rounds grow
    with the logarithm of the longest path; each round is written to the shared folder.
    """
    both = materialise(links.select(F.col("a").alias("u"), F.col("b").alias("v")).union(links.select("b", "a")).distinct(), "links")
    labels = materialise(both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("sid"), F.least("u", "m").alias("comp")), "labels")
    held = labels
    for _ in range(most_rounds):
        near = both.join(labels.withColumnsRenamed({"sid": "v"}), "v").groupBy(F.col("u").alias("sid")).agg(F.min("comp").alias("near"))
        lower = labels.join(near, "sid").select("sid", "comp", F.least("comp", "near").alias("to"))
        up = labels.select(F.col("sid").alias("to"), F.col("comp").alias("top"))
        after = materialise(lower.join(up, "to", "left").select("sid", F.least("to", F.coalesce("top", "to")).alias("comp"), (F.least("to", F.coalesce("top", "to")) < F.col("comp")).alias("fell")), "labels")
        forget(held)
        held, labels = after, after.select("sid", "comp")
        if after.filter("fell").isEmpty():
            return labels
    raise RuntimeError("the labels did not settle")


def _possible(percent: int):
    """Length bound, and the bound on what two sets can share from a common entry on."""
    n, m = F.col("n"), F.col("m")
    rest = 1 + F.least(n - F.col("place") - 1, m - F.col("spot") - 1)
    return (100 * F.least(n, m) >= percent * F.greatest(n, m)) & ((100 + percent) * rest >= percent * (n + m))


def _placed(lists: DataFrame, comps: DataFrame | None) -> DataFrame:
    """The entries of lists with the component of each set; a set without a link is its own."""
    if comps is None:
        return lists.withColumn("comp", F.col("sid"))
    return lists.join(comps, "sid", "left").withColumn("comp", F.coalesce("comp", "sid"))


def _merged(comps: DataFrame | None, links: DataFrame) -> DataFrame:
    """The components after more links; only these are followed, between the components so far."""
    if comps is None:
        return components(links)
    if links.isEmpty():
        return comps
    at = lambda side: comps.select(F.col("sid").alias(side), F.col("comp").alias(f"c{side}"))
    between = links.join(at("a"), "a", "left").join(at("b"), "b", "left").select(F.coalesce("ca", "a").alias("a"), F.coalesce("cb", "b").alias("b")).filter("a <> b")
    joined = components(between).toDF("comp", "to")
    moved = comps.join(joined, "comp", "left").select("sid", F.coalesce("to", "comp").alias("comp"))
    fresh = joined.select(F.col("comp").alias("sid"), F.col("to").alias("comp")).join(comps.select("sid"), "sid", "left_anti")
    return materialise(moved.unionByName(fresh), "labels")


def _split(placed: DataFrame, key: str) -> DataFrame:
    """The entries of lists that hold more than one component."""
    several = placed.groupBy(key).agg(F.min("comp").alias("low"), F.max("comp").alias("high")).filter("low < high").select(key)
    return placed.join(several, key, "left_semi")


def _stars(placed: DataFrame, key: str, turn: int, percent: int | None = None) -> DataFrame:
    """a, b, own: each set of a list with the list's centre, if they are of different components.

    The centre is the set with the least own.  In lists of subsets that is the set's size, in both turns:
    only a smallest set is sure to link with the rest.  In inverted lists (given with percent, held to the
    length and positional bounds) it is the number of shingles of its own, those before its first
    entry, in the first turn, as such a set is the one that its copies are most like; later it is one
    by hash.  Lists with much the same sets agree on it.
    """
    carried = [F.col("sid").alias("b"), F.col("own").alias("rank"), F.col("comp").alias("over"), *([F.col("n").alias("m"), F.col("place").alias("spot")] if percent else [])]
    order = [F.col("own").alias("o")] if turn == 0 or percent is None else []
    centre = placed.groupBy(key).agg(F.min(F.struct(*order, F.xxhash64("sid", F.lit(turn)).alias("h"), *carried)).alias("c"), F.count("*").alias("size")).filter("size > 1").select(key, "c.*").drop("h", "o")
    pairs = placed.join(centre, key).filter("comp <> over")
    return (pairs.filter(_possible(percent)) if percent else pairs).select(F.col("sid").alias("a"), "b", "rank")


def _one_each(pairs: DataFrame) -> DataFrame:
    """Of a set's centres the one with the least own."""
    return pairs.groupBy("a").agg(F.min(F.struct("rank", F.xxhash64("b").alias("h"), "b")).alias("c")).select("a", "c.b")


def _ordered(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def _across(placed: DataFrame, percent: int) -> DataFrame:
    """a, b: all pairs of a list that are of different components and within the bounds."""
    rest = _split(placed, "shingle")
    other = rest.select("shingle", F.col("sid").alias("b"), F.col("n").alias("m"), F.col("place").alias("spot"), F.col("comp").alias("over"))
    return rest.join(other, "shingle").filter((F.col("comp") < F.col("over")) & _possible(percent)).select(F.col("sid").alias("a"), "b")


def similarity_components(spark: SparkSession, docs: DataFrame, key: str = "doc_id", text: str = "text", percent: int = PERCENT) -> DataFrame:
    """Per row: key, n_shingles, component_id (the smallest key that links reach, itself included).

    A null text and one without words have an empty set, which links with nothing; equal sets link;
    repeated rows each give a row; rows without a key take part, and a component of such rows alone
    has no id.
    """
    sized = materialise(set_sizes(docs, key, text), "sets")
    hashes = sized.agg(F.sum(F.col("n").cast("bigint"))).first()[0] or 0
    table, mean = rarity(docs, key, text, hashes)
    light = boundary(mean, percent)
    raw = signatures(docs, key, text, spark.sparkContext.broadcast(table), light, percent)
    sets = materialise(raw.dropDuplicates(["sid"]), "signatures")

    entries = sets.select("sid", "n", F.array_min("places").alias("own"), F.explode(F.arrays_zip("entries", "places")).alias("e")).select("sid", "n", "own", F.col("e.entries").alias("shingle"), F.col("e.places").alias("place"))
    subsets = sets.select("sid", F.col("n").alias("own"), F.explode("subsets").alias("subset"))
    no_pairs = spark.createDataFrame([], "a bigint, b bigint")
    tried, comps = no_pairs, None
    for turn in range(2):
        near = _one_each(_stars(_placed(entries, comps), "shingle", turn, percent))
        near = near.union(_stars(_placed(subsets, comps), "subset", turn).select("a", "b") if turn else _one_each(_stars(_placed(subsets, comps), "subset", turn)))
        new = materialise(_ordered(near).join(tried, ["a", "b"], "left_anti"), "pairs")
        tried = tried.union(new)
        comps = _merged(comps, materialise(verified(new, sets, percent), "verified"))
    late = materialise(verified(_ordered(_across(_placed(entries, comps), percent)).join(tried, ["a", "b"], "left_anti"), sets, percent), "verified")
    comps = _merged(comps, late)

    labelled = materialise(sized.join(comps, "sid", "left").select("k", "n", F.coalesce("comp", "sid").alias("comp")), "classes")
    smallest = materialise(labelled.filter("comp is not null").groupBy("comp").agg(F.min("k").alias("least")), "components")
    return labelled.join(smallest, "comp", "left").select(F.col("k").alias(key), F.col("n").cast("bigint").alias("n_shingles"), F.when(F.col("comp").isNull(), F.col("k")).otherwise(F.col("least")).alias("component_id"))
