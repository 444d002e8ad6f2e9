"""Document fingerprints by SimHash, with DataFrame functions only.

A term is a run of five words (the whole text where it has fewer), and its weight is how often it
occurs.  Every occurrence votes on 64 signed bits: bit b of the fingerprint is set if terms with a
set bit b outweigh the others.  The 64 counters travel in 16 long sums of four 16-bit fields each,
so that voting stays inside generated code.
"""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import materialise

#: Words of a term, bits of a fingerprint, and terms whose votes share one set of packed counters.
TERM, BITS, CHUNK = 5, 64, 16384
#: Documents of a bucket of the order by id, and how many buckets there are at most.
BUCKET_ROWS, MOST_BUCKETS = 512, 1 << 16
MASK = 0x0001000100010001
#: Bits in which near fingerprints may differ, and blocks that the bits are cut into for their search.
RADIUS, BLOCKS = 3, 6
#: Every which id asks for its near documents.
ASKED = 20


def words(text: Column) -> Column:
    """Hashes of the words between ASCII white space, with A-Z made lower case."""
    lower = F.translate(F.coalesce(text, F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    return F.transform(F.filter(F.split(lower, r"[\x20\x09-\x0D]+"), lambda w: w != ""), lambda w: F.xxhash64(w))


def n_terms(hashes: Column) -> Column:
    return F.when(F.size(hashes) == 0, 0).otherwise(F.greatest(F.lit(1), F.size(hashes) - (TERM - 1)))


def fingerprints(df: DataFrame, keys: list[str], texts: list[str]) -> DataFrame:
    """keys and, for each named text column, fp_<name> (a long).

    keys must tell the rows apart and hold what df is already partitioned by, if no shuffle is
    wanted.  A null text or one without words has no votes and the fingerprint 0.
    """
    hashed = df.select(*keys, *(words(F.col(t)).alias(f"w_{t}") for t in texts))
    sized = hashed.select(*keys, *(f"w_{t}" for t in texts), *(n_terms(F.col(f"w_{t}")).alias(f"n_{t}") for t in texts))
    longest = F.greatest(*(F.col(f"n_{t}") for t in texts), F.lit(1))
    each = sized.withColumn("i", F.explode(F.sequence(F.lit(0), longest - 1)))

    def term(t: str) -> Column:
        w = F.col(f"w_{t}")
        return F.when(F.col("i") < F.col(f"n_{t}"), F.xxhash64(*(F.get(w, F.col("i") + k) for k in range(TERM)))).otherwise(F.lit(0).cast("bigint"))

    numbers = [f"n_{t}" for t in texts]
    voted = each.select(*keys, *numbers, (F.col("i") / CHUNK).cast("int").alias("chunk"), *(term(t).alias(f"h_{t}") for t in texts))
    packed = voted.groupBy(*keys, *numbers, "chunk").agg(*(F.sum(F.shiftright(f"h_{t}", k).bitwiseAND(F.lit(MASK))).alias(f"s_{t}_{k}") for t in texts for k in range(16)))
    fields = lambda t: F.array(*(F.shiftright(f"s_{t}_{k}", 16 * f).bitwiseAND(F.lit(0xFFFF)) for f in range(4) for k in range(16)))
    chunks = packed.select(*keys, *numbers, *(fields(t).alias(f"v_{t}") for t in texts)).groupBy(*keys, *numbers).agg(*(F.collect_list(f"v_{t}").alias(f"v_{t}") for t in texts))

    def bits(t: str) -> Column:
        return F.expr(
            f"aggregate(zip_with(sequence(0, {BITS - 1}), aggregate(v_{t}, array_repeat(0L, {BITS}), (a, v) -> zip_with(a, v, (x, y) -> x + y)), "
            f"(b, n) -> if(2 * n > n_{t}, shiftleft(1L, b), 0L)), 0L, (a, x) -> a | x)"
        )

    return chunks.select(*keys, *(bits(t).alias(f"fp_{t}") for t in texts))


def likeness(a: Column, b: Column) -> Column:
    """The share of bits in which two fingerprints agree."""
    return 1 - F.bit_count(a.bitwiseXOR(b)) / F.lit(float(BITS))


def as_text(fp: Column) -> Column:
    return F.lpad(F.lower(F.hex(fp)), BITS // 4, "0")


def _place(key: Column, spread: Column, edges: list[int]) -> Column:
    """The bucket of a key between ascending edges; a key that fills several buckets is cut by spread, a long."""
    table = F.split(F.lit(",".join(map(str, edges))), ",").cast("array<bigint>")
    steps = F.array(*(F.lit(1 << i) for i in reversed(range(len(edges).bit_length()))))

    def passed(below) -> Column:
        ahead = lambda p, s: (p + s <= len(edges)) & below(F.try_element_at(table, p + s), key)
        return F.aggregate(steps, F.lit(0), lambda p, s: F.when(ahead(p, s), p + s).otherwise(p))

    low, high = passed(lambda e, k: e < k), passed(lambda e, k: e <= k)
    share = (F.shiftright(spread, 32) + F.lit(1 << 31)) / float(1 << 32)
    return (low + F.floor(share * (high - low + 1))).cast("bigint")


def in_order(docs: DataFrame, key: str, text: str) -> DataFrame:
    """Each document beside its successor in ascending order of key (the first follows the last).

    Rows: bucket, place (ascending in a bucket), donor, id, this, next.  Keys are cut into buckets at
    their quantiles, so that buckets hold like numbers of rows however keys are spread; and a bucket also
    gets the first document of the one after it, marked donor; so one shuffle brings all pairs
    together.  Rows with equal keys follow in the order of their texts' hashes, by which a key in many rows
    is cut too; rows without a key follow themselves.
    """
    rows = docs.select(F.col(f"`{key}`").cast("bigint").alias("id"), F.col(f"`{text}`").alias("this")).withColumn("h", F.xxhash64("this"))
    cuts = max(1, min(MOST_BUCKETS, docs.count() // BUCKET_ROWS))
    edges = rows.agg(F.percentile_approx("id", [i / cuts for i in range(1, cuts)], 10 * cuts)).first()[0] if cuts > 1 else None
    numbered = rows.withColumn("bucket", F.when(F.col("id").isNull(), -1 - F.pmod("h", F.lit(MOST_BUCKETS))).otherwise(_place(F.col("id"), F.col("h"), edges) if edges else F.lit(0).cast("bigint")))
    heads = numbered.filter("id is not null").groupBy("bucket").agg(F.min(F.struct("id", "h")).alias("head"))
    order = Window.orderBy("bucket")
    heads = heads.select("head", F.lag("bucket").over(order).alias("before"), F.max("bucket").over(order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("last"))
    donors = rows.join(F.broadcast(heads), (F.col("id") == F.col("head.id")) & (F.col("h") == F.col("head.h"))).select(
        "id", "this", "h", F.coalesce("before", "last").alias("bucket"), F.lit(True).alias("donor"), F.col("before").isNull().cast("int").alias("late")
    )
    both = numbered.select("id", "this", "h", "bucket", F.lit(False).alias("donor"), F.lit(0).alias("late")).unionByName(donors.dropDuplicates(["bucket", "late"]))
    inside = Window.partitionBy("bucket").orderBy("late", "donor", "id", "h")
    paired = both.select("*", F.lead(F.coalesce("this", F.lit(""))).over(inside).alias("following"))
    return paired.select("bucket", F.monotonically_increasing_id().alias("place"), "donor", "id", "this", F.when(F.col("id").isNull(), F.coalesce("this", F.lit(""))).otherwise(F.col("following")).alias("next"))


def edited(this: Column, following: Column) -> Column:
    """The text whose last quarter is replaced by as many characters of the following text, or all of it."""
    this = F.coalesce(this, F.lit(""))
    quarter = F.floor(F.length(this) / 4).cast("int")
    return F.concat(F.substring(this, F.lit(1), F.length(this) - quarter), F.substring(F.coalesce(following, F.lit("")), F.lit(1), quarter))


def document_fingerprints(docs: DataFrame, key: str = "doc_id", text: str = "text", asked: int = ASKED, radius: int = RADIUS) -> DataFrame:
    """Per row: key, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next, n_within.

    n_within: for rows whose key is divisible by asked, how many other rows have a fingerprint at most
    radius bits away; null for the rest.  A null text counts as empty; empty texts have the fingerprint
    0; rows without a key, and the only row of a table, follow themselves; repeated rows each give a row.
    """
    rows = in_order(docs, key, text)
    full = rows.select("bucket", "place", "donor", "id", "this", edited(F.col("this"), F.col("next")).alias("that"))
    keyed = full.select("bucket", "place", "donor", "id", "this", "that", F.coalesce(F.length("this"), F.lit(0)).cast("bigint").alias("n_chars"), F.sha2(F.col("that").cast("binary"), 256).alias("sha"))
    voted = fingerprints(keyed, ["bucket", "place", "donor", "id", "n_chars", "sha"], ["this", "that"])
    after = F.when(F.col("id").isNull(), F.col("fp_this")).otherwise(F.lead("fp_this").over(Window.partitionBy("bucket").orderBy("place")))
    made = materialise(voted.withColumn("fp_next", after).filter(~F.col("donor")).select("id", "n_chars", "sha", "fp_this", "fp_that", "fp_next"), "fingerprints")
    asks = F.coalesce(F.pmod("id", F.lit(asked)) == 0, F.lit(False))
    counts = count_near(made.filter(asks), made, "fp_this", radius).toDF("fp", "near")
    counted = made.filter(asks).join(counts, F.col("fp_this") == F.col("fp")).select(*made.columns, (F.col("near") - 1).alias("n_within"))
    every = counted.unionByName(made.filter(~asks).withColumn("n_within", F.lit(None).cast("bigint")))
    return every.select(
        F.col("id").alias(key),
        "n_chars",
        F.col("sha").alias("edited_sha256"),
        as_text(F.col("fp_this")).alias("fingerprint"),
        as_text(F.col("fp_that")).alias("edited_fingerprint"),
        likeness(F.col("fp_this"), F.col("fp_that")).alias("near_edited"),
        likeness(F.col("fp_this"), F.col("fp_next")).alias("near_next"),
        "n_within",
    )


def block_masks(radius: int = RADIUS, blocks: int = BLOCKS) -> list[int]:
    """The bits of each choice of blocks - radius blocks, as longs.

    Two fingerprints within the radius differ in at most radius blocks, so they agree in one choice at least.
    """
    edges = [round(i * BITS / blocks) for i in range(blocks + 1)]
    masks = [sum(((1 << (edges[b + 1] - edges[b])) - 1) << edges[b] for b in chosen) for chosen in combinations(range(blocks), blocks - radius)]
    return [m - (1 << BITS) if m >> (BITS - 1) else m for m in masks]


def _tables(fps: DataFrame, fp: str, masks: list[int]) -> DataFrame:
    """The permuted tables: each row once for each choice of blocks, with its number and the bits in it."""
    return fps.select("*", F.posexplode(F.array(*(F.col(fp).bitwiseAND(F.lit(m)) for m in masks))).alias("table", "block"))


def _met(pairs: DataFrame, masks: list[int], radius: int) -> DataFrame:
    """Pairs (a, b) of one table within the radius, each from the first table that holds it alone."""
    apart = F.col("a").bitwiseXOR(F.col("b"))
    first = F.coalesce(*(F.when(apart.bitwiseAND(F.lit(m)) == 0, F.lit(i)) for i, m in enumerate(masks)))
    return pairs.filter((F.bit_count(apart) <= radius) & (F.col("table") == first)).withColumn("distance", F.bit_count(apart))


def count_near(asked: DataFrame, every: DataFrame, fp: str, radius: int = RADIUS, blocks: int = BLOCKS) -> DataFrame:
    """Each distinct fingerprint of asked, and how many rows of every are at most radius bits away.

    Rows with equal fingerprints are one entry of the block tables, with their number.
    """
    masks = block_masks(radius, blocks)
    queries = _tables(asked.select(F.col(f"`{fp}`").alias("a")).filter("a is not null").distinct(), "a", masks)
    held = _tables(every.groupBy(F.col(f"`{fp}`").alias("b")).agg(F.count("*").alias("n")).filter("b is not null"), "b", masks)
    return _met(queries.join(held, ["table", "block"]), masks, radius).groupBy("a").agg(F.sum("n").alias("near"))


def near_fingerprints(fps: DataFrame, fp: str, radius: int = RADIUS, blocks: int = BLOCKS) -> DataFrame:
    """All pairs a < b of distinct fingerprints at most radius bits apart, with their distance, by the block tables.

    Rows with equal fingerprints are one fingerprint here; nulls have no pair.
    """
    masks = block_masks(radius, blocks)
    tables = _tables(fps.select(F.col(f"`{fp}`").alias("a")).filter("a is not null").distinct(), "a", masks)
    pairs = tables.join(tables.withColumnRenamed("a", "b"), ["table", "block"]).filter("a < b")
    return _met(pairs, masks, radius).select("a", "b", "distance")
