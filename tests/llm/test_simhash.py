import hashlib
import random

from pyspark.sql import functions as F

from chronocluster.llm import simhash

SCHEMA = "doc_id bigint, text string, place string, fp_this bigint"


def words(rng, n):
    return " ".join(rng.choice("abcdefghij") * rng.randint(1, 4) + str(rng.randint(0, 30)) for _ in range(n))


def rows(spark, texts, ids=None):
    ids = ids or range(len(texts))
    return spark.createDataFrame([(i, t, "x", 1) for i, t in zip(ids, texts, strict=True)], SCHEMA)


def test_edited_texts_and_fingerprints(spark, monkeypatch):
    monkeypatch.setattr(simhash, "BUCKET_ROWS", 3)
    monkeypatch.setattr(simhash, "CHUNK", 16)
    rng = random.Random(1)
    texts = [words(rng, rng.randint(0, 60)) for _ in range(20)] + [None, "", "short one", "Ünï 日本 😀 " * 9]
    ids = rng.sample(range(0, 10**12, 7), len(texts))
    got = {r.doc_id: r for r in simhash.document_fingerprints(rows(spark, texts, ids)).collect()}
    order = sorted(zip(ids, texts, strict=True))
    fps = {}
    for k, (i, t) in enumerate(order):
        t, after = t or "", order[(k + 1) % len(order)][1] or ""
        q = len(t) // 4
        assert got[i].n_chars == len(t)
        assert got[i].edited_sha256 == hashlib.sha256((t[: len(t) - q] + after[:q]).encode()).hexdigest()
        fps[i] = int(got[i].fingerprint, 16)
    for k, (i, _) in enumerate(order):
        j = order[(k + 1) % len(order)][0]
        assert got[i].near_next == 1 - (fps[i] ^ fps[j]).bit_count() / 64
        assert got[i].near_edited == 1 - (fps[i] ^ int(got[i].edited_fingerprint, 16)).bit_count() / 64


def test_votes_equal_a_plain_count(spark, monkeypatch):
    monkeypatch.setattr(simhash, "CHUNK", 8)
    text = words(random.Random(2), 50)
    df = rows(spark, [text])
    hashes = df.select(simhash.words(F.col("text")).alias("w")).first().w
    terms = spark.createDataFrame([tuple(hashes[i : i + 5]) for i in range(len(hashes) - 4)], "a bigint, b bigint, c bigint, d bigint, e bigint")
    values = [r[0] for r in terms.select(F.xxhash64("a", "b", "c", "d", "e")).collect()]
    want = sum(1 << b for b in range(64) if 2 * sum(v >> b & 1 for v in values) > len(values))
    assert int(simhash.document_fingerprints(df).first().fingerprint, 16) == want


def test_odd_rows(spark):
    df = rows(spark, ["same text here", "same text here", None, "of no id"], [5, 5, None, None])
    out = simhash.document_fingerprints(df).collect()
    assert len(out) == 4 and len({r.fingerprint for r in out if r.doc_id == 5}) == 1
    assert {r.near_next for r in out} == {1.0}
    assert simhash.document_fingerprints(df.limit(0)).count() == 0
    one = simhash.document_fingerprints(rows(spark, ["the only row of all"])).first()
    assert one.near_next == 1.0 and one.edited_sha256 == hashlib.sha256(b"the only row of" b"the ").hexdigest()


def test_block_tables_find_every_pair(spark):
    rng = random.Random(3)
    base = [rng.getrandbits(64) for _ in range(40)]
    near = [b ^ sum(1 << x for x in rng.sample(range(64), rng.randint(0, 5))) for b in base]
    values = [v - (1 << 64) if v >> 63 else v for v in base + near + base[:3]]
    df = spark.createDataFrame([(v,) for v in [*values, None]], "fp bigint")
    got = {(r.a, r.b, r.distance) for r in simhash.near_fingerprints(df, "fp").collect()}
    distinct = sorted(set(values))
    want = {(a, b, ((a ^ b) & (2**64 - 1)).bit_count()) for a in distinct for b in distinct if a < b and ((a ^ b) & (2**64 - 1)).bit_count() <= 3}
    assert got == want and got


def test_edited_quarter_is_nearer_than_the_next(spark):
    rng = random.Random(4)
    out = simhash.document_fingerprints(rows(spark, [words(rng, 300) for _ in range(30)])).collect()
    assert sum(r.near_edited for r in out) / 30 > 0.7 > 0.6 > sum(r.near_next for r in out) / 30


def test_near_documents_of_asked_rows(spark):
    """n_within against all pairs, with copies, near copies and an empty text."""
    rng = random.Random(5)
    base = [words(rng, rng.randint(1, 400)) for _ in range(60)]
    texts = base + [b + " more" for b in base[:30]] + base[:15] * 3 + ["", None]
    out = simhash.document_fingerprints(rows(spark, texts, [5 * i for i in range(len(texts))])).collect()
    fps = {r.doc_id: int(r.fingerprint, 16) for r in out}
    for r in out:
        want = sum((f ^ fps[r.doc_id]).bit_count() <= 3 for f in fps.values()) - 1
        assert r.n_within == (want if r.doc_id % 20 == 0 else None)
    assert any(r.n_within for r in out)


def test_buckets_are_even_however_keys_are_spread(spark, monkeypatch):
    monkeypatch.setattr(simhash, "BUCKET_ROWS", 50)
    ids = [*range(2000), 10**12, *[77] * 1000, *[None] * 10]
    texts = [f"text {i}" for i in range(len(ids))]
    placed = simhash.in_order(rows(spark, texts, ids), "doc_id", "text").cache()
    sizes = [r["count"] for r in placed.groupBy("bucket").count().collect()]
    assert max(sizes) <= 200 and placed.filter("not donor").count() == len(ids)
    # The order: ascending keys, equal ones by the hash of the text, and each row's next is the text after it.
    order = placed.filter("not donor and id is not null").orderBy("id", F.xxhash64("this")).collect()
    assert [r.next for r in order] == [r.this for r in order[1:]] + [order[0].this]
    placed.unpersist()


def test_very_long_text(spark):
    rng = random.Random(6)
    long = words(rng, 120_000)
    out = {r.doc_id: r for r in simhash.document_fingerprints(rows(spark, [long, "a few words to follow it", long + " x"])).collect()}
    assert out[0].n_chars == len(long) and (int(out[0].fingerprint, 16) ^ int(out[2].fingerprint, 16)).bit_count() <= 2
