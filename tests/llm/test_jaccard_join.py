import random
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from chronocluster.llm import jaccard_join as jj

SCHEMA = "doc_id bigint, text string, comp string, n string"


def shingles(text):
    words = (text or "").encode().translate(jj.A_TO_Z).split()
    return frozenset(tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))) if words else frozenset()


def brute(rows):
    """n_shingles and component_id of each row, all pairs compared."""
    sets = [shingles(t) for _, t in rows]
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, a in enumerate(sets):
        for j in range(i):
            b = sets[j]
            if a and b and 100 * len(a & b) >= 75 * len(a | b):
                root[find(i)] = find(j)
    least = {}
    for i, (k, _) in enumerate(rows):
        if k is not None:
            least[find(i)] = min(least.get(find(i), k), k)
    return Counter((k, len(s), least.get(find(i)) if s else k) for i, ((k, _), s) in enumerate(zip(rows, sets, strict=True)))


def check(spark, rows):
    df = spark.createDataFrame([(*r, "x", "y") for r in rows], SCHEMA)
    got = Counter((r.doc_id, r.n_shingles, r.component_id) for r in jj.similarity_components(spark, df).collect())
    assert got == brute(rows)


def edited(rng, words, share):
    return [f"e{rng.randint(0, 10**6)}" if rng.random() < share else w for w in words]


def test_mixed_sizes(spark):
    rng = random.Random(7)
    passage = [f"p{i}" for i in range(60)]
    rows = []
    for _ in range(12):
        base = [f"w{rng.randint(0, 3000)}" for _ in range(rng.choice([3, 5, 6, 8, 10, 12, 14, 16, 20, 60, 150]))]
        for _ in range(rng.randint(1, 5)):
            rows.append(" ".join(edited(rng, base, rng.choice([0, 0.005, 0.02, 0.06]))))
        rows.append(" ".join(base + passage))
        rows.append(" ".join(base[: max(1, len(base) * 5 // 6)]))
    rows += [None, "", "   ", "one", "ONE", "a b c d", "A  b\tc d"]
    ids = rng.sample(range(1000), len(rows))
    check(spark, [*zip(ids, rows, strict=True), (ids[0], rows[0]), (ids[1], "other text with the same id as another"), (None, rows[2]), (None, None)])


def test_chains_and_common_shingles(spark, monkeypatch):
    monkeypatch.setattr(jj, "COMMON", 4)
    rng = random.Random(8)
    words = [f"c{i}" for i in range(120)]
    rows, step = [], 0
    for i in range(14):
        rows.append((100 - i, " ".join(words)))
        words = words[6:] + [f"n{step + j}" for j in range(6)]
        step += 6
    common = [f"k{i}" for i in range(50)]
    rows += [(200 + i, " ".join(common + [f"o{i}_{j}" for j in range(rng.randint(5, 40))])) for i in range(25)]
    rows += [(300 + i, " ".join(edited(rng, [f"h{j}" for j in range(200)], 0.01))) for i in range(30)]
    check(spark, rows)


def variants(rng, count, bases, size):
    """Bases and texts that go on for one word more: 3 of 4 shingles (at size 7) are shared, the least that links."""
    rows = []
    for i in range(bases):
        base = [f"b{i}_{j}" for j in range(size)]
        rows += [" ".join(base), *(" ".join([*base, f"v{i}_{j}"]) for j in range(count))]
    rng.shuffle(rows)
    return list(enumerate(rows))


@pytest.mark.parametrize("count", [2, 8, 50])
def test_short_variants_link_through_their_base_alone(spark, count):
    check(spark, variants(random.Random(count), count, 20 if count < 50 else 4, 7))
    check(spark, variants(random.Random(count), count, 3, 8))


def test_short_texts(spark):
    """All pairs of 1,000 texts of 5 to 14 words from a few words' stock, cut, lengthened and edited."""
    rng = random.Random(11)
    rows = []
    while len(rows) < 1000:
        base = [f"s{rng.randint(0, 400)}" for _ in range(rng.randint(5, 14))]
        for _ in range(rng.randint(1, 6)):
            lo, hi = rng.randint(0, 2), len(base) - rng.randint(0, 2)
            text = base[lo : max(hi, lo + 5)] + [f"t{rng.randint(0, 9)}" for _ in range(rng.choice([0, 0, 1, 2]))]
            rows.append(" ".join(text[:14]))
    ids = rng.sample(range(5000), len(rows))
    check(spark, list(zip(ids, rows, strict=True)))


def test_empty_table(spark):
    assert jj.similarity_components(spark, spark.createDataFrame([], SCHEMA)).count() == 0
    check(spark, [(1, None), (2, "")])


@pytest.mark.parametrize("n", range(1, 12))
def test_overlap_of_sizes(n):
    """Two sets of partner sizes link exactly if they share the overlap that their sizes ask for."""
    rng = random.Random(n)
    for _ in range(60):
        a = set(rng.sample(range(14), n))
        b = set(rng.sample(range(14), rng.choice(list(jj.partner_sizes(n))))) if max(jj.partner_sizes(n)) <= 14 else a
        links = 100 * len(a & b) >= 75 * len(a | b)
        assert links == (len(a & b) >= jj.overlap(len(a), len(b)))


def test_boundary_grows_with_list_length():
    assert jj.boundary(1.0) <= jj.boundary(3.0) <= jj.boundary(100.0) < 40


def test_bit_tables_hold_what_they_were_given():
    r = jj.Rarity(16, 1 << 16)
    s = np.unique(np.random.default_rng(1).integers(0, 2**64, 3000, dtype=np.uint64))
    bucket, short = r.split(s)
    for b in range(16):
        r.shared[b] = np.frombuffer(jj.Rarity.row(short[(bucket == b) & (np.arange(len(s)) % 2 == 0)], r.shared.shape[1]), np.uint8)
        r.common[b] = np.frombuffer(jj.Rarity.row(short[(bucket == b) & (np.arange(len(s)) % 6 == 0)], r.common.shape[1]), np.uint8)
    kinds = r.classes(s)
    assert (kinds[::2] >= 1).all() and (kinds[::6] == 2).all() and (kinds[1::2] == 0).mean() > 0.5


def test_components(spark):
    links = spark.createDataFrame([(1, 2), (2, 3), (3, 4), (4, 5), (9, 8), (8, 7)], "a bigint, b bigint")
    assert {r.sid: r.comp for r in jj.components(links).collect()} == {1: 1, 2: 1, 3: 1, 4: 1, 5: 1, 7: 7, 8: 7, 9: 7}
    assert jj.components(links.filter(F.lit(False))).count() == 0
