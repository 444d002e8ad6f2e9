import random

from chronocluster.llm import decontaminate as dc

DOCS, ITEMS = "doc_id bigint, text string, spans string, n_words string", "item_id bigint, text string, doc_id string"


def brute(docs, items, width=10):
    out = {}
    windows = []
    for item, text in items:
        w = dc.words_of(text)
        windows += [(item, w[i : i + width]) for i in range(max(1, len(w) - width + 1) if w else 0)]
    for k, text in docs:
        w, hit, found = dc.words_of(text), set(), set()
        for item, x in windows:
            for i in range(len(w) - len(x) + 1):
                if w[i : i + len(x)] == x:
                    hit |= set(range(i, i + len(x)))
                    found |= {str(item)} if item is not None else set()
        out[k] = (len(w), len(hit), len(found), dc.items_digest(list(found)), bool(hit))
    return out


def case(seed):
    rng = random.Random(seed)
    word = lambda: rng.choice("abcdefg") + rng.choice(["", "1", "é"])
    items = [(i, " ".join(word() for _ in range(rng.choice([0, 2, 4, 7, 10, 12, 30])))) for i in range(20)] + [(3, "again a 1 é b"), (None, "x y z"), (50, None), (51, "!!!")]
    docs = []
    for i in range(60):
        parts = [" ".join(word() for _ in range(rng.randint(0, 20)))]
        if rng.random() < 0.6:
            t = rng.choice(items)[1] or ""
            parts.append(rng.choice([t, t.upper().replace(" ", ", "), " ".join(t.split()[2:])]))
        rng.shuffle(parts)
        docs.append((i, " ".join(parts)))
    return [*docs, (100, None), (101, ""), (102, "X, y; Z"), (103, "no hit at all")], items


def run(spark, docs, items, **options):
    d = spark.createDataFrame([(*r, "a", "b") for r in docs], DOCS)
    b = spark.createDataFrame([(*r, "a") for r in items], ITEMS)
    return {r.doc_id: tuple(r)[1:] for r in dc.digest(dc.contamination(d, b, **options)).collect()}


def test_against_brute_force(spark):
    docs, items = case(1)
    assert run(spark, docs, items) == brute(docs, items)


def test_blocks_of_the_benchmark(spark):
    docs, items = case(2)
    assert run(spark, docs, items, block_words=60) == brute(docs, items)


def test_odd_tables(spark):
    docs, items = case(3)
    assert run(spark, docs, []) == brute(docs, [])
    assert run(spark, [], items) == {}
    rows = spark.createDataFrame([(1, "x y z", "", ""), (1, "x y z", "", ""), (None, "x y z", "", "")], DOCS)
    out = dc.digest(dc.contamination(rows, spark.createDataFrame([(None, "x y z", "a")], ITEMS))).collect()
    assert [(r.n_hit, r.n_items, r.contaminated) for r in out] == [(3, 0, True)] * 3


def test_windows_as_arrays():
    """The windows, their owners and the size of what is shipped for a larger block."""
    rng = random.Random(4)
    shared = " ".join(f"s{i}" for i in range(30))
    items = [(str(i), " ".join(f"w{rng.randint(0, 10**6)}" for _ in range(60))) for i in range(3000)] + [(f"x{i}", shared) for i in range(500)] + [("short", "one two"), ("none", "")]
    windows = dc.Windows(items, 10)
    windows.rank({})
    assert len(windows) == 3000 * 51 + 21 + 1
    arrays = [windows.words, windows.start, windows.size, windows.owner, windows.first, *(a for p in windows.prefix.values() for a in (p[0].codes, p[0].sieve, *p[1:]))]
    assert sum(a.nbytes for a in arrays) < 70 * len(windows.words)
    at, which = windows.find(dc.WordHashes().of(dc.words_of(f"a one two {shared} One, TWO")))
    assert sorted((int(a), int(windows.size[k])) for a, k in zip(at, which, strict=True)) == [(1, 2), *((i, 10) for i in range(3, 24)), (33, 2)]
    assert windows.items_of(which) == sorted(["short", *(f"x{i}" for i in range(500))])


def test_long_text(spark):
    """A very long text that repeats an item, and one of a single word over and over."""
    item = " ".join(f"w{i}" for i in range(12))
    docs = [(1, f"{item} and " * 20_000), (2, "w1 " * 200_000)]
    out = run(spark, docs, [(7, item), (8, "w1 " * 10)])
    assert out[1][:3] == (260_000, 240_000, 1) and out[2][:3] == (200_000, 200_000, 1)
