import random
from collections import defaultdict

from chronocluster.llm import substring_dedup as sd

SCHEMA = "doc_id bigint, text string, runs string, k string"


def sentence(rng, n):
    return " ".join(f"w{rng.randint(0, 10**6)}" for _ in range(n)) + "."


def brute(rows):
    """Kept texts by keys of rows, without hashes."""
    first, found = {}, defaultdict(list)
    for k, t in sorted({(k, t) for k, t in rows if t}):
        cut = sd.sentences(t)
        for _, _, i, j, s, e in sd.spans(t)[1]:
            key = tuple(tuple(t[a:b].lower().split()) for a, b in cut[i:j])
            found[key].append((k, t, i, s, e))
    drop = defaultdict(list)
    for places in found.values():
        for k, t, i, s, e in places:
            if (k, t, i) != min((p[0], p[1], p[2]) for p in places):
                drop[k, t].append((s, e))
    return {(k, t): "".join(c for x, c in enumerate(t) if not any(s <= x < e for s, e in drop[k, t])) if t else t for k, t in rows}


def test_passages_go_but_for_the_first(spark):
    rng = random.Random(5)
    passage = " ".join(sentence(rng, 12) for _ in range(5))
    line = sentence(rng, 8)
    rows = []
    for i in range(12):
        own = [sentence(rng, rng.randint(3, 15)) for _ in range(rng.randint(2, 8))]
        if i % 3 == 0:
            own.insert(rng.randint(0, len(own)), passage)
        if i % 2:
            own.append(line)
        rows.append((i, "\n".join(own) if i % 4 else " ".join(own)))
    rows += [(20, None), (21, ""), (22, passage + "\n" + passage), (23, "a. b. c."), (1, rows[1][1])]
    df = spark.createDataFrame([(*r, "x", "y") for r in rows], SCHEMA)
    out = sd.deduplicate(df).collect()
    want = brute(rows)
    assert len(out) == len(rows)
    source = defaultdict(set)
    for k, t in rows:
        source[k].add(t)
    for r in out:
        assert r.clean in {want[r.doc_id, t] for t in source[r.doc_id]}
    by = {r.doc_id: r for r in out}
    assert by[0].n_removed == 0 and passage in by[0].clean
    assert all(by[i].n_removed >= 5 and passage not in by[i].clean for i in (3, 6, 9, 22))
    assert by[20].clean is None and by[20].n_sentences == 0 and by[23].n_removed == 0
    assert line in by[1].clean and line in by[11].clean
    assert sd.deduplicate(df.limit(0)).count() == 0


def test_sentences_cover_the_text():
    for t in ("One. Two!  Three?\n\nFour", "", "no end", ". . .", "a.b.c d.\n"):
        cut = sd.sentences(t)
        assert "".join(t[a:b] for a, b in cut) == t


def test_null_keys(spark):
    rng = random.Random(6)
    text = " ".join(sentence(rng, 15) for _ in range(4))
    out = sd.deduplicate(spark.createDataFrame([(None, text, "", ""), (None, "x " + text, "", "")], SCHEMA)).collect()
    assert sorted(r.n_removed > 0 for r in out) == [False, True]


def all_runs(t):
    """Every run of several sentences with MIN_WORDS words, and every sentence with twice as many: words, first and last sentence."""
    words = [tuple(t[a:b].lower().split()) for a, b in sd.sentences(t)]
    for i in range(len(words)):
        for j in range(i + 1, len(words) + 1):
            n, several = sum(map(len, words[i:j])), sum(map(bool, words[i:j])) > 1
            if words[i] and words[j - 1] and n >= (sd.MIN_WORDS if several else 2 * sd.MIN_WORDS):
                yield tuple(words[i:j]), i, j


def test_every_sentence_of_a_repeated_run_goes(spark):
    rng = random.Random(7)
    pool = [sentence(rng, n) for n in (1, 2, 3, 5, 8, 13, 15, 16, 17, 20, 31, 32, 33, 40)]
    long, last = sentence(rng, 40), sentence(rng, 9)
    rows = [(0, f"{long} {last} {sentence(rng, 20)}"), (1, f"{sentence(rng, 4)} {long} {last}"), (2, f"\n {pool[8]}"), (3, f" \n {pool[8]} {sentence(rng, 2)}")]
    rows += [(i, rng.choice(["", "\n"]) + rng.choice(["\n", " "]).join(rng.choice(pool) if rng.random() < 0.8 else sentence(rng, 3) for _ in range(rng.randint(1, 12)))) for i in range(4, 60)]
    seen, want = set(), {}
    for k, t in rows:
        drop = set()
        for words, i, j in sorted(all_runs(t), key=lambda x: x[1:]):
            if words in seen:
                drop.update(range(i, j))
            seen.add(words)
        want[k] = len(drop), "".join(t[a:b] for i, (a, b) in enumerate(sd.sentences(t)) if i not in drop)
    got = {r.doc_id: (r.n_removed, r.clean) for r in sd.deduplicate(spark.createDataFrame([(*r, "", "") for r in rows], SCHEMA)).collect()}
    assert got == want
    assert got[1][0] == 2 and got[3][0] == 0


def test_one_occurrence_of_a_span_travels_to_its_count(spark):
    docs = spark.createDataFrame([(1, "a b."), (2, "a b.")], "doc_id bigint, text string")
    plans = []
    keep = sd.materialise
    sd.materialise = lambda df, name: plans.append(df._jdf.queryExecution().optimizedPlan().toString()) or df
    try:
        sd.repeats(sd.span_table(docs, "doc_id", "text", 1)).count()
    finally:
        sd.materialise = keep
    assert "min(struct" in plans[0] and "max(struct" not in plans[0]
