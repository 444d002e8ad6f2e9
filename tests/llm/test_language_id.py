import itertools
import zlib

import numpy as np

from chronocluster.llm import language_id as li


def small():
    field = li.LanguageField(["aa", "bb"])
    rng = np.random.default_rng(0)
    field.index = {f: i + 1 for i, f in enumerate(sorted({f for w in ("one", "two", "three") for f in li.word_features(w)}))}
    field.states = rng.standard_normal((len(field.index) + 1, 2))
    field.states[0] = 0
    field.transitions, field.start = rng.standard_normal((2, 2)), rng.standard_normal(2)
    return field


def test_marginals_equal_the_sum_over_all_labellings():
    field = small()
    docs = [["one", "two", "three", "two"], ["three"], [], ["two", "unknown"]]
    for words, got in zip(docs, field.marginals(docs), strict=True):
        scores = [sum(field.states[i] for i in field._ids(w)) + np.zeros(2) for w in words]
        total, want = 0.0, np.zeros((len(words), 2))
        for ys in itertools.product(range(2), repeat=len(words)):
            if not ys:
                continue
            v = np.exp(field.start[ys[0]] + sum(s[y] for s, y in zip(scores, ys, strict=True)) + sum(field.transitions[a, b] for a, b in zip(ys, ys[1:], strict=False)))
            total += v
            for t, y in enumerate(ys):
                want[t, y] += v
        assert got.shape == (len(words), 2)
        if words:
            assert np.allclose(got, want / total)


def test_gradient_is_that_of_the_likelihood():
    field = small()
    words = [["one", "two", "three"], ["two", "two", "one"]]
    kinds = ["one", "two", "three"]
    each = [field._ids(w) for w in kinds]
    ids = np.array([[kinds.index(w) for w in ws] for ws in words])
    y = np.array([[0, 1, 1], [1, 0, 0]])

    def likelihood():
        out = 0.0
        for i in range(2):
            e = np.array([field.states[each[w]].sum(0) for w in ids[i]])
            path = lambda ys: field.start[ys[0]] + sum(e[t][c] for t, c in enumerate(ys)) + sum(field.transitions[a, b] for a, b in zip(ys, ys[1:], strict=False))  # noqa: E731, B023
            out += path(y[i]) - np.log(sum(np.exp(path(p)) for p in itertools.product(range(2), repeat=3)))
        return out / 2

    gs, gt, g0 = field._gradient(ids, y, np.concatenate(each), np.array([len(x) for x in each]))
    for table, gradient, at in ((field.states, gs + 1e-5 * field.states, (3, 1)), (field.transitions, gt, (0, 1)), (field.start, g0, (1,))):
        before = likelihood()
        table[at] += 1e-5
        assert abs((likelihood() - before) / 1e-5 - gradient[at]) < 1e-3
        table[at] -= 1e-5


def test_held_out_accuracy_and_code_switching(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    field = li.train(docs)
    rows = docs.withColumn("held", li.held_out("doc_id")).collect()
    assert all(r.held == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in rows)
    held = [r for r in rows if r.held]
    labels, scores = field.predict([r.text for r in held])
    assert np.mean([a == r.lang for a, r in zip(labels, held, strict=True)]) > 0.97
    assert all(0 <= s <= 1 for s in scores)
    en, de = (next(li.words_of(r.text)[:30] for r in rows if r.lang == x and len(li.words_of(r.text)) > 60) for x in ("en", "de"))
    m = field.marginals([en + de])[0].argmax(1)
    assert (m[:30] == field.labels.index("en")).mean() > 0.7 and (m[30:] == field.labels.index("de")).mean() > 0.7


def test_rows(spark):
    rows = [(1, "the cat and the dog", "en", "s"), (2, "der hund und die katze", "de", "s"), (4, None, "en", "s"), (5, "123 456 !!", "de", "s"), (6, "", None, None), (7, "² ½", "en", "s"), (None, "the dog", "en", "s"), (1, "the cat and the dog", "en", "s")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, score string")
    out = li.identify(df, ["doc_id"], "text", li.train(df)).collect()
    got = {r.doc_id: (r.lang_pred, r.score) for r in out}
    assert len(out) == 8 and all(got[i] == ("und", 0.0) for i in (4, 5, 6, 7)) and got[1][0] in ("en", "de")
    empty = df.limit(0)
    assert li.identify(df, ["doc_id"], "text", li.train(empty)).filter("lang_pred = 'und'").count() == 8
    assert li.identify(empty, ["doc_id"], "text", li.train(empty)).count() == 0


def test_every_letter_of_a_word_counts():
    """Far beyond the first dozen letters, and in text without spaces."""
    assert len(li.word_features("a" * 500)) == 6 + 501 + 500
    field = li.LanguageField(["aa", "bb"]).fit([("kaka kako koka " * 20, "aa"), ("zuzu zuzi zizu " * 20, "bb")])
    for tail, want in (("kakokaka" * 400, "aa"), ("zuzizuzu" * 400, "bb")):
        assert field.predict(["q" * 60 + tail])[0] == [want]
    long = " ".join(["kaka kako"] * 30_000)
    (label,), (score,) = field.predict([long])
    assert label == "aa" and score > 0.9


def test_training_reads_a_bounded_number_of_rows(spark):
    """One key and text in most rows is one document; the bound holds for keys with many texts."""
    rows = [(4, "la casa roja", "es")] * 500 + [(4, f"le chat {i}", "fr") for i in range(300)] + [(9, "the red house", "en"), (None, "x y", "en"), (12, None, "en")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, lang string")
    field = li.train(df, per_language=20)
    assert field.labels == ["en", "es", "fr"] and field.predict(["la casa", "le chat", "the house"])[0] == ["es", "fr", "en"]
