from collections import Counter

import corpus_pipeline as cp
from chronocluster.llm import bpe, decontaminate, language_id, secrets
from chronocluster.llm.registry import tokenizer

from .test_decontaminate import brute as contamination
from .test_jaccard_join import brute as components


def test_stages_equal_a_plain_run(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    rows = docs.collect()
    kept = [r for r in rows if r.text and any(c.isalpha() for c in r.text)]
    classes = {k: c for k, _, c in components([(r.doc_id, r.text) for r in kept])}
    kept = [r for r in kept if classes[r.doc_id] == r.doc_id]
    hit = contamination([(r.doc_id, r.text) for r in kept], items)
    kept = [r for r in kept if not hit[r.doc_id][4]]
    words = tokenizer("byte_bpe_50k.json")
    forest, codec = secrets.train(words), bpe.codec(words)
    want = {}
    for r in kept:
        text = r.text
        for a, b, k in reversed(secrets.candidates(text)):
            if forest.predict(secrets.np.array([secrets.features(r.text, a, b, k, words)]))[0] >= 0.5:
                text = text[:a] + secrets.MASK + text[b:]
        want[r.doc_id] = (text, len(text) if text != r.text else r.n_chars, len(codec.encode(text)))
    got = {r.doc_id: (r.text, r.n_chars, r.n_tokens) for r in cp.run(spark, sf).collect()}
    assert got == want and 0 < len(got) < len(rows)


def test_columns_and_odd_rows(spark, sf):
    rows = [(1, None, "en", "s", 0), (2, "", None, None, None), (3, "words of a text", "en", "s", 15), (3, "words of a text", "en", "s", 15), (None, "words of another text", "en", "s", 21), (4, "WORDS of a text", "en", "s", 15), (5, "42", "en", "s", 2)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")
    for name, stage in cp.STAGES:
        docs = stage(spark, docs, sf)
        assert docs.columns[: len(cp.COLUMNS)] == cp.COLUMNS, name
    left = Counter(r.doc_id for r in docs.collect())
    assert left == Counter([3, None])
    empty = spark.createDataFrame([], docs.schema)
    for _, stage in cp.STAGES:
        empty = stage(spark, empty, sf)
    assert empty.count() == 0


def test_five_stages_in_order():
    assert [n for n, _ in cp.STAGES] == ["language_id", "jaccard_join", "decontamination", "secret_scan", "bpe_codec"]
    assert language_id.UNKNOWN == "und" and decontaminate.SHINGLE == 5
