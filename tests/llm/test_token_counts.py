import math

from chronocluster.llm.registry import tokenizer
from chronocluster.llm.token_counts import UnigramCounter, token_counts

PATH = tokenizer("byte_bpe_50k.tiktoken")


def plain(counter, key):
    """Segmentation of one key without a trie."""
    best = [(0.0, 0)] + [(-math.inf, 0)] * len(key)
    for j in range(1, len(key) + 1):
        for i in range(j):
            s = counter.score.get(key[i:j])
            if s is not None and (best[i][0] + s > best[j][0] or best[i][0] + s == best[j][0] and best[i][1] + 1 < best[j][1]):
                best[j] = (best[i][0] + s, best[i][1] + 1)
    return best[-1][1]


def test_counts_equal_plain_programming(spark):
    c = UnigramCounter(PATH)
    texts = ["the theory therefore them thesis", "Ünïcode straße 日本語 😀", "aaaaaaaaaaaaaaaaaaaaaaaaaaa bbb", "x" * 300 + " the", "", None, "a\n\n b  c\t"]
    tokens, pretokens = c.count_all(texts)
    for t, n, m in zip(texts, tokens, pretokens, strict=True):
        parts = c.pieces.findall(t) if t else []
        assert (n, m) == (sum(plain(c, p.encode()) for p in parts), len(parts))
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    rows = {r.doc_id: (r.n_tokens, r.n_pretokens, r.n_bytes) for r in token_counts(df, "doc_id", "text", PATH).collect()}
    assert rows == {i: (tokens[i], pretokens[i], len((t or "").encode())) for i, t in enumerate(texts)}


def test_forgetting_changes_nothing(monkeypatch):
    import chronocluster.llm.token_counts as module

    monkeypatch.setattr(module, "TERMINALS", 3)
    c, d = UnigramCounter(PATH), UnigramCounter(PATH)
    texts = ["one two three four", "five six one", "two seven"]
    assert [c.count_all([t])[0][0] for t in texts] == d.count_all(texts)[0]
