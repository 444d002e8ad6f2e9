import hashlib

import numpy as np
import pytest
import regex
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from chronocluster.llm import bpe
from chronocluster.llm.registry import tokenizer

PATH = tokenizer("byte_bpe_50k.json")
LIBRARY = Tokenizer.from_file(PATH)
#: Small leaves, so that short texts are joined too.
SMALL = bpe.TreeCodec(PATH, leaf_chars=24, leaf_bytes=8, unsplit=40)
WHOLE = bpe.codec(PATH)
BITS = ["a", "the ", "Hello", " ", "  ", "\n", "é", "'s", "'re", "123", "!!", "ß", "😀", "<|endoftext|>", "<|", "日本", "\t", "xxxxxxx", "\x1c", "\x85", "\xa0", "　", "\r\n", "²", "́"]


def library(text):
    return LIBRARY.encode(text, add_special_tokens=False).ids


@settings(max_examples=300, deadline=None)
@given(st.one_of(st.lists(st.sampled_from(BITS), max_size=80).map("".join), st.text(max_size=200), st.text("abcdefghing", min_size=40, max_size=400)))
def test_equals_the_library(text):
    text = text.encode("utf-8", "replace").decode()
    for codec in (SMALL, WHOLE):
        ids = codec.encode(text)
        assert ids.tolist() == library(text)
        assert codec.decode(ids) == LIBRARY.decode(ids.tolist(), skip_special_tokens=False) == text


def by_leaves(codec, text, size):
    parts = {}
    for part, how, strings in codec.leaves(text, size):
        assert "".join(strings) in codec.special or sum(map(len, strings)) <= size
        parts.setdefault(part, []).append((how, "".join(strings), codec.encode_leaf(how, strings)))
    ids = [codec.join_leaves(p[0][0], [t for _, t, _ in p], [i for _, _, i in p]) for p in parts.values()]
    return [i for x in ids for i in x.tolist()]


@settings(max_examples=300, deadline=None)
@given(st.one_of(st.lists(st.sampled_from(BITS), max_size=80).map("".join), st.text(max_size=200), st.text("abcdefghing", min_size=40, max_size=400)), st.integers(5, 60))
def test_leaves_as_rows_equal_the_library(text, size):
    text = text.encode("utf-8", "replace").decode()
    for codec in (SMALL, WHOLE):
        assert by_leaves(codec, text, size) == library(text)


@pytest.mark.parametrize("text", ["x" * 5000, " " * 3000 + "a", "ab1!" * 2000, "word " * 4000, "é" * 3000 + " end", "<|endoftext|>" * 50])
def test_long_texts(text):
    assert WHOLE.encode(text).tolist() == SMALL.encode(text).tolist() == library(text)


def test_pieces_are_those_of_the_library():
    text = "".join(BITS) * 2
    spans = [s for _, s in LIBRARY.pre_tokenizer.pre_tokenize_str(text)]
    assert [m.span() for m in regex.finditer(bpe.PIECES, text)] == spans


def test_texts_beyond_the_spread(spark):
    texts = [None, "", "short", "word " * 400, "word " * 400, "x" * 5000 + " end\n\n" + "y" * 2100, "<|endoftext|>" * 50 + "日本" * 300, " " * 3000 + "a", "é's it 12 !" * 300]
    df = spark.createDataFrame([(i // 2 if i != 6 else None, t, "x", "y") for i, t in enumerate(texts)], "doc_id bigint, text string, strings string, __sha2 string")
    for keys in (["doc_id"], ["doc_id", "text", "strings"]):
        near, far = (bpe.encode_decode(df, keys, "text", PATH, with_ids=True, spread=spread, size=100).collect() for spread in (10**9, 50))
        assert sorted(map(repr, near)) == sorted(map(repr, far)) and len(far) == len(texts)
    assert sorted(r.ids for r in far) == sorted(library(t or "") for t in texts)


def test_rows(spark):
    rows = [(1, None, "x"), (2, "", "y"), (3, "Hello world", "z"), (3, "Hello world", "z"), (None, "hi " * 3000, None)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, n_tokens string")
    out = sorted(bpe.encode_decode(df, ["doc_id"], "text", PATH, with_ids=True).collect(), key=lambda r: (r.doc_id is None, r.doc_id or 0))
    assert [r.n_tokens for r in out] == [0, 0, 2, 2, len(library("hi " * 3000))]
    assert out[0].ids_sha256 == hashlib.sha256(b"").hexdigest() == out[1].decoded_sha256
    assert out[2].ids_sha256 == hashlib.sha256(np.array(library("Hello world"), "<u4").tobytes()).hexdigest()
    assert out[4].decoded_sha256 == hashlib.sha256(("hi " * 3000).encode()).hexdigest()
    assert bpe.encode_decode(df.limit(0), ["doc_id"], "text", PATH).count() == 0
