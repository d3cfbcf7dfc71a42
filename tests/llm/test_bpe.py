import random

import pytest
from tokenizers import Tokenizer

from xorvault.llm.pair_index_bpe import PairIndexBpe, default_vocabulary, encode_documents


@pytest.fixture(scope="module")
def both():
    return PairIndexBpe(default_vocabulary()), Tokenizer.from_file(default_vocabulary())


def ids(bpe, text):
    import numpy as np

    return np.frombuffer(bpe.encode_batch([text])[0], "<u4").tolist()


CASES = ["", " ", "a", "aaaaaaaaaaaaaaaaa", "Hello  world\n\n it's", "<|endoftext|>", "a<|endoftext|>b <|endoftext|>", "\x1c\x1d \x85 x", "日本語 text 😀😀", "ÉÈ́ ß ñ", "᠎​﻿", "x" * 5000, "\x00\x01\x7f", "1234567 89", "\t\t\n  \r\n end  "]


@pytest.mark.parametrize("text", CASES)
def test_as_the_library(both, text):
    bpe, library = both
    want = library.encode(text, add_special_tokens=False).ids
    assert ids(bpe, text) == want
    assert bpe.decode(bpe.encode_batch([text])[0]) == library.decode(want, skip_special_tokens=False)


def test_random_texts_as_the_library(both):
    bpe, library = both
    rng = random.Random(5)
    alphabet = list("abcdefgh ABC.,'\n\t  0123éñ漢😀*$%") + ["the ", " ing", "'s", "'ll ", "<|endoftext|>"]
    texts = ["".join(rng.choices(alphabet, k=rng.randint(0, 300))) for _ in range(400)]
    for text, got in zip(texts, bpe.encode_batch(texts)):
        want = library.encode(text, add_special_tokens=False).ids
        assert list(memoryview(got).cast("I")) == want


def test_rows(spark):
    rows = [(1, None, "x"), (2, "", "x"), (3, "hello hello", "x"), (3, "hello hello", "x"), (None, "a b", "x")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, n_tokens string")
    got = {(r.doc_id, r.n_tokens) for r in encode_documents(docs).collect()}
    assert got == {(1, 0), (2, 0), (3, 2), (None, 2)}
    assert encode_documents(docs.limit(0)).count() == 0
