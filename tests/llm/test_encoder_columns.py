import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest

pytest.importorskip("approxset.llm")
from approxset.llm import packing, textkit

VOCAB = public_tokenizers.path("word_bpe_49k.json")
END = b"\x01\x00"


@pytest.fixture(scope="module")
def enc():
    return textkit.WordEncoder(VOCAB)


def of_library(enc, texts):
    return [np.array(enc.lib.encode(t or "", add_special_tokens=False).ids, enc.dtype).tobytes() + END for t in texts]


def test_columns_are_the_librarys_ids(enc):
    """Every character below U+3000 in a word, contractions, special tokens, white space, long pieces, nulls; in one run and in many."""
    texts = [f"a{chr(i)}'s Zz{chr(i)}1{chr(i)}{chr(i)} {chr(i)}b" for i in range(1, 0x3000)]
    texts += [None, "", " ", "\n\n", "a" * 64, "a" * 65, "é" * 32, "é" * 33, "!?" * 200, "'''s !'s 's't'll it's", "ΑΣ İst", "\U0001f600a ﻿", "x<|endoftext|> y", "<|startoftext|>", "<|start"]
    want = of_library(enc, texts)
    assert enc.columns(pa.array(texts), END).to_pylist() == want
    assert enc.columns(pa.array(["cut", *texts], pa.large_string()).slice(1), END, most=100).to_pylist() == want
    assert enc.columns(pa.array([], pa.string()), END).to_pylist() == []
    assert enc.columns(pa.array([None], pa.string()), END).to_pylist() == [END]


def test_random_words_are_merged_as_the_library_does(enc):
    rng = np.random.default_rng(4)
    letters = np.array(list("aaaeeinorsttthhé.!'7&"))
    texts = [" ".join("".join(rng.choice(letters, n)) for n in rng.integers(1, 30, 40)) for _ in range(200)]
    assert enc.columns(pa.array(texts), END).to_pylist() == of_library(enc, texts)


def test_a_word_below_u0180_needs_no_call_of_the_library():
    enc = textkit.WordEncoder(VOCAB)
    texts = ["Anblewh sttible, it's 1842.", "geché*** ÖL&&&"]
    want = of_library(enc, texts)
    enc.model = enc.lib = None
    assert enc.columns(pa.array(texts), END).to_pylist() == want
    assert not enc.pieces


def test_terms_of_many_documents():
    rng = np.random.default_rng(5)
    docs = [rng.integers(0, 50, n).astype(np.uint16) for n in (3, 1, 0, 400, 7)]
    for vocab in (50, 1 << 31):  # keys of 32 and of 64 bits
        term, tf, at = packing._terms(docs, vocab)
        for i, d in enumerate(docs):
            t, n = np.unique(d, return_counts=True)
            assert term[at[i] : at[i + 1]].tolist() == t.tolist() and tf[at[i] : at[i + 1]].tolist() == n.tolist()
