"""Cached encoding equals the tokenizer's own, on plain and on odd texts."""

import numpy as np
import pyarrow.parquet as pq
import pytest

from privbatch.llm.tokens import Encoder, default_path

ODD = [
    "", " ", "a", "It's DON'T we'll I'D 's't", "<|endoftext|> x <| y", "Ünïcödé ß ÿ Ÿ × ÷ ¿qué? ª º ² ½ µ", "x y\x85z\x1cw",
    "日本語 テキスト", "é é", "ΟΔΟΣ ΣΑΣ", "İstanbul ſ", "1234567890 3.14 a1b2", "---!!!??? a--b __x__ ​z", "a" * 300 + " " + "é" * 200,
    "emoji 😀😀 x", "\t\n tab\r\nline", "$$$%%% the### 'tis ''s",
]


@pytest.fixture(scope="module")
def encoder():
    return Encoder(default_path(), 2)


@pytest.mark.parametrize("text", ODD)
def test_odd_texts(encoder, text):
    own = encoder.tokenizer.encode(text, add_special_tokens=False).ids + [2]
    assert np.frombuffer(encoder(text), "<u4").tolist() == own
    assert np.frombuffer(encoder(text), "<u4").tolist() == own


def test_corpus(encoder):
    for text in pq.read_table("/root/testdata/sf0.001/documents.parquet")["text"].to_pylist():
        assert np.frombuffer(encoder(text), "<u4").tolist() == encoder.tokenizer.encode(text or "", add_special_tokens=False).ids + [2]
