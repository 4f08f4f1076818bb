"""Stretches cut in numpy encode as the tokenizers library encodes whole texts."""

import random

import public_tokenizers
import pytest

from codecut.llm import tokens

PATH = public_tokenizers.path("byte_bpe_50k.json")
ATOMS = [
    *"abcXYZ ,.!?'\"0189\n\t\r\x0b\x0c\x1c\x1f\x00-_<|>", "'s", "'t", "'re", "'ll", "  ", " ", " ", "　", "é", "Ü", "ß", "×", "÷", "ÿ", "ª", "º", "µ", "½", "²",
    "٣", "́", "\U0001f600", "漢", "<|endoftext|>", "<|endoftext", "|>", "hello", "Straßenbahnhaltestelle", " world", " été", "\u0085", "​", "﻿", "ﬁ",
]


@pytest.mark.parametrize("window, most", [(64, 300), (1 << 20, 50_000)])
def test_as_the_library(window, most, monkeypatch):
    monkeypatch.setattr(tokens, "WINDOW", window)
    monkeypatch.setattr(tokens, "_LONG", 20)
    encoder, draw = tokens.CachedEncoder(PATH, most=most), random.Random(window)
    for _ in range(60):
        texts = ["".join(draw.choice(ATOMS) for _ in range(draw.choice([0, 1, 2, 3, 8, 30, 200]))) for _ in range(40)]
        want = [e.ids for e in encoder.library.encode_batch_fast(texts, add_special_tokens=False)]
        assert [x.tolist() for x in encoder.encode(texts)] == want


def test_every_letter_beside_plain_signs():
    encoder = tokens.CachedEncoder(PATH)
    texts = [f"a{c}b {c}1{c} {c}!{c}'s{c}" for c in map(chr, [*range(0x3100), *range(0xFE00, 0x10000)])]
    want = [e.ids for e in encoder.library.encode_batch_fast(texts, add_special_tokens=False)]
    assert [x.tolist() for x in encoder.encode(texts)] == want


def test_long_texts_and_odd_files(tmp_path):
    encoder = tokens.CachedEncoder(PATH)
    texts = ["", "x" * 300_000, "word after word, " * 90_000, " \n" * 70_000 + "end", ""]
    assert [x.tolist() for x in encoder.encode(texts)] == [encoder.library.encode(t, add_special_tokens=False).ids for t in texts]
    assert encoder.encode([]) == []
    with pytest.raises(ValueError):
        tokens.CachedEncoder(public_tokenizers.path("word_bpe_49k.json"))
