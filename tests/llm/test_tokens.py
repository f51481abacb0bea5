"""Token ids against the library: words met alone first, in two orders, over a wide alphabet."""

from __future__ import annotations

import random

import numpy as np
import pyarrow as pa
import pytest
from tokenizers import Tokenizer

from motif_spark.llm import tokens

ALPHABET = [
    *"abcdehijtwyzABHIJKTWYZ019 ''.,;:!?-_|()*&%$#<>=/\\\"~^`@[]{}+\t\n\x0b\x0c\r\x1c\x1d\x1f\x00\x7f",
    *"éÉñßüÜçïÿÀ×÷ªºµ²½øŒœİıŁłſƒǰǅɐʰʼάΩσςΣЖжёЁѐѠ҂҈Ԁհאבعा॒กኀ中文字一あアㅎ한가각ﬁﬀ𝒳𐐷😀👍🏽é",
    "\u0085", " ", " ", " ", "　", "​", "‍", "﻿", "‘", "’", "“", "”", "–", "—", "…",
    "̀", "́", "̇", "̈", "̊", "̌", "̣", "̱", "̸", "ͅ", "҃", "ְ", "़", "ᄀ", "ᅡ", "ᆨ",
    "'s", "'t", "'re", "'ll", "don't", "<|", "<|endoftext|>", "the", "ing",
]


def random_texts(n: int, seed: int) -> list[str]:
    rng = random.Random(seed)
    return ["".join(rng.choices(ALPHABET, k=rng.randint(1, 9))) for _ in range(n)]


def encoded(coder: tokens.Coder, texts: list[str | None]) -> list[list[int]]:
    return [x.tolist() for x in coder(pa.array(texts, pa.string()))]


@pytest.fixture(scope="module")
def library():
    t = Tokenizer.from_file(tokens.tokenizer_path())
    return lambda texts: [e.ids for e in t.encode_batch([x or "" for x in texts], add_special_tokens=False)]


@pytest.mark.parametrize("backward", [False, True])
def test_halves_met_first(library, backward):
    texts = random_texts(20_000, 5)
    halves = [x[k:] if backward else x[:k] for x in texts for k in (1, 2)]
    whole = texts[::-1] if backward else texts
    coder = tokens.Coder(tokens.tokenizer_path(), 100_000)
    assert coder.exact
    assert encoded(coder, halves) == library(halves)
    assert encoded(coder, whole) == library(whole)


def test_every_pair_of_the_alphabet(library):
    pairs = [a + b for a in ALPHABET for b in ALPHABET]
    lines = [" ".join(pairs[k : k + 50]) for k in range(0, len(pairs), 50)]
    coder = tokens.Coder(tokens.tokenizer_path(), 100_000)
    assert encoded(coder, ALPHABET) == library(ALPHABET)
    assert encoded(coder, pairs) == library(pairs)
    assert encoded(coder, lines) == library(lines)


def test_small_cache_and_blocks(library, monkeypatch):
    texts = [" ".join(random_texts(30, k)) for k in range(60)] + [None, "", " \n", "x" * 9000, "ab, " * 4000]
    monkeypatch.setattr(tokens, "BLOCK", 2000)
    coder = tokens.Coder(tokens.tokenizer_path(), 50)
    assert encoded(coder, texts) == library(texts)
    assert encoded(coder, texts[::-1]) == library(texts[::-1])


def test_other_rules_go_through_the_library(tmp_path):
    import public_tokenizers

    path = public_tokenizers.path("byte_bpe_50k.json")
    coder, t = tokens.Coder(path, 100), Tokenizer.from_file(path)
    assert not coder.exact
    texts = random_texts(200, 9)
    assert encoded(coder, texts) == [t.encode(x, add_special_tokens=False).ids for x in texts]


def test_borders():
    data = np.frombuffer("ab.c1ж,é×—.İ.x's".encode(), np.uint8)
    words = [bytes(x).decode() for x in np.split(data, tokens.borders(data))]
    assert words == ["ab", ".", "c", "1", "ж", ",", "é×—.", "İ.", "x's"]
