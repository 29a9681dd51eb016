"""Words of any length go through the same merge rounds, and agree with the library."""

import random

import numpy as np
import pytest
import sentencepiece

from rasterchain.llm import sentencepiece_codec as codec


def agrees(texts):
    model = codec.model_bytes()
    library, encode = sentencepiece.SentencePieceProcessor(model_proto=model), codec.encoder(model)
    for text, ids in zip(texts, encode(texts), strict=True):
        assert np.frombuffer(ids, "<u4").tolist() == library.encode(text, add_bos=True, add_eos=True), (len(text), text[:40])


@pytest.mark.parametrize("n", [255, 256, 257, 511, 512, 513, 5000])
def test_long_words(n):
    rng = random.Random(n)
    agrees(["".join(rng.choice(letters) for _ in range(n)) for letters in ("=", " ", "ab", "=-_#", "theinganodrs", "\t\n ", "中文字", "éß😀a")])


def test_many_words_beside_a_long_one():
    rng = random.Random(4)
    agrees([" ".join("".join(rng.choice("abcdeinrst") for _ in range(rng.choice((1, 3, 8, 700)))) for _ in range(60)) for _ in range(5)] + ["", "x"])
