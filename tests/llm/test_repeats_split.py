"""Anchors with many different surroundings, split by their bytes, and surroundings that are compared as bytes."""

import random
from collections import Counter

import numpy as np
import pytest

from rasterchain.llm import suffix_dedup
from rasterchain.llm.suffix_sort import repeated_windows
from test_operators import brute_repeats


def letters(rng, n):
    return "".join(rng.choice("abcdefgh") for _ in range(n))


@pytest.mark.parametrize("part", [3, 40, 8192])
def test_passages_of_many_lengths_in_many_contexts(spark, part, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "PART", part)
    rng = random.Random(part)
    passage = letters(rng, 420)
    texts = []
    for k in range(120):
        a = rng.randrange(0, 200)
        texts.append(letters(rng, rng.randrange(0, 300)) + passage[a : a + rng.randrange(150, 260)] + letters(rng, rng.randrange(0, 300)))
    texts += ["x" + passage, "y" + passage, passage * 2, letters(rng, 50) + passage[:200], passage[219:] + "z"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string").repartition(6)
    got = Counter((r["doc_id"], r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in suffix_dedup.remove_repeats(df).collect())
    assert got == Counter((i, *b) for i, b in enumerate(brute_repeats(texts)))


def test_equal_bytes():
    rng = np.random.default_rng(0)
    data = np.concatenate([rng.integers(0, 2, 500).astype(np.uint8), np.zeros(40, np.uint8)])
    a, b, n = (rng.integers(0, m, 3000) for m in (460, 460, 40))
    want = [bytes(data[i : i + k]) == bytes(data[j : j + k]) for i, j, k in zip(a, b, n, strict=True)]
    assert suffix_dedup.equal_bytes(data, a, b, n, 40).tolist() == want


def test_windows_of_a_range_of_offsets():
    rng = random.Random(3)
    window, reach = 12, 6
    left = ["".join(rng.choice("ab") for _ in range(rng.randrange(0, 7))).encode() for _ in range(60)]
    right = ["".join(rng.choice("ab") for _ in range(rng.randrange(6, 13))).encode() for _ in range(60)]
    group = np.array([rng.randrange(2) for _ in range(60)])
    first = np.where(group == 0, 0, 2)
    last = np.where(group == 0, reach, 4)
    least, most = repeated_windows(left, right, group, window, first, last)
    for i in range(60):
        found = []
        for o in range(first[i], last[i] + 1):
            if o <= len(left[i]) and window - o <= len(right[i]):
                mine = (left[i][:o], right[i][: window - o])
                if any(j != i and group[j] == group[i] and o <= len(left[j]) and window - o <= len(right[j]) and (left[j][:o], right[j][: window - o]) == mine for j in range(60)):
                    found.append(o)
        assert (least[i], most[i]) == ((min(found), max(found)) if found else (-1, -1))
