"""Every paragraph, probability and agreement against a plain reading of the texts; wrapped notices."""

import math
import random
import re
from itertools import pairwise

import pytest

from helpers import DATA
from rasterchain.llm import license_scan as L


def brute(text, model):
    telling, weight = set(model["telling"]), dict(zip(model["features"], model["weight"], strict=True))
    template = {f: {f"{a} {b}" for n in notices for a, b in pairwise(L.words_of(n))} for f, notices in L.NOTICES.items()}
    every = set().union(*template.values())
    lines = (text or "").split("\n")
    blocks, found = [], []
    for i, line in enumerate(lines):
        if i == 0 or lines[i - 1].strip(" ") == "":
            blocks.append((i, []))
        blocks[-1][1].append(line)

    def runs(words):
        at = [i for i, p in enumerate(f"{a} {b}" for a, b in pairwise(words)) if p in every]
        out = []
        for i in at:
            if out and i - out[-1][1] <= L.GAP:
                out[-1] = (out[-1][0], i, out[-1][2] + 1)
            else:
                out.append((i, i, 1))
        return [words[a : b + 2] for a, b, n in out if n >= L.LEAST]

    def judge(block, at, wrapped, words):
        pairs = {f"{a} {b}" for a, b in pairwise(words)}
        some = [weight[f] for f in {*words, *pairs} if f in weight]
        if not some or not telling & set(words):
            return
        z = [(sum(w[k] for w in some) + model["bias"][k]) / model["temperature"] for k in range(len(model["classes"]))]
        k = z.index(max(z))
        family, probability = model["classes"][k], 1 / sum(math.exp(x - z[k]) for x in z)
        agreement = len(pairs & template.get(family, set())) / len(pairs) if pairs else 0
        if family != L.UNKNOWN and probability >= L.SURE and agreement >= L.AGREE:
            found.append((block, at, wrapped, family, probability, agreement, pairs & template[family], pairs))

    for block, own in blocks:
        for i, line in enumerate(own):
            words = L.words_of(line)
            judge(block, block + i, False, words)
            for sentence in re.split(r"(?<=[.!?])\s+", line, flags=re.A):
                for part in runs(L.words_of(sentence)):
                    judge(block, block + i, False, part)
        for sentence in re.split(r"(?<=[.!?])\s+", "\n".join(own), flags=re.A):
            if "\n" in sentence:
                for part in runs(L.words_of(sentence)):
                    judge(block, block, True, part)
    listed = {}
    for block, at, wrapped, family, probability, agreement, hits, _ in found:
        if wrapped or not any(v[0] == block and v[2] and hits <= v[7] for v in found):
            p, a = listed.get((at, family), (0, 0))
            listed[at, family] = max(p, probability), max(a, agreement)
    return sorted((*k, *v) for k, v in listed.items())


def agree(rows, model):
    for r in rows:
        want = brute(r["text"], model)
        got = [tuple(p) for p in r["paragraphs"]]
        assert [p[:2] for p in got] == [p[:2] for p in want]
        assert all(a[2:] == pytest.approx(b[2:], abs=2e-6) for a, b in zip(got, want, strict=True))
    return sum(len(r["paragraphs"]) for r in rows)


def test_scan_of_given_texts(spark):
    table = spark.read.parquet(f"{DATA}/documents.parquet").select("doc_id", "text")
    model = L.train(L.sampled_paragraphs(table, "text"))
    assert agree(L.scan(table, model).join(table, "doc_id").collect(), model) > 0


def wrap(text, width):
    out = [""]
    for w in text.split():
        out[-1:] = [f"{out[-1]} {w}".strip()] if len(out[-1]) + len(w) < width else [out[-1], w]
    return "\n".join(out)


def test_wrapped_notices(spark):
    rng = random.Random(3)
    prose = lambda n: " ".join(rng.choice(("alpha", "beta", "gamma", "delta")) + str(rng.randint(0, 30)) for _ in range(n))
    texts, want = [], []
    for family, notices in L.NOTICES.items():
        long = max(notices, key=len)
        for width in (30, 60):
            texts.append(f"{prose(20)}\n\n{wrap(long, width)}\n\n{prose(30)}")
            want.append([family])
    texts += [wrap(prose(400), 50), "a licence\nof some kind,\nor a work of\nart", None, "", "\n\n \n"]
    want += [[]] * 5
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    model = L.train([prose(30) for _ in range(60)])
    rows = L.scan(df, model).join(df, "doc_id").orderBy("doc_id").collect()
    agree(rows, model)
    assert [r["families"] for r in rows] == want
