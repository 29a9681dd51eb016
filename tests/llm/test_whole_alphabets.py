"""Language models over texts of many scripts: no character is lost, and both ways of scoring agree."""

import math
import random
from collections import Counter

import numpy as np
import pytest

from rasterchain.llm import lm_score


def brute(texts, good):
    """(n, target loss, background loss) of each text, by dictionaries."""
    cut = [list(zip([0, 0, *(t or "")], [0, *(t or ""), 1], [*(t or ""), 1], strict=False)) for t in texts]  # marks are no characters
    v = len({x[2] for c in cut for x in c})
    out = []
    for some in (good, range(len(texts))):
        c3 = Counter(x for i in some for x in cut[i])
        c2, c1, s3, s2 = Counter(), Counter(), Counter(), Counter()
        for (a, b, c), n in c3.items():
            c2[b, c] += n
            c1[c] += n
            s3[a, b] += n
            s2[b] += n
        total, w = sum(c1.values()), lm_score.LOWER_WEIGHT
        p1 = lambda c: (c1[c] + 1) / (total + v)  # noqa: B023, E731
        p2 = lambda b, c: (c2[b, c] + w * p1(c)) / (s2[b] + w)  # noqa: B023, E731
        p3 = lambda a, b, c: (c3[a, b, c] + w * p2(b, c)) / (s3[a, b] + w)  # noqa: B023, E731
        out.append([sum(-math.log(p3(*x)) for x in c) / len(c) for c in cut])
    return [(len(c), t, g) for c, t, g in zip(cut, *out, strict=True)]


@pytest.mark.parametrize("limit", [lm_score.TABLE, 0])
def test_scores_of_many_scripts(spark, monkeypatch, limit):
    monkeypatch.setattr(lm_score, "TABLE", limit)
    rng = random.Random(5)
    latin = [chr(c) for c in range(33, 250) if c != 127]
    # the frequent characters alone are more than 125; Chinese texts have rarer ones
    texts = ["".join(rng.choice(latin) for _ in range(400)) for _ in range(12)]
    good = [chr(0x4E00 + k) for k in range(40)]
    bad = [chr(0x5E00 + k) for k in range(40)]
    texts += ["".join(rng.choice(good) for _ in range(50)) for _ in range(6)] + ["".join(rng.choice(bad) for _ in range(50)) for _ in range(6)]
    texts += [None, "", "😀\x00", "a"]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)] + [(3, texts[3]), (None, "a")], "doc_id long, text string").repartition(3)
    target = spark.createDataFrame([(i,) for i in (12, 13, 14)], "doc_id long")
    got = lm_score.cross_entropy_difference(df, target).collect()
    assert len(got) == len(texts) + 2
    want = brute([*texts, texts[3], "a"], [12, 13, 14])
    for r in got:
        n, t, g = want[r["doc_id"] if r["doc_id"] is not None else len(texts) - 1]
        assert r["n_tokens"] == n and np.allclose([r["target_loss"], r["background_loss"], r["score"]], [t, g, t - g])
    score = {r["doc_id"]: r["score"] for r in got}
    assert max(score[i] for i in range(15, 18)) < min(score[i] for i in range(18, 24))
