"""Thresholds of groups of any size, and groups that are mostly copies."""

import random

import pytest
from pyspark.sql import functions as F

from rasterchain.llm import quality

WORDS = [w * 2 for w in ("ab", "cde", "fg", "hijk", "lm", "nop", "q", "rst", "uvw", "xyz")]


def text(rng, n, put=()):
    return " ".join(rng.choice([*WORDS, *put]) + str(rng.randrange(10)) for _ in range(n))


@pytest.mark.parametrize("n", [1, 5, 60])
def test_groups_of_any_size_keep_their_usual_texts(spark, n):
    rng = random.Random(n)
    rows = [(f"s{k}", text(rng, 120)) for k in range(4) for _ in range(n)] + [("s0", text(rng, 200)) for _ in range(60)]
    junk = [("s1", " ".join("#$%&" + w for w in text(rng, 100).split())), ("s2", " ".join(w * 9 for w in text(rng, 100).split()))]
    df = spark.createDataFrame([(i, "en", s, t) for i, (s, t) in enumerate(rows + junk)], "doc_id bigint, lang string, source string, text string")
    kept = {r["doc_id"]: r["kept"] for r in quality.quality_rules(df).collect()}
    assert sum(kept[i] for i in range(len(rows))) >= 0.97 * len(rows)
    assert not kept[len(rows)] and not kept[len(rows) + 1]


def test_copies_do_not_narrow_their_group(spark):
    rng = random.Random(1)
    one = text(rng, 150)
    rows = [("hot", one)] * 300 + [("hot", text(rng, 150)) for _ in range(60)] + [("b", text(rng, 150)) for _ in range(300)]
    df = spark.createDataFrame([(i, "en", s, t) for i, (s, t) in enumerate(rows)], "doc_id bigint, lang string, source string, text string")
    assert quality.quality_rules(df).where("not kept").count() <= 0.02 * len(rows)


def test_sketches_merge_by_adding(spark):
    rng = random.Random(2)
    df = spark.createDataFrame([(i, rng.choice(("en", None)), rng.choice(("a", "b", None)), text(rng, 100, ("#",))) for i in range(80)], "doc_id bigint, lang string, source string, text string")
    m = quality.measured(df)
    whole = quality.sketches(m)
    parts = quality.sketches(m.where("doc_id < 30")).union(quality.sketches(m.where("doc_id >= 30"))).groupBy("lang", "source", "signal", "bucket").agg(F.sum("n").alias("n"))
    assert sorted(map(str, whole.collect())) == sorted(map(str, parts.collect()))
