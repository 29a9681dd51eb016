import random

import pytest
from pyspark.sql import functions as F

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, h int, n string, kept string, _w int, id string, k1 string, size string, copies int"


def prose(rng: random.Random, n: int) -> str:
    return " ".join(rng.choice(("alpha", "beta", "gamma", "delta", "eps", "zeta", "eta", "theta", "iota", "kappa", "mu", "nu")) + str(rng.randint(0, 30)) for _ in range(n))


@pytest.fixture(scope="session")
def rows():
    """Odd rows: nulls, empty and very long texts, copies, near copies, repeated rows, ties, clashing names."""
    rng = random.Random(7)
    long = prose(rng, 300)
    texts = [None, "", "  \n\t ", "one", "one two", "one two three", "A b C d", "a B c D", long, long, long.replace("beta", "omega", 1), long + " tail", prose(rng, 9000), "x" * 5000, "ß" * 150 + "é" * 150, "ab " * 400, "line\nline\nline\n\nother # $ |\n", "Licensed under the Apache License, Version 2.0.\n" + prose(rng, 60), prose(rng, 80) + "\nReleased under the MIT License.", "\x00\x01 😀 中文字"]
    texts += [prose(rng, 120) for _ in range(15)] + ["\n".join([prose(rng, 50), long[:260], prose(rng, 40)]) for _ in range(4)]
    out = [(i, t, rng.choice(("en", "fr", None)), rng.choice(("s1", "s2", "s10", None)), None if t is None else len(t), 1, "z", "no", 2, "id", "k", "s", 3) for i, t in enumerate(texts)]
    out += [out[8], out[8], (None, "text of a row without an id", "en", None, 27, *out[0][5:]), (None, None, None, None, None, *[None] * 8)]
    return out


@pytest.fixture(scope="session")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).repartition(3, F.col("n_chars"))


@pytest.fixture(scope="session")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)
