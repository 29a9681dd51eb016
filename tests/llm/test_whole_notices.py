"""Whole notices on one line, and notices within longer lines, are found."""

import random

from rasterchain.llm import license_scan

MIT = 'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:'
BEFORE = "we wrote these few words of prose before it for no reason"


def prose(rng, n):
    return " ".join(rng.choice(("alpha", "beta", "gamma", "delta")) + str(rng.randint(0, 30)) for _ in range(n))


def test_notices_within_lines(spark):
    rng = random.Random(2)
    texts = {
        1: (MIT, ["mit"]),
        2: (f"{BEFORE} Released under the MIT License.", ["mit"]),
        3: (f"{prose(rng, 300)}. Licensed under the Apache License, Version 2.0. {prose(rng, 300)}. Released under the MIT License. {prose(rng, 200)}", ["apache-2.0", "mit"]),
        4: (f"{BEFORE} and nothing else was said of the software or the license in question", []),
        5: (prose(rng, 2000), []),
    }
    df = spark.createDataFrame([(k, t) for k, (t, _) in texts.items()], "doc_id long, text string")
    model = license_scan.train([prose(rng, 30) for _ in range(50)] + [BEFORE])
    assert {r["doc_id"]: r["families"] for r in license_scan.scan(df, model).collect()} == {k: f for k, (_, f) in texts.items()}
