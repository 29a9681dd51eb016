"""Licence scans by a trained paragraph classifier. DataFrame functions only on the data's path.

Words and word pairs of a paragraph (a line) are the sparse features of a multinomial
logistic regression over licence families and a class of unknown paragraphs. It is trained
on the driver from notices of each family, varied by a seeded rule, and from a bounded
sample of paragraphs of the corpus as they are and with stray licence words put in. A
temperature fitted on held-out variants calibrates its probabilities; a paragraph whose
likeliest class is unknown, or whose probability is low, stays unknown. A prediction counts
only if the paragraph's word pairs also agree with the family's notices. Paragraphs are read
whole and by the stretches of their sentences that run along with the notices, so that prose
around a notice, or a second notice, hides none of them; sentences that are wrapped over the
lines of a block (between empty lines) are read across its lines.

Features hold at least one telling word, a word of the notices that is rare in the sample.
So texts without a telling word need no scoring: they have no feature at all.
"""

from __future__ import annotations

import json
import random
import re
from itertools import pairwise

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rasterchain.llm.common import text_or_empty

#: Texts, and paragraphs of theirs, that the classifier is trained on, at most.
SAMPLE_TEXTS, SAMPLE = 250, 1000
#: A word in more than this share of the sampled paragraphs tells nothing.
COMMON = 0.01
#: Calibrated probability, and share of a paragraph's word pairs that the notices have, at least.
SURE, AGREE = 0.6, 0.5
#: Pairs of notices in a stretch, as many as the shortest notice has, and pairs between two of them (a word put in), at most.
LEAST, GAP = 4, 3
UNKNOWN = "unknown"

#: Notices of each family, as they are published.
NOTICES = {
    "apache-2.0": (
        "Licensed under the Apache License, Version 2.0.",
        'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License.',
        "You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0",
        'Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.',
    ),
    "mit": (
        "Released under the MIT License.",
        "This project is licensed under the terms of the MIT License.",
        'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:',
        "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.",
        'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.',
    ),
    "gpl-3.0": (
        "This work is licensed under the GNU General Public License, version 3.",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
        "You should have received a copy of the GNU General Public License along with this program. If not, see https://www.gnu.org/licenses/.",
    ),
    "lgpl-3.0": (
        "Licensed under the GNU Lesser General Public License, version 3.",
        "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 3 of the License, or (at your option) any later version.",
    ),
    "agpl-3.0": ("Licensed under the GNU Affero General Public License, version 3.", "you can redistribute it and/or modify it under the terms of the GNU Affero General Public License"),
    "bsd-3-clause": (
        "Licensed under the BSD 3-Clause License.",
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
        "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.",
    ),
    "mpl-2.0": ("This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.", "If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/."),
    "cc-by-nc-4.0": ("Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    "cc-by-4.0": ("Licensed under CC BY 4.0.", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    "cc-by-sa-4.0": ("Licensed under CC BY-SA 4.0.", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    "unlicense": ("This is free and unencumbered software released into the public domain.", "Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software"),
}


def words_of(text: str) -> list[str]:
    return [w for w in re.split("[^a-z0-9]+", text.lower()) if w]


def features_of(words: list[str], telling: set[str]) -> set[str]:
    return {w for w in words if w in telling} | {f"{a} {b}" for a, b in pairwise(words) if a in telling or b in telling}


def variants(seed: int = 3, each: int = 24) -> list[tuple[str, list[str]]]:
    """(family, words) of varied notices: parts of some length, words left out or put in."""
    rng = random.Random(seed)
    filler = "this the of software our code all files project here in and it".split()
    out = []
    for family, notices in NOTICES.items():
        for n in notices:
            out += [(family, words_of(n))] * 3
            for _ in range(each // len(notices)):
                w = words_of(n)
                if len(w) > 12:
                    a = rng.randrange(len(w) - 10)
                    w = w[a : a + rng.randint(10, len(w))]
                w = [x for x in w if rng.random() > 0.05]
                for _ in range(rng.randint(0, 3)):
                    w.insert(rng.randint(0, len(w)), rng.choice(filler))
                out.append((family, w))
    return out


#: What the classifier can see of a paragraph: words and word pairs that notices have.
KNOWN = frozenset(w for notices in NOTICES.values() for n in notices for w in words_of(n))
KNOWN_PAIRS = frozenset(f"{a} {b}" for notices in NOTICES.values() for n in notices for a, b in pairwise(words_of(n)))


def evidence(words: list[str]) -> tuple[set[str], set[str]]:
    return set(words) & KNOWN, {f"{a} {b}" for a, b in pairwise(words)} & KNOWN_PAIRS


def train(sample: list[str] | list[tuple[set[str], set[str]]], seed: int = 3, rounds: int = 400) -> dict:
    """classes, telling words, features with their weights, bias and temperature. sample: paragraphs, or their evidence."""
    rng = random.Random(seed)
    found = [evidence(words_of(p)) if isinstance(p, str) else p for p in sample]
    # licence paragraphs of the sample itself are no examples of unknown ones
    negative = [(w, p) for w, p in found if len(p) < 3] or [(set(), set())]
    df: dict[str, int] = {}
    for words, _ in negative:
        for x in words:
            df[x] = df.get(x, 0) + 1
    stop = set("the of and to in a is it or not with for on an any may this that be by as at from are all you can if".split())
    telling = {w for w in KNOWN - stop if df.get(w, 0) <= COMMON * len(negative)}
    classes = [*NOTICES, UNKNOWN]
    rows = [(classes.index(f), features_of(w, telling)) for f, w in variants(seed)]
    vocabulary = {f: k for k, f in enumerate(sorted(set().union(*(f for _, f in rows))))}
    some = sorted(telling)
    seen = [(words & telling) | {p for p in pairs if telling & set(p.split())} for words, pairs in negative]
    rows += [(len(classes) - 1, f) for f in seen]
    # stray licence words, alone or in other company
    rows += [(len(classes) - 1, rng.choice(seen) | {rng.choice(some) for _ in range(rng.randint(1, 3))}) for _ in range(300)]
    rng.shuffle(rows)
    x = np.zeros((len(rows), len(vocabulary)))
    for r, (_, features) in enumerate(rows):
        for f in features:
            if f in vocabulary:
                x[r, vocabulary[f]] = 1
    y = np.eye(len(classes))[[c for c, _ in rows]]
    held = np.arange(len(rows)) % 4 == 0
    weight, bias = np.zeros((len(vocabulary), len(classes))), np.zeros(len(classes))
    a, b = x[~held], y[~held]
    for _ in range(rounds):
        g = _softmax(a @ weight + bias) - b
        weight -= 2.0 * (a.T @ g / len(a) + 1e-4 * weight)
        bias -= 2.0 * g.mean(0)
    z = x[held] @ weight + bias
    temperature = min((0.25, 0.35, 0.5, 0.7, 1.0, 1.4, 2.0), key=lambda t: -np.log((_softmax(z / t) * y[held]).sum(1) + 1e-12).mean())
    right = (z.argmax(1) == y[held].argmax(1)).mean()
    return {"classes": classes, "telling": some, "features": sorted(vocabulary), "weight": weight.round(4).tolist(), "bias": bias.round(4).tolist(), "temperature": temperature, "held_out_accuracy": float(right)}


def _softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(1, keepdims=True))
    return e / e.sum(1, keepdims=True)


def sampled_paragraphs(docs: DataFrame, text_col: str) -> list[tuple[set[str], set[str]]]:
    """Evidence of the paragraphs of the texts with the least hashes, SAMPLE at most. Whole paragraphs are read; what is gathered of each is bounded by the notices."""
    hashed = docs.where(F.col(text_col).isNotNull()).select(F.xxhash64(text_col).alias("_h"), F.col(text_col).alias("_text"))
    # hashes are compared first, so that no task gathers texts that will not be taken
    least = hashed.select("_h").distinct().orderBy("_h").limit(SAMPLE_TEXTS).agg(F.max("_h")).first()[0]
    if least is None:
        return []
    few = hashed.where(F.col("_h") <= F.lit(least)).dropDuplicates(["_h"])
    w = few.select(F.explode(F.split("_text", "\n")).alias("p")).where("length(p) > 0").select(F.xxhash64("p").alias("h"), _words(F.col("p")).alias("w"))
    known, pairs = (F.array(*[F.lit(x) for x in sorted(k)]) for k in (KNOWN, KNOWN_PAIRS))
    lines = w.select("h", F.array_intersect("w", known).alias("w"), F.array_intersect(_pairs("w"), pairs).alias("p")).orderBy("h").limit(SAMPLE)
    return [(set(r["w"]), set(r["p"])) for r in lines.collect()]


def _held(df: DataFrame, name: str) -> DataFrame:
    """df, with a column that comes out of a generator: no filter on it is pushed below."""
    return df.withColumn("_m", F.explode(F.array(F.struct(name)))).withColumn(name, F.col(f"_m.{name}")).drop("_m")


def _stretches(sentences: DataFrame, known: Column) -> DataFrame:
    """sentences (with pairs in two) with s: (a, b, n), first and last pair, from 0, and number of pairs of each run along the pairs that known has.

    Each step is a column that is named twice in the next, as what is named once, within a lambda, would be worked out anew for every element. For
    the same reason nothing filters by a step: the filter would be pushed below it with all steps put into each other.
    """
    steps = sentences.withColumn("_some", F.array_intersect("two", known))
    steps = steps.withColumn("_at", F.expr("if(size(_some) = 0, array(), filter(transform(two, (x, i) -> if(array_contains(_some, x), i, -1)), i -> i >= 0))"))
    steps = steps.withColumn("_begin", F.expr(f"filter(transform(_at, (x, i) -> if(i = 0 or x - _at[i - 1] > {GAP}, i, -1)), i -> i >= 0)"))
    steps = steps.withColumn("s", F.expr("transform(_begin, (i, k) -> struct(i as i, coalesce(get(_begin, k + 1), size(_at)) - 1 as j))"))
    runs = F.expr(f"filter(transform(s, x -> struct(_at[x.i] as a, _at[x.j] as b, x.j - x.i + 1 as n)), x -> x.n >= {LEAST})")
    return _held(steps.withColumn("s", runs).drop("_some", "_at", "_begin"), "s")


def _pairs(w: str) -> Column:
    return F.expr(f"if(size({w}) < 2, cast(array() as array<string>), transform(slice({w}, 1, size({w}) - 1), (x, i) -> concat(x, ' ', {w}[i + 1])))")


def _words(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), "[^a-z0-9]+"), lambda w: w != "")


def scan(docs: DataFrame, model: dict | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, families array<string>, paragraphs array of (at, family, probability, agreement)), one row per input row.

    Paragraphs are the lines of a text, counted from 0; for a sentence that is wrapped over lines,
    the first line of its block. Only predicted and confirmed ones are
    listed, one of each family a line; families are sorted and distinct, and empty if there are none, as for null or
    empty texts. Repeated rows give repeated rows. Without a model, one is trained on docs.
    """
    spark = docs.sparkSession
    model = model or train(sampled_paragraphs(docs, text_col))
    classes = model["classes"]
    if not model["features"]:
        raise ValueError("the model has no features")
    text = text_or_empty(text_col)
    table = json.dumps([{"f": f, "w": w} for f, w in zip(model["features"], model["weight"], strict=True)])
    # at most the n-grams of the notices: a bounded table
    weights = spark.range(1).select(F.explode(F.from_json(F.lit(table), "array<struct<f: string, w: array<double>>>")).alias("x")).select("x.f", "x.w")
    telling = F.array(*[F.lit(w) for w in model["telling"]])
    key = F.xxhash64(F.col(id_col), F.col(text_col))
    rows = docs.select(F.col(id_col).alias("_id"), key.alias("_key"), text.alias("_text"))
    some = rows.where(F.arrays_overlap(F.split(F.lower("_text"), "[^a-z0-9]+"), telling)).withColumn("l", F.split("_text", "\n"))
    starts = F.expr("filter(sequence(0, size(l) - 1), i -> i = 0 or trim(l[i - 1]) = '')")
    cut = F.expr("transform(s, (x, j) -> struct(x as block, slice(l, x + 1, coalesce(get(s, j + 1), size(l)) - x) as l))")
    blocks = _held(some.withColumn("s", starts).withColumn("b", cut), "b").select("_id", "_key", F.explode("b").alias("b"))
    blocks = blocks.select("_id", "_key", "b.block", "b.l").where(F.exists("l", lambda x: F.arrays_overlap(_words(x), telling)))
    known = F.array(*[F.lit(p) for p in sorted(KNOWN_PAIRS)])
    # lines with their sentences, and sentences that run over several lines
    by_line = F.transform("l", lambda x, i: F.struct((F.col("block") + i).alias("at"), F.lit(False).alias("wrapped"), x.alias("line")))
    over_lines = F.transform(F.filter(F.split(F.array_join("l", "\n"), r"(?<=[.!?])\s+"), lambda x: x.contains("\n")), lambda x: F.struct(F.col("block").alias("at"), F.lit(True).alias("wrapped"), x.alias("line")))
    lines = blocks.select("_id", "_key", "block", F.explode(F.concat(by_line, over_lines)).alias("x")).select("_id", "_key", "block", "x.*").withColumn("w", _words(F.col("line"))).where(F.arrays_overlap("w", telling))
    sentences = lines.select("_id", "_key", "block", "at", "wrapped", F.explode(F.when(F.col("wrapped"), F.array("line")).otherwise(F.split("line", r"(?<=[.!?])\s+"))).alias("line")).withColumn("w", _words(F.col("line"))).where(F.arrays_overlap("w", telling)).withColumn("two", _pairs("w"))
    parts = _stretches(sentences, known).select("_id", "_key", "block", "at", "wrapped", "w", F.explode("s").alias("s")).select("_id", "_key", "block", "at", "wrapped", F.expr("slice(w, s.a + 1, s.b - s.a + 2)").alias("w"))
    place = ["_id", "_key", "block", "at", "wrapped", "part"]
    # words of a part tell it from others of its line; equal ones, and those of repeated rows, are one
    lines = lines.where("not wrapped").drop("line").unionByName(parts).withColumn("part", F.xxhash64("w")).dropDuplicates(place)
    lines = lines.withColumn("two", _pairs("w"))
    each = lines.select(*place, F.array_distinct("two").alias("two"), F.explode(F.array_distinct(F.concat("w", "two"))).alias("f"))
    sums = [F.sum(F.col("w")[k]).alias(f"s{k}") for k in range(len(classes))]
    scored = each.join(F.broadcast(weights), "f").groupBy(*place).agg(F.first("two").alias("two"), *sums)
    t = model["temperature"]
    z = F.array(*[(F.col(f"s{k}") + F.lit(model["bias"][k])) / F.lit(t) for k in range(len(classes))])
    names = F.array(*[F.lit(c) for c in classes])
    templates = F.create_map(*[y for c, notices in NOTICES.items() for y in (F.lit(c), F.array(*[F.lit(p) for p in sorted({f"{a} {b}" for n in notices for a, b in pairwise(words_of(n))})]))])
    best = scored.withColumn("z", z).withColumn("top", F.array_max("z")).withColumn("family", F.element_at(names, F.array_position("z", F.col("top")).cast("int"))).withColumn("probability", 1 / F.aggregate("z", F.lit(0.0), lambda a, x: a + F.exp(x - F.col("top"))))
    sure = best.where((F.col("family") != UNKNOWN) & (F.col("probability") >= SURE))
    sure = sure.withColumn("hits", F.array_intersect("two", F.element_at(templates, F.col("family"))))
    confirmed = sure.withColumn("agreement", F.when(F.size("two") > 0, F.size("hits") / F.size("two")).otherwise(F.lit(0.0))).where(F.col("agreement") >= AGREE)
    item = F.struct("at", "family", "probability", "agreement", "hits", "two")
    in_block = confirmed.groupBy("_id", "_key", "block").agg(F.collect_list(F.when(~F.col("wrapped"), item)).alias("own"), F.collect_list(F.when(F.col("wrapped"), item)).alias("over"))
    # a line that shows nothing but what a sentence around it shows is a piece of that sentence
    kept = F.concat(F.filter("own", lambda o: ~F.exists("over", lambda v: F.size(F.array_except(o["hits"], v["two"])) == 0)), F.col("over"))
    each_line = in_block.select("_id", "_key", F.explode(kept).alias("p")).groupBy("_id", "_key", "p.at", "p.family").agg(F.round(F.max("p.probability"), 6).alias("probability"), F.round(F.max("p.agreement"), 6).alias("agreement"))
    found = each_line.groupBy("_id", "_key").agg(F.sort_array(F.collect_list(F.struct("at", "family", "probability", "agreement"))).alias("paragraphs")).withColumnsRenamed({"_id": "_of", "_key": "_with"})
    out = rows.select("_id", "_key").join(found, F.col("_id").eqNullSafe(F.col("_of")) & (F.col("_key") == F.col("_with")), "left")
    none = F.array().cast("array<struct<at: int, family: string, probability: double, agreement: double>>")
    return out.select(F.col("_id").alias(id_col), F.coalesce("paragraphs", none).alias("paragraphs")).select(id_col, F.array_sort(F.array_distinct(F.col("paragraphs.family"))).alias("families"), "paragraphs")


def op10_license_scan(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    found = scan(docs)
    return found.select("doc_id", F.array_join("families", ",").alias("families"), F.size("paragraphs").cast("long").alias("n_paragraphs"), F.coalesce(F.array_max("paragraphs.probability"), F.lit(0.0)).alias("probability"), F.coalesce(F.array_max("paragraphs.agreement"), F.lit(0.0)).alias("agreement"))
