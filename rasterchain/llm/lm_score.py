"""Cross-entropy difference of two matched n-gram models.

The target model counts the trigrams of the target documents, the background model those of
all documents. Both have the same order, the same smoothing and one shared vocabulary: every
code point that occurs, with marks for begin and end. Each token of a text has a loss under
either model; the mean difference of the losses scores the text, and is lower the more the
text is like the target.

Counts cover all documents and all characters. A model is a table keyed by trigram (three
symbols of 21 bits in one long) that grows with the input. Tasks add up their own trigrams
before anything is shuffled. Losses are found by equality joins of the counts of each order;
texts are scored by an equality join of their distinct trigrams with the losses. Where the
losses are a small table, which is checked, that join is done in the tasks against a
broadcast copy; the scores are the same.

Trigrams and losses below are the dense form over 128 symbols, which is compared in tests.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rasterchain.llm.common import broadcast_if_small, checkpoint, small_enough

BITS = 7
SYMBOLS = 1 << BITS
BEGIN, END, OTHER = 0, 1, 2
FIRST = 3
CHUNK = 1 << 20
#: Bits of a symbol in the key of a trigram: a code point moved up by the two marks.
WIDE = 21
MASK = (1 << WIDE) - 1
#: Trigrams up to which the losses are sent to every task instead of being joined.
TABLE = 1 << 20
#: Weight of the next lower order, in tokens.
LOWER_WEIGHT = 5.0


def code_points(texts: list[str]) -> np.ndarray:
    return np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), "<u4")


def _chunks(texts: list[str]) -> Iterator[list[str]]:
    at = 0
    while at < len(texts):
        size, to = 0, at
        while to < len(texts) and (to == at or size + len(texts[to]) <= CHUNK):
            size += len(texts[to])
            to += 1
        yield texts[at:to]
        at = to


class Trigrams:
    """Trigrams of texts over a vocabulary, each text between two begin marks and an end mark."""

    def __init__(self, points: np.ndarray):
        self.symbol = np.full(0x110000, OTHER, np.uint8)
        self.symbol[points] = np.arange(FIRST, FIRST + len(points))

    def __call__(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Keys of all trigrams, and how many each text has."""
        size = np.fromiter(map(len, texts), np.int64, len(texts))
        ends = np.cumsum(size + 3)
        flat = np.full(int(ends[-1]) if len(ends) else 0, BEGIN, np.int32)
        flat[ends - 1] = END
        inside = np.ones(len(flat), bool)
        for at in (ends - 1, ends - size - 3, ends - size - 2):
            inside[at] = False
        flat[inside] = self.symbol[code_points(texts)]
        keys = (flat[:-2] << 2 * BITS) | (flat[1:-1] << BITS) | flat[2:]
        whole = np.ones(len(keys), bool)
        whole[ends[:-1] - 1] = whole[ends[:-1] - 2] = False
        return keys[whole], size + 1


def keyed_trigrams(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct keys in order, the place in them of every trigram, and how many trigrams each text has."""
    size = np.fromiter(map(len, texts), np.int64, len(texts))
    ends = np.cumsum(size + 3)
    flat = np.full(int(ends[-1]) if len(ends) else 0, BEGIN, np.int64)
    flat[ends - 1] = END
    inside = np.ones(len(flat), bool)
    for at in (ends - 1, ends - size - 3, ends - size - 2):
        inside[at] = False
    flat[inside] = code_points(texts).astype(np.int64) + 2
    whole = np.ones(max(len(flat) - 2, 0), bool)
    whole[ends[:-1] - 1] = whole[ends[:-1] - 2] = False
    present = np.flatnonzero(np.bincount(flat))
    v = len(present)
    if v**3 > 4 * CHUNK:
        keys, place = np.unique(((flat[:-2] << 2 * WIDE) | (flat[1:-1] << WIDE) | flat[2:])[whole], return_inverse=True)
        return keys, place, size + 1
    number = np.zeros(int(present[-1]) + 1 if v else 0, np.int64)
    number[present] = np.arange(v)
    near = number[flat]
    dense = ((near[:-2] * v + near[1:-1]) * v + near[2:])[whole]
    some = np.flatnonzero(np.bincount(dense, minlength=v**3))
    rank = np.zeros(v**3, np.int64)
    rank[some] = np.arange(len(some))
    keys = (present[some // (v * v)] << 2 * WIDE) | (present[some // v % v] << WIDE) | present[some % v]
    return keys, rank[dense], size + 1


def _added(parts: list[tuple[np.ndarray, np.ndarray]]) -> list[tuple[np.ndarray, np.ndarray]]:
    """Keys and counts (two columns) of all parts, added up by key."""
    keys, place = np.unique(np.concatenate([k for k, _ in parts]), return_inverse=True)
    total = np.zeros((len(keys), 2), np.int64)
    np.add.at(total, place, np.concatenate([n for _, n in parts]))
    return [(keys, total)]


def count_trigrams(docs: DataFrame, text_col: str, flag_col: str) -> DataFrame:
    """(key long, background long, target long): counts over all texts, and over those with the flag."""

    def out(parts: list[tuple[np.ndarray, np.ndarray]]) -> Iterator[pa.RecordBatch]:
        for keys, n in parts:
            for at in range(0, len(keys), 1 << 16):
                k, m = keys[at : at + (1 << 16)], n[at : at + (1 << 16)]
                yield pa.RecordBatch.from_arrays([pa.array(k), pa.array(m[:, 0].copy()), pa.array(m[:, 1].copy())], names=["key", "background", "target"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts: list[tuple[np.ndarray, np.ndarray]] = []
        for b in batches:
            flags = b.column(1).to_pylist()
            at = 0
            for texts in _chunks([x or "" for x in b.column(0).to_pylist()]):
                keys, place, n = keyed_trigrams(texts)
                flagged = np.repeat(np.array(flags[at : at + len(texts)], bool), n)
                parts.append((keys, np.stack([np.bincount(place, minlength=len(keys)), np.bincount(place[flagged], minlength=len(keys))], axis=1)))
                at += len(texts)
                if sum(len(k) for k, _ in parts) > CHUNK:
                    parts = _added(parts)
                    if len(parts[0][0]) > CHUNK // 2:  # what a task holds is bounded; the rest is added after the shuffle
                        yield from out(parts)
                        parts = []
        if parts:
            yield from out(_added(parts))

    counted = docs.select(text_col, flag_col).mapInArrow(run, "key long, background long, target long")
    return counted.groupBy("key").agg(F.sum("background").alias("background"), F.sum("target").alias("target"))


def loss_table(counts: DataFrame) -> DataFrame:
    """(key, t, g): loss of every trigram under the target and the background model, by interpolated orders.

    counts, which should be materialised, has the columns of count_trigrams.
    """
    names = {"t": "target", "g": "background"}
    by = lambda df, key, to, sums: df.groupBy(F.expr(key).alias(to)).agg(*[F.sum(c).alias(f"{c}{sums}") for c in names])
    c3 = counts.select("key", *[F.col(c).alias(k) for k, c in names.items()])
    c2 = checkpoint(by(c3, f"key & {(1 << 2 * WIDE) - 1}L", "pair", ""))
    # one row a code point at most
    c1 = checkpoint(by(c2, f"pair & {MASK}L", "last", "1"))
    total = c1.agg(F.count("*").alias("v"), *[F.coalesce(F.sum(f"{c}1"), F.lit(0)).alias(c) for c in names]).first()
    w = LOWER_WEIGHT
    p1 = c1.select("last", *[((F.col(f"{c}1") + 1) / F.lit(float(total[c] + total["v"]))).alias(f"{c}1") for c in names])
    after1 = by(c2, f"shiftright(pair, {WIDE})", "first", "s")
    p2 = c2.withColumn("last", F.expr(f"pair & {MASK}L")).withColumn("first", F.expr(f"shiftright(pair, {WIDE})")).join(broadcast_if_small(p1), "last").join(broadcast_if_small(after1), "first")
    p2 = p2.select("pair", *[((F.col(c) + w * F.col(f"{c}1")) / (F.col(f"{c}s") + w)).alias(f"{c}2") for c in names])
    after2 = by(c3, f"shiftright(key, {WIDE})", "head", "s")
    p3 = c3.withColumn("pair", F.expr(f"key & {(1 << 2 * WIDE) - 1}L")).withColumn("head", F.expr(f"shiftright(key, {WIDE})")).join(p2, "pair").join(after2, "head")
    return p3.select("key", *[(-F.log((F.col(c) + w * F.col(f"{c}2")) / (F.col(f"{c}s") + w))).alias(c) for c in names])


def losses(counts: np.ndarray) -> np.ndarray:
    """Loss of every trigram (negative log probability of its last symbol) by interpolated orders."""
    c3 = counts.reshape(SYMBOLS, SYMBOLS, SYMBOLS).astype(float)
    c2 = c3.sum(0)
    c1 = c2.sum(0)
    p1 = (c1 + 1) / (c1.sum() + SYMBOLS)
    p2 = (c2 + LOWER_WEIGHT * p1) / (c2.sum(1, keepdims=True) + LOWER_WEIGHT)
    p3 = (c3 + LOWER_WEIGHT * p2) / (c3.sum(2, keepdims=True) + LOWER_WEIGHT)
    return -np.log(p3).astype(np.float32).ravel()


def cross_entropy_difference(docs: DataFrame, target_ids: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_tokens, target_loss, background_loss, score), one row per input row.

    target_ids has the column id_col; ids that repeat count once, null ids are no target.
    n_tokens counts the characters and the end mark; null texts count as empty. Losses are
    means in nats. If no document is a target, the target model is uniform.
    """
    spark = docs.sparkSession
    wanted = checkpoint(target_ids.select(F.col(id_col).alias("_id")).where("_id is not null").distinct())
    flagged = docs.select(F.col(id_col), F.col(text_col)).join(broadcast_if_small(wanted.withColumn("_flag", F.lit(True)), 500_000), F.col(id_col) == F.col("_id"), "left").select(F.col(text_col), F.coalesce("_flag", F.lit(False)).alias("_flag"))
    table = checkpoint(loss_table(checkpoint(count_trigrams(flagged, text_col, "_flag"))))
    kind = docs.schema[id_col].dataType.simpleString()
    if not small_enough(table, TABLE):
        return _scored_by_join(docs, table, id_col, text_col, kind)
    local = table.toPandas().sort_values("key")
    both = spark.sparkContext.broadcast((local["key"].to_numpy(np.int64), local[["t", "g"]].to_numpy(float)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, model = both.value
        for b in batches:
            at = 0
            for texts in _chunks([x or "" for x in b.column(1).to_pylist()]):
                keys, place, n = keyed_trigrams(texts)
                sums = np.add.reduceat(model[np.searchsorted(known, keys)][place], np.cumsum(n) - n, axis=0)
                t, g = sums[:, 0] / n, sums[:, 1] / n
                yield pa.RecordBatch.from_arrays([b.column(0).slice(at, len(texts)), pa.array(n), pa.array(t), pa.array(g), pa.array(t - g)], names=[id_col, "n_tokens", "target_loss", "background_loss", "score"])
                at += len(texts)

    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, n_tokens long, target_loss double, background_loss double, score double")


def _scored_by_join(docs: DataFrame, table: DataFrame, id_col: str, text_col: str, kind: str) -> DataFrame:
    """Scores by an equality join of each text's distinct trigrams, which hold at least its end."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at = 0
            rows = b.column(1).to_pylist()
            for texts in _chunks([x or "" for x in b.column(2).to_pylist()]):
                keys, place, n = keyed_trigrams(texts)
                own, times = np.unique(np.repeat(np.arange(len(texts)), n) * len(keys) + place, return_counts=True)
                text = own // len(keys)
                ids = b.column(0).slice(at, len(texts))
                for i in range(0, len(own), 1 << 16):
                    part = slice(i, i + (1 << 16))
                    who = text[part]
                    yield pa.RecordBatch.from_arrays([ids.take(pa.array(who)), pa.array(np.array(rows[at : at + len(texts)], np.int64)[who]), pa.array(n[who]), pa.array(keys[own[part] % len(keys)]), pa.array(times[part])], names=["_id", "_row", "n_tokens", "key", "n"])
                at += len(texts)

    each = docs.select(F.col(id_col).alias("_id"), F.monotonically_increasing_id().alias("_row"), text_col).mapInArrow(run, f"_id {kind}, _row long, n_tokens long, key long, n long")
    sums = each.join(table, "key").groupBy("_row").agg(F.first("_id").alias(id_col), F.first("n_tokens").alias("n_tokens"), *[(F.sum(F.col("n") * F.col(c)) / F.first("n_tokens")).alias(c) for c in "tg"])
    return sums.select(id_col, "n_tokens", F.col("t").alias("target_loss"), F.col("g").alias("background_loss"), (F.col("t") - F.col("g")).alias("score"))


def op5_lm_scoring(spark, sf_dir: str) -> DataFrame:
    """Every document, scored against those that are labelled as good and not toxic."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    return cross_entropy_difference(docs, labels.where("quality = 1 and toxic = 0").select("doc_id"))
