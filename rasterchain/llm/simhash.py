"""SimHash near-duplicates by Golay-code fuzzy hashing.

A 64-bit fingerprint is cut into segments of 23, 23 and 18 bits, each read as a word of the
perfect (23, 12) Golay code. A word within distance two of its codeword keeps that codeword
as its only index; a word at distance three also gets the five codewords at distance four.
So if two words differ in at most one bit, the nearest codeword of the one is among the
indices of the other. Three differing bits over three segments leave two cases:

* one segment agrees and another differs in at most one bit: key = the exact segment and an
  index of the other, for the six ordered pairs of segments;
* each segment differs in exactly one bit: key = indices of the two long segments, the three
  parities, and the half of the short segment that agrees.

Each fingerprint is stored under its nearest codewords and searched under all its indices;
candidates meet by an equality join of the keys and are verified by their differing bits.
No link is lost, and no cap is set on partners.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import cache
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rasterchain.llm.common import checkpoint
from rasterchain.llm.components import connected_components, star_edges

#: The generator polynomial of the (23, 12) Golay code, and its lengths.
GENERATOR = 0b101011100011
LENGTH, CHECK_BITS = 23, 11
SEGMENTS = ((0, 23), (23, 23), (46, 18))  # shift and width

LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
SPACES = re.compile(rb"[\x20\x09-\x0D]+")
PAIRS_AT_ONCE = 1 << 21


def fingerprint(text: str | None, shingle: int = 3, seed: int = 42) -> int:
    """Bit-wise majority of the XXH64 values of all word shingles, repeats included; 0 if there is no word."""
    words = (text or "").encode("utf-8", "replace").translate(LOWER).split()
    if not words:
        return 0
    joined = b" ".join(words)
    if len(words) <= shingle:
        spans = [joined]
    else:
        ends = np.cumsum([len(w) + 1 for w in words]) - 1
        starts = np.concatenate([[0], ends[:-1] + 1])
        spans = [joined[a:b] for a, b in zip(starts[: len(words) - shingle + 1].tolist(), ends[shingle - 1 :].tolist(), strict=True)]
    digest = xxhash.xxh64_intdigest
    ones, at = np.zeros(64, np.int64), 0
    for at in range(0, len(spans), 8192):
        h = np.array([digest(s, seed) for s in spans[at : at + 8192]], dtype="<u8")
        ones += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    bits = (2 * ones > len(spans)).astype(np.uint8)
    return int(np.packbits(bits, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3, seed: int = 42) -> DataFrame:
    """(id, fp long): fp holds the 64 bits as a signed integer."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = np.array([fingerprint(t, shingle, seed) for t in b.column(1).to_pylist()], dtype=np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps, pa.int64())], names=[id_col, "fp"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, fp long")


@cache
def golay_tables() -> tuple[np.ndarray, np.ndarray]:
    """By syndrome: the error pattern of the nearest codeword, and the patterns of all indices, -1 where there are fewer than six."""
    near, count = np.full(1 << CHECK_BITS, -1, np.int64), np.zeros(1 << CHECK_BITS, np.int64)
    every = np.full((1 << CHECK_BITS, 6), -1, np.int64)
    for weight in range(5):
        for places in combinations(range(LENGTH), weight):
            error = sum(1 << p for p in places)
            s = int(syndromes(np.array([error]))[0])
            if weight <= 3:
                near[s] = error
            every[s, count[s]] = error
            count[s] += 1
    return near, every


def syndromes(words: np.ndarray) -> np.ndarray:
    """Remainders modulo the generator polynomial."""
    rest = words.astype(np.int64).copy()
    for bit in range(LENGTH - 1, CHECK_BITS - 1, -1):
        rest ^= np.where(rest >> bit & 1, GENERATOR << (bit - CHECK_BITS), 0)
    return rest


def indices(words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of 23-bit words: the index of the nearest codeword, and up to six indices (n, 6), -1 where there are fewer."""
    near, every = golay_tables()
    s = syndromes(words)
    errors = every[s]
    # only a word at distance three of its codeword has errors of weight four in its table row
    return (words ^ near[s]) >> CHECK_BITS, np.where(errors >= 0, (words[:, None] ^ errors) >> CHECK_BITS, -1)


def fuzzy_keys(fps: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Keys (twice the key, plus 1 for a search key) and the fingerprint that each belongs to."""
    u = fps.view(np.uint64)
    seg = [((u >> np.uint64(s)) & np.uint64((1 << w) - 1)).astype(np.int64) for s, w in SEGMENTS]
    near, every = zip(*(indices(x) for x in seg), strict=True)
    rows = np.arange(len(fps))
    keys: list[np.ndarray] = []
    owner: list[np.ndarray] = []

    def put(key: np.ndarray, who: np.ndarray, role: int) -> None:
        keys.append(key << 1 | role)
        owner.append(who)

    for case, (x, y) in enumerate((x, y) for x in range(3) for y in range(3) if x != y):
        head = case << 40 | seg[x] << 12
        put(head | near[y], rows, 0)
        at, k = np.nonzero(every[y] >= 0)
        put(head[at] | every[y][at, k], at, 1)
    odd = [np.bitwise_count(x).astype(np.int64) & 1 for x in seg]
    parity = odd[0] << 2 | odd[1] << 1 | odd[2]
    at, k = np.nonzero(np.repeat(every[0] >= 0, 6, axis=1) & np.tile(every[1] >= 0, (1, 6)))
    first, second = every[0][at, k // 6], every[1][at, k % 6]
    for half in range(2):
        agree = seg[2] >> (9 * half) & 511
        head = (6 + half) << 40 | agree << 27
        put(head | parity << 24 | near[0] << 12 | near[1], rows, 0)
        put(head[at] | (parity[at] ^ 7) << 24 | first << 12 | second, at, 1)
    return np.concatenate(keys), fps[np.concatenate(owner)]


def _emit_keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        fps = b.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
        for at in range(0, len(fps), 2000):
            k, f = fuzzy_keys(fps[at : at + 2000])
            yield pa.RecordBatch.from_arrays([pa.array(k), pa.array(f)], names=["k", "fp"])


def links_in_runs(k: np.ndarray, fp: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Spanning links of rows sorted by k, of whole runs of equal keys: stored rows precede search rows."""
    key, role = k >> 1, k & 1
    start = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    size = np.diff(np.concatenate([start, [len(k)]]))
    stored = np.add.reduceat(1 - role, start)
    wanted = size - stored
    alone = (size == 2) & (fp[start] == fp[np.minimum(start + 1, len(k) - 1)])  # a fingerprint that meets only itself
    live = np.flatnonzero((stored > 0) & (wanted > 0) & ~alone)
    out_u, out_v = [], []

    def keep(x: np.ndarray, y: np.ndarray) -> None:
        near = (np.bitwise_count((x ^ y).view(np.uint64)) <= bits) & (x != y)
        if near.any():
            u, v = star_edges(x[near], y[near])
            out_u.append(u)
            out_v.append(v)

    pairs = stored[live] * wanted[live]
    small = live[pairs <= PAIRS_AT_ONCE]
    n = stored[small] * wanted[small]
    cuts = np.flatnonzero(np.diff(np.cumsum(n) // PAIRS_AT_ONCE)) + 1
    for group in np.split(np.arange(len(small)), cuts):
        if not len(group):
            continue
        r, m = small[group], n[group]
        run = np.repeat(np.arange(len(r)), m)
        inside = np.arange(m.sum()) - np.repeat(np.cumsum(m) - m, m)
        width = wanted[r][run]
        keep(fp[start[r][run] + inside // width], fp[start[r][run] + stored[r][run] + inside % width])
    for r in live[pairs > PAIRS_AT_ONCE]:
        base = fp[start[r] : start[r] + stored[r]]
        search = fp[start[r] + stored[r] : start[r] + size[r]]
        step = max(1, PAIRS_AT_ONCE // len(base))
        for at in range(0, len(search), step):
            part = search[at : at + step]
            keep(np.repeat(part, len(base)), np.tile(base, len(part)))
    if not out_u:
        return fp[:0], fp[:0]
    return star_edges(np.concatenate(out_u), np.concatenate(out_v))


def _link_runs(bits: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        k, fp = np.empty(0, np.int64), np.empty(0, np.int64)
        for b in batches:
            k = np.concatenate([k, b.column(0).to_numpy()])
            fp = np.concatenate([fp, b.column(1).to_numpy()])
            if not len(k):
                continue
            whole = int(np.searchsorted(k >> 1, k[-1] >> 1))  # the last run may go on
            if whole >= 50_000:
                yield from emit(k[:whole], fp[:whole])
                k, fp = k[whole:], fp[whole:]
        if len(k):
            yield from emit(k, fp)

    def emit(k: np.ndarray, fp: np.ndarray) -> Iterator[pa.RecordBatch]:
        u, v = links_in_runs(k, fp, bits)
        if len(u):
            yield pa.RecordBatch.from_arrays([pa.array(u), pa.array(v)], names=["u", "v"])

    return run


def fingerprint_links(fps: DataFrame, bits: int = 3) -> DataFrame:
    """fps (fp long, distinct) -> spanning links (u, v) of the graph of fingerprints at bits (3 at most) or fewer differing bits."""
    if not 0 <= bits <= 3:
        raise ValueError("the keys cover up to three differing bits")
    keys = fps.select("fp").mapInArrow(_emit_keys, "k long, fp long")
    dealt = keys.repartition(F.shiftright("k", 1)).sortWithinPartitions("k")
    return dealt.mapInArrow(_link_runs(bits), "u long, v long")


def simhash_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3, seed: int = 42, bits: int = 3) -> DataFrame:
    """(id, fp long, fingerprint hex, component_id): one row per input row.

    Texts that are null, empty or without words get fingerprint zero and link like others.
    Repeated rows and equal fingerprints share a class. component_id is the smallest id of
    the class that is not null (null only if all ids of a class are null). Empty tables give
    empty results; other columns are ignored.
    """
    rows = checkpoint(fingerprints(docs, id_col, text_col, shingle, seed))
    lowest = rows.groupBy("fp").agg(F.min(id_col).alias("low"))
    labels = connected_components(fingerprint_links(lowest.select("fp"), bits))
    named = lowest.join(labels.withColumnRenamed("node", "fp"), "fp", "left").withColumn("component", F.coalesce("component", "fp"))
    named = checkpoint(named)
    first = named.groupBy("component").agg(F.min("low").alias("component_id"))
    classes = named.join(first, "component").select("fp", "component_id")
    return rows.join(classes, "fp").select(id_col, "fp", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op7_simhash(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return simhash_groups(docs).select("doc_id", "fingerprint", "component_id")
