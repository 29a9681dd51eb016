"""Removal of every byte covered by a repeated string of a given length, over a whole corpus.

Sorting all suffixes of a corpus is not needed to know which strings of `window` bytes occur
twice. Anchors chosen by content alone (the smallest hash of a `gram`-byte string in each
window) fall at the same place of equal windows, so only suffixes around repeated anchors
can take part:

1. each task hashes its texts and picks the anchors. Anchors of one task with equal
   surroundings, compared byte by byte, leave one row (so a passage that is repeated
   everywhere leaves one row a task);
2. anchors meet by hash; the surroundings of all that meet another are fetched from the text;
3. the surroundings of each anchor are ordered by deep-shallow sorting in both directions;
   equal ones, and classes of equal prefixes of the others, tell which windows around the
   anchor are repeated;
4. intervals are merged and cut from each text.

An anchor with more surroundings than one task sorts at once is split: windows whose part
before the anchor is short share more bytes after it, the others more bytes before it. Each
half of the windows is dealt out by the bytes that all of its windows share, and split again
while it is too large; a single window is counted. What sorts the parts is the same.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import cache, reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rasterchain.llm.common import broadcast_if_small, checkpoint, saved, text_or_empty
from rasterchain.llm.suffix_sort import repeated_windows

CHUNK = 1 << 19
#: Bytes of text whose anchors a task compares at once.
FLUSH = 24 << 20
#: Surroundings of one anchor that one task sorts at once, about 1 KB each; larger groups are split by their bytes.
PART = 32_768
NEVER = np.uint64(0xFFFFFFFFFFFFFFFF)


@cache
def _weights() -> np.ndarray:
    return np.random.default_rng(20240611).integers(1, 1 << 63, 256, dtype=np.uint64) | np.uint64(1)


_powers: dict[str, np.ndarray] = {}


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd base and of its inverse modulo 2 to the 64."""
    if len(_powers.get("up", ())) < n:
        base = 0x9E3779B97F4A7C15
        inverse = pow(base, -1, 1 << 64)
        for name, b in (("up", base), ("down", inverse)):
            p = np.full(n, b, np.uint64)
            p[0] = 1
            _powers[name] = np.cumprod(p, dtype=np.uint64)
    return _powers["up"][:n], _powers["down"][:n]


def mix(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(31))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(29)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(32)
    return x


def sliding(x: np.ndarray, width: int, best) -> np.ndarray:
    """best (np.minimum or np.maximum) of x[i : i + width]; the result is width - 1 shorter."""
    have, out = 1, x
    while have * 2 <= width:
        out = best(out[:-have], out[have:])
        have *= 2
    if have < width:
        out = best(out[: len(x) - width + 1], out[width - have : width - have + len(x) - width + 1])
    return out


def anchors(data: np.ndarray, ends: np.ndarray, window: int, gram: int) -> tuple[np.ndarray, ...]:
    """Of texts laid end to end: text number, place in the text, hash, hash of the surroundings, and first byte and length of the surroundings of each anchor."""
    n, reach = len(data), window - gram
    starts = np.concatenate([[0], ends[:-1]])
    empty = np.empty(0, np.int64)
    if n < window:
        return empty, empty, empty, empty, empty, empty
    up, down = powers(n + 1)
    total = np.zeros(n + 1, np.uint64)
    np.cumsum(_weights()[data] * up[:n], out=total[1:])
    h = mix((total[gram:] - total[:-gram]) * down[: n - gram + 1])
    np.minimum(h, NEVER - np.uint64(1), out=h)
    for e in ends[:-1]:
        h[max(0, e - gram + 1) : e] = NEVER
    low = sliding(h, reach + 1, np.minimum)  # of the window that starts here
    for e in ends[:-1]:
        low[max(0, e - window + 1) : e] = 0
    high = sliding(np.concatenate([np.zeros(reach, np.uint64), low, np.zeros(reach, np.uint64)]), reach + 1, np.maximum)
    at = np.flatnonzero((high == h) & (h != NEVER))
    text = np.searchsorted(ends, at, side="right")
    left, right = np.maximum(at - reach, starts[text]), np.minimum(at + window, ends[text])
    around = (total[right] - total[left]) * down[left]
    around = mix(around + (((at - left) << 20) | (right - at)).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))
    return text, at - starts[text], h[at].view(np.int64), around.view(np.int64), left, right - left


def _rows(kind: int, h, ctx, k1, k2, pos, flag) -> pa.RecordBatch:
    n = len(pos)
    flag = np.full(n, flag, bool) if np.isscalar(flag) else flag
    return pa.RecordBatch.from_arrays([pa.array(np.full(n, kind, np.int8)), pa.array(h), pa.array(ctx), pa.array(k1), pa.array(k2), pa.array(pos.astype(np.int64)), pa.array(flag)], names=["kind", "h", "ctx", "k1", "k2", "pos", "flag"])


ROWS = "kind byte, h long, ctx long, k1 long, k2 long, pos long, flag boolean"
#: Kinds of rows: an anchor (flag: it has a twin, which is another row's surroundings in its task), and an anchor whose surroundings are repeated as a whole.
ANCHOR, WHOLE = 0, 1


def equal_bytes(data: np.ndarray, a: np.ndarray, b: np.ndarray, n: np.ndarray, width: int) -> np.ndarray:
    """Whether data[a : a + n] and data[b : b + n] agree; data is followed by width bytes at least."""
    view = np.lib.stride_tricks.sliding_window_view(data, width)
    out = np.empty(len(a), bool)
    for at in range(0, len(a), 20_000):
        part = slice(at, at + 20_000)
        out[part] = ((view[a[part]] == view[b[part]]) | (np.arange(width) >= n[part, None])).all(axis=1)
    return out


def _find_anchors(window: int, gram: int):
    width = 2 * window - gram

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        kept: list[np.ndarray] = []
        size_held = 0
        for b in batches:
            k1, k2 = b.column(0).to_numpy(), b.column(1).to_numpy()
            texts = b.column(2)
            at = 0
            data = [x or b"" for x in texts.to_pylist()]
            while at < len(data):
                size, to = 0, at
                while to < len(data) and (to == at or size + len(data[to]) <= CHUNK):
                    size += len(data[to])
                    to += 1
                ends = np.cumsum([len(x) for x in data[at:to]])
                flat = np.frombuffer(b"".join(data[at:to]), np.uint8)
                t, pos, h, ctx, first, n = anchors(flat, ends, window, gram)
                held.append((h, ctx, k1[at:to][t], k2[at:to][t], pos, first + size_held, n))
                kept.append(flat)
                size_held += len(flat)
                at = to
                if size_held >= FLUSH:
                    yield from flush(held, kept)
                    held, kept, size_held = [], [], 0
        if size_held:
            yield from flush(held, kept)

    def flush(held: list[tuple], kept: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        h, ctx, k1, k2, pos, begin, n = (np.concatenate(x) for x in zip(*held, strict=True))
        if not len(h):
            return
        by = np.lexsort((ctx, h))
        h, ctx, k1, k2, pos, begin, n = (x[by] for x in (h, ctx, k1, k2, pos, begin, n))
        first = np.concatenate([[True], (h[1:] != h[:-1]) | (ctx[1:] != ctx[:-1]) | (n[1:] != n[:-1])])
        again = np.flatnonzero(~first)
        if len(again):
            data = np.concatenate([*kept, np.zeros(width, np.uint8)])
            first[again] = ~equal_bytes(data, begin[again - 1], begin[again], n[again], width)
        twin = np.concatenate([~first[1:], [False]])
        inside = ~first | twin
        yield _rows(ANCHOR, h[first], ctx[first], k1[first], k2[first], pos[first], twin[first])
        if inside.any():  # these pass through the exchange of the anchors, dealt out by text
            yield _rows(WHOLE, k1[inside], ctx[inside], k1[inside], k2[inside], pos[inside], True)

    return run


def _meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by h: those that share it with another one. Holds the last row of a batch only."""
    last: list[np.ndarray] | None = None
    shared = False  # whether the row that is held has met another one

    for b in batches:
        kind = b.column(0).to_numpy()
        cols = [b.column(i).to_numpy(zero_copy_only=False) for i in range(1, 7)]
        passed = kind == WHOLE
        if passed.any():
            yield _rows(WHOLE, *(c[passed] for c in cols))
            cols = [c[~passed] for c in cols]
        if not len(cols[0]):
            continue
        if last is not None:
            cols = [np.concatenate([a, c]) for a, c in zip(last, cols, strict=True)]
        h = cols[0]
        same = h[1:] == h[:-1]
        met = np.concatenate([[shared], same]) | np.concatenate([same, [False]])
        if met[:-1].any():
            yield _rows(ANCHOR, *(c[:-1][met[:-1]] for c in cols))
        last, shared = [c[-1:] for c in cols], bool(met[-1])
    if shared:
        yield _rows(ANCHOR, *last)


SPANS = "k1 long, k2 long, lo long, hi long"
#: Surroundings of an anchor: group, place, twin, first and last offset of the windows to be judged, bytes before the anchor, the bytes, and a hash of the row's other columns.
AROUND = ["g1", "g2", "k1", "k2", "pos", "flag", "first_o", "last_o", "before", "around", "tag"]


def _compare(window: int):
    """Rows with the columns AROUND, sorted by (g1, g2): intervals of repeated windows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        for b in batches:
            held += zip(*(c.to_pylist() for c in b.columns), strict=True)
            if len(held) > PART:
                cut = next((i for i in range(len(held) - 1, 0, -1) if held[i][:2] != held[i - 1][:2]), 0)
                if cut:
                    yield from done(held[:cut])
                    held = held[cut:]
        if held:
            yield from done(held)

    def done(rows: list[tuple]) -> Iterator[pa.RecordBatch]:
        rows.sort(key=lambda r: (r[0], r[1], r[8], r[9]))
        same = np.array([False, *(rows[i][:2] == rows[i - 1][:2] and rows[i][8:10] == rows[i - 1][8:10] for i in range(1, len(rows)))])
        kind = np.cumsum(~same) - 1
        one = [rows[i] for i in np.flatnonzero(~same)]
        group = np.cumsum([0, *(one[i][:2] != one[i - 1][:2] for i in range(1, len(one)))])
        least, most = np.full(len(one), -1, np.int64), np.full(len(one), -1, np.int64)
        several = np.bincount(group)[group] > 1
        if several.any():
            some = [one[i] for i in np.flatnonzero(several)]
            least[several], most[several] = repeated_windows([r[9][: r[8]][::-1] for r in some], [r[9][r[8] :] for r in some], group[several], window, np.array([r[6] for r in some]), np.array([r[7] for r in some]))
        # equal surroundings of two rows, or of rows of one task, are repeated as a whole
        twice = (np.bincount(kind, weights=[r[5] for r in rows]) > 0) | (np.bincount(kind) > 1)
        fits = np.array([min(r[7], r[8]) for r in one]), np.array([max(r[6], window - (len(r[9]) - r[8])) for r in one])
        most, least = np.where(twice, fits[0], most)[kind], np.where(twice, fits[1], least)[kind]
        hit = np.flatnonzero((most >= 0) & (least <= most))
        if len(hit):
            k1, k2, pos = (np.array([rows[i][c] for i in hit], np.int64) for c in (2, 3, 4))
            yield _spans(k1, k2, pos - most[hit], pos - least[hit] + window)

    return run


def _spans(k1, k2, lo, hi) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(x) for x in (k1, k2, lo, hi)], names=["k1", "k2", "lo", "hi"])


def _halves(around: DataFrame, window: int) -> DataFrame:
    """Each row once for either half of its windows, dealt by the bytes that all windows of the half share; rows without room for such a window are left out."""
    middle = F.expr("int((first_o + last_o) div 2)")
    both = F.explode(F.array(F.struct(F.col("first_o").alias("a"), middle.alias("z")), F.struct((middle + 1).alias("a"), F.col("last_o").alias("z"))))
    halves = around.withColumn("half", both).where(f"half.a <= before and length(around) - before >= {window} - half.z")
    core = F.expr(f"substring(around, before - half.a + 1, half.a + {window} - half.z)")
    keyed = halves.withColumns({"g1": F.xxhash64("g1", "g2", "half", core), "g2": F.xxhash64(F.lit(5), core, "half", "g2", "g1"), "first_o": F.col("half.a"), "last_o": F.col("half.z")})
    return keyed.select(*AROUND)


def _split(around: DataFrame, window: int) -> tuple[DataFrame, DataFrame]:
    """Of rows AROUND of groups with more than PART rows: parts that are small enough, and (k1, k2, lo, hi) of repeated single windows."""
    parts, windows, big = [], [], around
    while True:
        halves = saved(_halves(big, window))
        size = checkpoint(halves.groupBy("g1", "g2").agg(F.count("*").alias("n")).where("n > 1"))
        live = halves.join(broadcast_if_small(size), ["g1", "g2"])
        one = live.where("first_o = last_o").withColumn("w", F.expr(f"substring(around, before - first_o + 1, {window})"))
        twice = one.groupBy("g1", "g2", "w").agg((F.sum(F.col("flag").cast("int")) + F.count("*")).alias("c")).where("c > 1").select("g1", "g2", "w")
        windows.append(one.join(twice, ["g1", "g2", "w"]).select("k1", "k2", (F.col("pos") - F.col("first_o")).alias("lo"), (F.col("pos") - F.col("first_o") + window).alias("hi")))
        parts.append(live.where(f"first_o < last_o and n <= {PART}").select(*AROUND))
        big = live.where(f"first_o < last_o and n > {PART}").select(*AROUND)
        if big.isEmpty():
            return reduce(DataFrame.unionByName, parts), reduce(DataFrame.unionByName, windows)


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for lo, hi in sorted(spans):
        if out and lo <= out[-1][1]:
            out[-1] = (out[-1][0], max(hi, out[-1][1]))
        else:
            out.append((lo, hi))
    return out


def _cut(kind: str, id_col: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for data, lo, hi in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), b.column(3).to_pylist(), strict=True):
                data = data or b""
                spans = merged([(max(0, x), min(y, len(data))) for x, y in zip(lo or (), hi or (), strict=True)])
                kept, at = [], 0
                for x, y in spans:
                    kept.append(data[at:x])
                    at = y
                kept.append(data[at:])
                kept = b"".join(kept) if spans else data
                out.append((len(data), len(data) - len(kept), len(spans), [x for x, _ in spans], [y for _, y in spans], kept))
            n, removed, count, lo, hi, kept = zip(*out, strict=True) if out else ((),) * 6
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array(n, pa.int64()), pa.array(removed, pa.int64()), pa.array(count, pa.int64()), pa.array(lo, pa.list_(pa.int64())), pa.array(hi, pa.list_(pa.int64())), pa.array([hashlib.sha256(k).hexdigest() for k in kept], pa.string()), pa.array([k.decode("utf-8", "ignore") for k in kept], pa.string())],
                names=["id", "n_bytes", "n_removed", "n_spans", "starts", "ends", "kept_sha256", "kept_text"],
            )

    return run


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", window: int = 200, gram: int = 64, carry: tuple[str, ...] = ()) -> DataFrame:
    """(id, carried columns, n_bytes, n_removed, n_spans, starts, ends, kept_sha256, kept_text), one row per input row.

    Texts are UTF-8 bytes; null counts as empty. A byte goes if some string of `window` bytes
    that covers it also starts anywhere else in the input, in the same text or another, or in
    a repeated row; overlaps count. starts and ends are the removed runs. kept_text decodes
    what is left; a character cut in two leaves nothing there. Texts shorter than the window
    lose nothing. Empty tables give empty results.
    """
    reach = window - gram
    if gram < 8 or reach < 1:
        raise ValueError("the anchor needs at least 8 bytes and must be shorter than the window")
    body = F.encode(text_or_empty(text_col), "utf-8")
    carried = F.struct(F.col(id_col).alias("id"), *[F.col(c).alias(f"c{i}") for i, c in enumerate(carry)])
    keyed = docs.select(carried.alias("id"), body.alias("body"), F.xxhash64(F.col(id_col), F.col(text_col)).alias("k1"), F.xxhash64(F.lit(7), F.col(text_col), F.col(id_col)).alias("k2"))
    found = keyed.select("k1", "k2", "body").mapInArrow(_find_anchors(window, gram), ROWS)
    met = checkpoint(found.repartition("h").sortWithinPartitions("h").mapInArrow(_meet, ROWS))

    wanted = met.where(F.col("kind") == ANCHOR)
    near = F.expr(f"substring(body, cast(greatest(pos - {reach}, 0) + 1 as int), cast(pos + {window} - greatest(pos - {reach}, 0) as int))")

    def around(places: DataFrame) -> DataFrame:
        # all columns of keyed are read, as in the last join, so that one exchange of the texts serves both
        return places.join(keyed, ["k1", "k2"]).select(F.col("h").alias("g1"), F.lit(0).cast("long").alias("g2"), "k1", "k2", "pos", "flag", F.lit(0).alias("first_o"), F.lit(reach).alias("last_o"), F.least("pos", F.lit(reach)).cast("int").alias("before"), near.alias("around"), F.xxhash64("id").alias("tag"))

    big = checkpoint(wanted.groupBy("h").count().where(F.col("count") > PART).select("h"))
    whole = met.where(F.col("kind") == WHOLE).select("k1", "k2", F.greatest(F.col("pos") - reach, F.lit(0)).alias("lo"), (F.col("pos") + window).alias("hi"))
    if big.isEmpty():
        plain, spans = around(wanted), whole
    else:
        few = broadcast_if_small(big)
        of_big = checkpoint(wanted.join(few, "h", "left_semi"))
        parts, windows = _split(saved(around(broadcast_if_small(of_big))), window)
        plain, spans = around(wanted.join(few, "h", "left_anti")).unionByName(parts), whole.union(windows)
    partly = plain.repartition("g1", "g2").sortWithinPartitions("g1", "g2").mapInArrow(_compare(window), SPANS)
    spans = spans.union(partly)
    spans = spans.groupBy("k1", "k2").agg(F.collect_set(F.struct("lo", "hi")).alias("s"))
    kind = keyed.schema["id"].dataType.simpleString()
    cut = keyed.join(spans, ["k1", "k2"], "left").select("id", "body", "s.lo", "s.hi").mapInArrow(_cut(kind, id_col), f"id {kind}, n_bytes long, n_removed long, n_spans long, starts array<long>, ends array<long>, kept_sha256 string, kept_text string")
    return cut.select(F.col("id.id").alias(id_col), *[F.col(f"id.c{i}").alias(c) for i, c in enumerate(carry)], "n_bytes", "n_removed", "n_spans", "starts", "ends", "kept_sha256", "kept_text")


def op6_suffix_dedup(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return remove_repeats(docs).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")


#: DuckDB SQL for op6_suffix_dedup: every string of 200 bytes, by its MD5.
OP6_SQL = """
with d as materialized (select row_number() over () n, doc_id, encode(coalesce(text, '')) b from documents)
, s as (select n, i, md5(array_slice(b, i + 1, i + 200)) m from d, unnest(range(0, octet_length(b) - 199)) r(i))
, t as (select n, i from (select n, i, count(*) over (partition by m) c from s) where c > 1)
, g as (select n, i, sum(case when i <= p + 200 then 0 else 1 end) over (partition by n order by i) k from (select n, i, lag(i) over (partition by n order by i) p from t))
, r as (select n, k, min(i) lo, max(i) + 200 hi from g group by n, k)
, e as (select n, lo, hi, coalesce(lag(hi) over (partition by n order by lo), 0) since from r)
, x as (select n, sum(hi - lo)::bigint n_removed, count(*) n_spans, max(hi) upto, string_agg(hex(array_slice(b, since + 1, lo)), '' order by lo) head from e join d using (n) group by n)
select doc_id, octet_length(b)::bigint n_bytes, coalesce(n_removed, 0)::bigint n_removed, coalesce(n_spans, 0)::bigint n_spans, sha256(unhex(coalesce(head, '') || hex(array_slice(b, (coalesce(upto, 0) + 1)::bigint, octet_length(b))))) kept_sha256 from d left join x using (n)
"""
