"""Near-duplicate vectors by an inverted multi-index.

Equal vectors of a label are one stored vector with a weight, so that a group of copies of
any size is one row. Unit vectors are cut in halves; a codebook for each half, fitted on a bounded
sample, makes a grid of cells, and every vector is stored in the cell of its two nearest
codes. A query walks the grid by the multi-sequence order: cells by growing sum of squared
distances to their bisectors, which bound the step a near vector must make to lie in that
cell. It stops at the step that a share of `recall` of the vectors at the threshold would not
exceed, if they differ as vectors differ from their codes: the spread of those differences
along the directions between codes is measured on the sample, so that vectors of few
effective dimensions have longer steps. Pairs that meet in a cell are verified in double precision.

A cell with many vectors is dealt out over several tasks, each with a bounded part; queries
visit all parts in batches. Tasks emit counts and spanning links, never all pairs.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rasterchain.llm.common import broadcast_if_small, checkpoint, saved
from rasterchain.llm.components import connected_components, star_edges

#: Vectors that the codebooks are fitted on, at most.
SAMPLE = 8192
#: Stored vectors of a cell that one task takes. Each query goes to all parts of a cell, so parts are large.
PART = 8192
QUERIES_AT_ONCE = 512
#: Mean vectors of a cell that the size of the codebooks aims at. A codebook has at most as many codes as the sample has vectors.
OCCUPANCY = 256


def kmeans(x: np.ndarray, k: int, rounds: int = 12, seed: int = 5) -> np.ndarray:
    """Codes of the rows of x; the same for the same rows in the same order."""
    rng = np.random.default_rng(seed)
    codes = x[rng.choice(len(x), min(k, len(x)), replace=False)].copy()
    for _ in range(rounds):
        near = nearest(x, codes)
        n = np.bincount(near, minlength=len(codes))
        sums = np.stack([np.bincount(near, weights=x[:, d], minlength=len(codes)) for d in range(x.shape[1])], axis=1)
        codes = np.where(n[:, None] > 0, sums / np.maximum(n, 1)[:, None], codes)
    return codes


def squared(x: np.ndarray, codes: np.ndarray) -> np.ndarray:
    return (x * x).sum(1)[:, None] - 2 * x @ codes.T + (codes * codes).sum(1)[None, :]


def nearest(x: np.ndarray, codes: np.ndarray) -> np.ndarray:
    return squared(x, codes).argmin(1)


def to_bisectors(x: np.ndarray, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The nearest code of each row, and the row's distance to the bisector of it and every code (0 for itself)."""
    d = squared(x, codes)
    own = d.argmin(1)
    apart = np.sqrt(np.maximum(squared(codes, codes), 0))[own]
    gap = d - d[np.arange(len(x)), own][:, None]
    return own, np.where(apart > 0, np.maximum(gap, 0) / (2 * np.maximum(apart, 1e-300)), 0.0)


def multi_sequence(a: np.ndarray, b: np.ndarray, limit: float) -> list[tuple[int, int]]:
    """Pairs (i, j) by growing a[i] + b[j], as long as the sum is at most limit. a and b rise."""
    if not len(a) or not len(b):
        return []
    out, heap, seen = [], [(float(a[0] + b[0]), 0, 0)], {(0, 0)}
    while heap and heap[0][0] <= limit:
        _, i, j = heapq.heappop(heap)
        out.append((i, j))
        for p in ((i + 1, j), (i, j + 1)):
            if p[0] < len(a) and p[1] < len(b) and p not in seen:
                seen.add(p)
                heapq.heappush(heap, (float(a[p[0]] + b[p[1]]), *p))
    return out


def spread_along(x: np.ndarray, first: np.ndarray, second: np.ndarray) -> float:
    """Largest share of the mean squared difference between vectors and their codes that falls along two directions between codes, one of each half."""
    half = first.shape[1]
    rest = np.concatenate([x[:, :half] - first[nearest(x[:, :half], first)], x[:, half:] - second[nearest(x[:, half:], second)]], axis=1)
    cov = rest.T @ rest / len(rest)
    total = np.trace(cov)
    if not total > 0:
        return 1 / x.shape[1]

    def most(codes: np.ndarray, c: np.ndarray) -> float:
        best = 0.0
        for code in codes:
            u = codes - code
            long = np.sqrt((u * u).sum(1))
            u = u[long > 0] / long[long > 0, None]
            if len(u):
                best = max(best, float(((u @ c) * u).sum(1).max()))
        return best

    one = max(most(first, cov[:half, :half]), most(second, cov[half:, half:]), total / x.shape[1])
    both = float(np.linalg.norm(cov[:half, half:], 2))  # what the two directions may have in common
    return (one + both) / total


def step_limit(threshold: float, spread: float, recall: float) -> float:
    """Squared step, over two bisectors, within which a share of recall of vectors at the threshold stay."""
    each = 2 * (1 - threshold) * spread  # mean square of a difference along one direction
    return 2 * math.log(1 / (1 - recall)) * each


def _unit(rows: pa.Array) -> np.ndarray:
    """Rows of equal length as unit vectors in double precision."""
    x = rows.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(rows), -1)
    return x / np.sqrt((x * x).sum(1))[:, None]


def prepared(vectors: DataFrame, id_col: str, vector_col: str, label_col: str) -> DataFrame:
    """(vec_id, label, v array<double>, h1, h2): v is null where the vector links with nothing; h1 and h2 are hashes of label and v."""
    v = F.col(vector_col).cast("array<double>")
    good = F.col(label_col).isNotNull() & (F.size(v) > 0) & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0.0)
    # scaled by the largest component, so that squares neither overflow nor vanish; negative zeros are zeros
    most = F.array_max(F.transform(v, lambda x: F.abs(x)))
    rows = vectors.select(F.col(id_col).alias("vec_id"), F.col(label_col).cast("string").alias("label"), F.when(F.coalesce(good, F.lit(False)), F.transform(v, lambda x: x / most + F.lit(0.0))).alias("v"))
    return rows.withColumns({"h1": F.xxhash64("label", "v"), "h2": F.xxhash64(F.lit(7), "v", "label")})


def distinct_vectors(rows: DataFrame) -> DataFrame:
    """(u, w, low, label, dim, v, h1, h2): each vector of a label once, with a number, how often it occurs and its smallest id."""
    each = rows.where("v is not null").groupBy("h1", "h2").agg(F.count("*").alias("w"), F.min(F.col("vec_id").cast("long")).alias("low"), F.first("label").alias("label"), F.first("v").alias("v"))
    return each.select(F.monotonically_increasing_id().alias("u"), "w", "low", "label", F.size("v").alias("dim"), "v", "h1", "h2")


def fit_codebooks(groups: DataFrame) -> tuple[int, np.ndarray, np.ndarray, float] | None:
    """(dimension, codes of the first half, codes of the second half, spread) from a bounded sample, chosen by hash of the content."""
    # hashes are compared first, so that no task gathers vectors that will not be taken
    least = groups.select("h1").orderBy("h1").limit(SAMPLE).agg(F.max("h1")).first()[0]
    if least is None:
        return None
    sample = groups.where(F.col("h1") <= F.lit(least)).orderBy("h1", "h2").select("v").toPandas()["v"]
    lengths = np.array([len(v) for v in sample])
    dim = int(np.bincount(lengths).argmax())
    if dim < 2:
        return dim, np.zeros((1, dim // 2)), np.zeros((1, dim - dim // 2)), 1.0
    x = np.array([v for v in sample if len(v) == dim], float)
    x /= np.sqrt((x * x).sum(1))[:, None]
    # vectors meet within their label, so its size sets that of the grid
    n = groups.groupBy("label").count().agg(F.max("count")).first()[0]
    k = max(2, 2 ** round(math.log2(max(1.0, math.sqrt(n / OCCUPANCY)))))
    half = dim // 2
    first, second = kmeans(x[:, :half], k), kmeans(x[:, half:], k)
    return dim, first, second, spread_along(x, first, second)


CELLS = "label string, dim int, cell int, role byte, u long, w long, own boolean, v array<double>"


def _visit(books, threshold: float, recall: float):
    """Rows (u, w, label, dim, v) as stored rows (role 0) and as queries (role 1) of the cells to visit.

    Of two different cells, the one with the lower number sends the query. Vectors of another
    dimension than the codebooks' have one cell.
    """
    dim, first, second, spread = books
    half, limit = dim // 2, step_limit(threshold, spread, recall)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 500):
                b = whole.slice(at, 500)
                dims = b.column(3).to_numpy()
                cell, where, role, own = [], [], [], []
                same = np.flatnonzero(dims == dim) if dim >= 2 else np.empty(0, np.int64)
                if len(same):
                    u = _unit(b.column(4).take(pa.array(same)))
                    (ca, da), (cb, db) = to_bisectors(u[:, :half], first), to_bisectors(u[:, half:], second)
                    mine = ca * len(second) + cb
                    for r in range(len(same)):
                        a, c = np.flatnonzero(da[r] ** 2 <= limit), np.flatnonzero(db[r] ** 2 <= limit)
                        a, c = a[np.argsort(da[r][a], kind="stable")], c[np.argsort(db[r][c], kind="stable")]
                        visited = [int(a[i]) * len(second) + int(c[j]) for i, j in multi_sequence(da[r][a] ** 2, db[r][c] ** 2, limit)]
                        visited = [mine[r], *(x for x in visited if x > mine[r])]
                        cell += [mine[r], *visited]
                        where += [same[r]] * (1 + len(visited))
                        role += [0] + [1] * len(visited)
                        own += [True, True] + [False] * (len(visited) - 1)
                for r in np.flatnonzero((dims != dim) | (dim < 2)):
                    cell += [-1, -1]
                    where += [r, r]
                    role += [0, 1]
                    own += [True, True]
                take = pa.array(where, pa.int64())
                yield pa.RecordBatch.from_arrays([b.column(2).take(take), b.column(3).take(take), pa.array(cell, pa.int32()), pa.array(role, pa.int8()), b.column(0).take(take), b.column(1).take(take), pa.array(own, pa.bool_()), b.column(4).take(take)], names=["label", "dim", "cell", "role", "u", "w", "own", "v"])

    return run


FOUND = "u long, links long, a long, b long"


def _found(u: np.ndarray, links: np.ndarray | None, b: np.ndarray | None = None) -> pa.RecordBatch:
    """Counts of vectors u, or links between u and b."""
    none = pa.nulls(len(u), pa.int64())
    columns = [pa.array(u), pa.array(links), none, none] if b is None else [none, none, pa.array(u), pa.array(b)]
    return pa.RecordBatch.from_arrays(columns, names=["u", "links", "a", "b"])


def _verify(threshold: float):
    """Rows sorted by (label, dim, cell, part, role): weights of linked vectors (u, links) and spanning links (a, b)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, base, base_u, base_w, hits = None, [], None, None, None

        def counts(u: np.ndarray, links: np.ndarray) -> Iterator[pa.RecordBatch]:
            some = links > 0
            if some.any():
                yield _found(u[some], links[some])

        for batch in batches:
            keys = list(zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True))
            role, u, w = (batch.column(i).to_numpy() for i in (4, 5, 6))
            own = batch.column(7).to_numpy(zero_copy_only=False)
            change = [0, *(i for i in range(1, len(keys)) if keys[i] != keys[i - 1] or role[i] != role[i - 1]), len(keys)]
            for lo, hi in zip(change, change[1:], strict=False):
                if keys[lo] != now:
                    if hits is not None:
                        yield from counts(base_u, hits)
                    now, base, base_u, base_w, hits = keys[lo], [], np.empty(0, np.int64), np.empty(0, np.int64), None
                if role[lo] == 0:
                    base.append(_unit(batch.column(8).slice(lo, hi - lo)))
                    base_u, base_w = np.concatenate([base_u, u[lo:hi]]), np.concatenate([base_w, w[lo:hi]])
                    continue
                if not base:
                    continue
                if hits is None:
                    base, hits = [np.concatenate(base)], np.zeros(len(base_u), np.int64)
                for at in range(lo, hi, QUERIES_AT_ONCE):
                    to = min(hi, at + QUERIES_AT_ONCE)
                    near = _unit(batch.column(8).slice(at, to - at)) @ base[0].T >= threshold
                    near &= u[at:to][:, None] != base_u[None, :]
                    if not near.any():
                        continue
                    yield from counts(u[at:to], near @ base_w)
                    hits += (near & ~own[at:to, None]).T @ w[at:to]
                    q, s = np.nonzero(near)
                    a, b = star_edges(u[at:to][q], base_u[s])
                    yield _found(a, None, b)
        if hits is not None:
            yield from counts(base_u, hits)

    return run


def near_vectors(vectors: DataFrame, threshold: float = 0.93, recall: float = 0.999, id_col: str = "vec_id", vector_col: str = "embedding", label_col: str = "label") -> DataFrame:
    """(vec_id, n_links, component_id, kept), one row per input row.

    Vectors link if their labels are equal and not null, they have as many components, and
    their cosine is at least threshold; those that are null, empty, zero or hold null or
    non-finite components link with nothing. Ids are whole numbers of any sign. Repeated rows link with each other. A row with
    a null id is counted as a link of others, but has no component of its own (null, not
    kept). Tables without vectors give no links; empty tables give empty results.
    """
    rows = saved(prepared(vectors, id_col, vector_col, label_col))
    groups = saved(distinct_vectors(rows))
    books = fit_codebooks(groups)
    if books is None:
        return rows.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.col("vec_id").isNotNull().alias("kept"))
    walked = groups.select("u", "w", "label", "dim", "v").mapInArrow(_visit(books, threshold, recall), CELLS)
    cells = checkpoint(walked.where("role = 0").groupBy("label", "dim", "cell").agg(F.ceil(F.count("*") / PART).cast("int").alias("parts")).where("parts > 1"))
    parted = walked.join(broadcast_if_small(cells), ["label", "dim", "cell"], "left").withColumn("parts", F.coalesce("parts", F.lit(1)))
    # a stored vector goes to one part of its cell, a query to all
    part = F.explode(F.when(F.col("role") == 0, F.array(F.pmod(F.xxhash64("u"), F.col("parts")).cast("int"))).otherwise(F.sequence(F.lit(0), F.col("parts") - 1)))
    dealt = parted.withColumn("part", part).select("label", "dim", "cell", "part", "role", "u", "w", "own", "v").repartition("label", "dim", "cell", "part").sortWithinPartitions("label", "dim", "cell", "part", "role")
    found = checkpoint(dealt.mapInArrow(_verify(threshold), FOUND))
    links = found.where("links is not null").groupBy("u").agg(F.sum("links").alias("others"))
    labels = connected_components(found.where("a is not null").select(F.col("a").alias("u"), F.col("b").alias("v")))
    named = groups.select("u", "w", "low", "h1", "h2").join(links, "u", "left").join(labels, F.col("u") == F.col("node"), "left").withColumn("of", F.coalesce("component", "u"))
    named = checkpoint(named.select("of", "w", "low", "h1", "h2", "others"))
    first = named.groupBy("of").agg(F.min("low").alias("smallest"))
    told = named.join(first, "of").select("h1", "h2", "smallest", (F.col("w") - 1 + F.coalesce("others", F.lit(0))).alias("links"))
    out = rows.select("vec_id", F.when(F.col("v").isNotNull(), F.col("h1")).alias("h1"), "h2").join(told, ["h1", "h2"], "left")
    component = F.when(F.col("vec_id").isNotNull(), F.coalesce(F.col("smallest").cast(rows.schema["vec_id"].dataType), F.col("vec_id")))
    return out.select("vec_id", F.coalesce("links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, F.lit(False)).alias("kept"))


def op1_embedding_dedup(spark, sf_dir: str) -> DataFrame:
    return near_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))


#: DuckDB SQL for op1_embedding_dedup: all pairs of a label.
OP1_SQL = """
with recursive e as (select vec_id, label, embedding::double[] v from embeddings where label is not null and embedding is not null)
, k as (select * from e where len(v) > 0 and len(list_filter(v, lambda x: x is null or not isfinite(x))) = 0 and list_dot_product(v, v) > 0)
, l as (select a.vec_id a, b.vec_id b from k a join k b on a.label = b.label and a.vec_id <> b.vec_id and len(a.v) = len(b.v)
    where list_dot_product(a.v, b.v) / sqrt(list_dot_product(a.v, a.v)) / sqrt(list_dot_product(b.v, b.v)) >= 0.93)
, r as (select vec_id, vec_id c from embeddings union select l.b, r.c from r join l on l.a = r.vec_id)
, c as (select vec_id, min(c) c from r group by vec_id)
, n as (select a, count(*) n from l group by a)
select c.vec_id, coalesce(n, 0)::bigint n_links, c component_id, c.vec_id = c kept from c left join n on n.a = c.vec_id
"""
