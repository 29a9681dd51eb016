"""One task takes whole images: a shuffle by image, and no barrier however long the chain.

Rows come sorted by image and place, so a task streams through many small images and holds
one at a time.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from rasterchain import dtypes

Columns = dict[str, np.ndarray]


def shaped(img, y: np.ndarray, x: np.ndarray, columns: Columns) -> Columns:
    """The columns of one image, sorted by place, as two-dimensional arrays; raises if pixels lack or repeat."""
    h, w = int(y[-1]) + 1, int(x.max()) + 1
    if h * w != len(y) or not (np.array_equal(x, np.tile(np.arange(w), h)) and np.array_equal(y, np.repeat(np.arange(h), w))):
        raise ValueError(f"image {img} is not dense: {len(y)} pixels on {w} x {h}")
    return {k: v.reshape(h, w) for k, v in columns.items()}


def images(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, Columns]]:
    """Whole images of a stream of rows (img, y, x, columns...) sorted by img, y, x."""
    held: list[pa.RecordBatch] = []

    def close(parts: list[pa.RecordBatch]) -> Iterator[tuple[int, Columns]]:
        t = pa.Table.from_batches(parts)
        img = t.column(0).to_numpy()
        if t.num_rows and any(t.column(k).null_count for k in range(t.num_columns)):
            raise ValueError("pixels without a value: fill them first")
        cut = np.concatenate([[0], np.flatnonzero(img[1:] != img[:-1]) + 1, [len(img)]])
        cols = {t.column_names[k]: t.column(k).to_numpy() for k in range(1, t.num_columns)}
        for a, b in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True):
            part = {k: v[a:b] for k, v in cols.items()}
            yield int(img[a]), shaped(img[a], part.pop("y"), part.pop("x"), part)

    for b in batches:
        if not b.num_rows:
            continue
        img = b.column(0).to_numpy()
        last = int(np.argmax(img == img[-1]))
        if held and img[0] != held[-1].column(0)[-1].as_py() or last:
            if last:
                held.append(b.slice(0, last))
            yield from close(held)
            held = []
        held.append(b.slice(last))
    if held:
        yield from close(held)


def dealt(df: DataFrame) -> DataFrame:
    rest = [c for c in df.columns if c not in ("img", "y", "x")]
    return df.select("img", "y", "x", *rest).repartition("img").sortWithinPartitions("img", "y", "x")


def map_images(df: DataFrame, fn: Callable[[Columns], Columns], out: str = "v bigint") -> DataFrame:
    """fn from the columns of an image to new columns of the same shape -> (img, y, x, out)."""
    schema = f"img bigint, y int, x int, {out}"
    names = [c.split()[0] for c in out.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for img, columns in images(batches):
            result = fn(columns)
            h, w = next(iter(result.values())).shape
            kinds = [pa.int64(), pa.int32(), pa.int32(), *(_arrow(c.split()[1]) for c in out.split(", "))]
            flat = [np.full(h * w, img), np.repeat(np.arange(h), w), np.tile(np.arange(w), h), *(result[c].ravel() for c in names)]
            yield pa.RecordBatch.from_arrays([pa.array(v, kind) for v, kind in zip((np.asarray(f).astype(_numpy(k)) for f, k in zip(flat, kinds, strict=True)), kinds, strict=True)], names=["img", "y", "x", *names])

    return dealt(df).mapInArrow(run, schema)


def _arrow(kind: str) -> pa.DataType:
    return {"bigint": pa.int64(), "int": pa.int32(), "double": pa.float64(), "float": pa.float32(), "smallint": pa.int16()}[kind]


def _numpy(kind: pa.DataType):
    return kind.to_pandas_dtype()


def reduce_images(df: DataFrame, fn: Callable[[Columns], list[tuple]], out: str) -> DataFrame:
    """fn from the columns of an image to rows -> (img, out). Strips that hold whole images are read where they are, without an exchange."""
    names = [c.split()[0] for c in out.split(", ")]
    kinds = [_arrow(c.split()[1]) for c in out.split(", ")]
    strips = "payload" in df.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for img, columns in whole_strips(batches) if strips else images(batches):
            rows = fn(columns)
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array([img] * len(rows), pa.int64()), *(pa.array(list(c), k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True))], names=["img", *names])

    return (df if strips else dealt(df)).mapInArrow(run, f"img bigint, {out}")


def whole_strips(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, Columns]]:
    for b in batches:
        for row in b.to_pylist():
            if row["n"] != 1:
                raise ValueError(f"image {row['img']} has several strips")
            kind = dtypes.NUMPY[row["dtype"]]
            yield row["img"], {name: np.frombuffer(row[column], kind).reshape(row["h"], row["w"]) for name, column in (("v", "payload"), ("m", "mask")) if row[column] is not None}
