"""Layouts of a raster: pixels, rows and binary strips, and the way from one to another."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rasterchain import dtypes
from rasterchain.exec.saving import saved, small_enough
from rasterchain.exec.task import images, map_images  # noqa: F401

#: payload and mask hold height x width values of the dtype, row by row; n is the number of strips of the image.
STRIP = "img bigint, strip int, n int, y0 int, h int, w int, dtype string, payload binary, mask binary"
STRIP_ARROW = pa.schema([("img", pa.int64()), ("strip", pa.int32()), ("n", pa.int32()), ("y0", pa.int32()), ("h", pa.int32()), ("w", pa.int32()), ("dtype", pa.string()), ("payload", pa.binary()), ("mask", pa.binary())])


def strip_row(img: int, strip: int, n: int, y0: int, a: np.ndarray, dtype: str, mask: np.ndarray | None = None) -> pa.RecordBatch:
    """One strip as a batch."""
    return pa.RecordBatch.from_pylist([{"img": img, "strip": strip, "n": n, "y0": y0, "h": a.shape[0], "w": a.shape[1], "dtype": dtype, "payload": a.tobytes(), "mask": None if mask is None else mask.tobytes()}], schema=STRIP_ARROW)


def to_strips(df: DataFrame, rows: int, dtype: str = "i64") -> DataFrame:
    """Pixels (img, y, x, v[, m]) -> strips of so many rows. One shuffle by strip; an image is never in one place."""
    # one row an image
    n = df.groupBy("img").agg(F.ceil((F.max("y") + 1) / rows).cast("int").alias("n"))
    return cut_strips(df, rows, dtype).drop("n").join(n, "img").select(*STRIP_ARROW.names)


def saved_strips(df: DataFrame, rows: int, dtype: str = "i64") -> DataFrame:
    """to_strips by one reading of the pixels: they are written once as strips, and counted there."""
    cut = saved(cut_strips(df, rows, dtype))
    return _told(cut.drop("n"), cut.groupBy("img").agg((F.max("strip") + 1).alias("n"))).select(*STRIP_ARROW.names)


def _told(strips: DataFrame, images: DataFrame) -> DataFrame:
    """Strips with what a frame of one row an image says; strips of one image stay in their tasks if images are few."""
    return strips.join(F.broadcast(images) if small_enough(images) else images, "img")


def cut_strips(df: DataFrame, rows: int, dtype: str = "i64") -> DataFrame:
    """Strips that do not know their image's number of strips (n is 0)."""
    has_mask = "m" in df.columns
    cut = df.select("img", F.floor(F.col("y") / rows).cast("int").alias("strip"), (F.col("y") % rows).cast("int").alias("y"), "x", "v", *(["m"] if has_mask else []))
    dealt = cut.repartition("img", "strip").sortWithinPartitions("img", "strip", "y", "x")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # strips are read as images of their own, numbered in the order of their arrival
        keys: list[tuple[int, int]] = []

        def numbered() -> Iterator[pa.RecordBatch]:
            for b in batches:
                if not b.num_rows:
                    continue
                img, strip = b.column(0).to_numpy(), b.column(1).to_numpy()
                new = np.concatenate([[not keys or keys[-1] != (img[0], strip[0])], (img[1:] != img[:-1]) | (strip[1:] != strip[:-1])])
                number = len(keys) - 1 + np.cumsum(new)
                keys.extend(zip(img[new].tolist(), strip[new].tolist(), strict=True))
                yield pa.RecordBatch.from_arrays([pa.array(number), *b.columns[2:]], names=["img", *b.schema.names[2:]])

        for number, c in images(numbered()):
            img, strip = keys[number]
            yield strip_row(img, strip, 0, strip * rows, dtypes.checked(c["v"], dtype), dtype, dtypes.checked(c["m"], dtype) if has_mask else None)

    return dealt.mapInArrow(run, STRIP)


def bordered_strips(strips: DataFrame, inside: str = "max") -> DataFrame:
    """The marker and mask of border_marker, on strips without a mask: the image on its frame, its greatest (least) value inside."""
    best = np.max if inside == "max" else np.min
    real = lambda dtype: dtype[0] == "f"
    # whole and real values each in a column of their own, so that neither is rounded
    ends = "img bigint, y1 int, whole bigint, real double"

    def measured(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in strip_rows(batches):
            v = best(array_of(row))
            yield pa.RecordBatch.from_arrays([pa.array([row["img"]], pa.int64()), pa.array([row["y0"] + row["h"] - 1], pa.int32()), pa.array([None if real(row["dtype"]) else int(v)], pa.int64()), pa.array([float(v) if real(row["dtype"]) else None], pa.float64())], names=["img", "y1", "whole", "real"])

    pick = F.max if inside == "max" else F.min
    found = strips.select(*STRIP_ARROW.names).mapInArrow(measured, ends).groupBy("img").agg(F.max("y1").alias("y1"), pick("whole").alias("whole"), pick("real").alias("real"))

    def marked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in strip_rows(batches):
            a = array_of(row)
            b = np.full_like(a, row["real"] if real(row["dtype"]) else row["whole"])
            if row["y0"] == 0:
                b[0] = a[0]
            if row["y0"] + row["h"] - 1 == row["y1"]:
                b[-1] = a[-1]
            b[:, 0], b[:, -1] = a[:, 0], a[:, -1]
            yield strip_row(row["img"], row["strip"], row["n"], row["y0"], b, row["dtype"], a)

    return _told(strips, found).select(*STRIP_ARROW.names, "y1", "whole", "real").mapInArrow(marked, STRIP)


def array_of(row: dict, name: str = "payload") -> np.ndarray | None:
    data = row[name]
    return None if data is None else np.frombuffer(data, dtypes.NUMPY[row["dtype"]]).reshape(-1, row["w"])


#: Pixels of a batch.
BATCH = 1 << 18


def strip_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
    """Strips one at a time, however large a batch is."""
    for b in batches:
        for k in range(b.num_rows):
            yield b.slice(k, 1).to_pylist()[0]


def to_pixels(strips: DataFrame, kind: str = "bigint") -> DataFrame:
    """Strips -> pixels (img, y, x, v), in batches of bounded size."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.float64() if kind == "double" else pa.int64()
        for row in strip_rows(batches):
            a, w = array_of(row).ravel(), row["w"]
            for at in range(0, a.size, BATCH):
                part = a[at : at + BATCH]
                y, x = np.divmod(np.arange(at, at + part.size), w)
                yield pa.RecordBatch.from_arrays([pa.repeat(pa.scalar(row["img"], pa.int64()), part.size), pa.array((y + row["y0"]).astype(np.int32)), pa.array(x.astype(np.int32)), pa.array(part.astype(t.to_pandas_dtype()))], names=["img", "y", "x", "v"])

    return strips.select(*STRIP_ARROW.names).mapInArrow(run, f"img bigint, y int, x int, v {kind}")


def map_strips(strips: DataFrame, fn) -> DataFrame:
    """fn(array, mask) -> array on each strip as an image of its own: no exchange at all for one-strip images."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in strip_rows(batches):
            row["payload"] = np.ascontiguousarray(fn(array_of(row), array_of(row, "mask"))).astype(dtypes.NUMPY[row["dtype"]]).tobytes()
            yield pa.RecordBatch.from_pylist([row], schema=STRIP_ARROW)

    return strips.select(*STRIP_ARROW.names).mapInArrow(run, STRIP)
