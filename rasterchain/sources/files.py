"""Rasters from files and to files: graymaps, arrays, matrices of text, strips, and synthetic images."""

from __future__ import annotations

import io
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rasterchain.layout import STRIP_ARROW

PIXELS = "img bigint, y int, x int, v bigint"


def decode(data: bytes, fmt: str) -> np.ndarray:
    """An image file as an array: pgm (plain or binary, 8 or 16 bits) or npy."""
    if fmt == "npy":
        return np.load(io.BytesIO(data), allow_pickle=False)
    m = re.match(rb"(P[25])(?:\s|#[^\n]*\n)+(\d+)(?:\s|#[^\n]*\n)+(\d+)(?:\s|#[^\n]*\n)+(\d+)\s", data)
    if not m:
        raise ValueError("not a graymap")
    w, h, top = (int(x) for x in m.groups()[1:])
    if m[1] == b"P2":
        return np.array(data[m.end() :].split(), np.int64).reshape(h, w)
    kind = np.dtype(">u2") if top > 255 else np.dtype("u1")
    return np.frombuffer(data, kind, w * h, m.end()).reshape(h, w).astype(np.int64)


def encode(a: np.ndarray, fmt: str) -> bytes:
    if fmt == "npy":
        out = io.BytesIO()
        np.save(out, a)
        return out.getvalue()
    if a.size and (a.min() < 0 or a.max() > 65535):
        raise ValueError("graymaps hold values from 0 to 65535")
    wide = bool(a.size) and a.max() > 255
    return f"P5\n{a.shape[1]} {a.shape[0]}\n{65535 if wide else 255}\n".encode() + a.astype(">u2" if wide else "u1").tobytes()


def read_images(spark: SparkSession, path: str, fmt: str = "pgm") -> DataFrame:
    """(img, y, x, v, path): files of a folder, named by a hash of their path."""
    files = spark.read.format("binaryFile").option("pathGlobFilter", f"*.{fmt}").load(path)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for img, name, data in zip(*(c.to_pylist() for c in b.columns), strict=True):
                a = decode(data, fmt)
                h, w = a.shape
                yield pa.RecordBatch.from_arrays([pa.array(np.full(h * w, img)), pa.array(np.repeat(np.arange(h, dtype=np.int32), w)), pa.array(np.tile(np.arange(w, dtype=np.int32), h)), pa.array(a.ravel().astype(np.int64)), pa.array([name] * (h * w))], names=["img", "y", "x", "v", "path"])

    return files.select(F.xxhash64("path").alias("img"), "path", "content").mapInArrow(run, f"{PIXELS}, path string")


def encoded(df: DataFrame, fmt: str = "pgm") -> DataFrame:
    """(img, content binary): each image as a file's bytes."""
    from rasterchain.exec.task import dealt, images

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for img, c in images(batches):
            yield pa.RecordBatch.from_arrays([pa.array([img], pa.int64()), pa.array([encode(c["v"], fmt)], pa.binary())], names=["img", "content"])

    return dealt(df.select("img", "y", "x", "v")).mapInArrow(run, "img bigint, content binary")


def write_strips(strips: DataFrame, path: str, buckets: int = 64) -> None:
    """Strips as Parquet in folders by a bucket of the image, so that reads of one image prune."""
    strips.withColumn("bucket", F.pmod(F.xxhash64("img"), F.lit(buckets)).cast("int")).repartition("bucket").write.mode("overwrite").partitionBy("bucket").parquet(path)


def read_strips(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path).select(*STRIP_ARROW.names)


def read_matrix(spark: SparkSession, path: str, fmt: str = "csv") -> DataFrame:
    """One image of rows (y, values...) in csv, or (img, y, row array) in json, orc or parquet -> pixels."""
    if fmt == "csv":
        lines = spark.read.text(path).select(F.split("value", ",").alias("c"))
        rows = lines.select(F.lit(0).cast("bigint").alias("img"), F.col("c")[0].cast("int").alias("y"), F.transform(F.slice("c", 2, F.size("c")), lambda e: e.cast("bigint")).alias("row"))
    else:
        reader = spark.read.schema("img bigint, y int, row array<bigint>")
        rows = reader.json(path) if fmt == "json" else reader.orc(path) if fmt == "orc" else reader.parquet(path)
    return rows.select("img", "y", F.posexplode("row").alias("x", "v")).select("img", "y", "x", "v")


def synthetic(spark: SparkSession, kind: str, width: int, height: int, seed: int = 0) -> DataFrame:
    """ramp, checker, noise or serpentine (a corridor of 1 among 0), as pixels of image 0."""
    grid = spark.range(width * height).select(F.lit(0).cast("bigint").alias("img"), F.floor(F.col("id") / width).cast("int").alias("y"), (F.col("id") % width).cast("int").alias("x"))
    wall = (F.col("y") % 2 == 1) & ~F.when(F.col("y") % 4 == 1, F.col("x") == width - 1).otherwise(F.col("x") == 0)
    value = {
        "ramp": F.col("x") + F.col("y"),
        "checker": (F.col("x") + F.col("y")) % 2,
        "noise": F.pmod(F.xxhash64(F.lit(seed), F.col("y"), F.col("x")), F.lit(256)),
        "serpentine": F.when(wall, 0).otherwise(1),
    }[kind]
    return grid.withColumn("v", value.cast("bigint"))
