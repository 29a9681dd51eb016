"""Filters on streams: chains on rows as they arrive, and windows of events as rasters.

A fixed chain needs two rows of state for each filter; a row of the result leaves once the
row N below it, or the last row of the image, has come. Rows may come out of order: later
ones wait in the state. Repeated rows are dropped. Reconstruction needs whole images, so it
runs on windows that the watermark has closed.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rasterchain import kernels as K

OUT = "img bigint, y int, row array<bigint>"
STATE = "data binary"


class Min3State:
    """One filter between rows: what min3_rows holds, but resumable."""

    def __init__(self, kind: str):
        self.lo = kind == "MIN3"
        self.above = self.here = None

    def push(self, row: np.ndarray) -> list[np.ndarray]:
        lo = K.MIN if self.lo else K.MAX
        below, out = K.row3(row, lo, -1), []
        if self.here is not None:
            out.append(lo(self.here if self.above is None else lo(self.above, self.here), below))
        self.above, self.here = self.here, below
        return out

    def finish(self) -> list[np.ndarray]:
        lo = K.MIN if self.lo else K.MAX
        return [] if self.here is None else [self.here if self.above is None else lo(self.above, self.here)]


class ChainState:
    def __init__(self, kinds: list[str], height: int):
        self.filters, self.height = [Min3State(k) for k in kinds], height
        self.expected, self.emitted = 0, 0
        self.waiting: dict[int, np.ndarray] = {}

    def add(self, y: int, row) -> list[tuple[int, np.ndarray]]:
        """Rows of the result that this row sets free. Rows seen before are dropped."""
        if y < self.expected or y in self.waiting:
            return []
        self.waiting[y] = np.asarray(row, np.int64)
        out: list[np.ndarray] = []
        while self.expected in self.waiting:
            out += self._through(0, [self.waiting.pop(self.expected)])
            self.expected += 1
        if self.expected == self.height:
            for k, f in enumerate(self.filters):
                out += self._through(k + 1, f.finish())
            self.expected += 1
        named = [(self.emitted + i, r) for i, r in enumerate(out)]
        self.emitted += len(out)
        return named

    def _through(self, k: int, rows: list[np.ndarray]) -> list[np.ndarray]:
        for f in self.filters[k:]:
            rows = [o for r in rows for o in f.push(r)]
        return rows


def chain(rows: DataFrame, kinds: list[str], heights: int) -> DataFrame:
    """A stream of rows (img, y, row) of images of the given height -> a stream of rows of the chain's result."""

    def run(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        now = pickle.loads(state.get[0]) if state.exists else ChainState(kinds, heights)
        out = []
        for frame in frames:
            for y, row in sorted(zip(frame["y"].tolist(), frame["row"].tolist(), strict=True), key=lambda r: r[0]):
                out += now.add(int(y), row)
        state.update((pickle.dumps(now),))
        if out:
            yield pd.DataFrame({"img": key[0], "y": np.array([y for y, _ in out], np.int32), "row": [r.tolist() for _, r in out]})

    return rows.groupBy("img").applyInPandasWithState(run, OUT, STATE, "append", "NoTimeout")


def window_cells(events: DataFrame, window: str, slide: str | None = None, watermark: str = "1 hour", y: str = "user_id", step: int = 3600) -> DataFrame:
    """Counts (w_start, w_end, y, x) of windows of events; x counts steps of so many seconds in a window. Late events beyond the watermark are dropped and counted by Spark."""
    ts = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark)
    w = F.window("ts", window, slide) if slide else F.window("ts", window)
    # the window is made first, as the place of an event depends on it
    placed = ts.select(F.col("ts"), F.col(y).cast("int").alias("y"), w.alias("w")).withColumn("x", F.floor((F.unix_seconds("ts") - F.unix_seconds("w.start")) / step).cast("int"))
    return placed.groupBy("w", "y", "x").agg(F.count("*").alias("v")).select(F.unix_seconds("w.start").alias("w_start"), F.unix_seconds("w.end").alias("w_end"), "y", "x", "v")


def session_cells(events: DataFrame, gap: str, watermark: str = "1 hour") -> DataFrame:
    """(user_id, s_start, s_end, n): sessions of each user that are apart by more than the gap."""
    ts = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark)
    s = ts.groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count("*").alias("n"))
    return s.select(F.col("user_id").cast("bigint").alias("user_id"), F.unix_micros("s.start").alias("s_start"), F.unix_micros("s.end").alias("s_end"), "n")


def each_window(cells: DataFrame, operator, sink) -> object:
    """Runs a batch operator on the windows that a trigger has closed: a foreachBatch writer, not started."""

    def run(batch: DataFrame, batch_id: int) -> None:
        sink(operator(batch), batch_id)

    return cells.writeStream.foreachBatch(run)
