"""Long chains over strips: each round ships a few rows across strip edges and runs as many filters.

A strip that is read with k rows beyond each edge can run k filters alone; its own rows are
then exact. Only those rows are shuffled. Strips are written between rounds, so plans do not
grow and lost executors cost one round at most.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rasterchain import dtypes
from rasterchain import kernels as K
from rasterchain.chain import Chain, apply
from rasterchain.exec.saving import saved, shared_folder
from rasterchain.layout import STRIP, STRIP_ARROW, array_of

#: last: the last filter of the round that changed the strip's own rows, 0 if none did.
STATE = f"{STRIP}, last int"
STATE_ARROW = STRIP_ARROW.append(pa.field("last", pa.int32()))
MESSAGE = "img bigint, strip int, side int, rows binary, mask_rows binary"
MESSAGE_ARROW = pa.schema([("img", pa.int64()), ("strip", pa.int32()), ("side", pa.int32()), ("rows", pa.binary()), ("mask_rows", pa.binary())])
ABOVE, BELOW = 0, 1


def edges(state: DataFrame, k: int) -> DataFrame:
    """The first and last k rows of each strip, addressed to its neighbours. Strips have k rows at least, but for the last."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for row in b.to_pylist():
                a, m = array_of(row), array_of(row, "mask")
                for other, side, part in ((row["strip"] - 1, BELOW, slice(None, k)), (row["strip"] + 1, ABOVE, slice(max(0, row["h"] - k), None))):
                    if 0 <= other < row["n"]:
                        out.append({"img": row["img"], "strip": other, "side": side, "rows": a[part].tobytes(), "mask_rows": None if m is None else m[part].tobytes()})
            yield pa.RecordBatch.from_pylist(out, schema=MESSAGE_ARROW)

    return state.select(*STRIP_ARROW.names).mapInArrow(run, MESSAGE)


def with_edges(state: DataFrame, messages: DataFrame, fn: Callable) -> DataFrame:
    """fn(array, mask, rows above it) -> (array, last) on each strip and what its neighbours sent."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        out = []
        sent = {m["side"]: m for m in right.to_pylist()}
        for row in left.to_pylist():
            kind = dtypes.NUMPY[row["dtype"]]
            part = lambda side, name: np.frombuffer(sent[side][name], kind).reshape(-1, row["w"]) if side in sent and sent[side][name] is not None else np.empty((0, row["w"]), kind)  # noqa: B023, E731
            a, m = array_of(row), array_of(row, "mask")
            top = part(ABOVE, "rows")
            whole = np.concatenate([top, a, part(BELOW, "rows")])
            mask = None if m is None else np.concatenate([part(ABOVE, "mask_rows"), m, part(BELOW, "mask_rows")])
            new, last = fn(whole, mask, len(top), len(a))
            row["payload"] = np.ascontiguousarray(new).astype(kind).tobytes()
            row["last"] = last
            out.append(row)
        return pa.Table.from_pylist(out, schema=STATE_ARROW)

    return state.groupBy("img", "strip").cogroup(messages.groupBy("img", "strip")).applyInArrow(run, STATE)


def run_chain(strips: DataFrame, chain: Chain, per_round: int) -> DataFrame:
    """A fixed chain of elementary filters, so many of them a round."""
    state = saved(strips.withColumn("last", F.lit(0)))
    filters = chain.filters
    for at in range(0, len(filters), per_round):
        part = filters[at : at + per_round]

        def step(whole, mask, top, h, part=part):
            for f in part:
                whole = apply(whole, f, mask)
            return whole[top : top + h], 0

        state = saved(with_edges(state, edges(state, sum(f.halo for f in part)), step))
    return state.drop("last")


def until_stable(strips: DataFrame, by: str = "dilation", per_round: int = 8, cap: int = 100_000) -> tuple[DataFrame, DataFrame]:
    """Reconstruction of payload under (over) mask: strips, and (img, chain_len) as a synchronous run counts it.

    Strips of images that have settled leave the rounds for a table in the shared folder, so the plan does not grow. Raises beyond cap filters; a
    result is never cut short.
    """
    lo = K.MAX if by == "dilation" else K.MIN

    def step(whole, mask, top, h):
        last = 0
        for j in range(1, per_round + 1):
            new = K.geodesic(whole, mask, lo)
            if not np.array_equal(new[top : top + h], whole[top : top + h]):
                last = j
            whole = new
        return whole[top : top + h], last

    state, done = saved(strips.withColumn("last", F.lit(0))), 0
    spark, folder = strips.sparkSession, shared_folder(strips.sparkSession, "rounds")
    add = lambda df, name: df.write.mode("append").parquet(f"{folder}/{name}")
    add(state.drop("last").limit(0), "strips")
    while True:
        if done > cap:
            raise RuntimeError("the reconstruction did not settle within its cap")
        state = saved(with_edges(state, edges(state, per_round), step))
        # one row an image
        seen = saved(state.groupBy("img").agg(F.max("last").alias("last")))
        add(seen.select("img", F.when(F.col("last") > 0, F.col("last") + done).otherwise(F.lit(0)).cast("int").alias("chain_len")), "lengths")
        still, over = seen.where("last > 0").select("img"), seen.where("last = 0").select("img")
        done += per_round
        if not over.isEmpty():
            add(state.join(over, "img", "left_semi").select(*STRIP_ARROW.names), "strips")
            state = saved(state.join(still, "img", "left_semi").select(*STATE_ARROW.names))
        if still.isEmpty():
            lengths = spark.read.parquet(f"{folder}/lengths").groupBy("img").agg(F.max("chain_len").alias("chain_len"))
            return spark.read.parquet(f"{folder}/strips"), lengths
