"""Reconstruction over strips with the fewest rounds: work follows the moving front.

A strip runs to its own fixed point with one row from each neighbour; in the next round only
strips whose neighbours' edge rows changed run again. Filters are monotone and bounded by
the mask, so any fair order reaches the same limit; chain lengths are not known this way.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rasterchain import dtypes
from rasterchain import kernels as K
from rasterchain.chain import Chain
from rasterchain.exec.rounds import ABOVE, BELOW, run_chain
from rasterchain.exec.saving import saved
from rasterchain.layout import STRIP, STRIP_ARROW, array_of

#: above and below: the neighbours' edge rows as last heard; up and down: whether the own edge rows changed.
STATE = f"{STRIP}, above binary, below binary, up boolean, down boolean"
STATE_ARROW = pa.schema([*STRIP_ARROW, ("above", pa.binary()), ("below", pa.binary()), ("up", pa.bool_()), ("down", pa.bool_())])
MESSAGE = "img bigint, strip int, side int, row binary, mask_row binary"
MESSAGE_ARROW = pa.schema([("img", pa.int64()), ("strip", pa.int32()), ("side", pa.int32()), ("row", pa.binary()), ("mask_row", pa.binary())])


def _messages(state: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for row in b.to_pylist():
                a = array_of(row)
                if row["up"] and row["strip"] > 0:
                    out.append({"img": row["img"], "strip": row["strip"] - 1, "side": BELOW, "row": a[0].tobytes()})
                if row["down"] and row["strip"] + 1 < row["n"]:
                    out.append({"img": row["img"], "strip": row["strip"] + 1, "side": ABOVE, "row": a[-1].tobytes()})
            yield pa.RecordBatch.from_pylist(out, schema=MESSAGE_ARROW)

    return state.where("up or down").mapInArrow(run, MESSAGE)


def until_stable(strips: DataFrame, by: str = "dilation", cap: int = 10_000) -> tuple[DataFrame, int]:
    """Reconstruction of payload under (over) mask: strips, and the number of rounds. Raises beyond cap rounds."""
    lo = K.MAX if by == "dilation" else K.MIN

    def settle(first: bool):
        def run(left: pa.Table, right: pa.Table) -> pa.Table:
            out = []
            sent = {m["side"]: m["row"] for m in right.to_pylist()}
            for row in left.to_pylist():
                row["above"], row["below"] = sent.get(ABOVE, row["above"]), sent.get(BELOW, row["below"])
                if sent or first:
                    kind = dtypes.NUMPY[row["dtype"]]
                    a, m = array_of(row), array_of(row, "mask")
                    edge = {side: np.frombuffer(row[side], kind) for side in ("above", "below") if row[side] is not None}
                    # what the neighbours' rows bring in; they themselves stay as they were sent
                    b = K.settled(a, m, lo, edge.get("above"), edge.get("below"))
                    row["up"], row["down"] = first or not np.array_equal(a[0], b[0]), first or not np.array_equal(a[-1], b[-1])
                    row["payload"] = b.tobytes()
                else:
                    row["up"] = row["down"] = False
                out.append(row)
            return pa.Table.from_pylist(out, schema=STATE_ARROW)

        return run

    # one synchronous filter orders marker and mask; from then on any order of updates will do
    ordered = run_chain(strips, Chain.of("GEO_MAX3" if by == "dilation" else "GEO_MIN3"), 1)
    start = ordered.select(*STRIP_ARROW.names).withColumns({"above": F.lit(None).cast("binary"), "below": F.lit(None).cast("binary"), "up": F.lit(True), "down": F.lit(True)})
    state, rounds = saved(start), 0
    first = True
    while True:
        messages = _messages(state)
        state = saved(state.groupBy("img", "strip").cogroup(messages.groupBy("img", "strip")).applyInArrow(settle(first), STATE))
        first = False
        rounds += 1
        if rounds > cap:
            raise RuntimeError("the reconstruction did not settle within its cap")
        if state.where("(up and strip > 0) or (down and strip + 1 < n)").isEmpty():
            return state.select(*STRIP_ARROW.names), rounds
