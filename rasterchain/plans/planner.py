"""Physical choices: strategy, strip height, filters a round, and the method of a size-s filter."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rasterchain.chain import Chain

#: Bytes of all state of an image up to which one task takes it whole.
TASK_BYTES = 256 << 20
#: Bytes of a strip's payload that larger images are cut into.
STRIP_BYTES = 64 << 20
#: Share of a strip that may be computed twice.
RECOMPUTE = 8


@dataclass(frozen=True)
class PhysicalChoice:
    strategy: str
    strip_rows: int
    filters_per_round: int
    rounds: int | None
    why: str

    def explain(self) -> str:
        rounds = "until stable" if self.rounds is None else f"{self.rounds} rounds"
        return f"{self.strategy}: strips of {self.strip_rows} rows, {self.filters_per_round} filters a round, {rounds} ({self.why})"


def choose(width: int, height: int, pixel_bytes: int, chain: Chain | None = None, states: int = 1, want_length: bool = True) -> PhysicalChoice:
    """chain None: reconstruction. states: columns of state of a pixel. want_length: whether its chain length is asked for."""
    total = width * height * pixel_bytes * states
    if total <= TASK_BYTES:
        return PhysicalChoice("task", max(height, 1), chain.n_filters if chain else 0, 1 if chain else None, f"{total} bytes fit a task")
    rows = max(RECOMPUTE, min(height, STRIP_BYTES // max(1, width * pixel_bytes)))
    k = max(1, rows // RECOMPUTE)
    if chain is None:
        return PhysicalChoice("rounds" if want_length else "frontier", rows, k if want_length else 0, None, f"{total} bytes exceed a task")
    n = chain.n_filters
    k = min(n, k) or 1
    return PhysicalChoice("rounds", rows, k, -(-n // k), f"{total} bytes exceed a task")


def planned(df: DataFrame, chain: Chain | None = None, states: int = 2, want_length: bool = False) -> PhysicalChoice:
    """The choice for the largest image of a pixel frame, whose size one aggregate of its coordinates tells."""
    ends = df.agg((F.max("x") + 1).alias("w"), (F.max("y") + 1).alias("h")).first()
    return choose(ends["w"] or 1, ends["h"] or 1, 8, chain, states, want_length)


def method(s: int, faithful: bool = False) -> str:
    """Method of an erosion of size s; faithful keeps the chain of elementary filters."""
    return "chain" if faithful or s <= 2 else "prefix_suffix"
