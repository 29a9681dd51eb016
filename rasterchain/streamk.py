"""Row-streaming filters: rows in, rows out, one row late, holding two filtered rows.

Filters are generators, so a chain of them is a pipeline in which each filter runs a row
ahead of the next and no image is ever whole: N filters hold 2N rows.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np

from rasterchain import kernels as K


def min3_rows(rows: Iterable[np.ndarray], lo=K.MIN, counter: dict | None = None) -> Iterator[np.ndarray]:
    """The 3x3 filter. counter, if given, counts pairwise comparisons of pixels in its entry comparisons."""
    above = here = None
    for row in rows:
        below = K.row3(row, lo, -1)
        if here is not None:
            yield lo(here if above is None else lo(above, here), below)
        if counter is not None:
            counter["comparisons"] = counter.get("comparisons", 0) + 4 * len(row)
        above, here = here, below
    if here is not None:
        yield here if above is None else lo(above, here)


def geo3_rows(rows: Iterable[tuple[np.ndarray, np.ndarray]], lo=K.MAX) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """The geodesic filter on pairs (row, mask row)."""
    masks: list[np.ndarray] = []

    def plain() -> Iterator[np.ndarray]:
        for row, mask in rows:
            masks.append(mask)
            yield row

    clamp = K.MIN if lo is K.MAX else K.MAX
    for new in min3_rows(plain(), lo):
        mask = masks.pop(0)
        yield clamp(new, mask), mask


def lip3_rows(rows: Iterable[np.ndarray]) -> Iterator[np.ndarray]:
    """One pull-down of rows that lie more than 1 above their eroded neighbourhood."""
    held: list[np.ndarray] = []

    def plain() -> Iterator[np.ndarray]:
        for row in rows:
            held.append(row)
            yield row

    for low in min3_rows(plain()):
        yield np.minimum(held.pop(0), low + 1)


def residual_rows(rows: Iterable[tuple[np.ndarray, np.ndarray, np.ndarray]], step: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """One erosion of triples (row, d, r) that notes the step of a strictly larger loss."""
    held: list[tuple] = []

    def plain() -> Iterator[np.ndarray]:
        for t in rows:
            held.append(t)
            yield t[0]

    for low in min3_rows(plain()):
        row, d, r = held.pop(0)
        loss = row - low
        more = loss > r
        yield low, np.where(more, step, d), np.where(more, loss, r)


def pipeline(rows: Iterable[np.ndarray], kinds: list[str], counter: dict | None = None) -> Iterator[np.ndarray]:
    """A chain of MIN3 and MAX3 filters that advance together."""
    for kind in kinds:
        rows = min3_rows(rows, K.MIN if kind == "MIN3" else K.MAX, counter)
    return iter(rows)


def blocks(a: np.ndarray, kinds: list[str], block_rows: int = 128) -> np.ndarray:
    """The same chain over blocks of rows, each read with the rows that its filters reach beyond it."""
    n, out = len(kinds), np.empty_like(a)
    for y in range(0, len(a), block_rows):
        top, bottom = max(0, y - n), min(len(a), y + block_rows + n)
        part = a[top:bottom]
        for kind in kinds:
            part = K.sep3(part, K.MIN if kind == "MIN3" else K.MAX)
        out[y : y + block_rows] = part[y - top : y - top + block_rows]
    return out
