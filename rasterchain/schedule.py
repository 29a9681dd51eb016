"""Assignment of the filters of a chain to workers, and when a row may be read."""

from __future__ import annotations

from pyspark.sql import Column


def assign(j: int, workers: int) -> tuple[int, int]:
    """Worker (from 1) and pass (from 0) of filter j (from 1); j may be a column."""
    worker = (j - 1) % workers
    return 1 + worker, (j - 1 - worker) / workers if isinstance(j, Column) else (j - 1) // workers


def ready(row: int, finished: int, height: int) -> bool:
    """Whether a filter may process row, once its predecessor has finished so many rows: it reads one row ahead."""
    return finished >= min(row + 2, height)


def run_order(n_filters: int, height: int, workers: int) -> list[tuple[int, int]]:
    """An order (filter, row) of a cooperative run in which every worker takes a row whenever it may."""
    done = {j: 0 for j in range(0, n_filters + 1)}
    done[0] = height
    queues = {t: [j for j in range(1, n_filters + 1) if assign(j, workers)[0] == t] for t in range(1, workers + 1)}
    order = []
    while any(queues.values()):
        before = len(order)
        for q in queues.values():
            if q and ready(done[q[0]], done[q[0] - 1], height):
                order.append((q[0], done[q[0]]))
                done[q[0]] += 1
                if done[q[0]] == height:
                    q.pop(0)
        if len(order) == before:
            raise RuntimeError("the schedule is stuck")
    return order
