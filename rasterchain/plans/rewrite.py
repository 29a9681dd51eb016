"""Algebra of chains: laws of erosions and dilations by squares, applied before execution."""

from __future__ import annotations

from rasterchain.chain import Chain, FilterSpec

GROUP = {"MIN3": "MIN", "MIN": "MIN", "MAX3": "MAX", "MAX": "MAX"}


def fused(chain: Chain) -> Chain:
    """Neighbouring erosions (dilations) become one of the summed size."""
    out: list[FilterSpec] = []
    for f in chain.filters:
        kind = GROUP.get(f.kind)
        if kind and out and out[-1].kind == kind:
            out[-1] = FilterSpec(kind, out[-1].size + f.size)
        else:
            out.append(FilterSpec(kind, f.size) if kind else f)
    return Chain(tuple(out))


def absorbed(chain: Chain) -> Chain:
    """Of two openings (closings) in a row, the larger stays. Takes a fused chain.

    An opening of size a and one of size b read MIN a, MAX a + ... as MIN a, MAX a, MIN b, MAX b.
    """
    f = list(chain.filters)
    k = 0
    while k + 3 < len(f):
        a, b, c, d = f[k : k + 4]
        if a.kind == c.kind != b.kind == d.kind and {a.kind, b.kind} == {"MIN", "MAX"} and a.size == b.size and c.size == d.size:
            f[k : k + 4] = [a, b] if a.size >= c.size else [c, d]
        else:
            k += 1
    return Chain(tuple(f))


def unfused(chain: Chain) -> Chain:
    """Every filter as a chain of 3x3 filters."""
    out: list[FilterSpec] = []
    for f in chain.filters:
        out += [FilterSpec(f.kind + "3")] * f.size if f.kind in ("MIN", "MAX") else [f]
    return Chain(tuple(out))


def optimize(chain: Chain, fuse: bool = False) -> Chain:
    """fuse=False keeps the elementary filters, as timings of chains need them."""
    return absorbed(fused(chain)) if fuse else unfused(chain)


def read_window(chain: Chain, x0: int, y0: int, x1: int, y1: int) -> tuple[int, int, int, int]:
    """The pixels (inclusive bounds) that a fixed chain must read for a window of its result."""
    r = chain.halo
    return max(0, x0 - r), max(0, y0 - r), x1 + r, y1 + r
