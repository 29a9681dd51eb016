"""Filter chains: what is computed, apart from how. Chains are immutable and go to JSON and back."""

from __future__ import annotations

import json
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np

from rasterchain import kernels as K

#: Kinds that a strip, read with some rows around it, can compute on its own.
STREAMED = ("MIN3", "MAX3", "GEO_MIN3", "GEO_MAX3", "LIP3", "MIN", "MAX")


@dataclass(frozen=True)
class FilterSpec:
    """One filter. size is the half side of MIN and MAX; halo is how far a pixel looks."""

    kind: str
    size: int = 1

    @property
    def halo(self) -> int:
        return 0 if self.kind in POINTS else self.size

    @property
    def reads_mask(self) -> bool:
        return self.kind.startswith("GEO")

    @property
    def monotone(self) -> bool:
        return self.kind in STREAMED


@dataclass(frozen=True)
class Chain:
    """Filters in the order in which they are applied."""

    filters: tuple[FilterSpec, ...] = field(default_factory=tuple)

    @classmethod
    def of(cls, *kinds: str | FilterSpec) -> Chain:
        return cls(tuple(k if isinstance(k, FilterSpec) else FilterSpec(k) for k in kinds))

    def __add__(self, other: Chain) -> Chain:
        return Chain(self.filters + other.filters)

    def __mul__(self, n: int) -> Chain:
        return Chain(self.filters * n)

    @property
    def n_filters(self) -> int:
        """Elementary filters; a filter of size s counts as s."""
        return sum(f.size for f in self.filters if f.kind not in POINTS)

    @property
    def n_pointwise(self) -> int:
        return sum(f.kind in POINTS for f in self.filters)

    @property
    def halo(self) -> int:
        return sum(f.halo for f in self.filters)

    def to_json(self) -> str:
        return json.dumps([{"kind": f.kind, "size": f.size} for f in self.filters])

    @classmethod
    def from_json(cls, text: str) -> Chain:
        return cls(tuple(FilterSpec(f["kind"], f.get("size", 1)) for f in json.loads(text)))


POINTS: dict[str, Callable] = {"NEGATE": lambda a: -a}
CUSTOM: dict[str, Callable] = {}


def register_filter(name: str, rows: Callable[[np.ndarray], np.ndarray], halo: int = 1) -> None:
    """Adds a filter of one's own: a function of an image that looks no farther than halo pixels."""
    if halo not in (0, 1):
        raise ValueError("chains are made of filters that look one pixel far")
    (CUSTOM if halo else POINTS)[name] = rows


def apply(a: np.ndarray, f: FilterSpec, mask: np.ndarray | None = None) -> np.ndarray:
    match f.kind:
        case "MIN3":
            return K.sep3(a, K.MIN)
        case "MAX3":
            return K.sep3(a, K.MAX)
        case "GEO_MIN3":
            return K.geodesic(a, mask, K.MIN)
        case "GEO_MAX3":
            return K.geodesic(a, mask, K.MAX)
        case "LIP3":
            return K.lipschitz_step(a)
        case "MIN":
            return K.filtered(a, f.size, K.MIN)
        case "MAX":
            return K.filtered(a, f.size, K.MAX)
        case kind if kind in POINTS:
            return POINTS[kind](a)
        case kind:
            return CUSTOM[kind](a)


def run(a: np.ndarray, chain: Chain, mask: np.ndarray | None = None) -> np.ndarray:
    k = 0
    while k < len(chain.filters):
        f, n = chain.filters[k], 1
        while k + n < len(chain.filters) and chain.filters[k + n] == f:
            n += 1
        if f.kind in ("MIN3", "MAX3") and a.ndim == 2:
            a = K.chain3(a, n, K.MIN if f.kind == "MIN3" else K.MAX)
        else:
            for _ in range(n):
                a = apply(a, f, mask)
        k += n
    return a


def erosion(s: int) -> Chain:
    return Chain.of("MIN3") * s


def dilation(s: int) -> Chain:
    return Chain.of("MAX3") * s


def opening(s: int) -> Chain:
    return erosion(s) + dilation(s)


def closing(s: int) -> Chain:
    return dilation(s) + erosion(s)


def alternating(s: int, first: str = "open") -> Chain:
    """Openings and closings of sizes 1 to s."""
    one, two = (opening, closing) if first == "open" else (closing, opening)
    out = Chain()
    for k in range(1, s + 1):
        out = out + one(k) + two(k)
    return out
