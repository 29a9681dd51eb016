"""Pixel types: storage, neutral values and arithmetic."""

from __future__ import annotations

import numpy as np

NUMPY = {"u8": np.uint8, "u16": np.uint16, "i16": np.int16, "i32": np.int32, "i64": np.int64, "f32": np.float32, "f64": np.float64}
SPARK = {"u8": "smallint", "u16": "int", "i16": "smallint", "i32": "int", "i64": "bigint", "f32": "float", "f64": "double"}
#: Bits of a vector register, for the stride of the in-place kernels.
VECTOR_BITS = 256


def stride(dtype: str) -> int:
    """Pixels of this type that one vector instruction handles."""
    return VECTOR_BITS // (8 * np.dtype(NUMPY[dtype]).itemsize)


def highest(dtype) -> float | int:
    """The value that no minimum prefers."""
    d = np.dtype(dtype)
    return np.inf if d.kind == "f" else np.iinfo(d).max


def lowest(dtype) -> float | int:
    d = np.dtype(dtype)
    return -np.inf if d.kind == "f" else np.iinfo(d).min


def lowered(a: np.ndarray, h, arith: str = "real") -> np.ndarray:
    """a - h: widened to a signed type (real), or held at the type's lowest value (saturate)."""
    if a.dtype.kind == "f":
        return a - a.dtype.type(h)
    wide = a.astype(np.int64) - int(h)
    return np.maximum(wide, lowest(a.dtype)).astype(a.dtype) if arith == "saturate" else wide


def checked(a: np.ndarray, dtype: str) -> np.ndarray:
    """a as dtype; raises if a value does not fit."""
    out = a.astype(NUMPY[dtype])
    if out.dtype.kind != "f" and not np.array_equal(out, a):
        raise ValueError(f"values outside the range of {dtype}")
    return out
