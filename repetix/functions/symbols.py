"""Strings as arrays of symbols: code points, bytes, or integers that are given."""

from __future__ import annotations

import numpy as np

UNITS = ("codepoint", "byte", "symbol")


def encode(value, unit: str = "codepoint") -> np.ndarray:
    """Symbols of one value as int64; null is the empty string."""
    if value is None:
        return np.empty(0, np.int64)
    if unit == "codepoint":
        return np.frombuffer(value.encode("utf-32-le", "surrogatepass"), "<u4").astype(np.int64)
    if unit == "byte":
        raw = value if isinstance(value, bytes) else value.encode("utf-8", "surrogatepass")
        return np.frombuffer(raw, np.uint8).astype(np.int64)
    if unit == "symbol":
        return np.asarray(value, np.int64)
    raise ValueError(f"unit must be one of {UNITS}")
