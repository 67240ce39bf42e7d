"""A hash of packed fingerprints that SQL engines compute alike.

Affine in both residues modulo a Mersenne prime, then squared and scaled; every product is
below 2^62 and no sum overflows, so the values agree bit for bit between NumPy, Spark and other SQL
engines. Three seeds give independent hashes for level, bucket and order.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from .fingerprint import SHIFT

P = (1 << 31) - 1
SCALE, OFFSET = 48271, 11
#: (factor of the first residue, of the second, offset)
SEEDS = {"level": (1103515245, 747796405, 12345), "bucket": (1664525013, 1013904223, 374761), "order": (214013917, 1220703125, 2531011)}


def seed_for(kind: str, copy: int = 0) -> tuple[int, int, int]:
    """The seed of an independent copy of a hash."""
    a, b, c = SEEDS[kind]
    return ((a + 7_368_787 * copy) % P, (b + 15_485_863 * copy) % P, (c + 32_452_843 * copy) % P)


def _finish(x, lift=lambda v: v):
    return (x * x % lift(P)) * lift(SCALE) % lift(P) + lift(OFFSET)


def _folded(x: np.ndarray) -> np.ndarray:
    """x modulo P of uint64 as x >> 31 and its low 31 bits added, in place: not below P, but shorter."""
    high = x >> np.uint64(SHIFT)
    x &= np.uint64(P)
    x += high
    return x


def hash_array(fp: np.ndarray, kind: str, copy: int = 0) -> np.ndarray:
    a, b, c = seed_for(kind, copy)
    fp = fp.astype(np.int64, copy=False).view(np.uint64)
    x = fp & np.uint64(P)
    x *= np.uint64(b)
    high = fp >> np.uint64(SHIFT)
    high *= np.uint64(a)
    x += high
    x += np.uint64(c)
    x = _folded(x)
    if a + b >= P:  # else below 2^32 already
        x = _folded(x)
    x *= x
    x = _folded(x)  # below 2^34
    x *= np.uint64(SCALE)
    x = _folded(x)  # below 2 P
    np.minimum(x, np.subtract(x, np.uint64(P), out=high), out=x)  # the difference wraps around below P
    x += np.uint64(OFFSET)
    return x.view(np.int64)


def hash_column(fp: str | Column, kind: str, copy: int = 0) -> Column:
    fp = F.col(fp) if isinstance(fp, str) else fp
    a, b, c = (F.lit(x).cast("bigint") for x in seed_for(kind, copy))
    low = fp.bitwiseAND(F.lit((1 << SHIFT) - 1).cast("bigint"))
    return _finish((a * F.shiftright(fp, SHIFT) + b * low + c) % F.lit(P), F.lit)


def trailing_zeros(h: Column) -> Column:
    """Of a positive BIGINT."""
    return F.bit_count(h.bitwiseXOR(h - 1)) - 1
