"""Plans made before a job runs: sampled lengths, accuracy knobs, the stream's window and drop rule."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

GRIDS = ("with_unit", "literal", "powers_of_two")


def sampled_lengths(n: int, alpha: float = 1.25, grid: str = "with_unit", max_length: int | None = None, unsafe: bool = False) -> list[int]:
    """Lengths ceil(alpha^i) up to n.

    `with_unit` starts at length 1, which the ratio bound needs; `literal` starts at the first
    power and so never samples length 1; `powers_of_two` is the coarsest grid. Ratios over 2
    void the bound and are refused unless `unsafe`.
    """
    if grid not in GRIDS:
        raise ValueError(f"grid must be one of {GRIDS}")
    if grid == "powers_of_two":
        alpha = 2.0
    if alpha <= 1 or (alpha > 2 and not unsafe):
        raise ValueError("alpha must be in (1, 2]")
    if n < 1:
        return []
    top = math.floor(math.log(n) / math.log(alpha) + 1e-9)
    found = {math.ceil(alpha**i - 1e-12) for i in range(0 if grid != "literal" else 1, top + 1)}
    return sorted(k for k in found if k <= min(n, max_length or n))


def sampled_lengths_column(n: Column, alpha: float, first: int = 0) -> Column:
    """The same grid for every row, as an array<bigint>."""
    top = F.floor(F.log(n.cast("double")) / F.lit(math.log(alpha)) + 1e-9).cast("int")
    ks = F.transform(F.sequence(F.lit(first), F.greatest(top, F.lit(first))), lambda i: F.ceil(F.pow(F.lit(float(alpha)), i.cast("double")) - 1e-12))
    return F.when(top < first, F.array().cast("array<bigint>")).otherwise(F.array_distinct(ks))


@dataclass(frozen=True)
class AccuracyPlan:
    """epsilon is split between the grid and the count-distinct sketch: a quarter each for the measure, a twentieth for distances."""

    epsilon: float
    target: str
    alpha: float
    cd_error: float
    hll_lg_k: int
    theta_lg_k: int


def plan_accuracy(epsilon: float, target: str = "delta") -> AccuracyPlan:
    if not 0 < epsilon < 1:
        raise ValueError("epsilon must be in (0, 1)")
    share = epsilon / {"delta": 4, "distance": 20}[target]

    def lg(constant: float, least: int, most: int) -> int:
        return min(most, max(least, math.ceil(2 * math.log2(constant / share))))

    return AccuracyPlan(epsilon, target, 1 + share, share, lg(1.04, 4, 21), lg(1.0, 4, 26))


def window_length(n: int) -> int:
    """Symbols that the stream keeps: sqrt(n) * log2(n), rounded up."""
    return max(1, math.ceil(math.sqrt(n) * math.log2(max(2, n))))


def drop_threshold(n: int, window: int, constant: float = 8.0) -> float:
    return constant * n * math.log2(max(2, n)) ** 2 / window


def should_drop(runs: int, n: int, window: int, constant: float = 8.0) -> bool:
    """Once the transform has this many runs, the maximiser can't be longer than the window, so the transform isn't needed any more."""
    return runs >= drop_threshold(n, window, constant)


def length_bound(n: Column, delta: Column) -> Column:
    """Certificate: no maximiser is longer than n / delta."""
    return F.when(delta > 0, F.floor(n / delta)).otherwise(F.lit(0)).cast("bigint")
