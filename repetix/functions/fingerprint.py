"""Rabin fingerprints: parameters, NumPy kernels over all windows, and Column expressions.

A fingerprint is a polynomial in the base modulo a prime. Kernels never roll position by
position: the windows of length a + b come from those of length a and b by one vector
operation, so a length costs as many operations as it has binary digits.
"""

from __future__ import annotations

import math
import random
from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SHIFT = 31


def is_prime(n: int) -> bool:
    """Miller-Rabin with bases that decide every n below 3.3e24."""
    if n < 2:
        return False
    small = (2, 3, 5, 7, 11, 13, 17, 19, 23, 29, 31, 37)
    for p in small:
        if n % p == 0:
            return n == p
    d, s = n - 1, 0
    while d % 2 == 0:
        d, s = d // 2, s + 1
    for a in small:
        x = pow(a, d, n)
        if x in (1, n - 1):
            continue
        for _ in range(s - 1):
            x = x * x % n
            if x == n - 1:
                break
        else:
            return False
    return True


@dataclass(frozen=True)
class FingerprintParams:
    """Two primes below 2^31 make one 62-bit fingerprint; `moduli` of one prime halves it.

    The base is the size of the alphabet at least, the same for all strings that may be merged.
    """

    moduli: tuple[int, ...] = (2147483629, 2147483587)
    base: int = 1_114_112

    @classmethod
    def drawn(cls, seed: int, n_moduli: int = 2, base: int = 1_114_112) -> FingerprintParams:
        """Primes drawn uniformly from [2^30, 2^31)."""
        rng, found = random.Random(seed), []
        while len(found) < n_moduli:
            q = rng.randrange(1 << 30, 1 << 31)
            if is_prime(q) and q not in found:
                found.append(q)
        return cls(tuple(found), base)

    def with_random_base(self, seed: int, alphabet: int = 1_114_112) -> FingerprintParams:
        """The same primes with a base drawn uniformly from the residues above the alphabet's size."""
        return FingerprintParams(self.moduli, random.Random(seed).randrange(alphabet, min(self.moduli)))

    def weight(self, length: int) -> tuple[int, ...]:
        """base^length modulo each prime, by fast exponentiation."""
        return tuple(pow(self.base, length, q) for q in self.moduli)


def length_weights(lengths: Iterable[int], params: FingerprintParams = FingerprintParams()) -> dict[int, tuple[int, ...]]:
    """base^(k - 1) for every length: the weight of the symbol that leaves a window."""
    return {k: params.weight(k - 1) for k in lengths}


def pack(residues: list[np.ndarray]) -> np.ndarray:
    return residues[0] if len(residues) == 1 else residues[0] << SHIFT | residues[1]


def remainder(x: np.ndarray, q: int) -> np.ndarray:
    """x % q of int64 from 0 to below 2^63, for q up to 2^31; without a division where q is close below 2^31."""
    c = (1 << SHIFT) - q
    if not 0 < c < 1 << 10:
        return x % q
    high = x >> SHIFT
    high *= q
    x = x - high
    np.right_shift(x, SHIFT, out=high)
    high *= q
    x -= high
    # now below 2^31 + 2^21: q is taken off once at most, where that doesn't wrap around
    x = x.view(np.uint64)
    less = np.subtract(x, np.uint64(q), out=high.view(np.uint64))
    return np.minimum(x, less, out=x).view(np.int64)


class Prefixes:
    """Fingerprints of the prefixes of a stream, held for its last `keep` symbols: those of windows of any length are differences of two."""

    def __init__(self, params: FingerprintParams, keep: int):
        self.params, self.keep = params, keep
        self.held = [np.zeros(1, np.int64) for _ in params.moduli]

    def extend(self, symbols: np.ndarray) -> None:
        """Append symbols; windows that end in them are there until `trim`."""
        if len(symbols):
            self.held = [np.concatenate((h, self._scan(symbols, int(h[-1]), q))) for h, q in zip(self.held, self.params.moduli, strict=True)]

    def _scan(self, symbols: np.ndarray, first: int, q: int) -> np.ndarray:
        n, base = len(symbols), self.params.base
        columns = min(128, -(-math.isqrt(n) // 8))
        rows = -(-n // columns)
        grid = np.zeros(rows * columns, np.int64)
        grid[:n] = symbols % q
        grid = np.ascontiguousarray(grid.reshape(rows, columns).T)
        for j in range(1, columns):
            grid[j] = remainder(grid[j - 1] * base + grid[j], q)
        weights = [base % q]
        while len(weights) < columns:
            weights.append(weights[-1] * base % q)
        starts = [first]
        for end in grid[-1, :-1].tolist():
            starts.append((starts[-1] * weights[-1] + end) % q)
        whole = remainder(np.array(starts) * np.array(weights)[:, None] + grid, q)
        return whole.T.reshape(-1)[:n]

    def windows(self, k: int, first: int, block: int = 1 << 15) -> Iterator[np.ndarray]:
        """Packed fingerprints, in blocks, of the windows of length k from place `first` on, counted from the oldest prefix held."""
        end = len(self.held[0]) - k
        weights = [(q, q - w) for q, w in zip(self.params.moduli, self.params.weight(k), strict=True)]
        for a in range(first, end, block):
            b = min(a + block, end)
            found = []
            for h, (q, w) in zip(self.held, weights, strict=True):
                x = h[a:b] * w
                x += h[a + k : b + k]
                found.append(remainder(x, q))
            yield pack(found)

    def trim(self) -> None:
        self.held = [h[-self.keep - 1 :].copy() for h in self.held]


def window_fingerprints(symbols: np.ndarray, params: FingerprintParams = FingerprintParams()) -> Callable[[int], np.ndarray]:
    """A function of k that gives the packed fingerprints of all windows of length k, left to right."""
    powers: list[list[np.ndarray]] = [[symbols % q for q in params.moduli]]

    def joined(left: list[np.ndarray], right: list[np.ndarray], a: int, b: int) -> list[np.ndarray]:
        n = len(symbols) - a - b + 1
        return [remainder(x[:n] * w + y[a : a + n], q) for x, y, w, q in zip(left, right, params.weight(b), params.moduli, strict=True)]

    def of(k: int) -> np.ndarray:
        if k < 1 or k > len(symbols):
            return np.empty(0, np.int64)
        while 1 << len(powers) <= k:
            half = 1 << (len(powers) - 1)
            powers.append(joined(powers[-1], powers[-1], half, half))
        length, found = 0, None
        for bit in range(k.bit_length()):
            if k >> bit & 1:
                part = powers[bit]
                found = part if found is None else joined(found, part, length, 1 << bit)
                length += 1 << bit
        return pack(found)

    return of


def code_points(text: str | Column) -> Column:
    """array<int> of a string's code points."""
    text = F.col(text) if isinstance(text, str) else text
    places = F.when(F.length(text) > 0, F.sequence(F.lit(1), F.length(text))).otherwise(F.array().cast("array<int>"))
    return F.transform(places, lambda i: F.ascii(F.substring(text, i, F.lit(1))))


def fingerprint(symbols: str | Column, modulus: int, base: int = 1_114_112) -> Column:
    """Fingerprint of a whole array of symbols modulo one prime, as a Column."""
    return F.aggregate(symbols, F.lit(0).cast("bigint"), lambda f, s: (f * F.lit(base) + s) % F.lit(modulus))


def fingerprint_concat(first: Column, second: Column, second_weight: Column, modulus: int) -> Column:
    """Of the concatenation, from both fingerprints and base^(length of the second) modulo the prime."""
    return (first * second_weight + second) % F.lit(modulus)


def fingerprint_roll(old: Column, leaving: Column, entering: Column, leaving_weight: Column | int, modulus: int, base: int = 1_114_112) -> Column:
    """Of the window moved on by one symbol; `leaving_weight` is base^(k - 1) modulo the prime."""
    weight = F.lit(leaving_weight) if isinstance(leaving_weight, int) else leaving_weight
    rest = F.pmod(old - leaving.cast("bigint") * weight % F.lit(modulus), F.lit(modulus))
    return (rest * F.lit(base) + entering) % F.lit(modulus)


def power_mod(length: Column, modulus: int, base: int = 1_114_112) -> Column:
    """base^length modulo the prime, by squaring over the binary digits of the length."""
    start = F.struct(F.lit(1).cast("bigint").alias("value"), F.lit(base % modulus).cast("bigint").alias("square"))

    def step(acc: Column, bit: Column) -> Column:
        on = F.call_function("getbit", length.cast("bigint"), bit) == 1
        return F.struct(
            F.when(on, acc["value"] * acc["square"] % F.lit(modulus)).otherwise(acc["value"]).alias("value"),
            (acc["square"] * acc["square"] % F.lit(modulus)).alias("square"),
        )

    return F.aggregate(F.sequence(F.lit(0), F.lit(30)), start, step, lambda acc: acc["value"])
