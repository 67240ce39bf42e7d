"""Count-distinct registers made where the windows are: no fingerprint ever leaves its task.

A task keeps m byte registers for each key and length, each the greatest number of trailing
zeros among the hashes of its bucket, and emits them at the end; a set of strings, or a string
in chunks, costs a shuffle of registers only. Counts up to m / 4 windows are exact within a
string. The hash is not portable to SQL; `distinct` has families that are.
"""

from __future__ import annotations

import math
from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from repetix.functions.fingerprint import FingerprintParams, window_fingerprints
from repetix.functions.symbols import encode

from . import longstring
from .distinct import CountDistinct

#: Registers of so many keys and lengths are held by a task before they are passed on.
HELD = 20_000


def add(registers: np.ndarray, fps: np.ndarray) -> None:
    m = len(registers)
    x = fps.view(np.uint64) if fps.dtype == np.int64 else fps.astype(np.uint64)
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0x7FB5D329728EA185)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x81DADEF4BC2DD44D)
    x ^= x >> np.uint64(33)
    bucket = (x & np.uint64(m - 1)).astype(np.int64)
    rest = x >> np.uint64(m.bit_length() - 1) | np.uint64(1 << 50)
    level = (np.bitwise_count(rest ^ (rest - np.uint64(1)))).astype(np.uint8)  # trailing zeros plus 1
    np.maximum.at(registers, bucket, level)


def estimate(registers: np.ndarray) -> float:
    m = len(registers)
    zeros = int((registers == 0).sum())
    raw = 0.7213 / (1 + 1.079 / m) * m * m / float(np.ldexp(1.0, -registers.astype(np.int64)).sum())
    return m * math.log(m / zeros) if raw <= 2.5 * m and zeros else raw


def distinct_windows(fps: np.ndarray, m: int) -> float:
    """Distinct fingerprints of one string and length: exact when few, else by registers."""
    if len(fps) <= m // 4:
        return float(len(np.unique(fps)))
    registers = np.zeros(m, np.uint8)
    add(registers, fps)
    return estimate(registers)


def estimate_strings(df: DataFrame, lengths: Sequence[int], m: int = 4096, params: FingerprintParams = FingerprintParams(), **cols) -> DataFrame:
    """(id, n, delta, k_hat): estimates of every string in one narrow pass with m registers at a time."""
    from .profile import per_string

    wanted = sorted(set(lengths))

    def kernel(symbols: np.ndarray) -> list[tuple]:
        of = window_fingerprints(symbols, params)
        n, best, best_k = len(symbols), 0.0, 0
        for k in wanted:
            if k > n or (best_k and (n - k + 1) / k <= best):  # no longer length can win
                break
            ratio = distinct_windows(of(k), m) / k
            if ratio > best:
                best, best_k = ratio, k
        return [(n, best, best_k)]

    return per_string(df, "n bigint, delta double, k_hat int", kernel, **cols)


@dataclass(frozen=True)
class Packed(CountDistinct):
    """Registers as (keys, cd binary)."""

    m: int = 4096
    params: FingerprintParams = FingerprintParams()

    def from_strings(self, df: DataFrame, by: Sequence[str], lengths: Sequence[int], text_col: str = "text", unit: str | None = None, halo_col: str | None = None) -> DataFrame:
        """(by, k, cd), merged within each task. With a halo only windows that begin in the text count."""
        by, wanted, m, params = list(by), sorted(set(lengths)), self.m, self.params
        kept = df.select(*by, F.col(text_col).alias("__text"), F.coalesce(F.col(halo_col), F.lit("")).alias("__halo") if halo_col else F.lit("").alias("__halo"))
        types = dict(kept.dtypes)
        unit = unit or {"string": "codepoint", "binary": "byte"}.get(types["__text"], "symbol")

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held: dict[tuple, np.ndarray] = {}
            arrow = None

            def out() -> pa.RecordBatch:
                columns = [pa.array([key[i] for key in held], t) for i, t in enumerate(arrow)]
                return pa.RecordBatch.from_arrays(
                    [*columns, pa.array([key[-1] for key in held], pa.int32()), pa.array([r.tobytes() for r in held.values()], pa.binary())], names=[*by, "k", "cd"]
                )

            for batch in batches:
                arrow = [batch.column(c).type for c in by]
                keys = list(zip(*(batch.column(c).to_pylist() for c in by), strict=True)) if by else [()] * batch.num_rows
                for key, text, halo in zip(keys, batch.column("__text"), batch.column("__halo"), strict=True):
                    symbols = encode(text.as_py(), unit)
                    begin = len(symbols)
                    if halo.as_py():
                        symbols = np.concatenate((symbols, encode(halo.as_py(), unit)))
                    of = window_fingerprints(symbols, params)
                    for k in wanted:
                        if k > len(symbols):
                            break
                        place = (*key, k)
                        if place not in held:
                            held[place] = np.zeros(m, np.uint8)
                        add(held[place], of(k)[:begin])
                if len(held) > HELD:
                    yield out()
                    held.clear()
            if held:
                yield out()

        parts = kept.mapInArrow(run, ", ".join([*(f"`{c}` {types[c]}" for c in by), "k int", "cd binary"]))
        return self.merge(parts, [*by, "k"])

    def merge(self, sketches, keys):
        """One row for each key and task comes together, not one for each string."""
        types = dict(sketches.dtypes)

        def united(table: pa.Table) -> pa.Table:
            registers = np.zeros(0, np.uint8)
            for cd in table.column("cd"):
                other = np.frombuffer(cd.as_py(), np.uint8)
                registers = np.maximum(registers, other) if len(registers) else other
            return table.slice(0, 1).select(list(keys)).append_column("cd", pa.array([registers.tobytes()], pa.binary()))

        return sketches.select(*keys, "cd").groupBy(*keys).applyInArrow(united, ", ".join([*(f"`{c}` {types[c]}" for c in keys), "cd binary"]))

    def estimates(self, sketches, keys):
        @F.arrow_udf("double")
        def counted(values: pa.Array) -> pa.Array:
            return pa.array([estimate(np.frombuffer(v.as_py(), np.uint8)) for v in values], pa.float64())

        return sketches.select(*keys, counted("cd").alias("d"))

    def build(self, rows, keys):
        raise NotImplementedError("registers are made from strings: from_strings")


def long_string_sketch(chunks: DataFrame, lengths: Sequence[int], cd: Packed = Packed()) -> DataFrame:
    """(id, k, cd) of strings in ordered chunks (see longstring), for lengths up to a cap: registers only are shuffled after the halos."""
    ready = longstring.halos(longstring.offsets(chunks), max(lengths))
    return cd.from_strings(ready, ["id"], lengths, halo_col="halo")
