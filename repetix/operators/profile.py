"""Distinct substrings per length, the measure delta, and per-string comparators.

Each string is one row, so all of these are narrow: an Arrow kernel reads a batch and returns a
few numbers for each string, and nothing is shuffled. Counts over several strings are in
`distinct` and `sketch`.
"""

from __future__ import annotations

import bz2
import lzma
import zlib
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from repetix.functions import suffixes
from repetix.functions.fingerprint import FingerprintParams, window_fingerprints
from repetix.functions.symbols import encode


def per_string(df: DataFrame, fields: str, kernel: Callable[[np.ndarray], Iterable[tuple]], id_col: str = "id", text_col: str = "text", unit: str | None = None) -> DataFrame:
    """(id, fields): the rows that `kernel` makes of each string's symbols. `unit` defaults to code points, bytes or symbols by type."""
    kept = df.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    kinds = dict(kept.dtypes)
    unit = unit or {"string": "codepoint", "binary": "byte"}.get(kinds["text"], "symbol")
    schema = f"id {kinds['id']}, {fields}"
    names = [f.split()[0] for f in fields.split(", ")]
    arrow = {"bigint": pa.int64(), "int": pa.int32(), "double": pa.float64(), "boolean": pa.bool_(), "array<bigint>": pa.list_(pa.int64()), "string": pa.string()}
    types = [arrow[f.split()[1]] for f in fields.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows: list[tuple] = []
            of: list[int] = []
            for i, value in enumerate(batch.column("text")):
                made = list(kernel(encode(value.as_py(), unit)))
                rows += made
                of += [i] * len(made)
            columns = [batch.column("id").take(pa.array(of, pa.int64())), *(pa.array([r[j] for r in rows], t) for j, t in enumerate(types))]
            yield pa.RecordBatch.from_arrays(columns, names=["id", *names])

    return kept.mapInArrow(run, schema)


def substring_profile(df: DataFrame, lengths: Iterable[int], mode: str = "exact", params: FingerprintParams = FingerprintParams(), **cols) -> DataFrame:
    """(id, k, d): distinct substrings of every listed length. A length over a string's own has d = 0.

    `exact` names windows by refinement; `fingerprint` counts distinct fingerprints.
    """
    wanted = sorted(set(lengths))

    def kernel(symbols: np.ndarray) -> Iterator[tuple]:
        windows = suffixes.window_names(symbols) if mode == "exact" else window_fingerprints(symbols, params)
        for k in wanted:
            if k > len(symbols):
                yield k, 0
            elif mode == "exact":
                yield k, int(windows(k).max()) + 1
            else:
                yield k, len(np.unique(windows(k)))

    return per_string(df, "k int, d bigint", kernel, **cols)


def distinct_count(df: DataFrame, k: int, mode: str = "exact", **cols) -> DataFrame:
    return substring_profile(df, [k], mode, **cols).select("id", "d")


def profile_from_lcp(df: DataFrame, **cols) -> DataFrame:
    """(id, k, d) for every length of every string, from suffix arrays."""
    return per_string(df, "k int, d bigint", lambda s: ((k + 1, int(d)) for k, d in enumerate(suffixes.profile_from_lcp(s))), **cols)


def exact_delta(df: DataFrame, stop: str = "bound", **cols) -> DataFrame:
    """(id, n, delta, k_hat, k_checked). `bound` stops where no longer length can win; `none` looks at all; the values are the same."""
    fields = "n bigint, delta double, k_hat int, k_checked int"
    return per_string(df, fields, lambda s: [(len(s), *suffixes.exact_delta(s, stop == "bound"))], **cols)


def delta_from_lcp(df: DataFrame, **cols) -> DataFrame:
    """(id, n, delta, k_hat) by suffix arrays: another way to the same values."""
    return per_string(df, "n bigint, delta double, k_hat int", lambda s: [(len(s), *suffixes.delta_of_profile(suffixes.profile_from_lcp(s)))], **cols)


def delta_of_profile(profile: DataFrame, by: Iterable[str] = ("id",)) -> DataFrame:
    """(by, delta, k_hat) of a profile (by, k, d): the maximum of d / k and the least length that attains it."""
    ratio = F.col("d") / F.col("k")
    return profile.groupBy(*by).agg(F.max(ratio).alias("delta"), F.max_by("k", F.struct(ratio, -F.col("k"))).alias("k_hat"))


def local_maximum(profile: DataFrame, strict: bool = True) -> DataFrame:
    """(id, delta, k_hat) of the heuristic that stops at the first local maximum of d / k: before a fall, or with not `strict` before a stand."""
    order = Window.partitionBy("id").orderBy("k")
    ratio = F.col("d") / F.col("k")
    after = F.lead(ratio).over(order)
    stops = after.isNull() | (after < F.col("ratio") if strict else after <= F.col("ratio"))
    marked = profile.withColumn("ratio", ratio).withColumn("after", F.lead(ratio).over(order)).withColumn("stops", stops)
    return marked.where("stops").groupBy("id").agg(F.min_by("ratio", "k").alias("delta"), F.min("k").alias("k_hat"))


#: The least dictionary given to the LZMA encoder. It clears tables of the dictionary's size on each call, and preset 9 asks for 64 MB.
DICTIONARY = 1 << 20
PRESET_DICTIONARY = 1 << 26


def lzma_raw_size(b: bytes) -> int:
    """With a dictionary that holds the whole input, which finds the same matches as a larger one."""
    size = min(PRESET_DICTIONARY, max(DICTIONARY, 1 << len(b).bit_length()))
    return len(lzma.compress(b, lzma.FORMAT_RAW, filters=[{"id": lzma.FILTER_LZMA2, "preset": 9, "dict_size": size}]))


def xz_size(raw: int, n: int) -> int:
    """Bytes of the .xz file of one block of n bytes that are `raw` bytes in LZMA2: headers, padding, CRC64, index and footer."""
    if not n:
        return 32
    digits = lambda v: max(1, -(-v.bit_length() // 7))
    padded = lambda v: -(-v // 4) * 4
    return 12 + 12 + padded(raw) + 8 + padded(2 + digits(12 + raw + 8) + digits(n)) + 4 + 12


CODECS: dict[str, Callable[[bytes], int]] = {
    "gzip": lambda b: len(zlib.compress(b, 9, 31)),
    "bzip2": lambda b: len(bz2.compress(b, 9)),
    "xz": lambda b: xz_size(lzma_raw_size(b), len(b)),
    "lzma2_raw": lzma_raw_size,
}


def _bytes(value) -> bytes:
    return value if isinstance(value, bytes) else (value or "").encode("utf-8", "surrogatepass")


def codec_size(codec: str) -> Callable[[Column], Column]:
    """A function of a string or binary Column that gives the size of the codec's output; null counts as empty."""
    size = CODECS[codec]

    @F.arrow_udf("bigint")
    def of(values: pa.Array) -> pa.Array:
        return pa.array([size(_bytes(v)) for v in values.to_pylist()], pa.int64())

    return of


def codec_sizes(df: DataFrame, id_col: str = "id", text_col: str = "text") -> DataFrame:
    """(id, a column for each of CODECS): both sizes of LZMA come from one run of it."""
    kept = df.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for value in batch.column("text"):
                b = _bytes(value.as_py())
                raw = lzma_raw_size(b)
                known = {"lzma2_raw": raw, "xz": xz_size(raw, len(b))}
                rows.append([known[c] if c in known else size(b) for c, size in CODECS.items()])
            columns = [pa.array([r[i] for r in rows], pa.int64()) for i in range(len(CODECS))]
            yield pa.RecordBatch.from_arrays([batch.column("id"), *columns], names=["id", *CODECS])

    return kept.mapInArrow(run, ", ".join([f"id {dict(kept.dtypes)['id']}", *(f"{c} bigint" for c in CODECS)]))


def parse_sizes(df: DataFrame, **cols) -> DataFrame:
    """(id, z, z78, r, r_no_marker): phrases of both parses, runs of the transform with and without the end marker."""

    def kernel(s: np.ndarray) -> list[tuple]:
        transform = suffixes.bwt(s)
        return [(suffixes.lz77_phrases(s), suffixes.lz78_phrases(s), suffixes.runs(transform), suffixes.runs(transform, marker=False))]

    return per_string(df, "z bigint, z78 bigint, r bigint, r_no_marker bigint", kernel, **cols)


def grammar_size(df: DataFrame, **cols) -> DataFrame:
    """(id, g): size of the grammar of pair replacement, an upper bound of the smallest one's. Quadratic in the string."""
    return per_string(df, "g bigint", lambda s: [(suffixes.pair_grammar_size(s),)], **cols)


def entropies(df: DataFrame, orders: Iterable[int] = (0, 1, 2), **cols) -> DataFrame:
    """(id, k, bits): empirical entropy of these orders, bits a symbol."""
    wanted = sorted(set(orders))
    return per_string(df, "k int, bits double", lambda s: ((k, suffixes.entropy(s, k)) for k in wanted), **cols)


def transforms(df: DataFrame, **cols) -> DataFrame:
    """(id, bwt array<bigint>, lf array<bigint>, r): symbols plus 1 with marker 0, and LF places from 1."""

    def kernel(s: np.ndarray) -> list[tuple]:
        transform = suffixes.bwt(s)
        return [(transform.tolist(), (suffixes.lf(transform) + 1).tolist(), suffixes.runs(transform))]

    return per_string(df, "bwt array<bigint>, lf array<bigint>, r bigint", kernel, **cols)
