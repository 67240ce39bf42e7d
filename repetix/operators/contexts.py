"""Exact counts of a set's distinct substrings over a range of lengths, from one sort of the symbols that follow each place.

Neighbouring places whose windows of the least length have the same minimizer (the p-gram of least hash)
leave their task as one stretch, so that the shuffle takes about ten symbols a place for all lengths of a fourfold range, not a
fingerprint for each length. Equal windows have equal minimizers, so they meet in one bucket; there a place counts for
the lengths beyond those that it shares with the place before it in order.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from repetix.functions.symbols import encode

#: Symbols that a task gathers before it deals them out; bytes of contexts that are sorted at once, about.
GATHERED, SORTED = 1 << 21, 1 << 25
#: The longest p-gram of a minimizer.
GRAM = 8
MIX, STEP = np.uint64(0x7FB5D329728EA185), np.uint64(0x9E3779B97F4A7C15)


def alphabet(df: DataFrame, text_col: str = "text") -> np.ndarray:
    """The distinct code points of all texts, in order: 1,114,112 at most."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = np.zeros(0x110000, bool)
        for batch in batches:
            for value in batch.column(0):
                seen[encode(value.as_py())] = True
        yield pa.RecordBatch.from_arrays([pa.array(np.flatnonzero(seen), pa.int32())], names=["symbol"])

    found = df.select(text_col).mapInArrow(run, "symbol int").distinct().toPandas()
    return np.sort(found["symbol"].to_numpy(np.int64))


def gram_length(low: int) -> int:
    return max(1, min(GRAM, (low + 1) // 2))


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * MIX
    return x ^ (x >> np.uint64(29))


def minimizers(codes: np.ndarray, low: int) -> np.ndarray:
    """The least hash of a p-gram within each window of length `low`."""
    p, n = gram_length(low), len(codes) - low + 1
    wide = codes.astype(np.uint64)
    grams = wide[: len(codes) - p + 1].copy()
    for j in range(1, p):
        grams = grams * STEP + wide[j : len(codes) - p + 1 + j]
    least, width, wanted = _mixed(grams), 1, low - p + 1
    while width < wanted:
        step = min(width, wanted - width)
        least = np.minimum(least[: len(least) - step], least[step:])
        width += step
    return least[:n]


def stretches(codes: np.ndarray, low: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(starts, sizes, minimizers) of runs of places whose windows of length `low` hold no zero and share a minimizer; none has over low - p + 1 places."""
    least = minimizers(codes, low)
    n = len(least)
    fits = (codes[:n] != 0) & (codes[low - 1 : low - 1 + n] != 0)  # zeros stand in blocks that no window spans
    places = np.flatnonzero(fits)
    if not len(places):
        return places, places, least[:0]
    new = np.ones(len(places), bool)
    new[1:] = (np.diff(places) > 1) | (least[places[1:]] != least[places[:-1]])
    first = np.maximum.accumulate(np.where(new, np.arange(len(places)), 0))
    new |= (np.arange(len(places)) - first) % reach(low) == 0
    begins = np.flatnonzero(new)
    return places[begins], np.diff(np.append(begins, len(places))), least[places[begins]]


def reach(low: int) -> int:
    """Places of a stretch at most."""
    return min(255, low - gram_length(low) + 1)


def count_lengths(contexts: np.ndarray, low: int) -> np.ndarray:
    """Distinct prefixes of each length from `low` on of rows of symbols, padded with zeros."""
    n, high = contexts.shape
    order = np.sort(np.ascontiguousarray(contexts).view(f"S{high * contexts.itemsize}").reshape(-1))
    rows = order.view(contexts.dtype).reshape(n, high)
    unlike = rows[1:] != rows[:-1]
    shared = np.zeros(n, np.int64)
    shared[1:] = np.where(unlike.any(1), unlike.argmax(1), high)
    begin, end = np.maximum(shared + 1, low), np.count_nonzero(rows, axis=1)
    new = begin <= end
    change = np.bincount(begin[new], minlength=high + 2) - np.bincount(end[new] + 1, minlength=high + 2)
    return np.cumsum(change)[low : high + 1]


def range_profile(df: DataFrame, by: Sequence[str], low: int, high: int, text_col: str = "text", symbols: np.ndarray | None = None) -> DataFrame:
    """(by, k, d) for every length k from `low` to `high`: distinct substrings over all strings of a group, exact; lengths that no string has are left out. `symbols` holds the code points, if they are known."""
    by, symbols = list(by), alphabet(df, text_col) if symbols is None else symbols
    kind = np.dtype("u1" if len(symbols) < 255 else "<u2" if len(symbols) < 65_535 else "<u4")
    code_of = np.zeros(int(symbols[-1]) + 1 if len(symbols) else 1, kind)
    code_of[symbols] = np.arange(1, len(symbols) + 1)
    largest = df.groupBy(*by).agg(F.sum(F.length(text_col)).alias("n")).agg(F.max("n")).first()[0] or 0
    buckets, width, most = -(-largest * high * kind.itemsize // SORTED) or 1, reach(low) + high - 1, reach(low)
    kept = df.select(*by, F.col(text_col).alias("__text"))
    types = dict(kept.dtypes)
    named = [f"`{c}` {types[c]}" for c in by]

    def dealt(texts: dict[str, None]) -> Iterator[tuple[int, bytes, bytes]]:
        gap = np.zeros(width, kind)
        codes = np.concatenate([x for t in texts for x in (code_of[encode(t)], gap)])
        starts, sizes, least = stretches(codes, low)
        if not len(starts):
            return
        if most == 1 and high <= 8:  # short windows are few
            rows = np.lib.stride_tricks.sliding_window_view(codes, high)[starts]
            _, first = np.unique(np.ascontiguousarray(rows).view(f"S{high * kind.itemsize}").reshape(-1), return_index=True)
            starts, sizes, least = starts[first], sizes[first], least[first]
        bucket = ((least * STEP) >> np.uint64(33)).astype(np.int64) % buckets
        order = np.argsort(bucket, kind="stable")
        edges = np.flatnonzero(np.diff(bucket[order], prepend=-1))
        every = np.lib.stride_tricks.sliding_window_view(codes, width)
        for a, b in zip(edges, [*edges[1:], len(order)], strict=True):
            own = order[a:b]
            yield int(bucket[own[0]]), sizes[own].astype(np.uint8).tobytes(), every[starts[own]].tobytes()

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple, dict[str, None]] = {}
        arrow, size = [], 0

        def out() -> Iterator[pa.RecordBatch]:
            for key, texts in held.items():
                for bucket, sizes, data in dealt(texts):
                    values = [*(pa.array([v], t) for v, t in zip(key, arrow, strict=True)), pa.array([bucket], pa.int32()), pa.array([sizes], pa.binary()), pa.array([data], pa.binary())]
                    yield pa.RecordBatch.from_arrays(values, names=[*by, "bucket", "sizes", "data"])

        for batch in batches:
            arrow = [batch.column(c).type for c in by]
            keys = list(zip(*(batch.column(c).to_pylist() for c in by), strict=True)) if by else [()] * batch.num_rows
            for key, value in zip(keys, batch.column("__text"), strict=True):
                text = value.as_py()
                if text and text not in held.setdefault(key, {}):  # a copy has no windows of its own
                    held[key][text] = None
                    size += len(text)
                if size >= GATHERED:
                    yield from out()
                    held.clear()
                    size = 0
        yield from out()

    def count(table: pa.Table) -> pa.Table:
        sizes = [np.frombuffer(x.as_py(), np.uint8) for x in table.column("sizes")]
        parts = [np.frombuffer(x.as_py(), kind).reshape(-1, width) for x in table.column("data")]
        # a bucket with many places is counted in parts, by a hash of the windows of the least length
        split = -(-int(sum(s.sum(dtype=np.int64) for s in sizes)) * high * kind.itemsize // (2 * SORTED))
        total = np.zeros(high - low + 1, np.int64)
        for s in range(split):
            found = []
            for size, rows in zip(sizes, parts, strict=True):
                for j in range(most):
                    own = rows[size > j, j : j + high]
                    if split > 1:
                        h = np.zeros(len(own), np.uint64)
                        for i in range(low):
                            h = h * STEP + own[:, i]
                        own = own[_mixed(h) % np.uint64(split) == s]
                    if len(own):
                        found.append(own)
            if found:
                total += count_lengths(np.concatenate(found), low)
        n = high - low + 1
        keys = [pa.array(table.column(c)[:1].to_pylist() * n, table.schema.field(c).type) for c in by]
        return pa.table([*keys, pa.array(np.arange(low, high + 1), pa.int32()), pa.array(total, pa.int64())], names=[*by, "k", "d"])

    rows = kept.mapInArrow(deal, ", ".join([*named, "bucket int, sizes binary, data binary"]))
    counted = rows.groupBy(*by, "bucket").applyInArrow(count, ", ".join([*named, "k int, d bigint"]))
    return counted.groupBy(*by, "k").agg(F.sum("d").alias("d")).where("d > 0")
