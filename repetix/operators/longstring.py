"""Strings too long for one row: ordered chunks, sketched without ever being put together.

Two plans. `halo`: every chunk gets the first symbols of what follows, and each window is found by
the chunk that holds its first symbol; for lengths up to a cap. `block shift`: the fingerprint of
a window is the difference of two prefix fingerprints, so a block needs only the prefix
fingerprints of the blocks where its windows end; for any length.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from repetix.functions.fingerprint import FingerprintParams, pack, window_fingerprints
from repetix.functions.symbols import encode
from repetix.plans.accuracy import length_bound, sampled_lengths
from repetix.session import written

#: Rows summed or scanned together at each of two levels.
FAN = 4096


def chunk_table(df: DataFrame, order_col: str, text_col: str = "text", by: str | None = None) -> DataFrame:
    """(id, at, text): rows of one long string (or one for each `by`), to be read in the order of `at`."""
    return df.select((F.col(by) if by else F.lit(0)).alias("id"), F.col(order_col).alias("at"), F.coalesce(text_col, F.lit("")).alias("text"))


def offsets(chunks: DataFrame) -> DataFrame:
    """chunks plus n (symbols) and start (symbols before). Lengths only are sorted, in two levels, so no task sees all chunks of a string.

    Chunks are grouped by range of `at`; ties in `at` aren't allowed within a string.
    """
    sized = chunks.select("id", "at", F.length("text").cast("bigint").alias("n"))
    span = sized.groupBy("id").agg(F.min("at").alias("low"), F.count("*").alias("rows"), F.max("at").alias("high"))
    # ranges of equal width of `at`, about FAN chunks each when ids are dense
    width = F.greatest(F.lit(1), F.floor((F.col("high") - F.col("low") + 1) * FAN / F.col("rows"))).cast("bigint")
    placed = sized.join(F.broadcast(span), "id").withColumn("range", F.floor((F.col("at") - F.col("low")) / width).cast("bigint")).select("id", "at", "n", "range")
    totals = placed.groupBy("id", "range").agg(F.sum("n").alias("total"))
    before = F.sum("total").over(Window.partitionBy("id").orderBy("range").rowsBetween(Window.unboundedPreceding, -1))
    bases = totals.select("id", "range", F.coalesce(before, F.lit(0)).alias("base"))
    inside = F.sum("n").over(Window.partitionBy("id", "range").orderBy("at").rowsBetween(Window.unboundedPreceding, -1))
    local = placed.withColumn("inside", F.coalesce(inside, F.lit(0)))
    starts = local.join(bases, ["id", "range"]).select("id", "at", "n", (F.col("base") + F.col("inside")).alias("start"))
    return chunks.join(starts, ["id", "at"])


def halos(placed: DataFrame, cap: int) -> DataFrame:
    """placed plus halo: the next cap - 1 symbols after each chunk, gathered from the heads of the chunks that follow."""
    need = cap - 1
    if need == 0:
        return placed.withColumn("halo", F.lit(""))
    heads = placed.where("n > 0").select("id", F.col("start").alias("head_start"), F.left("text", F.lit(need)).alias("head"), F.floor(F.col("start") / need).alias("bin"))
    ends = placed.select("id", "at", (F.col("start") + F.col("n")).alias("end"))
    ends = ends.withColumn("bin", F.explode(F.array(F.floor(F.col("end") / need), F.floor(F.col("end") / need) + 1)))
    met = ends.join(heads, ["id", "bin"]).where("head_start >= end AND head_start < end + %d" % need)
    parts = F.transform(F.array_sort(F.collect_list(F.struct("head_start", "head"))), lambda p: p["head"])
    halo = met.groupBy("id", "at").agg(F.left(F.array_join(parts, ""), F.lit(need)).alias("halo"))  # cap - 1 heads at most
    return placed.join(halo, ["id", "at"], "left").withColumn("halo", F.coalesce("halo", F.lit("")))


def _emit(id_value, found: list[tuple[int, np.ndarray]], batch_type) -> pa.RecordBatch:
    sizes = [len(f) for _, f in found]
    ks = np.repeat(np.array([k for k, _ in found], np.int32), sizes)
    ids = pa.array([id_value] * sum(sizes), batch_type)
    return pa.RecordBatch.from_arrays([ids, pa.array(ks), pa.array(np.concatenate([f for _, f in found]).astype(np.int64))], names=["id", "k", "fp"])


def halo_windows(chunks: DataFrame, lengths: Sequence[int], params: FingerprintParams = FingerprintParams()) -> DataFrame:
    """(id, k, fp): fingerprints of all windows of the listed lengths, distinct within a chunk."""
    wanted = sorted(set(lengths))
    ready = halos(offsets(chunks), wanted[-1]).select("id", "text", "halo")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                text, halo = encode(batch.column("text")[i].as_py()), encode(batch.column("halo")[i].as_py())
                of = window_fingerprints(np.concatenate((text, halo)), params)
                found = [(k, np.unique(of(k)[: len(text)])) for k in wanted]
                yield _emit(batch.column("id")[i].as_py(), found, batch.column("id").type)

    return ready.mapInArrow(run, f"id {dict(ready.dtypes)['id']}, k int, fp bigint")


def equal_blocks(chunks: DataFrame, size: int) -> DataFrame:
    """(id, block, text): the string cut at multiples of `size`; a last block may be short, and an empty one ends a string of whole blocks."""
    placed = offsets(chunks).where("n > 0")
    last = F.floor((F.col("start") + F.col("n") - 1) / size)
    cut = placed.withColumn("block", F.explode(F.sequence(F.floor(F.col("start") / size), last)))
    first = F.greatest(F.col("block") * size, F.col("start"))
    stop = F.least((F.col("block") + 1) * size, F.col("start") + F.col("n"))
    pieces = cut.select("id", "block", first.alias("from"), F.substring("text", (first - F.col("start") + 1).cast("int"), (stop - first).cast("int")).alias("piece"))
    whole = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("from", "piece"))), lambda p: p["piece"]), "")
    blocks = pieces.groupBy("id", "block").agg(whole.alias("text"))
    ends = placed.groupBy("id").agg(F.max(F.col("start") + F.col("n")).alias("all")).where(F.col("all") % size == 0)
    return blocks.unionByName(ends.select("id", F.floor(F.col("all") / size).alias("block"), F.lit("").alias("text")))


def _prefixes(symbols: np.ndarray, q: int, base: int) -> np.ndarray:
    """Fingerprints of the prefixes of 0 .. n symbols modulo one prime, by doubling."""
    n = len(symbols)
    size = 1 << max(0, (n - 1).bit_length()) if n else 0
    sums = np.zeros(size, np.int64)
    sums[:n] = symbols % q
    width = 1
    while width < size:
        rows = sums.reshape(-1, 2 * width)
        weights = np.array([pow(base, 1, q)], np.int64)
        while len(weights) < width:  # base^1 .. base^width
            weights = np.concatenate((weights, weights * int(weights[-1]) % q))
        rows[:, width:] = (rows[:, width - 1 : width] * weights[:width] + rows[:, width:]) % q
        width *= 2
    return np.concatenate((np.zeros(1, np.int64), sums[:n]))


def prefix_scan(blocks: DataFrame, params: FingerprintParams = FingerprintParams()) -> DataFrame:
    """(id, block, carry array<bigint>): fingerprint of all before each block. One small row for each block is scanned, in two levels."""
    kind = dict(blocks.dtypes)["id"]
    moduli, base = params.moduli, params.base

    def summed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            arrays = [encode(t.as_py()) for t in batch.column("text")]
            prints = [[int(_prefixes(a, q, base)[-1]) for q in moduli] for a in arrays]
            yield pa.RecordBatch.from_arrays([batch.column("id"), batch.column("block"), pa.array([len(a) for a in arrays], pa.int64()), pa.array(prints, pa.list_(pa.int64()))], names=["id", "block", "n", "fp"])

    def scan(rows: pd.DataFrame, key: str) -> tuple[list[list[int]], list[int], int]:
        carry, n, out = [0] * len(moduli), 0, []
        for fp, size in zip(rows["fp"], rows["n"], strict=True):
            out.append(carry)
            carry = [(c * pow(base, int(size), q) + int(f)) % q for c, f, q in zip(carry, fp, moduli, strict=True)]
            n += int(size)
        return out, carry, n

    def inner(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values("block")
        carries, total, n = scan(rows, "block")
        before = np.concatenate(([0], np.cumsum(rows["n"])[:-1]))
        return pd.DataFrame({"id": rows["id"], "block": rows["block"], "part": rows["block"] // FAN, "carry": carries, "before": before, "n": n, "fp": [total] * len(rows)})

    def outer(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values("part")
        carries, _, _ = scan(rows, "part")
        return pd.DataFrame({"id": rows["id"], "part": rows["part"], "base": carries})

    prints = blocks.mapInArrow(summed, f"id {kind}, block bigint, n bigint, fp array<bigint>")
    local = prints.withColumn("part", F.floor(F.col("block") / FAN)).groupBy("id", "part").applyInPandas(
        inner, f"id {kind}, block bigint, part bigint, carry array<bigint>, before bigint, n bigint, fp array<bigint>"
    )
    parts = local.where(F.col("block") % FAN == 0).select("id", "part", "n", "fp").groupBy("id").applyInPandas(outer, f"id {kind}, part bigint, base array<bigint>")

    def shifted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            carry = [
                [(b * pow(base, n, q) + c) % q for b, c, q in zip(bs, cs, moduli, strict=True)]
                for bs, cs, n in zip(batch.column("base").to_pylist(), batch.column("carry").to_pylist(), batch.column("before").to_pylist(), strict=True)
            ]
            yield pa.RecordBatch.from_arrays([batch.column("id"), batch.column("block"), pa.array(carry, pa.list_(pa.int64()))], names=["id", "block", "carry"])

    joined = local.select("id", "block", "part", "carry", "before").join(parts, ["id", "part"]).select("id", "block", "base", "carry", "before")
    return joined.mapInArrow(shifted, f"id {kind}, block bigint, carry array<bigint>")


def block_shift_windows(chunks: DataFrame, lengths: Sequence[int], size: int = 1 << 20, params: FingerprintParams = FingerprintParams()) -> DataFrame:
    """(id, k, fp): fingerprints of all windows of the listed lengths, of any length, distinct within a block."""
    blocks = equal_blocks(chunks, size)
    kind, moduli, base = dict(blocks.dtypes)["id"], params.moduli, params.base
    carried = blocks.join(prefix_scan(blocks, params), ["id", "block"])

    def prefixes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for text, carry in zip(batch.column("text").to_pylist(), batch.column("carry").to_pylist(), strict=True):
                symbols = encode(text)
                rows = []
                for c, q in zip(carry, moduli, strict=True):
                    weights = np.array([1], np.int64)
                    while len(weights) <= len(symbols):
                        weights = np.concatenate((weights, weights * (int(weights[-1]) * base % q) % q))
                    rows.append((c * weights[: len(symbols) + 1] + _prefixes(symbols, q, base)) % q)
                out.append(np.stack(rows).astype("<u4").tobytes())
            yield pa.RecordBatch.from_arrays([batch.column("id"), batch.column("block"), pa.array(out, pa.binary())], names=["id", "block", "prefixes"])

    own = carried.mapInArrow(prefixes, f"id {kind}, block bigint, prefixes binary")
    ks = F.array(*[F.lit(int(k)) for k in sorted(set(lengths))])
    asked = own.select("id", F.explode(ks).alias("k"), F.col("block").alias("end"), F.col("prefixes").alias("after"))
    asked = asked.withColumn("block", F.explode(F.array(F.col("end") - F.floor(F.col("k") / size), F.col("end") - F.floor(F.col("k") / size) - 1))).where("block >= 0")
    met = own.join(asked, ["id", "block"]).select("id", "block", "k", "end", "prefixes", "after")

    def differ(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                here = np.frombuffer(row["prefixes"], "<u4").astype(np.int64).reshape(len(moduli), -1)
                there = np.frombuffer(row["after"], "<u4").astype(np.int64).reshape(len(moduli), -1)
                shift = row["block"] * size + row["k"] - row["end"] * size  # where the window of the block's first symbol ends, within `after`
                start = np.arange(min(here.shape[1], size))
                stop = start + shift
                inside = (stop >= 0) & (stop < min(there.shape[1], size))
                start, stop = start[inside], stop[inside]
                if len(start):
                    residues = [(there[j][stop] - here[j][start] * pow(base, row["k"], q)) % q for j, q in enumerate(moduli)]
                    yield _emit(row["id"], [(row["k"], np.unique(pack(residues)))], batch.column("id").type)

    return met.mapInArrow(differ, f"id {kind}, k int, fp bigint")


def sketch_long_strings(chunks: DataFrame, cd, alpha: float = 1.25, cap: int = 128, size: int = 1 << 20, params: FingerprintParams = FingerprintParams()) -> tuple[DataFrame, DataFrame]:
    """(sketches, found): (id, k, cd...) of strings in chunks, and (id, n, delta, k_hat, bound).

    Lengths up to `cap` come from chunks with halos. Only strings whose certificate n / delta is
    beyond it go on, by block shifts, to the sampled lengths up to their certificate, which more
    lengths can only lower; so no sampled length that could win is left out.
    """
    from .sketch import estimate_delta, merge_sketches

    sizes = chunks.groupBy("id").agg(F.sum(F.length("text")).cast("bigint").alias("n"))
    sketches = written(cd.build(halo_windows(chunks, sampled_lengths(cap, alpha), params), ["id", "k"]), "long-strings")

    def found() -> DataFrame:
        return estimate_delta(sketches, cd=cd).join(sizes, "id").withColumn("bound", length_bound(F.col("n"), F.col("delta")))

    beyond = written(found().where((F.col("bound") > cap) & (F.col("n") > cap)).select("id", F.least("bound", "n").alias("last")), "beyond")
    longest = beyond.agg(F.max("last")).first()[0]
    if longest:
        lengths = [k for k in sampled_lengths(int(longest), alpha) if k > cap]
        if lengths:
            more = cd.build(block_shift_windows(chunks.join(beyond, "id", "left_semi").select(chunks.columns), lengths, size, params), ["id", "k"])
            sketches = written(merge_sketches(sketches, more.select(sketches.columns), cd=cd), "long-strings")
    return sketches, found().select("id", "n", "delta", "k_hat", "bound")
