"""Count-distinct sketches over fingerprints, each with build, merge and estimate.

All take (keys, fp) rows and keep their state in rows or buffers of (keys, cd), so that partial
aggregation runs before any shuffle and merging is a second aggregation.
"""

from __future__ import annotations

import math
from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from repetix.functions.fingerprint import FingerprintParams, window_fingerprints
from repetix.functions.hashing import P, hash_array, hash_column, trailing_zeros
from repetix.functions.symbols import encode

from . import narrow


def window_rows(df: DataFrame, lengths: Sequence[int], by: Sequence[str] = ("id",), text_col: str = "text", unit: str | None = None, params: FingerprintParams = FingerprintParams()) -> DataFrame:
    """(by, k, fp): distinct fingerprints of every string's windows. The text leaves the plan here; repeats within a string never leave the task."""
    by = list(by)
    kept = df.select(*by, F.col(text_col).alias("__text"))
    types = dict(kept.dtypes)
    unit = unit or {"string": "codepoint", "binary": "byte"}.get(types["__text"], "symbol")
    wanted = sorted(set(lengths))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, value in enumerate(batch.column("__text")):
                of = window_fingerprints(encode(value.as_py(), unit), params)
                found = [(k, np.unique(of(k))) for k in wanted]
                sizes = [len(f) for _, f in found]
                if not sum(sizes):
                    continue
                places = pa.array(np.full(sum(sizes), i))
                ks = np.repeat(np.array([k for k, _ in found], np.int32), sizes)
                yield pa.RecordBatch.from_arrays([*(batch.column(c).take(places) for c in by), pa.array(ks), pa.array(np.concatenate([f for _, f in found]))], names=[*by, "k", "fp"])

    return kept.mapInArrow(run, ", ".join([*(f"`{c}` {types[c]}" for c in by), "k int", "fp bigint"]))


class CountDistinct:
    """build(rows, keys) and merge(sketches, keys) give (keys, cd); estimates(sketches, keys) gives (keys, d); of_strings gives (by, k, d) without a shuffle."""

    #: The kernel of `narrow` that gives the estimate of a string.
    def kernel(self) -> narrow.Kernel:
        raise NotImplementedError

    def most(self, members: np.ndarray) -> np.ndarray:
        """No estimate of so many members is greater."""
        return 2.0 * members

    def of_strings(self, df: DataFrame, by: Sequence[str], lengths: Sequence[int], grids: Sequence[Sequence[int]] | None = None, **options) -> DataFrame:
        """Estimates where every key has one string: in its task. With `grids`, which make up the lengths, only those that may be the maximiser of a grid."""
        if grids is not None:
            return narrow.per_key_of_grids(df, by, grids, self.kernel(), self.most, **options)
        return narrow.per_key(df, by, lengths, self.kernel(), "d double", **options)

    def deltas(self, df: DataFrame, by: Sequence[str], lengths: Sequence[int], **options) -> DataFrame:
        """(by, delta, k_hat) where every key has one string: in its task, which stops where no longer length can win."""
        return narrow.deltas(df, by, lengths, self.kernel(), **options)

    def build(self, rows: DataFrame, keys: Sequence[str]) -> DataFrame:
        raise NotImplementedError

    def merge(self, sketches: DataFrame, keys: Sequence[str]) -> DataFrame:
        raise NotImplementedError

    def estimates(self, sketches: DataFrame, keys: Sequence[str]) -> DataFrame:
        raise NotImplementedError


@dataclass(frozen=True)
class Exact(CountDistinct):
    """The set itself, a row for each member."""

    def kernel(self):
        return narrow.each(len)

    def build(self, rows, keys):
        return rows.select(*keys, F.col("fp").alias("cd")).distinct()

    def merge(self, sketches, keys):
        return sketches.select(*keys, "cd").distinct()

    def estimates(self, sketches, keys):
        return sketches.groupBy(*keys).agg(F.count("*").cast("double").alias("d"))


@dataclass(frozen=True)
class Buffered(CountDistinct):
    """Spark's own sketches in binary buffers."""

    lg_k: int = 12
    family = ""

    def most(self, members):
        """Few are counted; beyond that, ten standard errors."""
        return np.where(members <= self.counted(), 1.0, 1 + 10 * 1.04 / math.sqrt(1 << self.lg_k)) * members

    def counted(self) -> int:
        """So many distinct members are counted one by one."""
        raise NotImplementedError

    def build(self, rows, keys):
        return rows.groupBy(*keys).agg(getattr(F, f"{self.family}_sketch_agg")("fp", F.lit(self.lg_k)).alias("cd"))

    def merge(self, sketches, keys):
        return sketches.groupBy(*keys).agg(self.union_agg("cd").alias("cd"))

    def estimates(self, sketches, keys):
        return sketches.select(*keys, self.estimate("cd").cast("double").alias("d"))

    def union_agg(self, cd: str) -> Column:
        return getattr(F, f"{self.family}_union_agg")(cd)

    def union(self, a: Column, b: Column) -> Column:
        return getattr(F, f"{self.family}_union")(a, b)

    def estimate(self, cd: str | Column) -> Column:
        return getattr(F, f"{self.family}_sketch_estimate")(cd)


@dataclass(frozen=True)
class Hll(Buffered):
    family = "hll"

    def counted(self):
        return narrow.coupon_limit(self.lg_k)

    def kernel(self):
        return narrow.hll_counts(self.lg_k)


@dataclass(frozen=True)
class Theta(Buffered):
    family = "theta"

    def counted(self):
        return 1 << self.lg_k

    def kernel(self):
        k = 1 << self.lg_k
        return narrow.each(lambda h: len(h) if len(h) <= k else math.floor(k / (float(h[k]) / 2**63) + 0.5), lambda fps: narrow.murmur(fps)[0] >> np.uint64(1))


@dataclass(frozen=True)
class Kmv(CountDistinct):
    """The m least hashes, a row for each; exact while there are fewer than m."""

    m: int = 1024

    def kernel(self):
        return narrow.each(lambda h: len(h) if len(h) < self.m else float(P) * (self.m - 1) / h[self.m - 1], lambda fps: hash_array(fps, "order"))

    def _least(self, rows: DataFrame, keys: Sequence[str]) -> DataFrame:
        rank = F.row_number().over(Window.partitionBy(*keys).orderBy("cd"))
        return rows.distinct().withColumn("rank", rank).where(F.col("rank") <= self.m).drop("rank")

    def build(self, rows, keys):
        return self._least(rows.select(*keys, hash_column("fp", "order").alias("cd")), keys)

    def merge(self, sketches, keys):
        return self._least(sketches.select(*keys, "cd"), keys)

    def estimates(self, sketches, keys):
        n, top = F.count("*"), F.max("cd")
        full = F.lit(float((1 << 31) - 1) * (self.m - 1)) / top
        return sketches.groupBy(*keys).agg(F.when(n < self.m, n.cast("double")).otherwise(full).alias("d"))


@dataclass(frozen=True)
class F0(CountDistinct):
    """Subsampling by trailing zeros: m buckets keep their greatest level. A plain relative of the optimal sketch: the same ideas
    without packed bits and without the rough estimator that sets its level."""

    m: int = 4096
    copy: int = 0
    fill = 0.7

    def kernel(self):
        return narrow.f0_levels(self.m, [self.copy], self.fill)

    def build(self, rows, keys):
        level, bucket = hash_column("fp", "level", self.copy), hash_column("fp", "bucket", self.copy)
        coded = rows.select(*keys, (bucket % self.m).cast("int").alias("bucket"), trailing_zeros(level).cast("int").alias("level"))
        return self._greatest(coded, keys)

    def _greatest(self, rows: DataFrame, keys: Sequence[str]) -> DataFrame:
        return rows.groupBy(*keys, "bucket").agg(F.max("level").alias("level"))

    def merge(self, sketches, keys):
        return self._greatest(sketches.select(*keys, "bucket", "level"), keys)

    def estimates(self, sketches, keys):
        """From the least level at which at most `fill` of the buckets are taken."""
        per_level = sketches.groupBy(*keys, "level").agg(F.count("*").alias("n"))
        counts = per_level.groupBy(*keys).agg(F.map_from_entries(F.collect_list(F.struct("level", "n"))).alias("by"))  # 32 levels at most
        levels = F.sequence(F.lit(0), F.lit(31))
        at_least = F.transform(levels, lambda low: F.aggregate(levels, F.lit(0).cast("bigint"), lambda acc, x: acc + F.when(x >= low, F.coalesce(F.element_at("by", x), F.lit(0))).otherwise(0)))
        first = F.array_position(F.transform(at_least, lambda t: t <= int(self.fill * self.m)), True).cast("int") - 1
        taken = F.element_at(at_least, first + 1).cast("double")
        return counts.select(*keys, (F.pow(F.lit(2.0), first) * F.log(1 - taken / self.m) / math.log(1 - 1 / self.m)).alias("d"))


@dataclass(frozen=True)
class F0Median(CountDistinct):
    """The median of independent copies: the usual way to a high probability."""

    copies: int = 5
    m: int = 4096

    def kernel(self):
        return narrow.f0_levels(self.m, range(self.copies), F0.fill)

    def build(self, rows, keys):
        parts = [F0(self.m, c).build(rows, keys).withColumn("copy", F.lit(c)) for c in range(self.copies)]
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out

    def merge(self, sketches, keys):
        return F0(self.m).merge(sketches, [*keys, "copy"])

    def estimates(self, sketches, keys):
        return F0(self.m).estimates(sketches, [*keys, "copy"]).groupBy(*keys).agg(F.percentile("d", F.lit(0.5)).alias("d"))


@dataclass(frozen=True)
class LinearCounting(CountDistinct):
    """A bitmap of m bits; good for counts well below m."""

    m: int = 32768

    def kernel(self):
        return narrow.each(lambda h: -self.m * math.log(max(self.m - len(h), 1) / self.m), lambda fps: hash_array(fps, "bucket") % self.m)

    def build(self, rows, keys):
        bit = hash_column("fp", "bucket") % self.m
        return rows.groupBy(*keys).agg(F.bitmap_construct_agg(bit).alias("cd"))

    def merge(self, sketches, keys):
        return sketches.groupBy(*keys).agg(F.bitmap_or_agg("cd").alias("cd"))

    def estimates(self, sketches, keys):
        zeros = F.greatest(F.lit(self.m) - F.bitmap_count("cd"), F.lit(1)).cast("double")
        return sketches.select(*keys, (-self.m * F.log(zeros / self.m)).alias("d"))


FAMILY = {"exact": Exact, "hll": Hll, "theta": Theta, "kmv": Kmv, "f0": F0, "f0_median": F0Median, "linear": LinearCounting}


def count_distinct(kind: str, **options) -> CountDistinct:
    return FAMILY[kind](**options)


def approx_profile(rows: DataFrame, keys: Sequence[str], rsd: float = 0.02) -> DataFrame:
    """(keys, d) by approx_count_distinct: one shot, can't be merged."""
    return rows.groupBy(*keys).agg(F.approx_count_distinct("fp", rsd).cast("double").alias("d"))
