"""The sketch of a string or set of strings: one count-distinct sketch for every sampled length."""

from __future__ import annotations

import functools
import operator
from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from repetix.functions.fingerprint import FingerprintParams
from repetix.plans.accuracy import length_bound, plan_accuracy, sampled_lengths
from repetix.session import written

from . import narrow
from .distinct import Buffered, CountDistinct, Hll, count_distinct, window_rows
from .profile import local_maximum


#: What must be alike in sketches that are merged; kept as metadata of the column k, also through Parquet.
ABOUT = "sketch"


def described(sketches: DataFrame, about: dict) -> DataFrame:
    return sketches.withMetadata("k", {ABOUT: about})


def description(sketches: DataFrame) -> dict:
    """Kind and parameters of the count-distinct sketches, moduli, base, unit, and whether a key's sketch is that of a set of strings. Empty if unknown."""
    return sketches.schema["k"].metadata.get(ABOUT, {}) if "k" in sketches.columns else {}


def _kind(cd: CountDistinct) -> str:
    return repr(cd)


def longest(df: DataFrame, text_col: str = "text") -> int:
    size = F.size(text_col) if dict(df.dtypes)[text_col].startswith("array") else F.length(text_col)
    return df.agg(F.max(size)).first()[0] or 0


def build_sketch(
    df: DataFrame, by: Sequence[str] = ("id",), alpha: float = 1.25, cd: CountDistinct = Hll(), grid: str = "with_unit", max_length: int | None = None,
    lengths: Sequence[int] | None = None, text_col: str = "text", unit: str | None = None, params: FingerprintParams = FingerprintParams(), of_sets: bool | None = None, one_each: bool = False,
) -> DataFrame:
    """(by, k, cd...): sketches of the strings that share `by`.

    Without `lengths` the grid goes up to the longest string, or to `max_length`, which loses
    nothing where n / delta (see plans.length_bound) is below it. `of_sets` tells whether several
    strings may share a key; by default only the key `id` is that of one string. With `one_each` no
    two strings share one, so that Hll sketches are made in their tasks and not shuffled; those of
    keys without `id` are merged in their tasks first.
    """
    unit = unit or {"string": "codepoint", "binary": "byte"}.get(dict(df.dtypes)[text_col], "symbol")
    about = {"kind": _kind(cd), "moduli": list(params.moduli), "base": params.base, "unit": unit, "of_sets": tuple(by) != ("id",) if of_sets is None else of_sets}
    if lengths is None:
        lengths = sampled_lengths(max_length or longest(df, text_col), alpha, grid)
    if isinstance(cd, Hll) and one_each:
        return described(narrow.per_key(df, by, lengths, narrow.hll_images(cd.lg_k), "cd binary", text_col, unit, params), about)
    if isinstance(cd, Hll) and "id" not in by:
        return described(cd.merge(narrow.hll_of_sets(df, by, lengths, cd.lg_k, text_col, unit, params), [*by, "k"]), about)
    rows = window_rows(df, lengths, by, text_col, unit, params)
    return described(cd.build(rows, [*by, "k"]), about)


def build_for(df: DataFrame, epsilon: float, target: str = "delta", **options) -> DataFrame:
    """The sketch with grid and error chosen for an accuracy of epsilon."""
    plan = plan_accuracy(epsilon, target)
    return build_sketch(df, alpha=plan.alpha, cd=Hll(plan.hll_lg_k), **options)


def certified(found: DataFrame, strings: DataFrame, cap: int, by: Sequence[str] = ("id",), text_col: str = "text") -> DataFrame:
    """`found` (by, delta, ...) over lengths up to `cap`, with n (symbols of all its strings), bound (n / delta: no maximiser is longer) and certified (bound <= cap)."""
    size = F.size(text_col) if dict(strings.dtypes)[text_col].startswith("array") else F.length(text_col)
    sizes = strings.groupBy(*by).agg(F.sum(size).cast("bigint").alias("n"))
    bound = length_bound(F.col("n"), F.col("delta"))
    return found.join(sizes, list(by)).withColumn("bound", bound).withColumn("certified", F.col("bound") <= cap)


def estimate_delta(sketches: DataFrame, by: Sequence[str] = ("id",), cd: CountDistinct = Hll()) -> DataFrame:
    """(by, delta, k_hat): the largest estimate a length and the least length that attains it."""
    ratio = F.col("d") / F.col("k")
    counted = cd.estimates(sketches, [*by, "k"])
    return counted.groupBy(*by).agg(F.max(ratio).alias("delta"), F.max_by("k", F.struct(ratio, -F.col("k"))).alias("k_hat"))


def go_on(df: DataFrame, by: Sequence[str], found: DataFrame, low: int, counts: Callable[[DataFrame, list[int]], DataFrame], alpha: float | None = 1.25, text_col: str = "text") -> DataFrame:
    """(by, delta, k_hat) over all lengths, from `found` over those up to `low`.

    A set has no more distinct substrings of length k than windows, and windows / k falls with k; so a set goes on to
    longer lengths only while its windows of length low + 1 could beat its delta. `counts(strings, lengths)` gives
    (by, k, d). Every fourfold range of lengths is a round; without `alpha` all lengths in it count.
    """
    by = list(by)
    found = written(found.select(*by, "delta", "k_hat"), "delta")
    same = lambda a, b: functools.reduce(operator.and_, [a[c].eqNullSafe(b[c]) for c in by])
    while True:
        size = F.size(text_col) if dict(df.dtypes)[text_col].startswith("array") else F.length(text_col)
        longer = df.where(size > low)
        windows = longer.groupBy(*by).agg(F.sum(size - low).alias("windows"))
        best = found.select(*[F.col(c).alias(f"{c}__") for c in by], "delta")
        met = windows.join(best, functools.reduce(operator.and_, [F.col(c).eqNullSafe(F.col(f"{c}__")) for c in by]), "left")
        able = written(met.where(F.col("windows") > F.coalesce("delta", F.lit(0.0)) * (low + 1)).select(*by), "able")
        if able.isEmpty():
            return found
        high = 4 * low
        lengths = [k for k in (sampled_lengths(high, alpha) if alpha else range(1, high + 1)) if k > low]
        df = longer.join(able, same(longer, able), "left_semi")
        ratio = F.col("d") / F.col("k")
        more = counts(df, lengths).groupBy(*by).agg(F.max(ratio).alias("delta"), F.max_by("k", F.struct(ratio, -F.col("k"))).alias("k_hat"))
        both = found.unionByName(more.select(*by, "delta", "k_hat"))
        best = F.max_by(F.struct("delta", "k_hat"), F.struct("delta", -F.col("k_hat"))).alias("best")
        found = written(both.groupBy(*by).agg(best).select(*by, "best.delta", "best.k_hat"), "delta")
        low = high


def grow_to_local_maximum(df: DataFrame, counts: Callable[[DataFrame, list[int]], DataFrame], strict: bool = True, first: int = 8) -> DataFrame:
    """(id, delta, k_hat) of the heuristic that grows the length until d / k falls (or, not `strict`, stands), without a cap.

    `counts(strings, lengths)` gives (id, k, d), exact or sketched. Every fourfold range of
    lengths is a round, for the strings that haven't fallen yet; beyond its end a string has no
    windows, which is a fall.
    """
    out, high = None, first
    while True:
        size = F.size("text") if dict(df.dtypes)["text"].startswith("array") else F.length("text")
        every = df.select("id", F.explode(F.array(*map(F.lit, range(1, high + 1)))).alias("k"))
        counted = every.join(counts(df, list(range(1, high + 1))).select("id", "k", "d"), ["id", "k"], "left").withColumn("d", F.coalesce("d", F.lit(0)))
        found = written(local_maximum(counted, strict).join(df.select("id", size.alias("n")), "id"), "local-maxima")
        done = found.where((F.col("k_hat") < high) | (F.col("n") <= high)).select("id", "delta", "k_hat")
        out = done if out is None else out.unionByName(done)
        rest = found.where((F.col("k_hat") >= high) & (F.col("n") > high))
        if rest.isEmpty():
            return out
        df, high = df.join(rest.select("id"), "id", "left_semi"), 4 * high


def merge_sketches(*sketches: DataFrame, by: Sequence[str] = ("id",), cd: CountDistinct = Hll()) -> DataFrame:
    """Of the union of the sets: by key and length, where a sketch without a length counts as empty.

    All must have the same kind and parameters, that of `cd`; grids of one ratio but other
    lengths may differ. Sketches that say nothing about themselves merge only with their like.
    """
    told = [description(s) for s in sketches]
    alike = [{k: v for k, v in t.items() if k != "of_sets"} for t in told]
    if any(set(s.columns) != set(sketches[0].columns) for s in sketches) or any(t != alike[0] for t in alike):
        raise ValueError(f"sketches of different kinds can't be merged: {alike}")
    if alike[0] and alike[0]["kind"] != _kind(cd):
        raise ValueError(f"the sketches are {alike[0]['kind']}, not {_kind(cd)}")
    out = functools.reduce(lambda a, b: a.unionByName(b), sketches)
    merged = cd.merge(out, [*by, "k"])
    return described(merged, {**told[0], "of_sets": True}) if told[0] else merged


def extend_sketch(sketches: DataFrame, tails: DataFrame, chunks: DataFrame, lengths: Sequence[int], cd: CountDistinct = Hll(), id_col: str = "id") -> tuple[DataFrame, DataFrame]:
    """Append a chunk to every string: (sketches, tails) after it.

    tails: (id, tail), each string's last max(lengths) - 1 symbols; chunks: (id, text). Only
    windows that end in the chunk are added. Defined for single strings; sketches of sets are refused.
    """
    about = description(sketches)
    if about.get("of_sets"):
        raise ValueError("a sketch of a set of strings has no end to append to")
    keep = max(lengths) - 1
    longer = tails.join(chunks, id_col, "full_outer").select(id_col, F.concat(F.coalesce("tail", F.lit("")), F.coalesce("text", F.lit(""))).alias("text"))
    new = build_sketch(longer, (id_col,), lengths=lengths, cd=cd, of_sets=False)
    new = new if about else new.withMetadata("k", {})
    kept = longer.select(id_col, F.when(F.length("text") > keep, F.expr(f"right(text, {keep})")).otherwise(F.col("text")).alias("tail"))
    merged = merge_sketches(sketches, new, by=(id_col,), cd=cd)
    return described(merged, about) if about else merged, kept


def rollup_sketch(sketches: DataFrame, levels: Sequence[str], cd: Buffered = Hll()) -> DataFrame:
    """(levels, k, cd) at every level of the hierarchy, by unions of the finest sketches; no text is read again."""
    sets = [[*levels[:n], "k"] for n in range(len(levels), -1, -1)]
    return sketches.groupingSets(sets, *levels, "k").agg(cd.union_agg("cd").alias("cd"))


def save_sketch(sketches: DataFrame, path: str, alpha: float, kind: str) -> None:
    """Append to a store partitioned by kind and ratio, which may only be merged within a partition."""
    sketches.withColumn("cd_kind", F.lit(kind)).withColumn("alpha", F.lit(alpha)).write.mode("append").partitionBy("cd_kind", "alpha").parquet(path)


def load_sketch(spark, path: str, alpha: float, kind: str) -> tuple[DataFrame, CountDistinct]:
    return spark.read.parquet(path).where((F.col("cd_kind") == kind) & (F.col("alpha") == alpha)).drop("cd_kind", "alpha"), count_distinct(kind)
