"""Joins and tables that uses of the sketches need and Spark has no single operator for."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from repetix.functions.fingerprint import window_fingerprints
from repetix.functions.symbols import encode
from repetix.plans.accuracy import sampled_lengths

#: Windows that are broadcast at most.
FEW = 1 << 20


def as_of(left: DataFrame, right: DataFrame, key: str, left_ts: str, right_ts: str, values: list[str]) -> DataFrame:
    """left plus the values of the last row of right with the same key at or before its time: one shuffle and one sort of the union."""
    a = left.select(F.struct(*left.columns).alias("row"), F.col(key).alias("__key"), F.col(left_ts).alias("__ts"), F.lit(1).alias("__side"), F.lit(None).cast(_struct(right, values)).alias("__v"))
    b = right.select(F.lit(None).cast(_struct(left, left.columns)).alias("row"), F.col(key).alias("__key"), F.col(right_ts).alias("__ts"), F.lit(0).alias("__side"), F.struct(*values).alias("__v"))
    order = Window.partitionBy("__key").orderBy("__ts", "__side").rowsBetween(Window.unboundedPreceding, 0)
    filled = a.unionByName(b).withColumn("__v", F.last("__v", ignorenulls=True).over(order))
    return filled.where("__side = 1").select("row.*", *[F.col(f"__v.{v}").alias(v) for v in values])


def _struct(df: DataFrame, columns: list[str]) -> str:
    types = dict(df.dtypes)
    return "struct<" + ",".join(f"`{c}`:{types[c]}" for c in columns) + ">"


def range_join(points: DataFrame, ranges: DataFrame, point: str, low: str, high: str, width: int) -> DataFrame:
    """Pairs with low <= point < high, by equi-joining bins of `width`; a range is repeated for each bin it meets."""
    p = points.withColumn("__bin", F.floor(F.col(point) / width))
    r = ranges.withColumn("__bin", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor((F.col(high) - 1) / width))))
    return p.join(r, "__bin").where((F.col(point) >= F.col(low)) & (F.col(point) < F.col(high))).drop("__bin")


def top_by_group(df: DataFrame, group: str, order: list, n: int) -> DataFrame:
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(group).orderBy(*order))).where(F.col("rank") <= n)


def unique_substrings(rows: DataFrame) -> DataFrame:
    """(id, k, d): windows of (id, k, fp) that no other id has, counted."""
    owners = rows.groupBy("k", "fp").agg(F.count("*").alias("owners"), F.min("id").alias("id"))
    return owners.where("owners = 1").groupBy("id", "k").agg(F.count("*").alias("d"))


def containment(items: DataFrame, rows: DataFrame) -> DataFrame:
    """(id, k, d, shared): how many of each item's windows occur anywhere in `rows`; both are (id, k, fp)."""
    asked = items.select("k", "fp").distinct()
    rows = rows.select("k", "fp")
    if asked.count() <= FEW:
        rows = rows.join(F.broadcast(asked), ["k", "fp"], "left_semi")  # others needn't leave their tasks
    anywhere = rows.distinct().withColumn("met", F.lit(1))
    return items.join(anywhere.hint("merge"), ["k", "fp"], "left").groupBy("id", "k").agg(F.count("*").alias("d"), F.count("met").alias("shared"))


def register_sql(spark: SparkSession) -> None:
    """UDTFs for SQL: sampled_lengths(n, alpha) and substring_fps(text, k_max)."""

    @F.udtf(returnType="k: int")
    class SampledLengths:
        def eval(self, n: int, alpha: float) -> Iterator[tuple]:
            for k in sampled_lengths(n, float(alpha)):
                yield (k,)

    @F.udtf(returnType="k: int, fp: bigint")
    class SubstringFps:
        def eval(self, text: str, k_max: int) -> Iterator[tuple]:
            of = window_fingerprints(encode(text))
            for k in range(1, k_max + 1):
                for fp in set(of(k).tolist()):
                    yield k, fp

    spark.udtf.register("sampled_lengths", SampledLengths)
    spark.udtf.register("substring_fps", SubstringFps)
