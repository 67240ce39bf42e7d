"""Accuracy and cost measures."""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def relative_errors(exact: DataFrame, estimate: DataFrame, by: Sequence[str] = ("id",)) -> DataFrame:
    """(by, exact, estimate, error): |estimate - exact| / exact of two (by, delta)."""
    a, b = exact.select(*by, F.col("delta").alias("exact")), estimate.select(*by, F.col("delta").alias("estimate"))
    return a.join(b, list(by)).withColumn("error", F.when(F.col("exact") > 0, F.abs(F.col("estimate") - F.col("exact")) / F.col("exact")).otherwise(0.0))


def error_summary(errors: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    return errors.groupBy(*by).agg(
        F.count("*").alias("strings"), F.avg("error").alias("mean"), F.percentile("error", F.lit(0.99)).alias("p99"), F.max("error").alias("max")
    )


def error_histogram(errors: DataFrame, width: float = 0.01) -> DataFrame:
    return errors.groupBy((F.floor(F.col("error") / width) * width).alias("from")).agg(F.count("*").alias("strings"))


def maximiser_histogram(deltas: DataFrame) -> DataFrame:
    return deltas.groupBy("k_hat").agg(F.count("*").alias("strings"))


def sketch_size(sketches: DataFrame, by: Sequence[str] = ("id",)) -> DataFrame:
    """(by, lengths, bytes) of binary sketches."""
    return sketches.groupBy(*by).agg(F.count("*").alias("lengths"), F.sum(F.octet_length("cd")).alias("bytes"))


def collisions(exact_profile: DataFrame, fingerprint_profile: DataFrame) -> DataFrame:
    """(k, strings, lost): windows that fingerprints fail to tell apart."""
    a, b = exact_profile.select("id", "k", F.col("d").alias("e")), fingerprint_profile.select("id", "k", F.col("d").alias("f"))
    return a.join(b, ["id", "k"]).groupBy("k").agg(F.count("*").alias("strings"), F.sum(F.col("e") - F.col("f")).alias("lost"))


def normalised(measures: DataFrame) -> DataFrame:
    """(id, prefix_len, measure, value) plus by_range, (x - min) / (max - min), and by_max, x / max, within each string and measure."""
    w = Window.partitionBy("id", "measure")
    low, high = F.min("value").over(w), F.max("value").over(w)
    return measures.withColumn("by_range", F.when(high > low, (F.col("value") - low) / (high - low)).otherwise(0.0)).withColumn("by_max", F.when(high > 0, F.col("value") / high).otherwise(0.0))


def trend_agreement(measures: DataFrame) -> DataFrame:
    """(id, measure_a, measure_b, pearson, spearman) over the prefixes of each string."""
    ranked = measures.withColumn("rank", F.rank().over(Window.partitionBy("id", "measure").orderBy("value")).cast("double"))
    a = ranked.select("id", "prefix_len", F.col("measure").alias("measure_a"), F.col("value").alias("va"), F.col("rank").alias("ra"))
    b = ranked.select("id", "prefix_len", F.col("measure").alias("measure_b"), F.col("value").alias("vb"), F.col("rank").alias("rb"))
    met = a.join(b, ["id", "prefix_len"]).where("measure_a < measure_b")
    return met.groupBy("id", "measure_a", "measure_b").agg(F.corr("va", "vb").alias("pearson"), F.corr("ra", "rb").alias("spearman"))


def rank_auc(rows: DataFrame, score: str, label: str, ranges: int = 256) -> DataFrame:
    """(positives, negatives, auc): how often label 1 scores above label 0, ties half.

    One row for each score value is ranked, in ranges of the score and then over the ranges' sums, so that no task ranks all values.
    """
    by_score = rows.groupBy(F.col(score).alias("s")).agg(F.sum(F.col(label).cast("long")).alias("pos"), F.sum(1 - F.col(label).cast("long")).alias("neg"))
    cuts = by_score.agg(F.percentile_approx("s", F.array(*[F.lit(i / ranges) for i in range(1, ranges)]))).first()[0] or []
    edges = sorted(set(cuts))
    ranged = by_score.withColumn("range", F.size(F.filter(F.array(*map(F.lit, edges)), lambda e: e <= F.col("s"))) if edges else F.lit(0))
    sums = ranged.groupBy("range").agg(F.sum("neg").alias("n"))
    earlier = sums.select("range", F.coalesce(F.sum("n").over(Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))  # `ranges` rows at most
    inside = F.coalesce(F.sum("neg").over(Window.partitionBy("range").orderBy("s").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    below = ranged.withColumn("inside", inside).join(F.broadcast(earlier), "range")
    won = below.withColumn("won", F.col("pos") * (F.col("base") + F.col("inside") + F.col("neg") / 2))
    return won.agg(F.sum("pos").alias("positives"), F.sum("neg").alias("negatives"), (F.sum("won") / F.sum("pos") / F.sum("neg")).alias("auc"))


def throughput(name: str, n_bytes: int, job: Callable[[], object]) -> dict:
    """Seconds and MB a minute of a job over so many bytes."""
    start = time.perf_counter()
    job()
    seconds = time.perf_counter() - start
    return {"name": name, "seconds": round(seconds, 3), "mb_per_minute": round(n_bytes / 1e6 / seconds * 60, 1)}
