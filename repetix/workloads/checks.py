"""Properties and guarantees as queries that count violations; the expected count is zero."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from repetix.operators import distance, profile, sketch
from repetix.operators.distinct import F0, Hll
from repetix.plans.accuracy import plan_accuracy, sampled_lengths

from .common import SHORT, Registry, items, turns

query = Registry()
QUERIES, ORACLES = query.queries, query.oracles
EPS = 1e-9


def invariant(name: str):
    def add(f):
        def run(spark, sf_dir) -> DataFrame:
            return f(spark, sf_dir).agg(F.coalesce(F.sum((~F.col("holds")).cast("bigint")), F.lit(0)).alias("violations"), (F.count("*") > 0).alias("tested"))

        query(f"inv_{name}", "SELECT CAST(0 AS BIGINT) AS violations, true AS tested")(run)
        return f

    return add


def singles_and_pairs(spark, sf_dir):
    strings = items(spark, sf_dir)
    one = profile.delta_of_profile(profile.substring_profile(strings, SHORT)).select("id", "delta")
    both = distance.pair_delta(strings, distance.pair_ids(strings), SHORT)
    return both.join(one.toDF("id_a", "da"), "id_a").join(one.toDF("id_b", "db"), "id_b")


@invariant("subadditive")
def subadditive(spark, sf_dir):
    d = F.col("delta")
    return singles_and_pairs(spark, sf_dir).select(((d >= F.greatest("da", "db") - EPS) & (d <= F.col("da") + F.col("db") + EPS)).alias("holds"))


@invariant("distance_range")
def distance_range(spark, sf_dir):
    x = distance.compression_distance(F.col("da"), F.col("db"), F.col("delta"))
    return singles_and_pairs(spark, sf_dir).select(((x >= -EPS) & (x <= 1 + EPS)).alias("holds"))


@invariant("distance_error")
def distance_error(spark, sf_dir):
    """Estimates off by a fifth of epsilon either way move the distance by at most epsilon."""
    e = 0.2
    rows = singles_and_pairs(spark, sf_dir)
    up = lambda c: F.col(c) * (1 + e / 5)
    down = lambda c: F.col(c) * (1 - e / 5)
    true = distance.compression_distance(F.col("da"), F.col("db"), F.col("delta"))
    worst = [distance.compression_distance(a("da"), b("db"), c("delta")) for a in (up, down) for b in (up, down) for c in (up, down)]
    return rows.select(F.explode(F.array(*[F.abs(w - true) <= e + EPS for w in worst])).alias("holds"))


@invariant("estimate_error")
def estimate_error(spark, sf_dir):
    """Grid and sketch planned for epsilon give the measure within epsilon."""
    e = 0.2
    strings = turns(spark, sf_dir).where("text <> ''")
    cd = Hll(plan_accuracy(e).hll_lg_k)
    near = cd.deltas(strings, ["id"], sampled_lengths(60, plan_accuracy(e).alpha)).select("id", F.col("delta").alias("near"))
    return profile.exact_delta(strings).join(near, "id").select((F.abs(F.col("near") - F.col("delta")) <= e * F.col("delta")).alias("holds"))


@invariant("profile_step")
def profile_step(spark, sf_dir):
    """The next length has at most one substring less."""
    p = profile.profile_from_lcp(items(spark, sf_dir))
    after = p.select("id", (F.col("k") - 1).alias("k"), F.col("d").alias("next"))
    return p.join(after, ["id", "k"]).select((F.col("next") >= F.col("d") - 1).alias("holds"))


@invariant("concat_monotone")
def concat_monotone(spark, sf_dir):
    rows = turns(spark, sf_dir)
    half = rows.select("id", F.left("text", F.floor(F.length("text") / 2).cast("int")).alias("text"))
    return profile.exact_delta(rows).join(profile.exact_delta(half).select("id", F.col("delta").alias("less")), "id").select((F.col("less") <= F.col("delta") + EPS).alias("holds"))


@invariant("reversal")
def reversal(spark, sf_dir):
    rows = turns(spark, sf_dir)
    other = profile.exact_delta(rows.select("id", F.reverse("text").alias("text"))).select("id", F.col("delta").alias("other"))
    return profile.exact_delta(rows).join(other, "id").select((F.col("other") == F.col("delta")).alias("holds"))


@invariant("permutation")
def permutation(spark, sf_dir):
    rows = turns(spark, sf_dir)
    other = profile.exact_delta(rows.select("id", F.translate("text", "abcdefghij", "jihgfedcba").alias("text"))).select("id", F.col("delta").alias("other"))
    return profile.exact_delta(rows).join(other, "id").select((F.col("other") == F.col("delta")).alias("holds"))


def with_parses(spark, sf_dir):
    rows = turns(spark, sf_dir).where("text <> ''")
    return profile.exact_delta(rows).join(profile.parse_sizes(rows), "id")


@invariant("delta_below_parses")
def below_parses(spark, sf_dir):
    """Delta bounds the phrases and the runs from below."""
    return with_parses(spark, sf_dir).select(((F.col("delta") <= F.col("z") + EPS) & (F.col("delta") <= F.col("r") + EPS)).alias("holds"))


@invariant("runs_bound")
def runs_bound(spark, sf_dir):
    return with_parses(spark, sf_dir).where("n >= 8").select((F.col("r") <= 8 * F.col("delta") * F.pow(F.log2("n"), 2) + EPS).alias("holds"))


@invariant("maximiser_bound")
def maximiser_bound(spark, sf_dir):
    return with_parses(spark, sf_dir).select((F.col("k_hat") <= F.col("n") / F.col("delta") + EPS).alias("holds"))


@invariant("marker_runs")
def marker_runs(spark, sf_dir):
    return with_parses(spark, sf_dir).select(((F.col("r") - 2 <= F.col("r_no_marker")) & (F.col("r_no_marker") <= F.col("r"))).alias("holds"))


@invariant("merge_registers")
def merge_registers(spark, sf_dir):
    """Merged sketches are the sketch of the union, whatever the order, and merging twice changes nothing."""
    cd, rows = F0(256), items(spark, sf_dir)
    keys = ["id", "k"]
    alone = sketch.build_sketch(rows, cd=cd, lengths=SHORT).withColumn("id", F.floor(F.col("id") / 3))
    whole = sketch.build_sketch(rows.withColumn("id", F.floor(F.col("id") / 3)), cd=cd, lengths=SHORT)
    once, twice = cd.merge(alone, keys), cd.merge(alone.unionByName(alone).orderBy(F.desc("level")), keys)
    met = whole.withColumnRenamed("level", "a").join(once.withColumnRenamed("level", "b"), [*keys, "bucket"], "full_outer").join(twice.withColumnRenamed("level", "c"), [*keys, "bucket"], "full_outer")
    return met.select((F.col("a").eqNullSafe(F.col("b")) & F.col("b").eqNullSafe(F.col("c"))).alias("holds"))


@invariant("profiles_agree")
def profiles_agree(spark, sf_dir):
    """Refinement, suffix arrays and fingerprints count alike."""
    rows = turns(spark, sf_dir)
    a = profile.substring_profile(rows, SHORT).where("d > 0")
    b = profile.profile_from_lcp(rows).where(F.col("k") <= max(SHORT)).withColumnRenamed("d", "b")
    c = profile.substring_profile(rows, SHORT, mode="fingerprint").where("d > 0").withColumnRenamed("d", "c")
    met = a.join(b, ["id", "k"], "full_outer").join(c, ["id", "k"], "full_outer")
    return met.select((F.col("d").eqNullSafe(F.col("b")) & F.col("d").eqNullSafe(F.col("c"))).alias("holds"))


@invariant("parses_polylog")
def parses_polylog(spark, sf_dir):
    """Phrases and runs are at most delta times a polylogarithm."""
    limit = 8 * F.col("delta") * F.pow(F.log2("n"), 2) + EPS
    return with_parses(spark, sf_dir).where("n >= 8").select(((F.col("z") <= limit) & (F.col("r") <= limit)).alias("holds"))


@invariant("capped_then_exact")
def capped_then_exact(spark, sf_dir):
    """Counts up to three symbols, carried on where the certificate isn't met, give what all lengths give."""
    strings = turns(spark, sf_dir)
    counts = lambda rows, lengths: profile.substring_profile(rows, lengths)
    capped = profile.delta_of_profile(counts(strings, [1, 2, 3]))
    whole = sketch.go_on(strings, ["id"], capped, 3, counts, alpha=None).select("id", F.col("delta").alias("got"))
    return profile.exact_delta(strings).join(whole, "id", "left").select((F.abs(F.coalesce("got", F.lit(0.0)) - F.col("delta")) <= EPS).alias("holds"))
