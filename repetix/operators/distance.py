"""Pair measures and compression distances, exact and from sketches.

All pairs are met in blocks: every string has a bucket, and a pair of buckets is the key of an
equi-join or group, so that the work is spread over many keys and no task holds more than two
buckets. Asked pairs only open the blocks that they lie in.
"""

from __future__ import annotations

import math
from collections.abc import Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from repetix.functions.fingerprint import FingerprintParams, window_fingerprints
from repetix.functions.symbols import encode

from . import narrow
from .distinct import Buffered, Hll, window_rows
from .profile import codec_size, delta_of_profile, exact_delta
from .sketch import build_sketch

#: Strings of a bucket, about, where whole sets of fingerprints are compared.
BUCKET = 48
#: Distinct fingerprints compared at a time within a block.
COLUMNS = 1 << 16


def compression_distance(a: Column, b: Column, both: Column) -> Column:
    """How much the pair adds to the smaller of the two, as a share of the larger; 0 where both are 0."""
    most = F.greatest(a, b)
    return F.when(most > 0, (both - F.least(a, b)) / most).otherwise(F.lit(0.0))


def pair_ids(df: DataFrame, id_col: str = "id") -> DataFrame:
    """(id_a, id_b) with id_a < id_b of all ids: what an all-pairs workload asks for, so its rows are quadratic by definition."""
    ids = df.select(F.col(id_col).alias("id_a")).distinct()
    return ids.join(ids.toDF("id_b"), F.col("id_a") < F.col("id_b"))


def block_join(df: DataFrame, columns: Sequence[str], on: Sequence[str] = (), blocks: int | None = None, spread: bool = False) -> DataFrame:
    """All pairs id_a < id_b of (id, columns..., on...) as (id_a, id_b, <column>_a, <column>_b, on...), by an equi-join on pairs of hash buckets.

    With `spread` one side is dealt out by the pairs of buckets even if the other is small enough for a broadcast: for work that costs more than its bytes.
    """
    tasks = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    blocks = blocks or max(8, math.ceil(math.sqrt(2 * tasks)))
    own = df.select("id", *columns, *on, F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int").alias("__own"))
    left = own.select("*", F.col("__own").alias("__i"), F.explode(F.sequence(F.col("__own"), F.lit(blocks - 1))).alias("__j"))
    right = own.select(F.col("id").alias("__id"), *[F.col(c).alias(f"__{c}") for c in columns], *on, F.col("__own").alias("__j"), F.explode(F.sequence(F.lit(0), F.col("__own"))).alias("__i"))
    if spread:
        left = left.repartition(max(tasks, blocks * (blocks + 1) // 2), "__i", "__j")
    met = left.join(right.hint("merge"), ["__i", "__j", *on]).where("__i < __j AND id <> __id OR id < __id")
    first = F.col("id") < F.col("__id")
    both = [x for c in columns for x in (F.when(first, F.col(c)).otherwise(F.col(f"__{c}")).alias(f"{c}_a"), F.when(first, F.col(f"__{c}")).otherwise(F.col(c)).alias(f"{c}_b"))]
    return met.select(F.least("id", "__id").alias("id_a"), F.greatest("id", "__id").alias("id_b"), *both, *on)


def string_sets(df: DataFrame, lengths: Sequence[int], params: FingerprintParams = FingerprintParams()) -> DataFrame:
    """(id, k, fps binary): the sorted fingerprints of every string's windows, empty where a string has none."""
    kept = df.select("id", "text")
    types = dict(kept.dtypes)
    unit = {"string": "codepoint", "binary": "byte"}.get(types["text"], "symbol")
    wanted = sorted(set(lengths))

    def run(batches):
        for batch in batches:
            for i, value in enumerate(batch.column("text")):
                of = window_fingerprints(encode(value.as_py(), unit), params)
                sets = [np.unique(of(k)).astype("<i8").tobytes() for k in wanted]
                yield pa.RecordBatch.from_arrays([batch.column("id").take(pa.array([i] * len(wanted))), pa.array(wanted, pa.int32()), pa.array(sets, pa.binary())], names=["id", "k", "fps"])

    return kept.mapInArrow(run, f"id {types['id']}, k int, fps binary")


def shared_counts(sets: list[np.ndarray]) -> np.ndarray:
    """Sizes of all pairwise intersections of sorted sets, by products of membership matrices over ranges of the members."""
    of = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    every = np.concatenate(sets) if sets else np.empty(0, np.int64)
    order = np.argsort(every, kind="stable")
    every, of = every[order], of[order]
    member = np.cumsum(np.concatenate(([0], every[1:] != every[:-1]))) if len(every) else every
    shared = np.zeros((len(sets), len(sets)))
    for low in range(0, int(member[-1]) + 1 if len(member) else 0, COLUMNS):
        a, b = np.searchsorted(member, [low, low + COLUMNS])
        has = np.zeros((len(sets), min(COLUMNS, int(member[b - 1]) - low + 1)), np.float32)
        has[of[a:b], member[a:b] - low] = 1
        shared += has @ has.T  # exact: below 2^24 in each range
    return shared.astype(np.int64)


def pair_profile(df: DataFrame, pairs: DataFrame | None, lengths: Sequence[int], buckets: DataFrame | None = None) -> DataFrame:
    """(id_a, id_b, k, d): sizes of the unions of both strings' substring sets, of `pairs` (id_a < id_b) or of all.

    Every string goes to the blocks, pairs of buckets, that hold a pair that is asked for; its sets,
    which take many times its bytes, are made and compared there, length by length. Buckets are of a hash of the id, or of
    `buckets` (id, bucket), which can keep pairs that need no comparison in blocks of their own.
    """
    texts = df.select("id", "text")
    kinds, wanted = dict(texts.dtypes), sorted(set(lengths))
    kind, unit = kinds["id"], {"string": "codepoint", "binary": "byte"}.get(kinds["text"], "symbol")
    if buckets is None:
        n = -(-df.select("id").distinct().count() // BUCKET) or 1
        texts = texts.withColumn("bucket", F.pmod(F.xxhash64("id"), F.lit(n)))
        own = df.select("id").distinct().withColumn("bucket", F.pmod(F.xxhash64("id"), F.lit(n)))
    else:
        texts, own = texts.join(buckets, "id"), buckets
    names = own.select("bucket").distinct()
    if pairs is None:
        blocks = names.select(F.col("bucket").alias("i")).join(names.select(F.col("bucket").alias("j")), F.col("i") <= F.col("j"))  # of buckets, not of strings
    else:
        located = pairs.join(own.toDF("id_a", "a"), "id_a").join(own.toDF("id_b", "b"), "id_b")
        blocks = located.select(F.least("a", "b").alias("i"), F.greatest("a", "b").alias("j")).distinct()
    opened = blocks.select("i", "j", F.explode(F.array_distinct(F.array("i", "j"))).alias("bucket"))

    def compare(table: pa.Table) -> pa.Table:
        ids, bucket = table.column("id").to_pylist(), table.column("bucket").to_numpy()
        i, j, k = (table.column(c)[0].as_py() for c in ("i", "j", "k"))
        found = [np.unique(window_fingerprints(encode(t.as_py(), unit))(k)) for t in table.column("text")]
        shared, sizes = shared_counts(found), [len(f) for f in found]
        out = []
        for x in range(len(ids)):
            for y in range(x + 1, len(ids)):
                if i == j or bucket[x] != bucket[y]:
                    a, b = (x, y) if ids[x] < ids[y] else (y, x)
                    out.append((ids[a], ids[b], k, int(sizes[a] + sizes[b] - shared[a, b])))
        columns = list(zip(*out, strict=True)) if out else [[], [], [], []]
        types = [table.schema.field("id").type, pa.int32(), pa.int64()]
        return pa.table({"id_a": pa.array(columns[0], types[0]), "id_b": pa.array(columns[1], types[0]), "k": pa.array(columns[2], types[1]), "d": pa.array(columns[3], types[2])})

    # neither side is broadcast: Spark can't tell the sizes of either
    placed = texts.join(opened.hint("merge"), "bucket").withColumn("k", F.explode(F.array(*map(F.lit, wanted)).cast("array<int>")))
    met = placed.groupBy("i", "j", "k").applyInArrow(compare, f"id_a {kind}, id_b {kind}, k int, d bigint")
    return met if pairs is None else met.join(pairs.select("id_a", "id_b"), ["id_a", "id_b"], "left_semi")


def pair_delta(df: DataFrame, pairs: DataFrame | None, lengths: Sequence[int], semantics: str = "union", buckets: DataFrame | None = None) -> DataFrame:
    """(id_a, id_b, delta): of the union of substring sets (all pairs if `pairs` is None), or of the concatenation, which has windows across the border."""
    if semantics == "union":
        return delta_of_profile(pair_profile(df, pairs, lengths, buckets), ("id_a", "id_b")).drop("k_hat")
    text = df.select("id", "text")
    joined = pairs.join(text.toDF("id_a", "text_a"), "id_a").join(text.toDF("id_b", "text_b"), "id_b")
    whole = joined.select(F.struct("id_a", "id_b").alias("id"), F.concat("text_a", "text_b").alias("text"))
    return exact_delta(whole).select("id.id_a", "id.id_b", "delta")


def group_profile(df: DataFrame, by: Sequence[str], lengths: Sequence[int], text_col: str = "text") -> DataFrame:
    """(by, k, d): distinct substrings over all strings of a group, exact in fingerprints."""
    return window_rows(df, lengths, by, text_col).groupBy(*by, "k").agg(F.count_distinct("fp").alias("d"))


def with_distance(pairs: DataFrame, singles: DataFrame) -> DataFrame:
    """(id_a, id_b, dist) from (id_a, id_b, delta) and (id, delta)."""
    a, b = singles.select(F.col("id").alias("id_a"), F.col("delta").alias("da")), singles.select(F.col("id").alias("id_b"), F.col("delta").alias("db"))
    return pairs.join(a, "id_a").join(b, "id_b").select("id_a", "id_b", compression_distance(F.col("da"), F.col("db"), F.col("delta")).alias("dist"))


def certified_lengths(df: DataFrame) -> list[int]:
    """All lengths that can be the maximiser of a pair: a pair's windows are at most twice those of its longer string, and its delta is at least that string's."""
    most = exact_delta(df).where("delta > 0").agg(F.max(F.floor(2 * F.col("n") / F.col("delta")))).first()[0]
    return list(range(1, int(most or 1) + 1))


def all_pairs_exact(df: DataFrame, lengths: Sequence[int] | None = None) -> DataFrame:
    """(id_a, id_b, dist) from exact counts, over all lengths that could win unless `lengths` are given."""
    lengths = lengths or certified_lengths(df)
    profile = string_sets(df, lengths).select("id", "k", (F.octet_length("fps") / 8).cast("bigint").alias("d"))
    return with_distance(pair_delta(df, None, lengths), delta_of_profile(profile))


def pairs_within(singles: DataFrame, limit: float) -> DataFrame:
    """(id_a, id_b): all pairs of (id, delta) that may be within `limit`, joined on bands of delta and the next, so no cross join; limit is below 1."""
    banded = singles.where("delta > 0").withColumn("band", F.floor(F.log("delta") / -math.log(1 - limit)))
    a = banded.select(F.col("id").alias("id_a"), F.col("delta").alias("da"), "band")
    b = banded.select(F.col("id").alias("id_b"), F.col("delta").alias("db"), F.explode(F.array(*[F.col("band") + i for i in (-1, 0, 1)])).alias("band"))
    return a.join(b, "band").where("id_a < id_b").where(may_be_within(F.col("da"), F.col("db"), limit)).select("id_a", "id_b")


def delta_buckets(singles: DataFrame, limit: float, size: int = BUCKET) -> DataFrame:
    """(id, bucket) of (id, delta): ranges of delta of the width of `limit`, large ones split by a hash, so that blocks hold pairs of like measure."""
    band = F.floor(F.log(F.greatest("delta", F.lit(1e-9))) / -math.log(1 - limit)).cast("bigint")
    banded = singles.select("id", band.alias("band"))
    counts = banded.groupBy("band").agg(F.ceil(F.count("*") / size).cast("bigint").alias("parts"))
    return banded.join(counts, "band").select("id", (F.col("band") * (1 << 32) + F.pmod(F.xxhash64("id"), F.col("parts"))).alias("bucket"))


def all_pairs_sketch(sketches: DataFrame, cd: Buffered = Hll(), pairs: DataFrame | None = None, blocks: int | None = None) -> DataFrame:
    """(id_a, id_b, dist) from stored sketches (id, k, cd): unions only, no text. Of `pairs` (id_a, id_b) only, if given; else of all, met in blocks."""
    ratio = (cd.estimate("cd") / F.col("k")).alias("ratio")
    singles = sketches.select("id", ratio).groupBy("id").agg(F.max("ratio").alias("delta"))
    if pairs is None:
        met = block_join(sketches, ["cd"], ["k"], blocks)
    else:
        a = sketches.select(F.col("id").alias("id_a"), "k", F.col("cd").alias("cd_a"))
        b = sketches.select(F.col("id").alias("id_b"), "k", F.col("cd").alias("cd_b"))
        met = pairs.join(a, "id_a").join(b, ["id_b", "k"])
    ratios = met.select("id_a", "id_b", (cd.estimate(cd.union(F.col("cd_a"), F.col("cd_b"))) / F.col("k")).alias("ratio"))
    united = ratios.groupBy("id_a", "id_b").agg(F.max("ratio").alias("met"))
    # where only one string has a length, the union is that string's set
    pairs = united.join(singles.toDF("id_a", "da"), "id_a").join(singles.toDF("id_b", "db"), "id_b")
    return pairs.select("id_a", "id_b", compression_distance(F.col("da"), F.col("db"), F.greatest("met", "da", "db")).alias("dist"))


#: Lengths at which pairs are looked at before they are formed, and strings of a bucket there, about.
PROBES, CROWD = (3, 5, 8, 12), 1024
#: What an estimate from taken registers, or a measure, may be over that of the whole sketch.
SLACK = 0.9


def taken_registers(df: DataFrame, cd: Hll = Hll(), probes: Sequence[int] = PROBES) -> DataFrame:
    """(id, bits): for each of `probes` a bit for each register of the string's sketch, set if it is taken; none where the string is shorter."""
    kept, m = df.select("id", "text"), 1 << cd.lg_k

    def run(batches):
        for batch in batches:
            for first, strings in narrow.chunks(batch, "text", "codepoint"):
                bits = np.zeros((len(strings), len(probes), m // 8), np.uint8)
                for k, owners, fps in narrow.windows(strings, probes, FingerprintParams()):
                    taken = np.zeros((len(strings), m), bool)
                    taken[owners, narrow.coupons(fps) & (m - 1)] = True
                    bits[:, list(probes).index(k)] = np.packbits(taken, axis=1)
                yield pa.RecordBatch.from_arrays([batch.column("id").slice(first, len(strings)), pa.array([b.tobytes() for b in bits], pa.binary())], names=["id", "bits"])

    return kept.mapInArrow(run, f"id {dict(kept.dtypes)['id']}, bits binary")


def pairs_by_registers(df: DataFrame, singles: DataFrame, limit: float, cd: Hll = Hll(), probes: Sequence[int] = PROBES) -> DataFrame:
    """(id_a, id_b): all pairs that may be within `limit` by their measures (id, delta) and by the registers that either string takes.

    A pair within the limit has at no length k a union of over k times its own measure, which is at most min + limit * max of both. Buckets of
    like measure meet in blocks, where a product of matrices gives the registers that neither takes, so no sketch leaves its task.
    """
    m, kind = 1 << cd.lg_k, dict(df.dtypes)["id"]
    wide = 1 - (1 - limit) * SLACK
    placed = singles.where("delta > 0").join(delta_buckets(singles.where("delta > 0"), wide, CROWD), "id").withColumn("band", F.floor(F.log(F.greatest("delta", F.lit(1e-9))) / -math.log(1 - wide)).cast("bigint"))
    names = placed.select("bucket", "band").distinct()
    near = names.select(F.col("bucket").alias("j"), F.explode(F.array(*[F.col("band") + x for x in (-1, 0, 1)])).alias("band"))
    blocks = names.withColumnRenamed("bucket", "i").join(near, "band").where("i <= j").select("i", "j")  # of buckets, not of strings
    opened = blocks.select("i", "j", F.explode(F.array_distinct(F.array("i", "j"))).alias("bucket"))

    def compare(table: pa.Table) -> pa.Table:
        i, j = table.column("i")[0].as_py(), table.column("j")[0].as_py()
        bucket, delta = table.column("bucket").to_numpy(), table.column("delta").to_numpy()
        bits = np.frombuffer(b"".join(table.column("bits").to_pylist()), np.uint8).reshape(len(bucket), len(probes), m // 8)
        left, right = np.flatnonzero(bucket == i), np.flatnonzero(bucket == j)
        least, most = np.minimum.outer(delta[left], delta[right]), np.maximum.outer(delta[left], delta[right])
        able = least >= (1 - wide) * most
        if i == j:
            able &= np.tri(len(left), k=-1, dtype=bool)
        for x, k in enumerate(probes):
            if not able.any():
                break
            free = 1 - np.unpackbits(bits[:, x], axis=1).astype(np.float32)
            neither = free[left] @ free[right].T
            counted = np.where(neither >= 20, m * np.log(m / np.maximum(neither, 1)), 0)  # with fewer, the estimate says too little
            able &= SLACK * counted <= k * (least + limit * most)
        a, b = np.nonzero(able)
        ids = table.column("id").combine_chunks()
        return pa.table({"x": ids.take(pa.array(left[a])), "y": ids.take(pa.array(right[b]))})

    rows = placed.select("id", "delta", "bucket").join(taken_registers(df, cd, probes), "id").join(opened.hint("merge"), "bucket")
    met = rows.groupBy("i", "j").applyInArrow(compare, f"x {kind}, y {kind}")
    return met.select(F.least("x", "y").alias("id_a"), F.greatest("x", "y").alias("id_b")).where("id_a < id_b").distinct()


def merge_cost(sketches: DataFrame) -> DataFrame:
    """(id_a, id_b, unions): unions of count-distinct sketches that merging each pair takes, one a length that both have."""
    return block_join(sketches.select("id", "k"), [], ["k"]).groupBy("id_a", "id_b").agg(F.count("*").alias("unions"))


def all_pairs_codec(df: DataFrame, codec: str = "xz") -> DataFrame:
    """(id_a, id_b, dist) with a codec's output size as the measure: every pair's concatenation is compressed."""
    size = codec_size(codec)
    met = block_join(df.select("id", "text", size(F.col("text")).cast("double").alias("z")), ["text", "z"], spread=True).withColumn("zab", size(F.concat("text_a", "text_b")).cast("double"))
    return met.select("id_a", "id_b", compression_distance(F.col("z_a"), F.col("z_b"), F.col("zab")).alias("dist"))


def all_pairs_distance(df: DataFrame, measure: str = "sketch", alpha: float = 1.25, lg_k: int = 12, lengths: Sequence[int] | None = None) -> DataFrame:
    """(id_a, id_b, dist) by `delta` (exact), `sketch`, or a codec's name."""
    if measure == "sketch":
        cd = Hll(lg_k)
        sketches = build_sketch(df, alpha=alpha, cd=cd, lengths=lengths)
        return all_pairs_sketch(sketches, cd)
    if measure == "delta":
        return all_pairs_exact(df, lengths)
    return all_pairs_codec(df, measure)


def both_ways(distances: DataFrame) -> DataFrame:
    """(id, other, dist): every pair from either side."""
    return distances.toDF("id", "other", "dist").unionByName(distances.select(F.col("id_b").alias("id"), F.col("id_a").alias("other"), "dist"))


def nearest(distances: DataFrame, n: int = 1) -> DataFrame:
    """(id, other, dist): the n nearest of every id, ties by id."""
    rank = F.row_number().over(Window.partitionBy("id").orderBy("dist", "other"))
    return both_ways(distances).withColumn("rank", rank).where(F.col("rank") <= n).drop("rank")


def may_be_within(da: Column, db: Column, limit: float) -> Column:
    """A distance is at least 1 - min / max of the two measures, so other pairs needn't be formed."""
    return F.least(da, db) >= (1 - limit) * F.greatest(da, db)


def jaccard(sketches: DataFrame) -> DataFrame:
    """(id_a, id_b, k, jaccard) from Theta sketches (id, k, cd), which also intersect: shared windows over all windows."""
    both = F.theta_sketch_estimate(F.theta_intersection("cd_a", "cd_b")) / F.theta_sketch_estimate(F.theta_union("cd_a", "cd_b"))
    return block_join(sketches, ["cd"], ["k"]).select("id_a", "id_b", "k", both.alias("jaccard"))
