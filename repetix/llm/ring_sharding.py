"""Sharding on a consistent-hash ring with virtual nodes and bounded loads, in DataFrame functions.

Every shard owns `vnodes` points of a ring; a key belongs to the first point at or after its
hash. A shard takes its own keys, in ring order, up to its capacity; what overflows goes on
clockwise to the next shards with room. Only the number of keys on each arc decides where
arcs are cut, so the walk around the ring runs over shards * vnodes counts (a bound that the
parameters set, whatever the data) and the keys follow by their rank on the arc.
"""

from __future__ import annotations

from collections import deque

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import checked, materialise

CELL_BITS = 12
POS_BITS = 62
#: Keys that one window ranks, about; arcs of more are ranked in several. Windows are fewer than keys / WINDOW_ROWS + arcs.
WINDOW_ROWS = 500_000
#: Copies of a repeated row that are written out at a time.
CHUNK = 10_000


def _position(*what) -> F.Column:
    return F.shiftrightunsigned(F.xxhash64(*what), 64 - POS_BITS)


def ring_arcs(spark: SparkSession, shards: int, vnodes: int) -> DataFrame:
    """(arc, shard, lo, hi): the arc's shard takes positions in [lo, hi); the last point's arc wraps to the first's shard."""
    points = spark.range(shards * vnodes).select(
        (F.col("id") % shards).cast("int").alias("shard"),
        _position(F.lit("ring point"), (F.col("id") % shards), F.floor(F.col("id") / shards)).alias("at"),
    )
    in_order = Window.orderBy("at", "shard")  # shards * vnodes rows
    arcs = points.select(
        (F.row_number().over(in_order) - 1).alias("arc"), "shard",
        F.coalesce(F.lag("at").over(in_order) + 1, F.lit(0)).alias("lo"), (F.col("at") + 1).alias("hi"),
    )
    first = arcs.where("arc = 0").select(F.lit(shards * vnodes).alias("arc"), "shard")
    tail = first.crossJoin(arcs.agg(F.max("hi").alias("lo"))).select("arc", "shard", "lo", F.lit(1 << POS_BITS).alias("hi"))
    return arcs.unionByName(tail)


def plan_segments(arcs: list[tuple[int, int, int]], capacity: dict[int, int]) -> list[tuple[int, int, int, int, int]]:
    """From (arc, shard, keys) in ring order to (arc, lo, hi, shard, slot): ranks lo..hi-1 of the arc go to the shard's slots from slot on."""
    free, used, segments, over = dict(capacity), dict.fromkeys(capacity, 0), [], {}

    def put(arc: int, lo: int, n: int, shard: int) -> None:
        segments.append((arc, lo, lo + n, shard, used[shard]))
        used[shard] += n
        free[shard] -= n

    for arc, shard, n in arcs:
        own = min(n, free[shard])
        if own:
            put(arc, 0, own, shard)
        if own < n:
            over[arc] = (own, n)
    waiting: deque[list[int]] = deque()
    for lap in range(2):
        for arc, shard, _ in arcs:
            while waiting and free[shard]:
                origin, lo, hi = waiting[0]
                n = min(hi - lo, free[shard])
                put(origin, lo, n, shard)
                if lo + n == hi:
                    waiting.popleft()
                else:
                    waiting[0][1] = lo + n
            if lap == 0 and arc in over:
                waiting.append([arc, *over[arc]])
    if waiting:
        raise ValueError("capacities sum to less than the number of keys")
    return segments


def capacities(rows: int, shards: int, slack: float | None) -> dict[int, int]:
    """With slack: ceil((1 + slack) * rows / shards) each. Without: shares of rows that differ by one at most and sum to rows."""
    if slack is None:
        return {s: rows // shards + (s < rows % shards) for s in range(shards)}
    most = -int(-(1 + slack) * rows // shards)
    return dict.fromkeys(range(shards), most)


def assign_shards(
    docs: DataFrame, shards: int, vnodes: int = 128, slack: float | None = None, id_col: str = "doc_id", text_col: str = "text", window_rows: int = WINDOW_ROWS, chunk: int = CHUNK
) -> DataFrame:
    """One row for each row: doc_id, size, text_crc32, shard, slot (gapless from 0 in each shard).

    The key is the id; a null id is a key like any other, a null text has size 16 and the crc of
    no bytes. Rows alike in id, size and crc are counted before they are dealt. All rows of one
    id start on one arc, whatever their texts, and go on clockwise from its shard when that is
    full, in the order of a hash of id, size and crc; an arc of many rows is ranked in ranges of
    that hash, and a row repeated very often is written out in chunks, so that neither is one
    task's work. No shard takes more than its capacity. An empty table gives no rows.
    """
    spark = docs.sparkSession
    text = F.coalesce(F.col(text_col), F.lit("")).cast("binary")
    keys = (
        checked(docs, id_col, text_col)
        .select(F.col(id_col).alias("doc_id"), (F.octet_length(text).cast("long") + 16).alias("size"), F.crc32(text).alias("text_crc32"))
        .groupBy("doc_id", "size", "text_crc32")
        .agg(F.count("*").alias("alike"))
        .withColumn("at", _position(F.lit("key"), "doc_id"))
        .withColumn("turn", _position(F.lit("turn"), "doc_id", "size", "text_crc32"))
    )
    arcs = ring_arcs(spark, shards, vnodes)
    shift = POS_BITS - CELL_BITS
    cells = arcs.withColumn("cell", F.explode(F.sequence(F.shiftright("lo", shift), F.shiftright(F.greatest(F.col("hi") - 1, F.col("lo")), shift))))
    keys = keys.withColumn("cell", F.shiftright("at", shift))
    on_arc = (keys["cell"] == cells["cell"]) & (keys["at"] >= cells["lo"]) & (keys["at"] < cells["hi"])
    keys = materialise(keys.join(F.broadcast(cells), on_arc).select("arc", "turn", "doc_id", "size", "text_crc32", "alike"), "ring-keys")

    counts = {r["arc"]: (r["n"], r["keys"]) for r in keys.groupBy("arc").agg(F.sum("alike").alias("n"), F.count("*").alias("keys")).collect()}  # shards * vnodes + 1 rows at most
    ring = [(r["arc"], r["shard"], counts.get(r["arc"], (0, 0))[0]) for r in arcs.select("arc", "shard").orderBy("arc").collect()]
    segments = spark.createDataFrame(
        plan_segments(ring, capacities(sum(n for n, _ in counts.values()), shards, slack)), "arc int, from_rank long, to_rank long, shard int, first_slot long"
    )
    # arcs of many keys in ranges of the hash, each with the rows before it
    pieces = F.broadcast(spark.createDataFrame([(arc, -(-n // window_rows)) for arc, (_, n) in counts.items()], "arc int, pieces int"))
    pieced = keys.join(pieces, "arc").withColumn("piece", F.floor(F.col("turn") / float(1 << POS_BITS) * F.col("pieces"))).drop("pieces")
    earlier = Window.partitionBy("arc").orderBy("piece").rowsBetween(Window.unboundedPreceding, -1)
    starts = pieced.groupBy("arc", "piece").agg(F.sum("alike").alias("n")).select("arc", "piece", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("start"))
    along = Window.partitionBy("arc", "piece").orderBy("turn", "doc_id", "size", "text_crc32").rowsBetween(Window.unboundedPreceding, 0)
    placed = pieced.withColumn("upto", F.sum("alike").over(along)).join(F.broadcast(starts), ["arc", "piece"])  # one row for each window
    first = placed.select("arc", "doc_id", "size", "text_crc32", "alike", (F.col("start") + F.col("upto") - F.col("alike")).alias("rank"))

    nth = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), n.cast("long") - 1))
    few = first.where(F.col("alike") <= chunk)
    many = first.where(F.col("alike") > chunk).withColumn("chunk", nth(F.ceil(F.col("alike") / chunk))).repartition("doc_id", "size", "text_crc32", "chunk")
    many = many.withColumn("rank", F.col("rank") + F.col("chunk") * chunk).withColumn("alike", F.least(F.lit(chunk), F.col("alike") - F.col("chunk") * chunk)).drop("chunk")
    ranked = few.unionByName(many).withColumn("nth", nth(F.col("alike"))).withColumn("rank", F.col("rank") + F.col("nth"))
    inside = (ranked["arc"] == segments["arc"]) & (ranked["rank"] >= segments["from_rank"]) & (ranked["rank"] < segments["to_rank"])
    return ranked.join(F.broadcast(segments), inside).select(
        "doc_id", "size", "text_crc32", "shard", (F.col("first_slot") + F.col("rank") - F.col("from_rank")).alias("slot")
    )


def op5_ring_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The law held is `rows`: capacities are shares of the rows that differ by one at most."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return assign_shards(docs, 40).select(
        "doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard")
    )
