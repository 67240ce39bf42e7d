"""Chat formatting with collapse of cumulative snapshots.

A log often holds a conversation again and again as it grows. Each turn gets a hash that
depends on its place, role and text; the exclusive-or of a conversation's first hashes is a
rolling hash of that prefix. A conversation whose whole hash is a proper prefix hash of a
longer one goes by an anti-join, and of equal conversations the least id stays. Only the
conversations that stay are rendered.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import checked, materialise

OPEN, CLOSE = "<|im_start|>", "<|im_end|>"


def prefix_hashes(turns: DataFrame) -> DataFrame:
    """conv_id, place (from 1), h1, h2 (rolling hash up to the place), last; rows repeated whole count once."""
    hashed = turns.select(
        "conv_id", "turn", F.xxhash64(F.lit(1), "role", F.lit("/"), "text").alias("c1"), F.xxhash64(F.lit(2), "text", F.lit("/"), "role").alias("c2")
    )
    order = Window.partitionBy("conv_id").orderBy("turn", "c1", "c2")
    same = F.lag(F.struct("turn", "c1", "c2")).over(order).eqNullSafe(F.struct("turn", "c1", "c2"))
    placed = hashed.withColumn("same", same).where(~F.col("same")).drop("same").withColumn("place", F.row_number().over(order))
    so_far = order.rowsBetween(Window.unboundedPreceding, 0)
    return placed.select(
        "conv_id",
        "place",
        F.bit_xor(F.xxhash64("place", "c1", "c2")).over(so_far).alias("h1"),
        F.bit_xor(F.xxhash64("c2", "place", "c1")).over(so_far).alias("h2"),
        F.lead("place").over(order).isNull().alias("last"),
    )


def maximal(turns: DataFrame) -> DataFrame:
    """conv_id, n_turns, n_copies of the conversations that no longer one continues; of equal ones the least id."""
    hashes = materialise(prefix_hashes(turns), "prefix-hashes")
    whole = hashes.where("last").groupBy("h1", "h2", F.col("place").alias("n_turns")).agg(F.min("conv_id").alias("conv_id"), F.count("*").alias("n_copies"))
    inner = hashes.where("NOT last").select("h1", "h2", F.col("place").alias("n_turns")).distinct()
    return whole.join(inner, ["h1", "h2", "n_turns"], "left_anti").select("conv_id", "n_turns", "n_copies")


def rendered(role: str, text: str) -> Column:
    """One turn between marks; marks inside a text are broken up, so that a text can't close its turn."""
    said = F.replace(F.col(text), F.lit("<|"), F.lit("< |"))
    return F.concat(F.lit(OPEN), F.col(role), F.lit("\n"), said, F.lit(CLOSE + "\n"))


def collapse_and_render(conversations: DataFrame) -> DataFrame:
    """conv_id, n_turns, n_copies, rendered: one row for each maximal conversation.

    Columns read: conv_id, turn, role, text. Turns are ordered by turn number, then content;
    null turns come first. A null role is `unknown`, a null text empty, a null conv_id a
    conversation like any other (never the least id of equal ones). A row is one conversation,
    so its size is that of the conversation; rows repeated whole count once. An empty table
    gives no rows.
    """
    turns = checked(conversations, "conv_id", "turn", "role", "text").select(
        "conv_id", "turn", F.coalesce("role", F.lit("unknown")).alias("role"), F.coalesce("text", F.lit("")).alias("text")
    )
    kept = maximal(turns)
    mine = turns.withColumnRenamed("conv_id", "of")
    joined = mine.join(kept, mine["of"].eqNullSafe(kept["conv_id"]))
    said = F.struct("turn", F.xxhash64(F.lit(1), "role", F.lit("/"), "text").alias("c1"), F.xxhash64(F.lit(2), "text", F.lit("/"), "role").alias("c2"), rendered("role", "text").alias("said"))
    together = joined.groupBy("conv_id", "n_turns", "n_copies").agg(F.sort_array(F.collect_set(said)).alias("turns"))
    return together.select("conv_id", "n_turns", "n_copies", F.array_join(F.transform("turns", lambda t: t["said"]), "").alias("rendered"))


def op10_snapshot_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = collapse_and_render(spark.read.parquet(f"{sf_dir}/conversations.parquet"))
    return out.select("conv_id", F.col("n_turns").cast("long").alias("n_turns"), "n_copies", "rendered")


ORACLE = """
WITH t AS (SELECT DISTINCT conv_id, turn, coalesce(role, 'unknown') AS role, coalesce(text, '') AS text FROM conversations),
c AS (
  SELECT conv_id, count(*) AS n_turns, list(role || chr(1) || text ORDER BY turn) AS said,
         string_agg('<|im_start|>' || role || chr(10) || replace(text, '<|', '< |') || '<|im_end|>' || chr(10), '' ORDER BY turn) AS rendered
  FROM t GROUP BY conv_id
), p AS (SELECT DISTINCT list_slice(said, 1, k) AS head FROM (SELECT said, unnest(generate_series(1, n_turns - 1)) AS k FROM c WHERE n_turns > 1))
SELECT min(conv_id) AS conv_id, n_turns, count(*) AS n_copies, min(rendered) AS rendered
FROM c WHERE said NOT IN (SELECT head FROM p) GROUP BY said, n_turns
"""
