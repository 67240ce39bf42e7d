"""Tables and derived string sets."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def load_table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    """A Parquet table, with only these columns read."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def ensure_columns(df: DataFrame, **types: str) -> DataFrame:
    """Fails unless the columns are there with these types."""
    have = dict(df.dtypes)
    wrong = [f"{c} {t} (have {have.get(c)})" for c, t in types.items() if have.get(c) != t]
    if wrong:
        raise ValueError("columns needed: " + ", ".join(wrong))
    return df


def read_files(spark: SparkSession, path: str, form: str = "text") -> DataFrame:
    """(id, text) of raw files: `text` is one string for each file, `lines` one for each line, `binary` bytes."""
    if form == "binary":
        return spark.read.format("binaryFile").load(path).select(F.col("path").alias("id"), F.col("content").alias("text"))
    whole = spark.read.text(path, wholetext=form == "text")
    return whole.select(F.concat_ws("#", F.col("_metadata.file_path"), F.monotonically_increasing_id().cast("string")).alias("id"), F.col("value").alias("text"))


def _sequences(df: DataFrame, key: str, order: list[str], symbol) -> DataFrame:
    turns = F.sort_array(F.collect_list(F.struct(*order, symbol.alias("symbol"))))
    return df.groupBy(F.col(key).alias("id")).agg(F.transform(turns, lambda t: t["symbol"]).alias("text"))


def code_of(column: str, values: list[str]):
    """Index of the value in a fixed list shared by all strings; -1 for others."""
    return F.coalesce(F.array_position(F.array(*map(F.lit, values)), F.col(column)).cast("int") - 1, F.lit(-1))


EVENT_TYPES = ["click", "error", "purchase", "signup", "view"]


def event_sequences(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, text array<int>): each user's event types in time."""
    events = load_table(spark, sf_dir, "events", ["event_id", "ts", "user_id", "event_type"])
    return _sequences(events, "user_id", ["ts", "event_id"], code_of("event_type", EVENT_TYPES))


def order_sequences(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, text array<int>): each customer's order states by date."""
    orders = load_table(spark, sf_dir, "orders", ["o_custkey", "o_orderkey", "o_orderdate", "o_orderstatus"])
    return _sequences(orders, "o_custkey", ["o_orderdate", "o_orderkey"], code_of("o_orderstatus", ["F", "O", "P"]))


def line_sequences(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, text array<int>): each supplier's line flags by ship date."""
    order = ["l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_extendedprice"]
    lines = load_table(spark, sf_dir, "lineitem", ["l_suppkey", *order, "l_returnflag", "l_linestatus"])
    flag = 2 * code_of("l_returnflag", ["A", "N", "R"]) + code_of("l_linestatus", ["F", "O"])
    return _sequences(lines, "l_suppkey", order, flag)
