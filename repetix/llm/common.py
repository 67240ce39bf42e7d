"""Shared pieces: the folder all executors see, materialised tables, hot-key joins."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from repetix.session import fresh_path, passing

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write `df` to the shared folder and read it back: lineage ends there, and lost executors lose nothing. The files go when the application ends."""
    path = fresh_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(passing(df.sparkSession, path))


def remove(spark: SparkSession, path: str) -> None:
    """Delete the files at `path` in whatever store it is."""
    place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(place, True)


def drop_table(spark: SparkSession, table: str, path: str | None = None) -> None:
    """Drop a table from the catalog and, if `path` is given, its files."""
    spark.sql(f"DROP TABLE IF EXISTS {table}")
    if path:
        remove(spark, path)


def ascii_lower(text: str | Column) -> Column:
    """Lower-case A-Z only; null counts as empty."""
    return F.translate(F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit("")), UPPER, UPPER.lower())


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def attach(rows: DataFrame, table: DataFrame, key: str, size: str, total: int) -> DataFrame:
    """Inner join of `rows` with `table` (one row for each key; `size` counts the key's rows).

    Keys with over a thousandth of all rows are at most a thousand, so those are broadcast;
    the rest are joined by a shuffle whose keys are all small.
    """
    bar = max(1000, total // 1000)
    hot = F.broadcast(table.where(F.col(size) > bar))
    cold = table.where(F.col(size) <= bar)
    kept = [c for c in rows.columns if c != key]
    left_over = rows.join(F.broadcast(table.where(F.col(size) > bar).select(key)), key, "left_anti")
    cols = [key, *kept, *[c for c in table.columns if c != key]]
    return rows.join(hot, key).select(cols).unionByName(left_over.join(cold, key).select(cols))


def checked(df: DataFrame, *columns: str) -> DataFrame:
    """Only the columns needed, so that other columns can't clash with the operator's own."""
    missing = [c for c in columns if c not in df.columns]
    if missing:
        raise ValueError(f"missing columns: {', '.join(missing)}")
    return df.select(*columns)


#: Rows that a broadcast may name: 8 bytes each, a few hundred MB in a hash table at most.
BROADCAST_ROWS = 4_000_000


#: The column of row numbers in a table that with_row_numbers wrote.
WRITTEN_NO = "__written_row_no"


def numbered(docs: DataFrame) -> DataFrame:
    """`docs` with row_no: the written number if there is one, else a number that holds for this one read only.

    Spark packs file splits by the cores at hand, so two reads of the same files may number them differently.
    """
    return docs.withColumn("row_no", F.col(WRITTEN_NO) if WRITTEN_NO in docs.columns else F.monotonically_increasing_id())


def written_no(docs: DataFrame) -> list[str]:
    return [c for c in docs.columns if c == WRITTEN_NO]


def with_row_numbers(docs: DataFrame) -> DataFrame:
    """A written copy of `docs` whose rows carry their numbers, so that every later read agrees on them."""
    return materialise(docs.withColumn(WRITTEN_NO, F.monotonically_increasing_id()), "numbered")


def without_rows(docs: DataFrame, dropped: DataFrame) -> DataFrame:
    """The rows of `docs`, from with_row_numbers, whose row_no isn't in `dropped`. Few of these are broadcast, so that no text moves; many are joined by a shuffle."""
    if WRITTEN_NO not in docs.columns:
        raise ValueError("rows are named by numbers that were written: with_row_numbers")
    dropped = materialise(dropped.select("row_no"), "dropped")
    few = dropped.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS
    dropped = dropped.withColumnRenamed("row_no", WRITTEN_NO)  # the caller's columns may have a row_no of their own
    return docs.join(F.broadcast(dropped) if few else dropped, WRITTEN_NO, "left_anti").drop(WRITTEN_NO)
