"""Exact dedup over a persistent digest index.

The index is a table bucketed and sorted by the SHA-256 of the normalised text. A batch is
reduced to one row for each digest, anti-joined with the index by sort-merge on the
buckets, and what is new is appended. Later batches meet the entries of earlier ones. Which
digests are hot is judged by the batch's own counts.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ascii_lower, attach, checked, drop_table, fresh_path, materialise, numbered, partitions, written_no


def digest_rows(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(row_no, doc_id, digest) of every row; row_no tells repeated rows apart."""
    return numbered(checked(docs, id_col, text_col, *written_no(docs))).select(
        "row_no",
        F.col(id_col).alias("doc_id"),
        F.unhex(F.sha2(ascii_lower(text_col).cast("binary"), 256)).alias("digest"),
    )


class DigestIndex:
    """A bucketed table of digest, keep_id, group_size and attempt, with its number of buckets and its finished batches beside it.

    `path` holds three folders: entries (the bucketed files), about (the number of buckets) and
    batches (a line for each finished batch). An append that failed half-way has entries but no
    line, so nobody reads them, and a batch that is appended again changes nothing. One writer
    at a time.
    """

    BATCHES = "batch string, attempt string"

    def __init__(self, spark: SparkSession, path: str | None = None, buckets: int | None = None):
        self.spark = spark
        self.path = path or fresh_path(spark, "digest-index")
        stored = self._read("about", "buckets int")
        if stored and buckets not in (None, stored[0]["buckets"]):
            raise ValueError(f"the index at {self.path} has {stored[0]['buckets']} buckets, not {buckets}")
        self.buckets = stored[0]["buckets"] if stored else buckets or partitions(spark)
        self.table = f"digest_index_{uuid.uuid4().hex}"
        spark.sql(
            f"CREATE TABLE {self.table} (digest BINARY, keep_id BIGINT, group_size BIGINT, attempt STRING) "
            f"USING parquet CLUSTERED BY (digest) SORTED BY (digest) INTO {self.buckets} BUCKETS LOCATION '{self.path}/entries'"
        )
        if not stored:
            spark.createDataFrame([(self.buckets,)], "buckets int").coalesce(1).write.mode("overwrite").json(f"{self.path}/about")

    def _read(self, folder: str, schema: str) -> list:
        place = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{folder}")
        there = place.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).exists(place)
        return self.spark.read.schema(schema).json(f"{self.path}/{folder}").collect() if there else []

    def finished(self) -> dict[str, str]:
        """batch -> attempt: one short line for each append ever made."""
        return {r["batch"]: r["attempt"] for r in self._read("batches", self.BATCHES)}

    def entries(self) -> DataFrame:
        """The entries of finished batches."""
        return self.spark.table(self.table).where(F.col("attempt").isin(list(self.finished().values())))

    def append(self, groups: DataFrame, batch: str) -> str:
        """Add an entry for each of `groups` (digest, keep_id, group_size; one row a digest) that the index lacks; returns the batch's attempt."""
        done = self.finished()
        if batch in done:
            return done[batch]
        attempt = uuid.uuid4().hex
        new = groups.join(self.entries().select("digest").hint("merge"), "digest", "left_anti")
        new = new.select("digest", "keep_id", "group_size", F.lit(attempt).alias("attempt"))
        new.repartition(self.buckets, "digest").sortWithinPartitions("digest").write.insertInto(self.table)
        self.spark.catalog.refreshTable(self.table)
        self.spark.createDataFrame([(batch, attempt)], self.BATCHES).coalesce(1).write.mode("append").json(f"{self.path}/batches")
        return attempt

    def drop(self, files: bool = False) -> None:
        """Forget the table; its files stay at `path` for a later session unless `files`."""
        drop_table(self.spark, self.table, self.path if files else None)


def deduplicate(docs: DataFrame, index: DigestIndex | None = None, id_col: str = "doc_id", text_col: str = "text", batch: str | None = None) -> DataFrame:
    """One row for each row of `docs`: row_no, doc_id, keep_id, group_size, kept, text_sha256.

    A text is kept once over all batches that met `index` (a new one for this call by default):
    an entry of an earlier batch beats later rows, and within a batch the largest doc_id stays.
    group_size counts the rows of the batch that brought the entry. A `batch` that was finished
    before gives the same rows again and adds nothing. Null texts count as empty, null ids as
    lowest; of rows repeated whole, one stays. An empty table gives no rows.
    """
    spark = docs.sparkSession
    own = index or DigestIndex(spark)
    rows = materialise(digest_rows(docs, id_col, text_col), "digests")
    best = rows.groupBy("digest").agg(F.max(F.struct("doc_id", "row_no")).alias("keep"), F.count("*").alias("alike"))
    groups = materialise(best, "digest-groups")  # one row a digest, whatever the joins below move
    attempt = own.append(groups.select("digest", F.col("keep.doc_id").alias("keep_id"), F.col("alike").alias("group_size")), batch or uuid.uuid4().hex)
    met = groups.select("digest", "alike", F.col("keep.row_no").alias("best_row")).join(own.entries().hint("merge"), "digest")
    named = materialise(met.select("digest", "alike", "keep_id", "group_size", F.when(F.col("attempt") == attempt, F.col("best_row")).alias("keep_row")), "digest-entries")
    if index is None:
        own.drop(files=True)
    return attach(rows, named, "digest", "alike", rows.count()).select(
        "row_no",
        "doc_id",
        "keep_id",
        "group_size",
        F.coalesce(F.col("row_no") == F.col("keep_row"), F.lit(False)).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
    )


def op2_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return deduplicate(docs).select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


ORACLE = """
WITH d AS (
  SELECT doc_id, sha256(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')) AS text_sha256
  FROM documents
)
SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size,
       doc_id = max(doc_id) OVER w AS kept, text_sha256
FROM d WINDOW w AS (PARTITION BY text_sha256)
"""
