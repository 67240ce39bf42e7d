"""The corpus pipeline: quality, exact copies, near copies, benchmark passages, tokens.

Each stage takes (spark, docs, sf_dir) and works on all rows its predecessor kept. All but the
last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from repetix.llm import exact_dedup, latent_votes, rank_array_bpe, simhash_trie, suffix_decontam
from repetix.llm.common import checked, materialise, with_row_numbers, without_rows

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep documents whose neighbours' votes say quality 1."""
    model = latent_votes.fit_votes(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return latent_votes.score_documents(docs, model, keep=COLUMNS).where("score >= 0.5").select(*COLUMNS)


def exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts keep that of the largest doc_id."""
    docs = with_row_numbers(checked(docs, *COLUMNS))
    return without_rows(docs, exact_dedup.deduplicate(docs).where("NOT kept"))


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep the least doc_id of each component of near fingerprints."""
    docs = with_row_numbers(checked(docs, *COLUMNS))
    return without_rows(docs, simhash_trie.near_duplicates(docs).where("row_no <> keep_row"))


def benchmark_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents of whose words a twentieth or more lie in windows of test items; leave the rest as they are."""
    found = suffix_decontam.find_hits(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"), keep=COLUMNS)
    return found.where(~suffix_decontam.is_contaminated()).select(*COLUMNS)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, lang, source, n_tokens, token_ids and the digest of the decoded text."""
    found = rank_array_bpe.encode_documents(docs, rank_array_bpe.default_tokenizer(), keep=("lang", "source"))
    return found.select(
        "doc_id", "lang", "source", F.size("token_ids").cast("long").alias("n_tokens"), "token_ids", F.sha2(F.col("decoded").cast("binary"), 256).alias("decoded_sha256")
    )


STAGES = [
    ("quality classifier", quality),
    ("exact dedup", exact_copies),
    ("SimHash near-dedup", near_copies),
    ("benchmark decontamination", benchmark_passages),
    ("BPE encoding and decoding", tokens),
]

ORACLE_SQL = None  # scores, XXH64 and merges are beyond SQL; tests hold run() against a brute-force version


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for n, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if n + 1 < len(STAGES):
            docs = materialise(docs, f"stage-{n}")
    return docs
