"""String tables and SQL pieces that the queries share."""

from __future__ import annotations

from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from repetix.sources.tables import load_table

#: Every length up to here; the maximisers of the short strings are below it.
SHORT = tuple(range(1, 13))


def strings(spark: SparkSession, sf_dir: str, table: str, id_col: str, text_col: str = "text", *more: str) -> DataFrame:
    df = load_table(spark, sf_dir, table, [id_col, text_col, *more])
    return df.select(F.col(id_col).alias("id"), F.coalesce(text_col, F.lit("")).alias("text"), *more)


def items(spark: SparkSession, sf_dir: str) -> DataFrame:
    return strings(spark, sf_dir, "benchmark", "item_id")


def docs(spark: SparkSession, sf_dir: str, *more: str) -> DataFrame:
    return strings(spark, sf_dir, "documents", "doc_id", "text", *more)


def turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, text) of conversation turns, the id made of both keys."""
    df = load_table(spark, sf_dir, "conversations", ["conv_id", "turn", "text"])
    return df.select((F.col("conv_id") * 100000 + F.col("turn")).alias("id"), F.coalesce("text", F.lit("")).alias("text"))


ITEMS = "SELECT item_id AS id, coalesce(text, '') AS text FROM benchmark"
DOCS = "SELECT doc_id AS id, coalesce(text, '') AS text FROM documents"
TURNS = "SELECT conv_id * 100000 + turn AS id, coalesce(text, '') AS text FROM conversations"


def sql_list(values: Iterable[int]) -> str:
    return "[" + ", ".join(map(str, values)) + "]"


def windows_cte(source: str, lengths: Iterable[int] | None) -> str:
    """CTEs s(id, text), ks(id, k) and w(id, k, i, g): every window; all lengths if `lengths` is None."""
    ks = "generate_series(1, length(text))" if lengths is None else sql_list(lengths)
    return f"""s AS ({source}), ks AS (SELECT id, text, unnest({ks}) AS k FROM s),
w AS (SELECT id, k, i, substr(text, i, k) AS g FROM (SELECT id, text, k, unnest(generate_series(1, length(text) - k + 1)) AS i FROM ks WHERE length(text) >= k))"""


def profile_cte(source: str, lengths: Iterable[int] | None) -> str:
    """windows_cte plus p(id, k, d)."""
    return windows_cte(source, lengths) + """,
p AS (SELECT ks.id, CAST(ks.k AS INTEGER) AS k, coalesce(c.d, 0) AS d FROM ks LEFT JOIN (SELECT id, k, count(DISTINCT g) AS d FROM w GROUP BY id, k) c ON ks.id = c.id AND ks.k = c.k)"""


def profile_sql(source: str, lengths: Iterable[int] | None) -> str:
    return f"WITH {profile_cte(source, lengths)} SELECT id, k, d FROM p"


DELTA = "SELECT {by}, max(d / k) AS delta, min(k) FILTER (d / k = top) AS k_hat FROM (SELECT *, max(d / k) OVER (PARTITION BY {by}) AS top FROM {p}) GROUP BY {by}"


def delta_of(p: str, by: str = "id") -> str:
    return DELTA.format(by=by, p=p)


class Registry:
    """Collects queries and their oracles in a module."""

    def __init__(self):
        self.queries: dict[str, Callable] = {}
        self.oracles: dict[str, str] = {}

    def __call__(self, name: str, oracle: str | None = None):
        def add(f: Callable) -> Callable:
            self.queries[name] = f
            if oracle:
                self.oracles[name] = oracle
            return f

        return add
