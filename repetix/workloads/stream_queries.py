"""One-pass streams: of users' events, and of the documents of each source as they arrive."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from repetix.plans.accuracy import sampled_lengths, window_length
from repetix.session import fresh_path, passing
from repetix.sources.tables import EVENT_TYPES, code_of, load_table
from repetix.streaming import stream_sketch as streams

from .checks import invariant
from .common import Registry, windows_cte
from .core import EVENTS, Q1, Q2, sql_print
from .sketches import M_F0, f0_sql

query = Registry()
QUERIES, ORACLES = query.queries, query.oracles
STREAMED = (1, 2, 3, 5)
ORDER = ["ts", "event_id"]


def event_symbol():
    """An event's symbol is a small letter, that before `a` for types not known."""
    return (code_of("event_type", EVENT_TYPES) + ord("a")).alias("symbol")


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    stream = spark.readStream.schema(schema).parquet(f"{sf_dir}/events.parque[t]")  # a pattern, as a stream's plain path must be a folder
    return stream.select(F.col("user_id").alias("id"), *ORDER, event_symbol())


def longest_stream(spark: SparkSession, sf_dir: str) -> int:
    """n_max of the streams: the events of the user who has most, 100,000 at least."""
    most = load_table(spark, sf_dir, "events", ["user_id"]).groupBy("user_id").count().agg(F.max("count")).first()[0]
    return max(100_000, most or 0)


def in_batches(parts: list[DataFrame], name: str) -> DataFrame:
    """A stream whose n-th micro-batch is the n-th of these tables."""
    spark = parts[0].sparkSession
    path = fresh_path(spark, name)
    for n, part in enumerate(parts):
        part.coalesce(1).write.parquet(f"{path}/part={n}")
    passing(spark, path)
    return spark.readStream.schema(parts[0].schema).option("maxFilesPerTrigger", 1).parquet(f"{path}/part=*")


STREAM_SQL = f"""WITH {windows_cte(EVENTS, STREAMED)}, p AS (SELECT id, CAST(k AS INTEGER) AS k, CAST(count(DISTINCT g) AS DOUBLE) AS d FROM w GROUP BY id, k) SELECT p.id, p.k, p.d FROM p"""


def streamed(**options):
    def run(spark, sf_dir):
        rows = streams.stream_sketch(event_stream(spark, sf_dir), ORDER, n_max=longest_stream(spark, sf_dir), lengths=list(STREAMED), cd="exact", **options)
        last = streams.latest(streams.run_to_table(rows, "stream"))
        return last.select("id", F.explode("profile").alias("p")).select("id", "p.k", "p.d")

    return run


for _name, _options in (("stream_final_profile", {"window": 2}), ("stream_window_only", {"transform": False})):
    query(_name, STREAM_SQL)(streamed(**_options))



@query("stream_naive_buffer", STREAM_SQL)
def stream_naive_buffer(spark, sf_dir):
    """The baseline that keeps the whole stream as its window."""
    return streamed(window=longest_stream(spark, sf_dir), transform=False)(spark, sf_dir)


PRINTS = f"""{windows_cte(EVENTS, STREAMED)}, f AS (SELECT id, CAST(k AS INTEGER) AS k, {sql_print('g', Q1)} AS fp1, {sql_print('g', Q2)} AS fp2 FROM (SELECT DISTINCT id, k, g FROM w))"""


@query("stream_f0_registers", f"WITH {PRINTS} {f0_sql('f')}")
def stream_f0_registers(spark, sf_dir):
    """The registers in the state after the whole stream, windows of 3 and 5 symbols by the transform and its bookmarks."""
    rows = streams.stream_sketch(event_stream(spark, sf_dir), ORDER, registers=True, n_max=longest_stream(spark, sf_dir), lengths=list(STREAMED), window=2, cd="f0", m=M_F0)
    last = streams.latest(streams.run_to_table(rows, "stream-registers"))
    return last.select("id", F.explode("registers").alias("r")).select("id", "r.*")


@query("stream_drop_policy", "SELECT user_id AS id, count(*) AS n, true AS dropped FROM events GROUP BY user_id")
def stream_drop_policy(spark, sf_dir):
    """With a low constant the transform of every stream is dropped."""
    rows = streams.stream_sketch(event_stream(spark, sf_dir), ORDER, n_max=longest_stream(spark, sf_dir), lengths=[1, 2, 4], window=3, discard_constant=1e-9)
    return streams.latest(streams.run_to_table(rows, "stream-drop")).select("id", "n", "dropped")


@query("stream_update_cost", f"SELECT id, length(text) AS n, CAST({' + '.join(f'greatest(0, length(text) - {k} + 1)' for k in STREAMED)} AS BIGINT) AS adds FROM ({EVENTS})")
def stream_update_cost(spark, sf_dir):
    """Additions to count-distinct states: one a symbol and length once there are so many symbols."""
    rows = streams.stream_sketch(event_stream(spark, sf_dir), ORDER, n_max=longest_stream(spark, sf_dir), lengths=list(STREAMED), window=2)
    return streams.latest(streams.run_to_table(rows, "stream-cost")).select("id", "n", "adds")


DELAYED = "event_id % 20 = 0"


@query(
    "stream_late_rows",
    f"SELECT e.user_id AS id, e.event_id FROM events e JOIN (SELECT user_id, max((ts, event_id)) AS last FROM events WHERE NOT {DELAYED} GROUP BY user_id) o "
    f"ON e.user_id = o.user_id WHERE {DELAYED.replace('event_id', 'e.event_id')} AND (e.ts, e.event_id) < o.last",
)
def stream_late_rows(spark, sf_dir):
    """Every twentieth event arrives after all others; those behind their user's last one go to the side table."""
    events = load_table(spark, sf_dir, "events", ["user_id", "ts", "event_id", "event_type"]).select(F.col("user_id").alias("id"), *ORDER, event_symbol())
    stream = in_batches([events.where(f"NOT {DELAYED}"), events.where(DELAYED)], "late-events")
    rows = streams.stream_sketch(stream, ORDER, n_max=longest_stream(spark, sf_dir), lengths=[1, 2], transform=False)
    return streams.late_rows(streams.run_to_table(rows, "stream-late")).select("id", "event_id")


def runs_by_batch(spark, sf_dir):
    """(id, n, runs, words, dropped): the state of every user's stream after each quarter of the events."""
    events = load_table(spark, sf_dir, "events", ["user_id", "ts", "event_id", "event_type"]).select(F.col("user_id").alias("id"), *ORDER, event_symbol())
    quarters = [r for r in events.select(F.percentile_approx("event_id", F.array(*map(F.lit, (0.25, 0.5, 0.75))))).first()[0] or []]
    edges = [None, *quarters, None]
    inside = lambda lo, hi: (F.lit(lo is None) | (F.col("event_id") > F.lit(lo))) & (F.lit(hi is None) | (F.col("event_id") <= F.lit(hi)))
    stream = in_batches([events.where(inside(lo, hi)) for lo, hi in zip(edges, edges[1:], strict=False)], "quarters")
    rows = streams.stream_sketch(stream, ORDER, n_max=longest_stream(spark, sf_dir), lengths=list(STREAMED), window=2)
    return streams.run_to_table(rows, "stream-runs").select("id", "n", "runs", "words", "dropped")


query("stream_runs_by_batch")(runs_by_batch)


@invariant("stream_runs_never_fall")
def runs_never_fall(spark, sf_dir):
    """Runs without the marker only grow, and never outnumber the symbols."""
    before = F.lag("runs").over(Window.partitionBy("id").orderBy("n"))
    return runs_by_batch(spark, sf_dir).select(((F.col("runs") >= F.coalesce(before, F.lit(0))) & (F.col("runs") <= F.col("n"))).alias("holds"))


def document_streams(spark, sf_dir, transform: bool = True, constant: float = 8.0, longest: int | None = None):
    """(id, n, delta, k_hat, bound, certified, runs, dropped_at, words, state_bytes) of the documents of each source, read in doc_id order as one stream.

    The window and the drop rule are those of the largest source; lengths go on beyond the window up to four times its size,
    or up to `longest`.
    """
    documents = load_table(spark, sf_dir, "documents", ["doc_id", "source", "text"])
    n_max = documents.groupBy("source").agg(F.sum(F.length("text")).alias("n")).agg(F.max("n")).first()[0] or 1
    lengths = sampled_lengths(min(n_max, longest or 4 * window_length(n_max)), 2.0)
    stream = spark.readStream.schema(documents.schema).parquet(f"{sf_dir}/documents.parque[t]")
    stream = stream.select(F.coalesce("source", F.lit("")).alias("id"), "doc_id", "text")
    rows = streams.stream_sketch(stream, ["doc_id"], n_max=n_max, lengths=lengths, m=4096, transform=transform, discard_constant=constant)
    last = streams.latest(streams.run_to_table(rows, "document-streams"))
    return last.select("id", "n", "delta", "k_hat", "bound", "certified", "runs", "dropped_at", "words", "state_bytes")


@query("stream_documents_by_source")
def stream_documents(spark, sf_dir):
    """Without the transform, as the published runs have it; `certified` tells that no length beyond the window could win."""
    return document_streams(spark, sf_dir, transform=False)


@query("stream_documents_with_transform")
def stream_documents_transform(spark, sf_dir):
    """With the transform until the drop rule ends it."""
    return document_streams(spark, sf_dir)


@query(
    "stream_state_size",
    "SELECT coalesce(source, '') AS id, CAST(sum(length(text)) AS BIGINT) AS n, true AS within FROM documents GROUP BY ALL",
)
def stream_state_size(spark, sf_dir):
    """The state is the window and a fixed number of words a length, whatever the stream's length."""
    rows = document_streams(spark, sf_dir, transform=False)
    n_max = rows.agg(F.max("n")).first()[0] or 1
    window = window_length(n_max)
    lengths = len(sampled_lengths(min(n_max, 4 * window), 2.0))
    return rows.select("id", "n", (F.col("words") <= window + 512 * lengths).alias("within"))
