"""Comparators: transform runs, parses, grammars, codecs, entropies, the local-maximum heuristic."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from repetix.operators import distance, metrics, profile, sketch
from repetix.operators.distinct import Hll
from repetix.sources.tables import load_table
from repetix.session import written

from .common import DOCS, ITEMS, TURNS, Registry, delta_of, docs, items, profile_cte, strings, turns

query = Registry()
QUERIES, ORACLES = query.queries, query.oracles
PARITIES = (64, 256, 1024, 4096)

# suffixes in binary order with the empty one first are what a marker below all symbols gives
BWT = f"""s AS ({ITEMS}), x AS (SELECT id, text, unnest(generate_series(1, length(text) + 1)) AS i FROM s),
b AS (SELECT id, row_number() OVER (PARTITION BY id ORDER BY substr(text, i)) AS place, CASE WHEN i = 1 THEN 0 ELSE unicode(substr(text, i - 1, 1)) + 1 END AS sym FROM x),
l AS (SELECT *, row_number() OVER (PARTITION BY id ORDER BY sym, place) AS lf FROM b)"""


@query("bwt_items", f"WITH {BWT} SELECT id, place, CAST(sym AS BIGINT) AS sym, lf FROM l")
def bwt_items(spark, sf_dir):
    out = profile.transforms(items(spark, sf_dir))
    return out.select("id", F.posexplode(F.arrays_zip("bwt", "lf"))).select("id", (F.col("pos") + 1).cast("bigint").alias("place"), F.col("col.bwt").alias("sym"), F.col("col.lf").alias("lf"))


@query("bwt_sql_items", f"WITH {BWT} SELECT id, place, CAST(sym AS BIGINT) AS sym FROM l")
def bwt_sql_items(spark, sf_dir):
    """The same without Python, for short strings: suffixes as rows, sorted in a window."""
    suffixes = items(spark, sf_dir).select("id", "text", F.explode(F.sequence(F.lit(1), F.length("text") + 1)).alias("i"))
    order = Window.partitionBy("id").orderBy(F.substring("text", F.col("i"), F.length("text")))
    symbol = F.when(F.col("i") == 1, F.lit(0)).otherwise(F.ascii(F.substring("text", F.col("i") - 1, F.lit(1))) + 1)
    return suffixes.select("id", F.row_number().over(order).cast("bigint").alias("place"), symbol.cast("bigint").alias("sym"))


RUNS = """SELECT id, count(*) FILTER (before IS NULL OR before <> sym) AS r FROM (SELECT id, sym, lag(sym) OVER (PARTITION BY id ORDER BY place) AS before FROM {b}) GROUP BY id"""


@query("bwt_runs_items", f"WITH {BWT}, a AS ({RUNS.format(b='b')}), c AS ({RUNS.format(b='b WHERE sym > 0')}) SELECT a.id, a.r, c.r AS r_no_marker FROM a JOIN c ON a.id = c.id")
def bwt_runs(spark, sf_dir):
    return profile.parse_sizes(items(spark, sf_dir)).select("id", "r", "r_no_marker")


@query(
    "lz77_phrases_items",
    f"""WITH RECURSIVE s AS ({ITEMS}), z(id, text, pos, phrases) AS (
SELECT id, text, 1, 0 FROM s UNION ALL
SELECT id, text, pos + greatest(1, len(list_filter(generate_series(1, length(text) - pos + 1), lambda n: contains(substr(text, 1, pos + n - 2), substr(text, pos, n))))), phrases + 1
FROM z WHERE pos <= length(text))
SELECT id, CAST(max(phrases) AS BIGINT) AS z FROM z GROUP BY id""",
)
def lz77_items(spark, sf_dir):
    return profile.parse_sizes(items(spark, sf_dir)).select("id", "z")


@query("parse_sizes_documents")
def parse_sizes_documents(spark, sf_dir):
    return profile.parse_sizes(docs(spark, sf_dir))


@query("lz78_phrases_turns")
def lz78_turns(spark, sf_dir):
    return profile.parse_sizes(turns(spark, sf_dir)).select("id", "z78")


@query("grammar_size_turns")
def grammar_turns(spark, sf_dir):
    return profile.grammar_size(turns(spark, sf_dir))


@query("codec_sizes_documents")
def codec_sizes(spark, sf_dir):
    return profile.codec_sizes(docs(spark, sf_dir))


@query(
    "entropy0_documents",
    f"""WITH s AS ({DOCS}), c AS (SELECT id, unnest(string_split(text, '')) AS sym FROM s), n AS (SELECT id, sym, count(*) AS n FROM c WHERE sym <> '' GROUP BY id, sym),
p AS (SELECT id, n, n / sum(n) OVER (PARTITION BY id) AS p FROM n) SELECT id, CAST(0 AS INTEGER) AS k, -sum(p * log2(p)) AS bits FROM p GROUP BY id""",
)
def entropy0(spark, sf_dir):
    return profile.entropies(docs(spark, sf_dir).where("text <> ''"), [0])


def entropy_sql(k: int) -> str:
    return f"""WITH s AS ({TURNS}), c AS (SELECT id, substr(text, i, {k}) AS ctx, substr(text, i + {k}, 1) AS sym FROM (SELECT id, text, unnest(generate_series(1, length(text) - {k})) AS i FROM s WHERE length(text) > {k})),
n AS (SELECT id, ctx, sym, count(*) AS n FROM c GROUP BY ALL), p AS (SELECT id, n, n / sum(n) OVER (PARTITION BY id, ctx) AS p, sum(n) OVER (PARTITION BY id) AS m FROM n)
SELECT s.id, CAST({k} AS INTEGER) AS k, coalesce(b.bits, 0) AS bits FROM s LEFT JOIN (SELECT id, -sum(n * log2(p)) / max(m) AS bits FROM p GROUP BY id) b ON s.id = b.id"""


for _k in (1, 2, 4):
    query(f"entropy{_k}_turns", entropy_sql(_k))(lambda spark, sf_dir, k=_k: profile.entropies(turns(spark, sf_dir), [k]))


def local_sql(strict: bool) -> str:
    return f"""WITH {profile_cte(ITEMS, range(1, 41))}, q AS (SELECT id, k, d / k AS ratio, lead(d / k) OVER (PARTITION BY id ORDER BY k) AS after FROM p),
t AS (SELECT id, ratio, k FROM q WHERE after IS NULL OR after {'<' if strict else '<='} ratio QUALIFY row_number() OVER (PARTITION BY id ORDER BY k) = 1) SELECT id, ratio AS delta, k AS k_hat FROM t"""


for _name, _strict in (("local_max_delta", True), ("local_max_plateau_delta", False)):
    query(_name, local_sql(_strict))(lambda spark, sf_dir, strict=_strict: profile.local_maximum(profile.substring_profile(items(spark, sf_dir), range(1, 41)), strict))


def exact_counts(rows, lengths):
    return profile.substring_profile(rows, lengths)


def sketched_counts(rows, lengths):
    return HLL.estimates(sketch.build_sketch(rows, cd=HLL, lengths=lengths), ["id", "k"])


HLL = Hll(14)
query("local_max_uncapped", local_sql(True))(lambda spark, sf_dir: sketch.grow_to_local_maximum(items(spark, sf_dir), exact_counts))
query("local_max_sketched")(lambda spark, sf_dir: sketch.grow_to_local_maximum(items(spark, sf_dir), sketched_counts))


@query("local_max_misses")
def local_max_misses(spark, sf_dir):
    """Strings on which the heuristic is wrong: documents, and adversarial ones."""
    rows = written(docs(spark, sf_dir).select(F.col("id").cast("string").alias("id"), "text").where("text <> ''").unionByName(adversarial(spark)).repartition(16), "strings")
    rules = [sketch.grow_to_local_maximum(rows, exact_counts, strict).select("id", F.col("delta").alias("heuristic"), F.lit(name).alias("stops_before")) for name, strict in (("fall", True), ("stand", False))]
    missed = profile.exact_delta(rows).join(rules[0].unionByName(rules[1]), "id").where("heuristic < delta - 1e-9")
    return missed.select("id", "n", "delta", "k_hat", "heuristic", "stops_before")


def adversarial(spark):
    """(id, text): strings whose first local maximum is not the greatest."""
    parity = spark.range(4096).select(F.col("id"), (F.bit_count("id") % 2).cast("string").alias("c"))
    out = None
    for n in (64, 256, 1024, 4096):
        one = parity.where(F.col("id") < n).agg(F.sort_array(F.collect_list(F.struct("id", "c"))).alias("s")).select(
            F.lit(f"parity-{n}").alias("id"), F.array_join(F.transform("s", lambda x: x["c"]), "").alias("text")
        )
        out = one if out is None else out.unionByName(one)
    others = spark.createDataFrame([("plateau", "aaaabaabbababb"), ("two scales", "a" * 30 + "abbabaab" * 4 + "b" * 30)], "id string, text string")
    return out.unionByName(others)


PARITY = f"""SELECT 'parity-' || n || '-' || (c_custkey // n) AS id, string_agg(CAST(bit_count(c_custkey) % 2 AS VARCHAR), '' ORDER BY c_custkey) AS text
FROM customer, (SELECT unnest([{", ".join(map(str, PARITIES))}]) AS n) GROUP BY ALL"""


def parities(spark, sf_dir):
    """(id, text): parities of the bits of customer keys in key order, in blocks of keys: pieces of the parity sequence, as in `adversarial`."""
    keys = load_table(spark, sf_dir, "customer", ["c_custkey"]).withColumn("n", F.explode(F.array(*map(F.lit, PARITIES))))
    name = F.concat(F.lit("parity-"), F.col("n").cast("string"), F.lit("-"), F.floor(F.col("c_custkey") / F.col("n")).cast("string"))
    blocks = keys.groupBy(name.alias("id")).agg(F.sort_array(F.collect_list(F.struct("c_custkey", (F.bit_count("c_custkey") % 2).cast("string").alias("c")))).alias("s"))  # at most n keys
    return blocks.select("id", F.array_join(F.transform("s", lambda x: x["c"]), "").alias("text"))


# both symbols occur from three symbols on, so delta is 2 at least and no maximiser is longer than (n + 1) / 3
@query(
    "adversarial_delta",
    f"""WITH s AS ({PARITY}), ks AS (SELECT id, text, unnest(generate_series(1, greatest(2, (length(text) + 1) // 3))) AS k FROM s),
p AS (SELECT id, CAST(k AS INTEGER) AS k, count(DISTINCT hash(substr(text, i, k))) AS d FROM (SELECT id, text, k, unnest(generate_series(1, length(text) - k + 1)) AS i FROM ks WHERE length(text) >= k) GROUP BY id, k) {delta_of('p')}""",
)
def adversarial_delta(spark, sf_dir):
    return profile.exact_delta(parities(spark, sf_dir)).select("id", "delta", "k_hat")


for _codec in profile.CODECS:
    query("distance_by_codec" if _codec == "xz" else f"distance_by_{_codec}")(lambda spark, sf_dir, codec=_codec: distance.all_pairs_distance(items(spark, sf_dir), codec))


@query("maximiser_histogram")
def maximisers(spark, sf_dir):
    return metrics.maximiser_histogram(profile.exact_delta(docs(spark, sf_dir)))


@query("markup_delta")
def markup_delta(spark, sf_dir):
    """Pages raw and without their tags."""
    raw = strings(spark, sf_dir, "pages", "page_id", "html")
    bare = raw.select("id", F.regexp_replace("text", r"(?s)<(script|style).*?</\1>|<[^>]*>", " ").alias("text"))
    return profile.exact_delta(raw).select("id", F.col("delta").alias("raw")).join(profile.exact_delta(bare).select("id", F.col("delta").alias("bare")), "id")


@query("json_field_counts", "SELECT CAST(json_extract(props, '$.k') AS INTEGER) AS field, count(*) AS rows FROM events GROUP BY 1")
def json_fields(spark, sf_dir):
    events = load_table(spark, sf_dir, "events", ["props"])
    return events.select(F.from_json("props", "k int")["k"].alias("field")).groupBy("field").agg(F.count("*").alias("rows"))
