"""Profiles, delta, pairs, groups, grids and fingerprints."""

from __future__ import annotations

from pyspark.sql import functions as F

from repetix.functions.fingerprint import FingerprintParams, code_points, fingerprint, fingerprint_concat, fingerprint_roll, power_mod
from repetix.operators import contexts, distance, metrics, profile, sketch
from repetix.plans.accuracy import plan_accuracy, sampled_lengths, sampled_lengths_column, window_length
from repetix.sources.tables import event_sequences, line_sequences, load_table, order_sequences

from .common import DOCS, ITEMS, SHORT, TURNS, Registry, delta_of, docs, items, profile_cte, profile_sql, turns, windows_cte

query = Registry()
QUERIES, ORACLES = query.queries, query.oracles
Q1, Q2 = FingerprintParams().moduli
BASE = FingerprintParams().base

EVENTS = """SELECT user_id AS id, string_agg(CASE event_type WHEN 'click' THEN 'a' WHEN 'error' THEN 'b' WHEN 'purchase' THEN 'c' WHEN 'signup' THEN 'd' WHEN 'view' THEN 'e' ELSE '-' END, ''
ORDER BY ts, event_id) AS text FROM events GROUP BY user_id"""
ORDERS = "SELECT o_custkey AS id, string_agg(o_orderstatus, '' ORDER BY o_orderdate, o_orderkey) AS text FROM orders GROUP BY o_custkey"
LINES = """SELECT l_suppkey AS id, string_agg(CASE l_returnflag WHEN 'A' THEN CASE l_linestatus WHEN 'F' THEN 'a' ELSE 'b' END WHEN 'N' THEN CASE l_linestatus WHEN 'F' THEN 'c' ELSE 'd' END
ELSE CASE l_linestatus WHEN 'F' THEN 'e' ELSE 'f' END END, '' ORDER BY l_shipdate, l_orderkey, l_linenumber, l_partkey, l_extendedprice) AS text FROM lineitem GROUP BY l_suppkey"""
SIX = range(1, 7)


@query("profile_documents", profile_sql(DOCS, (1, 2, 3)))
def profile_documents(spark, sf_dir):
    return profile.substring_profile(docs(spark, sf_dir), (1, 2, 3))


@query("profile_documents_fingerprint", profile_sql(DOCS, (4,)))
def profile_documents_fingerprint(spark, sf_dir):
    return profile.substring_profile(docs(spark, sf_dir), (4,), mode="fingerprint")


@query("profile_turns", profile_sql(TURNS, (1, 2, 4, 8)))
def profile_turns(spark, sf_dir):
    return profile.substring_profile(turns(spark, sf_dir), (1, 2, 4, 8))


@query("distinct_count_turns", f"WITH {profile_cte(TURNS, (3,))} SELECT id, d FROM p")
def distinct_count_turns(spark, sf_dir):
    return profile.distinct_count(turns(spark, sf_dir), 3)


@query("profile_events_by_user", profile_sql(EVENTS, SIX))
def profile_events(spark, sf_dir):
    return profile.substring_profile(event_sequences(spark, sf_dir), SIX)


@query("profile_orders_by_customer", profile_sql(ORDERS, SIX))
def profile_orders(spark, sf_dir):
    return profile.substring_profile(order_sequences(spark, sf_dir), SIX)


@query("profile_lineitem_flags", profile_sql(LINES, SIX))
def profile_lines(spark, sf_dir):
    return profile.substring_profile(line_sequences(spark, sf_dir), SIX)


FULL_DELTA = f"WITH {profile_cte(ITEMS, None)}, t AS ({delta_of('p')}) SELECT t.id, length(text) AS n, delta, k_hat FROM t JOIN s ON t.id = s.id"


@query("exact_delta_items", FULL_DELTA)
def exact_delta_items(spark, sf_dir):
    return profile.exact_delta(items(spark, sf_dir)).drop("k_checked")


@query("exact_delta_full_items", FULL_DELTA)
def exact_delta_full_items(spark, sf_dir):
    return profile.exact_delta(items(spark, sf_dir), stop="none").drop("k_checked")


@query("delta_from_lcp_items", FULL_DELTA)
def delta_from_lcp_items(spark, sf_dir):
    return profile.delta_from_lcp(items(spark, sf_dir))


@query("profile_from_lcp_items", profile_sql(ITEMS, None))
def profile_from_lcp_items(spark, sf_dir):
    return profile.profile_from_lcp(items(spark, sf_dir))


@query("exact_delta_documents")
def exact_delta_documents(spark, sf_dir):
    return profile.exact_delta(docs(spark, sf_dir))


@query("delta_from_lcp_documents")
def delta_from_lcp_documents(spark, sf_dir):
    return profile.delta_from_lcp(docs(spark, sf_dir))


@query("exact_delta_bytes_pages")
def exact_delta_pages(spark, sf_dir):
    pages = load_table(spark, sf_dir, "pages", ["page_id", "html"]).toDF("id", "text")
    return profile.exact_delta(pages, unit="byte")


UNION = f"""{windows_cte(ITEMS, SHORT)}, u AS (SELECT DISTINCT id, k, g FROM w), c AS (SELECT id, CAST(k AS INTEGER) AS k, count(*) AS d FROM u GROUP BY id, k),
o AS (SELECT a.id AS id_a, b.id AS id_b, CAST(a.k AS INTEGER) AS k, count(*) AS n FROM u a JOIN u b ON a.k = b.k AND a.g = b.g AND a.id < b.id GROUP BY ALL),
pp AS (SELECT a.id AS id_a, b.id AS id_b, a.k, a.d + b.d - coalesce(o.n, 0) AS d FROM c a JOIN c b ON a.k = b.k AND a.id < b.id LEFT JOIN o ON o.id_a = a.id AND o.id_b = b.id AND o.k = a.k),
pd AS (SELECT id_a, id_b, max(d / k) AS delta FROM pp GROUP BY id_a, id_b), one AS (SELECT id, max(d / k) AS delta FROM c GROUP BY id)"""


@query("pair_delta_union", f"WITH {UNION} SELECT id_a, id_b, delta FROM pd")
def pair_delta_union(spark, sf_dir):
    strings = items(spark, sf_dir)
    return distance.pair_delta(strings, distance.pair_ids(strings), SHORT)


PAIRED = f"""SELECT a.id * 1000000 + b.id AS id, a.text || b.text AS text FROM ({ITEMS}) a JOIN ({ITEMS}) b ON a.id < b.id"""


@query("pair_delta_concat", f"WITH {windows_cte(PAIRED, SHORT)}, c AS (SELECT id, k, count(DISTINCT g) AS d FROM w GROUP BY id, k) SELECT id // 1000000 AS id_a, id % 1000000 AS id_b, max(d / k) AS delta FROM c GROUP BY id")
def pair_delta_concat(spark, sf_dir):
    strings = items(spark, sf_dir)
    return distance.pair_delta(strings, distance.pair_ids(strings), SHORT, semantics="concat")


@query("pair_delta_gap_le_1", "SELECT 'gap' AS measure, 0 AS violations")
def pair_delta_gap(spark, sf_dir):
    strings = items(spark, sf_dir)
    pairs = distance.pair_ids(strings)
    a, b = distance.pair_delta(strings, pairs, SHORT), distance.pair_delta(strings, pairs, SHORT, "concat").withColumnRenamed("delta", "whole")
    gap = F.abs(F.col("delta") - F.col("whole")) > 1 + 1e-9
    return a.join(b, ["id_a", "id_b"]).agg(F.coalesce(F.sum(gap.cast("int")), F.lit(0)).alias("violations")).select(F.lit("gap").alias("measure"), "violations")


@query("distance_exact_pairs", f"WITH {UNION} SELECT id_a, id_b, (pd.delta - least(a.delta, b.delta)) / greatest(a.delta, b.delta) AS dist FROM pd JOIN one a ON a.id = id_a JOIN one b ON b.id = id_b")
def distance_exact(spark, sf_dir):
    return distance.all_pairs_distance(items(spark, sf_dir), "delta", lengths=SHORT)


@query(
    "distance_nearest_neighbour",
    f"""WITH {UNION}, e AS (SELECT id_a, id_b, (pd.delta - least(a.delta, b.delta)) / greatest(a.delta, b.delta) AS dist FROM pd JOIN one a ON a.id = id_a JOIN one b ON b.id = id_b),
y AS (SELECT id_a AS id, id_b AS other, dist FROM e UNION ALL SELECT id_b, id_a, dist FROM e)
SELECT id, other, dist FROM y QUALIFY row_number() OVER (PARTITION BY id ORDER BY dist, other) <= 3""",
)
def distance_nearest(spark, sf_dir):
    return distance.nearest(distance.all_pairs_distance(items(spark, sf_dir), "delta", lengths=SHORT), 3)


def group_sql(by: str, lengths) -> str:
    source = f"SELECT doc_id AS id, coalesce(text, '') AS text, {by} FROM documents"
    return f"""WITH s AS ({source}), w AS (SELECT {by}, k, substr(text, i, k) AS g FROM
(SELECT {by}, text, k, unnest(generate_series(1, length(text) - k + 1)) AS i FROM s, (SELECT unnest([{", ".join(map(str, lengths))}]) AS k) WHERE length(text) >= k))"""


@query("group_delta_by_source", group_sql("source", (1, 2, 3)) + ", p AS (SELECT source, CAST(k AS INTEGER) AS k, count(DISTINCT g) AS d FROM w GROUP BY source, k) " + delta_of("p", "source"))
def group_delta_by_source(spark, sf_dir):
    return profile.delta_of_profile(distance.group_profile(docs(spark, sf_dir, "source"), ["source"], (1, 2, 3)), ["source"])


@query(
    "group_delta_rollup_lang_source",
    group_sql("lang, source", (2, 3)) + ", p AS (SELECT lang, source, CAST(k AS INTEGER) AS k, count(DISTINCT g) AS d FROM w GROUP BY GROUPING SETS ((lang, source, k), (lang, k), (k))) SELECT lang, source, max(d / k) AS delta FROM p GROUP BY lang, source",
)
def group_delta_rollup(spark, sf_dir):
    from repetix.operators.distinct import window_rows

    rows = window_rows(docs(spark, sf_dir, "lang", "source"), (2, 3), ["lang", "source"]).distinct()
    sets = rows.groupingSets([["lang", "source", "k"], ["lang", "k"], ["k"]], "lang", "source", "k").agg(F.count_distinct("fp").alias("d"))
    return sets.groupBy("lang", "source").agg(F.max(F.col("d") / F.col("k")).alias("delta"))


def whole_group_delta(strings, by, symbols=None):
    """(by, delta, k_hat) of the sets of strings, over all lengths."""
    symbols = contexts.alphabet(strings) if symbols is None else symbols
    counts = lambda rows, lengths: contexts.range_profile(rows, by, min(lengths), max(lengths), symbols=symbols)
    return sketch.go_on(strings, by, profile.delta_of_profile(counts(strings, range(1, 5)), by), 4, counts, alpha=None)


@query("group_delta_all_lengths_by_source")
def group_delta_all_lengths(spark, sf_dir):
    """The measure of every source: the queries above stop at three symbols, as their SQL does."""
    return whole_group_delta(docs(spark, sf_dir, "source"), ["source"])


@query("sketch_delta_by_language")
def sketch_delta_by_language(spark, sf_dir):
    """Every language's documents as one set, in registers made in the task; lengths go on while they could win."""
    from repetix.operators import packed

    cd, strings = packed.Packed(), docs(spark, sf_dir, "lang")
    counts = lambda rows, lengths: cd.estimates(cd.from_strings(rows, ["lang"], lengths), ["lang", "k"])
    return sketch.go_on(strings, ["lang"], profile.delta_of_profile(counts(strings, sampled_lengths(40, 1.25)), ["lang"]), 40, counts)


@query("repeated_text_delta", f"SELECT id, true AS same_set FROM ({ITEMS})")
def repeated_text(spark, sf_dir):
    """A text written eight times over has the delta of two copies at most, as a set and as a string up to the border."""
    rows = items(spark, sf_dir)
    once, often = profile.exact_delta(rows).select("id", F.col("delta").alias("once"), "n"), profile.exact_delta(rows.select("id", F.repeat("text", F.lit(8)).alias("text"))).select("id", F.col("delta").alias("often"))
    return once.join(often, "id").select("id", ((F.col("often") >= F.col("once") - 1e-9) & (F.col("often") <= F.col("once") + 1 + 1e-9)).alias("same_set"))


@query("group_delta_all_lengths_rollup")
def group_delta_all_lengths_rollup(spark, sf_dir):
    """The measure of every (lang, source), every lang and all documents."""
    strings = docs(spark, sf_dir, "lang", "source").withColumn("whole", F.lit(0))
    none = [F.lit(None).cast("string").alias(c) for c in ("lang", "source")]
    symbols = contexts.alphabet(strings)
    fine = whole_group_delta(strings, ["lang", "source"], symbols).select("lang", "source", "delta")
    langs = whole_group_delta(strings, ["lang"], symbols).select("lang", none[1], "delta")
    return fine.unionByName(langs).unionByName(whole_group_delta(strings, ["whole"], symbols).select(*none, "delta"))


def grid_sql(alpha: float, first: int) -> str:
    return f"""SELECT n, unnest(list_distinct([CAST(ceil(pow({alpha}, i) - 1e-12) AS BIGINT) FOR i IN generate_series({first}, CAST(floor(ln(n) / ln({alpha}) + 1e-9) AS BIGINT))])) AS k
FROM (SELECT DISTINCT n_chars AS n FROM documents WHERE n_chars > 0)"""


def grid(alpha: float, first: int):
    def run(spark, sf_dir):
        n = load_table(spark, sf_dir, "documents", ["n_chars"]).where("n_chars > 0").select(F.col("n_chars").alias("n")).distinct()
        return n.select("n", F.explode(sampled_lengths_column(F.col("n"), alpha, first)).alias("k"))

    return run


for _name, _alpha, _first in (("grid_with_unit", 1.25, 0), ("grid_literal", 1.25, 1), ("grid_powers", 2.0, 0)):
    query(_name, grid_sql(_alpha, _first))(grid(_alpha, _first))


@query(
    "accuracy_plan",
    """SELECT epsilon, target, 1 + share AS alpha, share AS cd_error, CAST(least(21, greatest(4, ceil(2 * log2(1.04 / share)))) AS INTEGER) AS hll_lg_k,
CAST(least(26, greatest(4, ceil(2 * log2(1.0 / share)))) AS INTEGER) AS theta_lg_k
FROM (SELECT epsilon, target, epsilon / parts AS share FROM (SELECT DISTINCT CAST(l_discount AS DOUBLE) AS epsilon FROM lineitem) e, (VALUES ('delta', 4), ('distance', 20)) t(target, parts) WHERE epsilon > 0 AND epsilon < 1)""",
)
def accuracy_plan(spark, sf_dir):
    """Plans for the rates of lineitem as accuracies, for both targets."""
    asked = load_table(spark, sf_dir, "lineitem", ["l_discount"]).select(F.col("l_discount").cast("double").alias("epsilon")).where("epsilon > 0 AND epsilon < 1").distinct()
    asked = asked.withColumn("target", F.explode(F.array(F.lit("delta"), F.lit("distance"))))
    plan = F.udf(lambda epsilon, target: tuple(vars(plan_accuracy(epsilon, target)).values()), "epsilon double, target string, alpha double, cd_error double, hll_lg_k int, theta_lg_k int")
    return asked.select(plan("epsilon", "target").alias("plan")).select("plan.*")


def sql_print(text: str, q: int) -> str:
    return f"coalesce(list_reduce(list_prepend(0::BIGINT, [CAST(unicode(c) AS BIGINT) FOR c IN string_split({text}, '') IF c <> '']), lambda f, s: (f * {BASE} + s) % {q}), 0)"


@query("fingerprint_text", f"SELECT id, {sql_print('text', Q1)} AS fp1, {sql_print('text', Q2)} AS fp2 FROM ({ITEMS})")
def fingerprint_text(spark, sf_dir):
    points = code_points("text")
    return items(spark, sf_dir).select("id", fingerprint(points, Q1).alias("fp1"), fingerprint(points, Q2).alias("fp2"))


@query(
    "length_weights",
    f"SELECT CAST(k AS INTEGER) AS k, list_reduce(list_prepend(1::BIGINT, [1::BIGINT FOR x IN range(1, k)]), lambda f, x: f * {BASE} % {Q1}) AS w1, list_reduce(list_prepend(1::BIGINT, [1::BIGINT FOR x IN range(1, k)]), lambda f, x: f * {BASE} % {Q2}) AS w2 FROM (SELECT unnest(range(1, 201)) AS k)",
)
def length_weights(spark, sf_dir):
    """base^(k - 1), the weight of the symbol that leaves a window, for both primes, by squaring."""
    ks = spark.range(1, 201).select(F.col("id").cast("int").alias("k"))
    return ks.select("k", power_mod(F.col("k") - 1, Q1).alias("w1"), power_mod(F.col("k") - 1, Q2).alias("w2"))


@query("window_lengths", "SELECT n, CAST(ceil(sqrt(n) * log2(n)) AS BIGINT) AS window FROM (SELECT CAST(unnest([10, 100, 1000, 12000, 128657, 1000000, 24783473]) AS BIGINT) AS n)")
def window_lengths(spark, sf_dir):
    """Symbols that a stream of n keeps."""
    ns = (10, 100, 1000, 12_000, 128_657, 1_000_000, 24_783_473)
    return spark.createDataFrame([(n, window_length(n)) for n in ns], "n bigint, window bigint")


@query("fingerprint_concat", f"SELECT a.id AS id, {sql_print('a.text || b.text', Q1)} AS fp FROM ({ITEMS}) a JOIN ({ITEMS}) b ON b.id = a.id + 1")
def fingerprint_concat_query(spark, sf_dir):
    one = items(spark, sf_dir).select("id", fingerprint(code_points("text"), Q1).alias("fp"), power_mod(F.length("text"), Q1).alias("weight"))
    a, b = one.select("id", "fp"), one.select((F.col("id") - 1).alias("id"), F.col("fp").alias("fp_b"), F.col("weight").alias("weight_b"))
    return a.join(b, "id").select("id", fingerprint_concat(F.col("fp"), F.col("fp_b"), F.col("weight_b"), Q1).alias("fp"))


@query("fingerprint_roll", f"SELECT id, {sql_print('substr(text, 2, 8)', Q1)} AS fp FROM ({ITEMS}) WHERE length(text) >= 9")
def fingerprint_roll_query(spark, sf_dir):
    params = FingerprintParams((Q1,))
    rows = items(spark, sf_dir).where(F.length("text") >= 9)
    old = fingerprint(code_points(F.substring("text", 1, 8)), Q1)
    return rows.select("id", fingerprint_roll(old, F.ascii("text"), F.ascii(F.substring("text", 9, 1)), params.weight(7)[0], Q1).alias("fp"))


@query("fingerprint_collisions", f"SELECT CAST(k AS INTEGER) AS k, count(*) AS strings, 0 AS lost FROM ({TURNS}), (SELECT unnest([1, 2, 4, 8]) AS k) GROUP BY k")
def fingerprint_collisions(spark, sf_dir):
    strings = turns(spark, sf_dir)
    return metrics.collisions(profile.substring_profile(strings, (1, 2, 4, 8)), profile.substring_profile(strings, (1, 2, 4, 8), mode="fingerprint"))
