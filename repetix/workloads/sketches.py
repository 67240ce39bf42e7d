"""Count-distinct families, sketches, long strings and streams."""

from __future__ import annotations

from pyspark.sql import functions as F

from repetix.functions.fingerprint import FingerprintParams
from repetix.functions.hashing import OFFSET, P, SCALE, seed_for
from repetix.operators import distance, longstring, metrics, narrow, packed, profile, sketch
from repetix.operators.distinct import F0, Exact, F0Median, Hll, Kmv, LinearCounting, Theta, approx_profile, window_rows
from repetix.plans.accuracy import sampled_lengths
from repetix.sources.tables import load_table
from repetix.streaming import stream_sketch as streams
from repetix.session import written

from .common import ITEMS, SHORT, Registry, delta_of, docs, items, turns, windows_cte
from .common import strings as texts
from .core import EVENTS, sql_print

query = Registry()
QUERIES, ORACLES = query.queries, query.oracles
Q1, Q2 = FingerprintParams().moduli
SOME = (2, 4, 6)
M_KMV, M_F0, M_BITS = 64, 256, 32768


def hash_sql(kind: str, copy: int = 0) -> str:
    a, b, c = seed_for(kind, copy)
    x = f"(({a} * fp1 + {b} * fp2 + {c}) % {P})"
    return f"(({x} * {x} % {P}) * {SCALE} % {P} + {OFFSET})"


PRINTS = f"""{windows_cte(ITEMS, SOME)}, f AS (SELECT id, CAST(k AS INTEGER) AS k, {sql_print('g', Q1)} AS fp1, {sql_print('g', Q2)} AS fp2 FROM (SELECT DISTINCT id, k, g FROM w))"""
#: The same, with two items of neighbouring ids as one set.
MERGED = PRINTS + ", m AS (SELECT DISTINCT id // 2 AS id, k, fp1, fp2 FROM f)"


def kmv_sql(source: str) -> str:
    return f"SELECT id, k, cd FROM (SELECT DISTINCT id, k, {hash_sql('order')} AS cd FROM {source}) QUALIFY row_number() OVER (PARTITION BY id, k ORDER BY cd) <= {M_KMV}"


def f0_sql(source: str) -> str:
    h = hash_sql("level")
    return f"SELECT id, k, CAST({hash_sql('bucket')} % {M_F0} AS INTEGER) AS bucket, CAST(max(bit_count(xor({h}, {h} - 1)) - 1) AS INTEGER) AS level FROM {source} GROUP BY ALL"


KMV_D = f"SELECT id, k, CASE WHEN count(*) < {M_KMV} THEN count(*) ELSE {float(P) * (M_KMV - 1)} / max(cd) END AS d FROM r GROUP BY id, k"
F0_D = f"""SELECT id, k, pow(2, low) * ln(1 - taken / {M_F0}.0) / ln(1 - 1 / {M_F0}.0) AS d FROM
(SELECT id, k, low, count(*) FILTER (level >= low) AS taken FROM r, (SELECT unnest(generate_series(0, 31)) AS low) GROUP BY id, k, low)
WHERE taken <= {int(0.7 * M_F0)} QUALIFY low = min(low) OVER (PARTITION BY id, k)"""


def rows_of(spark, sf_dir):
    return window_rows(items(spark, sf_dir), SOME)


def halved(sketches):
    return sketches.withColumn("id", F.floor(F.col("id") / 2))


@query("kmv_registers", f"WITH {PRINTS} {kmv_sql('f')}")
def kmv_registers(spark, sf_dir):
    return Kmv(M_KMV).build(rows_of(spark, sf_dir), ["id", "k"])


@query("kmv_merge", f"WITH {MERGED} {kmv_sql('m')}")
def kmv_merge(spark, sf_dir):
    cd = Kmv(M_KMV)
    return cd.merge(halved(cd.build(rows_of(spark, sf_dir), ["id", "k"])), ["id", "k"])


@query("kmv_delta", f"WITH {PRINTS}, r AS ({kmv_sql('f')}), p AS ({KMV_D}) {delta_of('p')}")
def kmv_delta(spark, sf_dir):
    cd = Kmv(M_KMV)
    return sketch.estimate_delta(cd.build(rows_of(spark, sf_dir), ["id", "k"]), cd=cd)


@query("f0_registers", f"WITH {PRINTS} {f0_sql('f')}")
def f0_registers(spark, sf_dir):
    return F0(M_F0).build(rows_of(spark, sf_dir), ["id", "k"])


@query("f0_merge", f"WITH {MERGED} {f0_sql('m')}")
def f0_merge(spark, sf_dir):
    cd = F0(M_F0)
    return cd.merge(halved(cd.build(rows_of(spark, sf_dir), ["id", "k"])), ["id", "k"])


@query("f0_delta", f"WITH {PRINTS}, r AS ({f0_sql('f')}), p AS ({F0_D}) SELECT id, max(d / k) AS delta FROM p GROUP BY id")
def f0_delta(spark, sf_dir):
    cd = F0(M_F0)
    return sketch.estimate_delta(cd.build(rows_of(spark, sf_dir), ["id", "k"]), cd=cd).drop("k_hat")


@query(
    "linear_counting_delta",
    f"WITH {PRINTS}, p AS (SELECT id, k, -{M_BITS}.0 * ln(({M_BITS} - count(DISTINCT {hash_sql('bucket')} % {M_BITS})) / {M_BITS}.0) AS d FROM f GROUP BY id, k) SELECT id, max(d / k) AS delta FROM p GROUP BY id",
)
def linear_counting_delta(spark, sf_dir):
    cd = LinearCounting(M_BITS)
    return sketch.estimate_delta(cd.build(rows_of(spark, sf_dir), ["id", "k"]), cd=cd).drop("k_hat")


def on_items(cd):
    """Over all lengths; those of the queries above are fixed by their SQL."""

    def run(spark, sf_dir):
        counts = lambda rows, lengths: cd.estimates(cd.build(window_rows(rows, lengths), ["id", "k"]), ["id", "k"])
        strings = items(spark, sf_dir)
        return sketch.go_on(strings, ["id"], profile.delta_of_profile(counts(strings, range(1, 9))), 8, counts, alpha=None)

    return run


for _name, _cd in (("kmv", Kmv(M_KMV)), ("f0", F0(M_F0)), ("linear_counting", LinearCounting(M_BITS))):
    query(f"{_name}_delta_all_lengths")(on_items(_cd))


def sketched_on(strings, by, sketches, low, cd=Hll()):
    """The delta of `sketches`, whose lengths end at `low`, with longer lengths where those could win."""
    counts = lambda rows, lengths: cd.estimates(sketch.build_sketch(rows, by, cd=cd, lengths=lengths), [*by, "k"])
    return sketch.go_on(strings, by, sketch.estimate_delta(sketches, by, cd), low, counts)


def estimated(cd):
    """Every document has a sketch of its own, so it is made and estimated in its task, over all lengths that could win."""

    def run(spark, sf_dir):
        strings = docs(spark, sf_dir)
        return cd.deltas(strings, ["id"], sampled_lengths(sketch.longest(strings), 1.25))

    return run


for _name, _cd in (("hll_delta", Hll()), ("theta_delta", Theta())):
    query(_name)(estimated(_cd))


@query("packed_delta")
def packed_delta(spark, sf_dir):
    """The fast path: every document's estimate in one narrow pass."""
    strings = docs(spark, sf_dir)
    return packed.estimate_strings(strings, sampled_lengths(sketch.longest(strings), 1.25))  # a string stops where no longer length can win


@query("packed_group_delta")
def packed_group_delta(spark, sf_dir):
    cd = packed.Packed()
    strings = docs(spark, sf_dir, "source")
    counts = lambda rows, lengths: cd.estimates(cd.from_strings(rows, ["source"], lengths), ["source", "k"])
    return sketch.go_on(strings, ["source"], profile.delta_of_profile(counts(strings, sampled_lengths(40, 1.25)), ["source"]), 40, counts)


@query("f0_median_delta")
def f0_median_delta(spark, sf_dir):
    """Every turn's estimate, over all lengths that could win."""
    strings = turns(spark, sf_dir)
    return F0Median(3, 1024).deltas(strings, ["id"], sampled_lengths(sketch.longest(strings), 1.25))


@query("exact_cd_delta", f"WITH {windows_cte(ITEMS, SHORT)}, p AS (SELECT id, CAST(k AS INTEGER) AS k, count(DISTINCT g) AS d FROM w GROUP BY id, k) {delta_of('p')}")
def exact_cd_delta(spark, sf_dir):
    return sketch.estimate_delta(sketch.build_sketch(items(spark, sf_dir), cd=Exact(), lengths=SHORT), cd=Exact())


@query("approx_count_distinct_delta")
def approx_delta(spark, sf_dir):
    rows = window_rows(turns(spark, sf_dir), SHORT)
    return profile.delta_of_profile(approx_profile(rows, ["id", "k"]))


@query("sketch_size_documents")
def sketch_size_documents(spark, sf_dir):
    """Lengths and bytes of every document's sketch, which goes up to the document's own length."""
    return metrics.sketch_size(sketch.build_sketch(docs(spark, sf_dir), one_each=True))


GRID = sampled_lengths(1 << 24, 1.25)


@query(
    "merge_cost_items",
    f"WITH s AS ({ITEMS}), k AS (SELECT unnest([{', '.join(map(str, GRID))}]) AS k) SELECT a.id AS id_a, b.id AS id_b, count(*) AS unions FROM s a JOIN s b ON a.id < b.id JOIN k ON k <= length(a.text) AND k <= length(b.text) GROUP BY a.id, b.id",
)
def merge_cost_items(spark, sf_dir):
    return distance.merge_cost(sketch.build_sketch(items(spark, sf_dir)))


@query("certified_documents")
def certified_documents(spark, sf_dir):
    """The estimate over lengths up to 16 of every document, with the certificate that tells whether longer lengths could win."""
    strings = docs(spark, sf_dir)
    return sketch.certified(Hll().deltas(strings, ["id"], sampled_lengths(16, 1.25)), strings, 16)


@query("hll_merge_delta")
def hll_merge_delta(spark, sf_dir):
    """Sketches of the documents of each source in a task, merged by source; a text is read again only where lengths over 40 could win."""
    merged = sketch.build_sketch(docs(spark, sf_dir, "source"), by=("source",), max_length=40)
    return sketched_on(docs(spark, sf_dir, "source"), ["source"], merged, 40)


@query("sketch_rollup")
def sketch_rollup(spark, sf_dir):
    strings = docs(spark, sf_dir, "lang", "source").withColumn("whole", F.lit(0))
    sketches = written(sketch.build_sketch(strings, by=("whole", "lang", "source"), max_length=40), "sketches")
    levels, out = ["whole", "lang", "source"], None
    for n in (3, 2, 1):
        by = levels[:n]
        found = sketched_on(strings, by, sketch.merge_sketches(sketches.select(*by, "k", "cd"), by=by), 40)
        level = found.select(*[F.col(c) if c in by else F.lit(None).cast("string").alias(c) for c in levels[1:]], "delta", "k_hat")
        out = level if out is None else out.unionByName(level)
    return out


@query("sketch_extend", f"WITH {windows_cte(ITEMS, (1, 2, 4, 8))}, p AS (SELECT id, CAST(k AS INTEGER) AS k, count(DISTINCT g) AS d FROM w GROUP BY id, k) SELECT id, k, CAST(d AS DOUBLE) AS d FROM p")
def sketch_extend(spark, sf_dir):
    """Every item in two chunks: the first is sketched, the second appended."""
    lengths, cd = (1, 2, 4, 8), Exact()
    rows = items(spark, sf_dir)
    half = (F.length("text") / 2).cast("int")
    first = rows.select("id", F.substring("text", F.lit(1), half).alias("text"))
    second = rows.select("id", F.substring("text", half + 1, F.length("text")).alias("text"))
    start = sketch.build_sketch(first, cd=cd, lengths=lengths)
    tails = first.select("id", F.right("text", F.lit(7)).alias("tail"))
    extended, _ = sketch.extend_sketch(start, tails, second, lengths, cd)
    return cd.estimates(extended, ["id", "k"])


@query("sketch_error_by_alpha")
def sketch_error_by_alpha(spark, sf_dir):
    """(alpha, cd, strings, mean, p99, max): one sketch of all lengths of the grids, up to the longest document, serves every ratio."""
    strings = docs(spark, sf_dir)
    exact, longest = written(profile.exact_delta(strings).select("id", "delta"), "exact"), sketch.longest(strings)
    grids = {a: sampled_lengths(longest, a) for a in (2.0, 1.5, 1.25, 1.1, 1.05)}
    grids |= {-2.0: sampled_lengths(longest, 2.0, "literal")}
    wanted = sorted({k for ks in grids.values() for k in ks})
    by_grid = spark.createDataFrame([(a, k) for a, ks in grids.items() for k in ks], "alpha double, k int")
    out = []
    for name, cd in (("hll", Hll()), ("theta", Theta())):
        counted = cd.of_strings(strings, ["id"], wanted, list(grids.values()))
        deltas = counted.join(F.broadcast(by_grid), "k").groupBy("id", "alpha").agg(F.max(F.col("d") / F.col("k")).alias("delta"))
        errors = deltas.join(exact.withColumnRenamed("delta", "exact"), "id").withColumn("error", F.abs(F.col("delta") - F.col("exact")) / F.col("exact"))
        out.append(metrics.error_summary(errors, ["alpha"]).withColumn("cd", F.lit(name)))
    return out[0].unionByName(out[1])


@query("grid_error_exact_counts")
def grid_error(spark, sf_dir):
    """The share of the error that the grid alone makes: exact counts on sampled lengths."""
    strings = docs(spark, sf_dir)
    grids = {a: sampled_lengths(100, a) for a in (2.0, 1.5, 1.25, 1.1)}
    by_grid = spark.createDataFrame([(a, k) for a, ks in grids.items() for k in ks], "alpha double, k int")
    counted = profile.substring_profile(strings, {k for ks in grids.values() for k in ks}, mode="fingerprint")
    deltas = counted.join(F.broadcast(by_grid), "k").groupBy("id", "alpha").agg(F.max(F.col("d") / F.col("k")).alias("delta"))
    errors = deltas.join(profile.exact_delta(strings).select("id", F.col("delta").alias("exact")), "id").withColumn("error", F.abs(F.col("delta") - F.col("exact")) / F.col("exact"))
    return metrics.error_summary(errors, ["alpha"])


@query("all_pairs_sketch_error", "SELECT count(*) * (count(*) - 1) // 2 AS pairs, CAST(0 AS BIGINT) AS beyond FROM benchmark")
def all_pairs_sketch_error(spark, sf_dir):
    """Sketch distances of all pairs of items, against exact ones: none is off by over 0.1."""
    strings = items(spark, sf_dir)
    exact = distance.all_pairs_distance(strings, "delta", lengths=SHORT)
    near = distance.all_pairs_distance(strings, "sketch", lengths=SHORT).withColumnRenamed("dist", "near")
    beyond = (F.abs(F.col("dist") - F.col("near")) > 0.1).cast("bigint")
    return exact.join(near, ["id_a", "id_b"]).agg(F.count("*").alias("pairs"), F.sum(beyond).alias("beyond"))


def conversations(spark, sf_dir):
    df = load_table(spark, sf_dir, "conversations", ["conv_id", "text"])
    return df.select(F.col("conv_id").alias("id"), F.coalesce("text", F.lit("")).alias("text"))


@query("sketch_error_other_corpora")
def sketch_error_other_corpora(spark, sf_dir):
    """(corpus, cd, alpha, strings, mean, p99, max) on pages and on conversations as sets of turns, by every family; `exact` is the grid's own share."""
    ratios = (2.0, 1.5, 1.25, 1.1, 1.05, 1.025)
    grids = {a: sampled_lengths(64, a) for a in ratios}
    families = {"exact": Exact(), "hll": Hll(), "theta": Theta(), "kmv": Kmv(1024), "f0": F0(4096), "f0_median": F0Median(3, 4096), "linear": LinearCounting(M_BITS)}
    kernels = {name: cd.kernel() for name, cd in families.items()} | {"approx_count_distinct": narrow.approx_counts(*narrow.approx_tables(spark))}
    out = None
    for corpus, strings in (("pages", texts(spark, sf_dir, "pages", "page_id", "html")), ("conversations", conversations(spark, sf_dir))):
        dealt = strings.where("id IS NOT NULL").repartition(int(spark.conf.get("spark.sql.shuffle.partitions")), "id")  # by a number of its own: the work is many times the bytes
        sets = dealt.groupBy("id").agg(F.collect_list("text").alias("texts"))
        errors = written(narrow.set_errors(sets, grids, kernels), "errors")
        summary = metrics.error_summary(errors, ["cd", "alpha"]).select("alpha", "strings", "mean", "p99", "max", "cd").withColumn("corpus", F.lit(corpus))
        out = summary if out is None else out.unionByName(summary)
    return out


WHOLE = "SELECT 0 AS id, string_agg(text, '' ORDER BY item_id) AS text FROM benchmark"


def whole_sql(lengths) -> str:
    return f"WITH {windows_cte(WHOLE, lengths)} SELECT CAST(k AS INTEGER) AS k, count(DISTINCT g) AS d FROM w GROUP BY k"


@query("halo_profile", whole_sql((1, 2, 5, 9, 30)))
def halo_profile(spark, sf_dir):
    """All items as one string, in chunks with halos."""
    chunks = longstring.chunk_table(load_table(spark, sf_dir, "benchmark"), "item_id")
    return longstring.halo_windows(chunks, (1, 2, 5, 9, 30)).groupBy("k").agg(F.count_distinct("fp").alias("d"))


@query("block_shift_profile", whole_sql((1, 3, 100, 1000, 3000)))
def block_shift_profile(spark, sf_dir):
    """All items as one string, in blocks of 512 symbols; windows span several blocks."""
    chunks = longstring.chunk_table(load_table(spark, sf_dir, "benchmark"), "item_id")
    return longstring.block_shift_windows(chunks, (1, 3, 100, 1000, 3000), size=512).groupBy("k").agg(F.count_distinct("fp").alias("d"))


POWERS = [1 << i for i in range(13)]


@query("long_string_plan", f"WITH {windows_cte(WHOLE, POWERS)}, p AS (SELECT id, CAST(k AS INTEGER) AS k, count(DISTINCT g) AS d FROM w GROUP BY id, k), n AS (SELECT 0 AS id, sum(length(text)) AS n FROM benchmark) SELECT x.id, CAST(n AS BIGINT) AS n, delta, k_hat, CAST(floor(n / delta) AS BIGINT) AS bound FROM ({delta_of('p')}) x JOIN n ON n.id = x.id")
def long_string_plan(spark, sf_dir):
    """All items as one string: lengths up to 4 with halos, longer ones by block shift up to the certificate."""
    chunks = longstring.chunk_table(load_table(spark, sf_dir, "benchmark"), "item_id")
    return longstring.sketch_long_strings(chunks, Exact(), alpha=2.0, cap=4, size=512)[1]


@query("long_string_delta")
def long_string_delta(spark, sf_dir):
    """All documents as one string, with sketches: delta, its maximiser, and the certificate: lengths go on until they reach it."""
    chunks = longstring.chunk_table(load_table(spark, sf_dir, "documents", ["doc_id", "text"]), "doc_id")
    from repetix.plans.accuracy import length_bound

    cd = packed.Packed()
    n = load_table(spark, sf_dir, "documents", ["text"]).agg(F.coalesce(F.sum(F.length("text")), F.lit(0)).cast("bigint").alias("n"))
    sketches, low, high = None, 0, 128
    while True:
        more = packed.long_string_sketch(chunks, [k for k in sampled_lengths(high, 1.25) if k > low], cd)
        sketches = written(more if sketches is None else sketches.unionByName(more), "long-string")
        found = sketch.estimate_delta(sketches, cd=cd).crossJoin(F.broadcast(n)).withColumn("bound", length_bound(F.col("n"), F.col("delta")))
        if found.where(F.col("bound") > high).where(F.col("n") > high).isEmpty():
            return found
        low, high = high, 4 * high


PAGES_BY_DAY = """SELECT date_trunc('day', ts) AS start, CAST(k AS INTEGER) AS k, CAST(count(DISTINCT substr(props, i, k)) AS DOUBLE) AS d
FROM (SELECT ts, props, k, unnest(generate_series(1, length(props) - k + 1)) AS i FROM events, (SELECT unnest([2, 3]) AS k) WHERE length(props) >= k) GROUP BY ALL"""


def windowed(kind: str):
    def run(spark, sf_dir):
        events = load_table(spark, sf_dir, "events", ["ts", "props"]).select(F.col("ts"), F.col("props").cast("string").alias("text"))
        window = {"tumbling": F.window("ts", "1 day"), "sliding": F.window("ts", "2 days", "1 day"), "session": F.session_window("ts", "6 hours")}[kind]
        return streams.windowed_profile(events, "ts", window, [], (2, 3))

    return run


query("sketch_windows_tumbling", PAGES_BY_DAY)(windowed("tumbling"))
query(
    "sketch_windows_sliding",
    PAGES_BY_DAY.replace("date_trunc('day', ts) AS start", "start").replace("FROM events,", "FROM (SELECT *, unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS start FROM events),").replace("SELECT ts, props", "SELECT start, props"),
)(windowed("sliding"))
query("sketch_windows_session")(windowed("session"))
