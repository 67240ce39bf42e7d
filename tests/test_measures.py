"""Queries without an oracle, held against independent figures, and the guards of sketches."""

import bz2
import lzma
import zlib

import duckdb
import pytest
from pyspark.sql import functions as F

from repetix import workloads
from repetix.functions import suffixes
from repetix.functions.fingerprint import FingerprintParams, window_fingerprints
from repetix.functions.symbols import encode
from repetix.operators import distance, metrics, profile, sketch
from repetix.operators.distinct import Exact, Hll, Kmv
from repetix.workloads.common import docs, items, turns


def run(spark, sf_dir, name):
    return workloads.queries()[name](spark, sf_dir).collect()


@pytest.fixture(scope="module")
def texts(sf_dir):
    return dict(duckdb.sql(f"SELECT doc_id, coalesce(text, '') FROM '{sf_dir}/documents.parquet'").fetchall())


@pytest.fixture(scope="module")
def exact(spark, sf_dir):
    return {r["id"]: r["delta"] for r in profile.exact_delta(docs(spark, sf_dir)).collect()}


def test_codec_sizes(spark, sf_dir, texts):
    for r in run(spark, sf_dir, "codec_sizes_documents"):
        raw = texts[r["id"]].encode()
        assert r["gzip"] == len(zlib.compress(raw, 9, 31)) and r["bzip2"] == len(bz2.compress(raw, 9)) and r["xz"] == len(lzma.compress(raw, lzma.FORMAT_XZ, preset=9))


@pytest.mark.parametrize("codec,pack", [("gzip", lambda b: zlib.compress(b, 9, 31)), ("bzip2", lambda b: bz2.compress(b, 9)), ("xz", lambda b: lzma.compress(b, preset=9))])
def test_distances_by_codec(spark, sf_dir, codec, pack):
    said = dict(duckdb.sql(f"SELECT item_id, text FROM '{sf_dir}/benchmark.parquet'").fetchall())
    rows = run(spark, sf_dir, "distance_by_codec" if codec == "xz" else f"distance_by_{codec}")
    assert len(rows) == 780 and all(r["id_a"] < r["id_b"] for r in rows)
    size = lambda s: len(pack(s.encode()))
    for r in rows[::60]:
        a, b = said[r["id_a"]], said[r["id_b"]]
        assert r["dist"] == pytest.approx((size(a + b) - min(size(a), size(b))) / max(size(a), size(b)))


def plain_lz78(text):
    phrases, at, seen = 0, "", set()
    for c in text:
        at += c
        if at not in seen:
            seen.add(at)
            phrases, at = phrases + 1, ""
    return phrases + bool(at)


def test_parses_and_grammar(spark, sf_dir):
    said = {r["id"]: r["text"] for r in turns(spark, sf_dir).collect()}
    for r in run(spark, sf_dir, "lz78_phrases_turns"):
        assert r["z78"] == plain_lz78(said[r["id"]])
    grammar = run(spark, sf_dir, "grammar_size_turns")
    assert len(grammar) == len(said)
    sizes = {r["id"]: r[1] for r in grammar}
    assert all(sizes[i] <= len(t) + 1 for i, t in said.items()) and any(sizes[i] < len(t) for i, t in said.items())
    found = run(spark, sf_dir, "parse_sizes_documents")
    assert len(found) == 200 and all(r["z"] > 0 and r["r"] > 0 for r in found if r["id"] in (1, 2, 3))


@pytest.mark.parametrize("name,mean", [("packed_delta", 0.05), ("certified_documents", 0.06)])
def test_document_estimates(spark, sf_dir, exact, name, mean):
    rows = run(spark, sf_dir, name)
    errors = [abs(r["delta"] - exact[r["id"]]) / exact[r["id"]] for r in rows if exact[r["id"]]]
    assert len(rows) >= 199 and sum(errors) / len(errors) < mean


@pytest.mark.parametrize("name,most", [("f0_median_delta", 0.2), ("approx_count_distinct_delta", 0.2)])
def test_turn_estimates(spark, sf_dir, name, most):
    truth = {r["id"]: r["delta"] for r in profile.exact_delta(turns(spark, sf_dir)).collect()}
    rows = run(spark, sf_dir, name)
    assert rows and max(abs(r["delta"] - truth[r["id"]]) / truth[r["id"]] for r in rows if truth[r["id"]]) < most


def test_groups(spark, sf_dir):
    groups = {r["source"]: r["delta"] for r in run(spark, sf_dir, "packed_group_delta")}
    truth = {r["source"]: r["delta"] for r in run(spark, sf_dir, "group_delta_all_lengths_by_source")}
    assert groups.keys() == truth.keys() and all(abs(groups[s] - d) / d < 0.15 for s, d in truth.items())
    assert {r["lang"] for r in run(spark, sf_dir, "sketch_delta_by_language")} == {"de", "en", "es", "fr"}


def test_error_tables(spark, sf_dir):
    grid = {r["alpha"]: r for r in run(spark, sf_dir, "grid_error_exact_counts")}
    assert grid[1.1]["mean"] <= grid[2.0]["mean"] < 0.1 and grid[2.0]["max"] < 0.5
    by = {(r["cd"], r["alpha"]): r for r in run(spark, sf_dir, "sketch_error_by_alpha")}
    assert by["hll", 1.05]["mean"] < 0.02 and by["theta", 1.05]["mean"] < 0.02 and by["hll", 2.0]["mean"] >= by["hll", 1.05]["mean"]
    assert by["hll", -2.0]["max"] > by["hll", 2.0]["max"]  # the grid without length 1 misses maximisers


def test_sizes_and_pages(spark, sf_dir):
    assert all(r["lengths"] <= 19 and 0 < r["bytes"] < 19 * 4200 for r in run(spark, sf_dir, "sketch_size_documents"))
    pages = dict(duckdb.sql(f"SELECT page_id, html FROM '{sf_dir}/pages.parquet'").fetchall())
    raw = {r["id"]: r["raw"] for r in run(spark, sf_dir, "markup_delta")}
    assert raw.keys() == pages.keys()
    for i in list(pages)[:5]:
        assert raw[i] == pytest.approx(suffixes.exact_delta(encode(pages[i]))[0])
    for r in run(spark, sf_dir, "exact_delta_bytes_pages")[:5]:
        assert r["delta"] == pytest.approx(suffixes.exact_delta(encode(pages[r["id"]], "byte"))[0])


@pytest.mark.parametrize("name", ["prefix_trend_correlation", "prefix_trend_by_source"])
def test_measures_follow_one_trend(spark, sf_dir, name):
    rows = run(spark, sf_dir, name)
    by = [r["pearson"] for r in rows if {r["measure_a"], r["measure_b"]} <= {"delta", "delta_sketch", "r", "z"} and r["pearson"] is not None]
    assert by and sum(by) / len(by) > 0.9


def test_prefix_measures(spark, sf_dir):
    for name, strings in (("prefix_measures", 5), ("prefix_measures_by_source", 20)):
        rows = run(spark, sf_dir, name)
        assert len(rows) == strings * 10 * 6 and all(0 <= r["by_range"] <= 1 and 0 < r["by_max"] <= 1 for r in rows)


def test_trees_and_sequences(spark, sf_dir):
    rows = run(spark, sf_dir, "all_pairs_sequences")
    assert len(rows) == 3 * 406 and all(-0.05 <= r["dist"] <= 1.1 for r in rows)
    assert run(spark, sf_dir, "tree_average_linkage")
    trees = run(spark, sf_dir, "tree_distance")
    assert len(trees) == 6 and all(0 <= r["rf"] <= 1 for r in trees)


def test_sketched_heuristic(spark, sf_dir):
    near = {r["id"]: r["delta"] for r in run(spark, sf_dir, "local_max_sketched")}
    truth = {r["id"]: r["delta"] for r in run(spark, sf_dir, "local_max_uncapped")}
    assert near.keys() == truth.keys() and all(abs(near[i] - d) / d < 0.1 for i, d in truth.items())


def test_other_corpora(spark, sf_dir):
    rows = {(r["corpus"], r["cd"], r["alpha"]): r for r in run(spark, sf_dir, "sketch_error_other_corpora")}
    assert len(rows) == 2 * 8 * 6
    assert rows["pages", "hll", 1.025]["mean"] < 0.05 and rows["conversations", "theta", 1.025]["mean"] < 0.05
    assert rows["conversations", "exact", 1.025]["mean"] <= rows["conversations", "exact", 2.0]["mean"]


def test_documents_as_streams(spark, sf_dir):
    """The stream's estimate of a source is that of its documents put together."""
    rows = {r["id"]: r for r in run(spark, sf_dir, "stream_documents_with_transform")}
    plain = {r["id"]: r for r in run(spark, sf_dir, "stream_documents_by_source")}
    whole = duckdb.sql(f"SELECT source, string_agg(text, '' ORDER BY doc_id) FROM '{sf_dir}/documents.parquet' GROUP BY source").fetchall()
    for source, text in whole[:6]:
        truth = suffixes.exact_delta(encode(text))[0]
        for r in (rows[source], plain[source]):
            assert r["n"] == len(text) and abs(r["delta"] - truth) / truth < 0.25 and r["certified"]
        assert 0 < rows[source]["runs"] <= len(text) and plain[source]["runs"] is None


def test_state_per_batch(spark, sf_dir):
    rows = run(spark, sf_dir, "stream_runs_by_batch")
    assert {r["id"] for r in rows} == {i for (i,) in duckdb.sql(f"SELECT DISTINCT user_id FROM '{sf_dir}/events.parquet'").fetchall()} and len(rows) > 15


def test_sketches_of_other_kinds_are_refused(spark):
    df = spark.createDataFrame([(1, "abab"), (2, "abc")], "id bigint, text string")
    build = lambda cd=Hll(), **o: sketch.build_sketch(df, cd=cd, lengths=[1, 2], **o)
    assert sketch.merge_sketches(build(), build()).count() == 4
    for a, b, cd in (
        (build(Exact()), build(Kmv()), Exact()), (build(Kmv(8)), build(Kmv(16)), Kmv(8)), (build(Hll(12)), build(Hll(10)), Hll(12)), (build(), build(), Hll(11)),
        (build(), build(params=FingerprintParams.drawn(1)), Hll()), (build(), build(params=FingerprintParams().with_random_base(3)), Hll()), (build(), build(unit="byte"), Hll()),
    ):
        with pytest.raises(ValueError):
            sketch.merge_sketches(a, b, cd=cd)
    tails, chunk = df.select("id", F.right("text", F.lit(1)).alias("tail")), df
    longer, _ = sketch.extend_sketch(build(Exact()), tails, chunk, [1, 2], Exact())
    assert sketch.description(longer)["of_sets"] is False
    with pytest.raises(ValueError):
        sketch.extend_sketch(sketch.merge_sketches(build(Exact()), cd=Exact()), tails, chunk, [1, 2], Exact())


def test_metadata_lives_through_files(spark, tmp_path):
    df = spark.createDataFrame([(1, "abab")], "id bigint, text string")
    made = sketch.build_sketch(df, cd=Exact(), lengths=[1])
    made.write.parquet(str(tmp_path / "s"))
    assert sketch.description(spark.read.parquet(str(tmp_path / "s"))) == sketch.description(made) != {}


def test_a_random_base_tells_strings_apart():
    params = FingerprintParams().with_random_base(9)
    assert 1_114_112 <= params.base < min(params.moduli) and params == FingerprintParams().with_random_base(9) != FingerprintParams().with_random_base(10)
    s = encode("abracadabra")
    assert [len(set(window_fingerprints(s, params)(k).tolist())) for k in (1, 2, 3)] == [5, 7, 7]


def test_blocks_are_the_keys_of_all_pairs(spark):
    rows = spark.range(40).select("id", F.concat(F.lit("text "), F.col("id") % 7, F.lit(" of "), F.col("id") % 5).alias("text"))
    near = distance.all_pairs_sketch(sketch.build_sketch(rows, lengths=[1, 2, 3]))
    plan = near._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "NestedLoop" not in plan and "__i" in plan and "__j" in plan
    whole = distance.all_pairs_exact(rows, [1, 2, 3])
    plan = whole._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan
    assert near.count() == whole.count() == 40 * 39 // 2
    some = spark.createDataFrame([(0, 35), (3, 8)], "id_a bigint, id_b bigint")
    asked = {(r["id_a"], r["id_b"], r["k"]): r["d"] for r in distance.pair_profile(rows, some, [2], rows.select("id", (F.col("id") % 3).alias("bucket"))).collect()}
    said = {r["id"]: r["text"] for r in rows.collect()}
    bigrams = lambda t: {t[i : i + 2] for i in range(len(t) - 1)}
    assert asked == {(a, b, 2): len(bigrams(said[a]) | bigrams(said[b])) for a, b in ((0, 35), (3, 8))}


def test_exact_pairs_reach_their_certificate(spark):
    """The maximisers of these pairs are beyond a dozen symbols."""
    rng = __import__("random").Random(3)
    texts = {i: "".join("a" * 20 + rng.choice("bc") for _ in range(40)) for i in range(4)}
    rows = spark.createDataFrame(list(texts.items()), "id bigint, text string")
    sets = lambda t, k: {t[i : i + k] for i in range(len(t) - k + 1)}
    delta = lambda *ts: max(len(set().union(*(sets(t, k) for t in ts))) / k for k in range(1, 841))
    for r in distance.all_pairs_distance(rows, "delta").collect():
        a, b = texts[r["id_a"]], texts[r["id_b"]]
        both, da, db = delta(a, b), delta(a), delta(b)
        assert r["dist"] == pytest.approx((both - min(da, db)) / max(da, db))


def test_shared_counts_over_many_members(monkeypatch):
    import numpy as np

    monkeypatch.setattr(distance, "COLUMNS", 5)
    rng = np.random.default_rng(0)
    sets = [np.unique(rng.integers(0, 60, n)) for n in (0, 3, 30, 50, 50)]
    assert distance.shared_counts(sets).tolist() == [[len(np.intersect1d(a, b)) for b in sets] for a in sets]
    assert distance.shared_counts([]).shape == (0, 0)


def test_auc_in_ranges(spark):
    import random

    rng = random.Random(1)
    rows = [(round(rng.random(), 2), rng.randint(0, 1)) for _ in range(500)]
    pos, neg = [s for s, y in rows if y], [s for s, y in rows if not y]
    truth = sum((p > n) + 0.5 * (p == n) for p in pos for n in neg) / len(pos) / len(neg)
    for ranges in (2, 7, 256):
        assert metrics.rank_auc(spark.createDataFrame(rows, "s double, y int"), "s", "y", ranges).first()["auc"] == pytest.approx(truth)
