"""Sketches made in the task against those of Spark's aggregates."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from repetix import workloads
from repetix.functions import suffixes
from repetix.operators import narrow, sketch
from repetix.operators.distinct import F0, Exact, F0Median, Hll, Kmv, LinearCounting, Theta, window_rows

from .test_pairs_unbroadcast import plan_of
from .test_whole_job import documents

LENGTHS = [1, 2, 3, 7, 30]


@pytest.fixture(scope="module")
def strings(spark):
    rng = random.Random(7)
    texts = ["", "a", "ab" * 300, "".join(rng.choice("abcdefgh") for _ in range(9000))] + ["".join(rng.choice("abcd") for _ in range(n)) for n in (5, 9, 40, 150, 380, 390, 700, 2500)]
    return spark.createDataFrame(list(enumerate(texts)), "id bigint, text string").coalesce(2)


def content(cd):
    """Registers or coupons and the size; the running estimate depends on the order."""
    raw = bytes(cd)
    if raw[7] == 10:
        return raw[40:], raw[32:36], len(raw)
    ints = np.frombuffer(raw, "<u4")[2 if raw[7] == 8 else 3 :]
    return raw[:8], tuple(sorted(ints[ints > 0].tolist())), len(raw)


@pytest.mark.parametrize("lg_k", [9, 12])
def test_images_are_those_of_the_aggregate(strings, lg_k):  # F8
    a = Hll(lg_k).build(window_rows(strings, LENGTHS), ["id", "k"])
    b = narrow.per_key(strings, ["id"], LENGTHS, narrow.hll_images(lg_k), "cd binary")
    read = lambda df: {(r["id"], r["k"]): r for r in df.select("id", "k", "cd", F.hll_sketch_estimate("cd").alias("e")).collect()}
    x, y = read(a), read(b)
    assert {i: content(r["cd"]) for i, r in x.items()} == {i: content(r["cd"]) for i, r in y.items()}
    assert {i: r["e"] for i, r in y.items()} == pytest.approx({i: r["e"] for i, r in x.items()}, rel=0.15 if lg_k == 9 else 0.06)
    counts = {(r["id"], r["k"]): r["d"] for r in Hll(lg_k).of_strings(strings, ["id"], LENGTHS).collect()}
    assert counts == {i: r["e"] for i, r in y.items()}


@pytest.mark.parametrize("cd", [Theta(), Exact(), Kmv(64), F0(256), F0Median(3, 256), LinearCounting()], ids=repr)
def test_estimates_are_those_of_the_aggregate(strings, cd):  # F10, F18
    a = {(r["id"], r["k"]): r["d"] for r in cd.estimates(cd.build(window_rows(strings, LENGTHS), ["id", "k"]), ["id", "k"]).collect()}
    assert {(r["id"], r["k"]): r["d"] for r in cd.of_strings(strings, ["id"], LENGTHS).collect()} == pytest.approx(a)


def test_sets_have_the_registers_of_the_aggregate(strings):  # F7, F16
    sets = strings.withColumn("g", F.col("id") % 3)
    a = Hll().build(window_rows(sets, LENGTHS, ["g"]), ["g", "k"])
    b = sketch.build_sketch(sets, by=("g",), lengths=LENGTHS)
    read = lambda df: {(r["g"], r["k"]): content(r["cd"]) for r in df.collect()}
    assert read(a) == read(b)


def test_deltas_stop_where_no_longer_length_can_win(strings):  # F6, F13, F15
    cd = Exact()
    whole = {r["id"]: (r["delta"], r["k_hat"]) for r in sketch.estimate_delta(cd.build(window_rows(strings, range(1, 60)), ["id", "k"]), cd=cd).collect()}
    assert {r["id"]: (r["delta"], r["k_hat"]) for r in cd.deltas(strings, ["id"], range(1, 60)).collect()} == whole


@pytest.mark.parametrize("name", ["hll_delta", "theta_delta", "sketch_size_documents", "certified_documents"])
def test_windows_of_documents_are_not_shuffled(spark, tmp_path, name):  # F6, F8, F13, F18
    sf = documents(spark, tmp_path, ["abcabc" * 9, "xyz" * 30])
    plan = plan_of(workloads.queries()[name](spark, sf)).split("== Physical Plan ==")[1]
    assert "fp#" not in plan and "sketch_agg" not in plan


def test_errors_of_sets_are_those_of_the_families(spark):
    from repetix.operators.distinct import approx_profile

    rng = random.Random(9)
    rows = [(i % 5, "".join(rng.choice("abcdefgh"[: 2 + i % 7]) for _ in range(n))) for i, n in enumerate([0, 3, 40, 900, 6000, 30_000, 1, 25, 300, 2000, 9000])] + [(9, "")]
    df = spark.createDataFrame(rows, "id int, text string").coalesce(1)
    grids = {2.0: [1, 2, 4, 8, 16], 1.5: [1, 2, 3, 4, 6, 8, 12]}
    families = {"exact": Exact(), "hll": Hll(), "theta": Theta(), "kmv": Kmv(64), "f0": F0(256), "f0_median": F0Median(3, 256), "linear": LinearCounting(32768)}
    kernels = {n: cd.kernel() for n, cd in families.items()} | {"approx": narrow.approx_counts(*narrow.approx_tables(spark))}
    found: dict = {}
    for r in narrow.set_errors(df.groupBy("id").agg(F.collect_list("text").alias("texts")), grids, kernels).collect():
        found.setdefault((r["cd"], r["alpha"]), []).append(r["error"])
    windows = window_rows(df, sorted({k for ks in grids.values() for k in ks})).distinct().cache()
    counts = {n: {(r["id"], r["k"]): r["d"] for r in cd.estimates(cd.build(windows, ["id", "k"]), ["id", "k"]).collect()} for n, cd in families.items()}
    counts["approx"] = {(r["id"], r["k"]): r["d"] for r in approx_profile(windows, ["id", "k"]).collect()}
    top = lambda of, i, ks: max(of[i, k] / k for k in ks if (i, k) in of)
    every = sorted({k for ks in grids.values() for k in ks})
    for name, of in counts.items():
        for alpha, ks in grids.items():
            wanted = [abs(top(of, i, ks) / top(counts["exact"], i, every) - 1) for i in range(5)]
            assert sorted(found[name, alpha]) == pytest.approx(sorted(wanted), abs=0.06 if name == "hll" else 1e-9), name


def test_errors_of_other_corpora_shuffle_no_windows(spark, sf_dir):
    found = workloads.queries()["sketch_error_other_corpora"](spark, sf_dir)
    rows = found.collect()
    assert len(rows) == 2 * 8 * 6 and all(r["mean"] <= r["p99"] + 0.2 and r["max"] < 0.6 for r in rows)
    assert {r["strings"] for r in rows if r["corpus"] == "pages"} == {50}


def test_strings_of_a_set_wait_for_each_other(monkeypatch):  # F16
    import random

    import numpy as np
    import pyarrow as pa

    from repetix.functions.fingerprint import FingerprintParams, window_fingerprints
    from repetix.functions.symbols import encode
    from repetix.operators import narrow

    class Here:
        def mapInArrow(self, run, schema):
            return run

    rng = random.Random(8)
    rows = [(f"s{i % 4}", "".join(rng.choice("abcdefgh") for _ in range(30 if i % 7 else i % 3))) for i in range(3000)]
    batches = [pa.table({"source": [r[0] for r in rows[i : i + 500]], "__text": [r[1] for r in rows[i : i + 500]]}).to_batches()[0] for i in range(0, 3000, 500)]
    calls, made = [], narrow.coupons
    monkeypatch.setattr(narrow, "coupons", lambda *a: calls.append(1) or made(*a))
    monkeypatch.setattr(narrow, "_kept", lambda *a: (Here(), {"source": "string", "__text": "string"}, "codepoint"))
    lengths = [1, 2, 3, 5, 8]
    found = {(r["source"], r["k"]): r["cd"] for out in narrow.hll_of_sets(None, ["source"], lengths, 12)(iter(batches)) for r in out.to_pylist()}
    assert len(calls) <= 2 * 4 * len(lengths)  # one for each key and length of every 256 strings before
    for s in ("s0", "s3"):
        for k in lengths:
            fps = np.concatenate([window_fingerprints(encode(t), FingerprintParams())(k) for key, t in rows if key == s])
            every = np.unique(made(fps))
            if len(every) > narrow.coupon_limit(12):
                state = np.zeros(4096, np.uint8)
                np.maximum.at(state, every & 4095, (every >> 26).astype(np.uint8))
                assert found[s, k] == narrow.register_images(state[None])[0].tobytes()
            else:
                assert found[s, k] == narrow.coupon_images(np.zeros(len(every), np.int64), every, 12)[1].tobytes()


def test_lengths_that_cannot_win_on_a_grid_are_passed_over(spark):  # F2
    rng = random.Random(4)
    texts = ["".join(rng.choice("abcdefghij"[:a]) for _ in range(n)) * times for a in (1, 2, 10) for n, times in ((1, 1), (2, 1), (40, 1), (2500, 1), (90, 40), (700, 5))]
    df = spark.createDataFrame([(i, t) for i, t in enumerate([*texts, ""])], "id int, text string").coalesce(2)
    grids = [[1, 2, 4, 8, 16, 32, 64, 128, 256], [1, 2, 3, 4, 6, 8, 12, 18, 26, 39, 58, 87, 130, 195], [2, 4, 8, 16, 32, 64, 128]]
    every = sorted({k for ks in grids for k in ks})
    for cd in (Hll(), Theta(), Exact(), F0Median(3, 256)):
        best = lambda df, ks: {r["id"]: r["best"] for r in df.where(F.col("k").isin(ks)).groupBy("id").agg(F.max(F.col("d") / F.col("k")).alias("best")).collect()}
        whole, some = cd.of_strings(df, ["id"], every).cache(), cd.of_strings(df, ["id"], every, grids).cache()
        assert some.count() < whole.count() / 1.5
        for ks in grids:
            assert best(some, ks) == best(whole, ks)


def test_exact_delta_passes_over_lengths_that_cannot_win():  # F2
    rng = np.random.default_rng(3)
    words = [rng.integers(-2, a, n).astype(np.int64) for a in (0, 3, 300, 3_000_000) for n in (0, 1, 5, 80, 700)]
    for s in [*words, *(np.tile(w, 30) for w in words), np.concatenate([np.append(np.zeros(90, np.int64), rng.integers(1, 3)) for _ in range(60)])]:
        assert suffixes.exact_delta(s)[:2] == suffixes.delta_of_profile(suffixes.profile_from_lcp(s))
