"""Queries over tables on which a cut would show."""

import random
from datetime import datetime, timedelta

import pytest

from repetix import workloads
from repetix.plans.accuracy import sampled_lengths

COLUMNS = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def documents(spark, path, texts):
    rows = [(i, t, "en", f"s{i % 2}", len(t)) for i, t in enumerate(texts)]
    spark.createDataFrame(rows, COLUMNS).write.parquet(f"{path}/documents.parquet")
    return str(path)


def run(spark, name, sf):
    return workloads.queries()[name](spark, sf).collect()


def test_a_user_of_many_events_is_counted(spark, tmp_path):
    start = datetime(2024, 1, 1)
    rows = [(i, start + timedelta(seconds=i), 1 if i < 100_050 else 2, "click" if i % 3 else "view") for i in range(100_060)]
    spark.createDataFrame(rows, "event_id bigint, ts timestamp, user_id bigint, event_type string").coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    assert {(r["id"], r["n"]) for r in run(spark, "stream_drop_policy", str(tmp_path))} == {(1, 100_050), (2, 10)}


def test_bands_of_very_long_documents(spark, tmp_path):
    sf = documents(spark, tmp_path, ["x" * 204_999, "x" * 205_000, "x" * 412_345, ""])
    assert {(r["id"], r["low"]) for r in run(spark, "range_blocks", sf)} == {(0, 200_000), (1, 205_000), (2, 410_000), (3, 0)}


def brute(texts):
    best = 0
    for k in range(1, max(map(len, texts)) + 1):
        if sum(max(0, len(t) - k + 1) for t in texts) <= best * k:
            break
        best = max(best, len({t[i : i + k] for t in texts for i in range(len(t) - k + 1)}) / k)
    return best


def far_texts():
    """Their maximiser is beyond a hundred symbols."""
    rng = random.Random(5)
    return ["".join("a" * 40 + rng.choice("bc") for _ in range(100)) for _ in range(2)]


def test_lengths_go_on_until_none_can_win(spark, tmp_path):
    texts = far_texts()
    sf, alone = documents(spark, tmp_path, texts), [brute([t]) for t in texts]
    both = brute(texts)
    assert min(alone) > 3.5
    for name in ("hll_delta", "theta_delta", "packed_delta"):
        assert [r["delta"] for r in sorted(run(spark, name, sf), key=lambda r: r["id"])] == pytest.approx(alone, rel=0.2)
    for name in ("packed_group_delta", "hll_merge_delta"):
        assert {r["source"]: r["delta"] for r in run(spark, name, sf)} == pytest.approx({"s0": alone[0], "s1": alone[1]}, rel=0.2)
    rolled = {(r["lang"], r["source"]): r["delta"] for r in run(spark, "sketch_rollup", sf)}
    assert rolled == pytest.approx({("en", "s0"): alone[0], ("en", "s1"): alone[1], ("en", None): both, (None, None): both}, rel=0.2)
    assert run(spark, "long_string_delta", sf)[0]["delta"] > 0.8 * both


def on_grid(text, alpha=1.25):
    """(delta, its length) over the sampled lengths."""
    return max((len({text[i : i + k] for i in range(len(text) - k + 1)}) / k, -k) for k in sampled_lengths(len(text), alpha))


def test_median_of_copies_goes_on_until_no_length_can_win(spark, tmp_path):  # F4
    texts = far_texts()
    spark.createDataFrame([(1, i, t) for i, t in enumerate(texts)], "conv_id bigint, turn int, text string").write.parquet(f"{tmp_path}/conversations.parquet")
    found = sorted(run(spark, "f0_median_delta", str(tmp_path)), key=lambda r: r["id"])
    assert min(r["k_hat"] for r in found) > 40
    assert [r["delta"] for r in found] == pytest.approx([on_grid(t)[0] for t in texts], rel=0.06)


def test_errors_by_ratio_are_over_all_lengths(spark, tmp_path):  # F5
    texts = far_texts()
    sf = documents(spark, tmp_path, texts)
    found = {(r["cd"], r["alpha"]): r["max"] for r in run(spark, "sketch_error_by_alpha", sf)}
    for alpha in (2.0, 1.5, 1.25, 1.1, 1.05):
        wanted = max(1 - on_grid(t, alpha)[0] / brute([t]) for t in texts)  # the grid's own share
        assert found["theta", alpha] == pytest.approx(wanted, abs=1e-9) and found["hll", alpha] == pytest.approx(wanted, abs=0.05)


def test_sketches_go_up_to_each_documents_length(spark, tmp_path):  # F6
    rng = random.Random(6)
    texts = ["".join(rng.choice("abcd") for _ in range(n)) for n in (1, 90, 101, 5000)]
    found = {r["id"]: (r["lengths"], r["bytes"]) for r in run(spark, "sketch_size_documents", documents(spark, tmp_path, texts))}
    assert {i: n for i, (n, _) in found.items()} == {i: len(sampled_lengths(len(t))) for i, t in enumerate(texts)}
    assert found[3][1] > 4096 * sum(4 ** k > 1000 and 5000 - k > 1000 for k in sampled_lengths(5000))


def test_group_delta_over_all_lengths(spark, tmp_path):
    rng = random.Random(1)
    texts = ["".join(rng.choice("ab") for _ in range(600)) for _ in range(4)] + [""]
    sf = documents(spark, tmp_path, texts)
    groups = {f"s{j}": brute(texts[j::2]) for j in range(2)}
    assert {r["source"]: r["delta"] for r in run(spark, "group_delta_all_lengths_by_source", sf)} == pytest.approx(groups)
    rolled = {(r["lang"], r["source"]): r["delta"] for r in run(spark, "group_delta_all_lengths_rollup", sf)}
    assert rolled == pytest.approx({("en", s): d for s, d in groups.items()} | {("en", None): brute(texts), (None, None): brute(texts)})


@pytest.mark.parametrize("name", ["kmv", "f0", "linear_counting"])
def test_items_over_all_lengths(spark, sf_dir, name):
    exact = {r["id"]: r["delta"] for r in run(spark, "exact_delta_items", sf_dir)}
    near = {r["id"]: r["delta"] for r in run(spark, f"{name}_delta_all_lengths", sf_dir)}
    assert near == pytest.approx(exact, rel=0.5 if name == "kmv" else 0.3)


def test_overlap_and_near_copies_of_documents(spark, tmp_path):
    rng = random.Random(2)
    words = lambda n: " ".join("".join(rng.choice("abcdefgh") for _ in range(6)) for _ in range(n))
    item, text = words(20), words(300)
    sf = documents(spark, tmp_path, [text, words(300) + item, text[:1000] + "x" + text[1000:], words(40), words(300)])
    spark.createDataFrame([(1, item), (2, words(20))], "item_id bigint, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    assert {(r["id"], r["d"] == r["shared"], r["shared"] > 0) for r in run(spark, "benchmark_overlap_documents", sf)} == {(1, True, True), (2, False, False)}
    assert [(r["id_a"], r["id_b"]) for r in run(spark, "near_documents_by_sketch", sf)] == [(0, 2)]
