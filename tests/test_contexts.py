"""Counts of sets over ranges of lengths, against plain ones."""

import random

import numpy as np
import pytest

from repetix.operators import contexts


def plain(texts, low, high):
    return {k: d for k in range(low, high + 1) if (d := len({t[i : i + k] for t in texts for i in range(len(t) - k + 1)}))}


def some_texts(letters):
    rng = random.Random(len(letters))
    texts = ["".join(rng.choice(letters) for _ in range(rng.choice([0, 1, 3, 4, 5, 16, 17, 40, 300]))) for _ in range(40)]
    return texts + texts[:5] + ["", letters[0] * 200, texts[-1][:100] + "\0" + texts[-1], letters[-1] * 17]


@pytest.mark.parametrize("low,high", [(1, 4), (5, 16), (17, 64), (3, 5), (65, 256)])
@pytest.mark.parametrize("letters", ["ab", "abcdefgh \n\U0001f600é", "".join(map(chr, range(0x4E00, 0x4E00 + 400)))], ids=["two", "some", "many"])
def test_counts_of_ranges(spark, monkeypatch, low, high, letters):
    texts = some_texts(letters)
    rows = [(None if i % 3 == 2 else f"g{i % 3}", t) for i, t in enumerate(texts)]
    df = spark.createDataFrame(rows, "g string, text string").repartition(3)
    monkeypatch.setattr(contexts, "SORTED", 20_000)  # several buckets, counted in parts
    found: dict = {}
    for r in contexts.range_profile(df, ["g"], low, high).collect():
        found.setdefault(r["g"], {})[r["k"]] = r["d"]
    assert found == {g: p for g in (None, "g0", "g1") if (p := plain([t for h, t in rows if h == g], low, high))}


def test_less_than_a_fingerprint_for_each_length_is_dealt_out():
    rng = np.random.default_rng(1)
    codes = np.concatenate((rng.integers(1, 30, 100_000).astype(np.uint8), np.zeros(100, np.uint8)))
    for low, high in ((5, 16), (17, 64)):
        starts, sizes, _ = contexts.stretches(codes, low)
        assert sizes.sum() == 100_000 - low + 1 and sizes.max() <= contexts.reach(low)
        assert len(starts) * (contexts.reach(low) + high) < 16 * 100_000  # `window_rows` had 12 bytes for each of the lengths


def test_rollup_reads_the_code_points_once(spark, tmp_path, monkeypatch):
    from repetix import workloads

    calls, read = [], contexts.alphabet
    monkeypatch.setattr(contexts, "alphabet", lambda *a: calls.append(1) or read(*a))
    rows = [(i, t, "en" if i % 2 else "de", f"s{i % 3}", len(t)) for i, t in enumerate(["abcab" * 8, "bcdbcd", "", "xyzxyzzy", "abc"])]
    spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint").write.parquet(f"{tmp_path}/documents.parquet")
    found = {(r["lang"], r["source"]): r["delta"] for r in workloads.queries()["group_delta_all_lengths_rollup"](spark, str(tmp_path)).collect()}
    sets = {(a, b): [t for _, t, x, y, _ in rows if a in (None, x) and b in (None, y)] for _, _, x, y, _ in rows for a, b in ((x, y), (x, None), (None, None))}
    assert found == pytest.approx({g: max((d / k for k, d in plain(ts, 1, 40).items()), default=0) for g, ts in sets.items() if any(ts)}) and len(calls) == 1
