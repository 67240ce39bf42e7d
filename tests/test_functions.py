import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from repetix.functions import suffixes
from repetix.functions.fingerprint import FingerprintParams, code_points, fingerprint, is_prime, length_weights, power_mod, window_fingerprints
from repetix.functions.hashing import hash_array, hash_column, trailing_zeros
from repetix.functions.symbols import encode
from repetix.plans.accuracy import plan_accuracy, sampled_lengths, should_drop, window_length

strings = st.text(alphabet="ab\n é\U0001f600", max_size=40)


def profile(s):
    return [len({s[i : i + k] for i in range(len(s) - k + 1)}) for k in range(1, len(s) + 1)]


def delta(s):
    return max((d / k for k, d in enumerate(profile(s), 1)), default=0.0)


@settings(max_examples=150, deadline=None)
@given(strings)
def test_profiles_agree_with_brute_force(s):
    x, expected = encode(s), profile(s)
    assert suffixes.profile_from_lcp(x).tolist() == expected
    names, prints = suffixes.window_names(x), window_fingerprints(x)
    for k, d in enumerate(expected, 1):
        assert names(k).max() + 1 == d == len(np.unique(prints(k)))
    for patience in (3, 64):
        assert suffixes.exact_delta(x, patience=patience)[0] == pytest.approx(delta(s))
    assert suffixes.exact_delta(x, bounded=False)[0] == pytest.approx(delta(s))


@settings(max_examples=100, deadline=None)
@given(strings)
def test_parses_and_transform(s):
    x = encode(s)
    i = phrases = 0
    while i < len(s):
        n = 0
        while i + n < len(s) and s.find(s[i : i + n + 1], 0, i + n) != -1:
            n += 1
        i += max(1, n)
        phrases += 1
    assert suffixes.lz77_phrases(x) == phrases
    order = sorted(range(len(s) + 1), key=lambda j: s[j:])
    assert suffixes.bwt(x).tolist() == [0 if j == 0 else ord(s[j - 1]) + 1 for j in order]
    r, without = suffixes.runs(suffixes.bwt(x)), suffixes.runs(suffixes.bwt(x), marker=False)
    assert r - 2 <= without <= r
    assert suffixes.lz77_phrases(x, overlapping=False) >= phrases


def test_worked_transform():
    transform = suffixes.bwt(encode("abbab"))
    assert [chr(c - 1) if c else "$" for c in transform] == list("bb$aba")
    assert suffixes.runs(transform) == 5 and suffixes.lf(transform)[1] + 1 == 5


@pytest.mark.parametrize("n,value,k", [(64, 3.0769230769, 13), (256, 3.2653061224, 49), (1024, 3.3160621762, 193), (4096, 3.3289986996, 769)])
def test_parity_words_have_long_maximisers(n, value, k):
    found = suffixes.exact_delta(np.array([bin(i).count("1") % 2 for i in range(n)]))
    assert found[0] == pytest.approx(value) and found[1] == k


@pytest.mark.parametrize("s,value,k", [("abcdef", 6, 1), ("aaa", 1, 1), ("babba", 2, 1), ("", 0, 0), ("x", 1, 1), ("aaaabaabbababb", 2.75, 4)])
def test_small_deltas(s, value, k):
    assert suffixes.exact_delta(encode(s))[:2] == (value, k)


def test_entropy_and_grammar():
    assert suffixes.entropy(encode("abab")) == 1 and suffixes.entropy(encode("abab"), 1) == 0
    assert suffixes.pair_grammar_size(encode("abababab")) < 8
    assert suffixes.lz78_phrases(encode("aababc")) == 3


def test_fingerprints():
    params = FingerprintParams()
    q = params.moduli[0]
    x = encode("substring")
    for k in (1, 3, 9):
        expected = [sum(int(c) * pow(params.base, k - 1 - j, q) for j, c in enumerate(x[i : i + k])) % q for i in range(len(x) - k + 1)]
        assert (window_fingerprints(x)(k) >> 31).tolist() == expected
    assert len(window_fingerprints(x)(10)) == 0
    assert length_weights([5])[5][0] == pow(params.base, 4, q)
    assert all(is_prime(p) for p in FingerprintParams.drawn(3).moduli) and not is_prime(2147483629 * 3)


def test_column_forms_match_kernels(spark):
    rng = random.Random(0)
    rows = [(i, "".join(rng.choice("abcé\U0001f600") for _ in range(i))) for i in range(0, 40)]
    df = spark.createDataFrame(rows, "id int, text string")
    q = FingerprintParams().moduli[0]
    got = df.select("text", fingerprint(code_points("text"), q).alias("f"), power_mod(F.length("text"), q).alias("w")).collect()
    for r in got:
        f = 0
        for c in r["text"]:
            f = (f * 1114112 + ord(c)) % q
        assert r["f"] == f and r["w"] == pow(1114112, len(r["text"]), q)
    fps = [rng.randrange(1 << 62) for _ in range(200)]
    got = spark.createDataFrame([(f,) for f in fps], "fp bigint").select("fp", *[hash_column("fp", k).alias(k) for k in ("level", "bucket", "order")], trailing_zeros(hash_column("fp", "level")).alias("z")).collect()
    for r in got:
        for k in ("level", "bucket", "order"):
            assert hash_array(np.array([r["fp"]]), k)[0] == r[k]
        assert r["z"] == (r["level"] & -r["level"]).bit_length() - 1


def test_grids_and_plans():
    assert sampled_lengths(100, 1.5) == [1, 2, 3, 4, 6, 8, 12, 18, 26, 39, 58, 87]
    assert 1 not in sampled_lengths(100, 1.25, "literal")
    assert sampled_lengths(64, grid="powers_of_two") == [1, 2, 4, 8, 16, 32, 64]
    assert set(sampled_lengths(50, 1.1)) <= set(sampled_lengths(5000, 1.1))
    with pytest.raises(ValueError):
        sampled_lengths(10, 3.0)
    assert plan_accuracy(0.2).alpha == pytest.approx(1.05) and plan_accuracy(0.2, "distance").alpha == pytest.approx(1.01)
    assert plan_accuracy(0.1, "distance").hll_lg_k == 16
    n = 128_657
    assert window_length(n) == 6089 and should_drop(48_706, n, 6089) and not should_drop(48_000, n, 6089)


def test_hash_without_divisions_is_the_hash():  # F20
    import numpy as np

    from repetix.functions import hashing

    rng = np.random.default_rng(5)
    fps = np.concatenate([rng.integers(0, 2147483629, 20_000) << 31 | rng.integers(0, 2147483587, 20_000), np.array([0, 1, 2147483628 << 31 | 2147483586])])
    for kind in hashing.SEEDS:
        for copy in (0, 1, 2, 60):
            a, b, c = hashing.seed_for(kind, copy)
            assert (hashing.hash_array(fps, kind, copy) == hashing._finish((a * (fps >> 31) + b * (fps & hashing.P) + c) % hashing.P)).all()
