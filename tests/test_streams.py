import random

import pytest
from pyspark.sql import functions as F

from repetix.functions.suffixes import exact_delta
from repetix.operators.distinct import F0, window_rows
from repetix.streaming import stream_sketch as streams
from repetix.streaming.run_length_bwt import Bookmarks, RunLengthBwt
from repetix.streaming.stream_sketch import StreamSketch


def brute(stream):
    text = stream[::-1] + [0]
    order = sorted(range(len(text)), key=lambda i: text[i:])
    return [text[i - 1] for i in order]


def test_worked_example():
    bwt, marks, seen = RunLengthBwt(), Bookmarks([2]), []
    for n, a in enumerate([2, 1, 1], 1):  # b, a, a
        marks.advance(bwt, bwt.extend(a), n)
        seen.append(([bwt.access(i) for i in range(len(bwt))], marks.places.get(2, -1) + 1))
    assert seen == [([2, 0], 0), ([2, 0, 1], 1), ([2, 0, 1, 1], 4)]


@pytest.mark.parametrize("seed", range(6))
def test_transform_grows_like_brute_force(seed):
    rng = random.Random(seed)
    bwt, lengths, stream, before = RunLengthBwt(), [1, 2, 5, 20], [], 0
    marks = Bookmarks(lengths)
    for n in range(1, 120):
        stream.append(rng.randint(1, 3) if seed % 2 else 1 + n * n // 5 % 3)
        marks.advance(bwt, bwt.extend(stream[-1]), n)
        assert [bwt.access(i) for i in range(len(bwt))] == brute(stream)
        assert all(marks.symbol(bwt, k) == stream[-k] for k in lengths if n >= k)
        r, kept = bwt.runs(), bwt.runs(marker=False)
        assert r - 2 <= kept <= r and kept >= before
        before = kept
        if n % 25 == 0:
            bwt = RunLengthBwt.restore(bwt.state())


@pytest.mark.parametrize("window,constant", [(4, 8.0), (400, 8.0), (4, 0.01)])
def test_stream_counts(window, constant):
    rng = random.Random(window)
    stream, lengths = [rng.randint(0, 2) for _ in range(250)], [1, 2, 3, 5, 9, 30]
    sketch = StreamSketch(500, lengths, window=window, discard_constant=constant, cd="exact")
    at = 0
    while at < len(stream):
        step = rng.randint(1, 40)
        sketch = StreamSketch.loads(sketch.extend(stream[at : at + step]).dumps())
        at += step
    for k, d in sketch.profile():
        exact = len({tuple(stream[i : i + k]) for i in range(len(stream) - k + 1)})
        assert d == exact if k not in sketch.frozen() else d <= exact
    assert (sketch.dropped_at is not None) == (constant < 1)
    with pytest.raises(ValueError):
        sketch.extend(range(1000))


def test_naive_buffer_is_the_window_of_the_whole_stream():
    stream = [0, 1, 1, 0] * 30
    sketch = StreamSketch(len(stream), list(range(1, 121)), window=len(stream), transform=False, cd="exact").extend(stream)
    import numpy as np

    assert sketch.estimate() == exact_delta(np.array(stream))[:2]
    assert sketch.words() >= len(stream)


def test_registers_equal_batch(spark):
    rng = random.Random(1)
    text = "".join(rng.choice("abcd") for _ in range(2000))
    sketch = StreamSketch(5000, [3, 6], cd="f0", m=128, transform=False)
    for i in range(0, 2000, 77):
        sketch.extend(map(ord, text[i : i + 77]))
    rows = F0(128).build(window_rows(spark.createDataFrame([(1, text)], "id int, text string"), [3, 6]), ["id", "k"]).collect()
    for k in (3, 6):
        batch = {r["bucket"]: r["level"] for r in rows if r["k"] == k}
        assert {b: int(x) for b, x in enumerate(sketch.states[k].values) if x >= 0} == batch


def test_spark_stream_over_batches_and_restart(spark, tmp_path):
    rng = random.Random(2)
    symbols = {u: [rng.randint(0, 3) for _ in range(60)] for u in range(4)}
    schema = "id bigint, seq bigint, symbol int"
    source = str(tmp_path / "in")

    def put(start, stop):
        rows = [(u, i, s[i]) for u, s in symbols.items() for i in range(start, stop)]
        rng.shuffle(rows)
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(source)

    def go():
        stream = spark.readStream.schema(schema).parquet(source)
        rows = streams.stream_sketch(stream, ["seq"], n_max=1000, lengths=[1, 2, 7], window=3, cd="exact")
        q = rows.writeStream.format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start()
        q.awaitTermination()
        return rows.schema

    put(0, 20)
    go()
    put(20, 60)
    schema_out = go()
    last = streams.latest(spark.read.schema(schema_out).parquet(str(tmp_path / "out"))).collect()
    assert len(last) == 4
    for r in last:
        s = symbols[r["id"]]
        assert r["n"] == 60
        for p in r["profile"]:
            assert p["d"] == len({tuple(s[i : i + p["k"]]) for i in range(60 - p["k"] + 1)})


def test_windowed_profile(spark):
    rows = spark.createDataFrame([("2024-01-01 01:00:00", "abab"), ("2024-01-01 05:00:00", "abc"), ("2024-01-02 01:00:00", "zz")], "ts string, text string").withColumn("ts", F.to_timestamp("ts"))
    got = {(str(r["start"])[:10], r["k"]): r["d"] for r in streams.windowed_profile(rows, "ts", F.window("ts", "1 day"), [], [1, 2]).collect()}
    assert got == {("2024-01-01", 1): 3, ("2024-01-01", 2): 3, ("2024-01-02", 1): 1, ("2024-01-02", 2): 1}


def test_words_held_follow_the_window():
    rng = random.Random(8)
    sketch = StreamSketch(1 << 20, [1, 2, 4, 8, 16], window=64, cd="kmv", m=256, transform=False)
    sizes = []
    for _ in range(20):
        sizes.append(sketch.extend(rng.randint(0, 3) for _ in range(1000)).words())
    assert sizes[-1] == sizes[5] and sizes[-1] <= 64 + 5 * 256 + 10
    assert sketch.adds >= 5 * (20_000 - 16)


def test_default_state_is_sub_linear_and_runs_are_counted_as_they_come():
    rng = random.Random(4)
    n = 40_000
    sketch = StreamSketch(n, [1, 2, 4, 8, 16, 4096, 16384], discard_constant=0.2)
    sizes = [sketch.extend(rng.randint(0, 3) for _ in range(4000)).words() for _ in range(10)]
    assert sketch.window == 3058 and sketch.short == [1, 2, 4, 8, 16]
    assert sketch.dropped_at is not None and sketch.runs() is None and sketch.frozen() == [4096, 16384]
    assert sizes[-1] <= sketch.window + 7 * 128 + 2 * 2 and len(sketch.dumps()) < 8 * n / 4
    kept = StreamSketch(n, [1, 2, 4, 8, 16, 4096, 16384]).extend(rng.randint(0, 1) for _ in range(6000))
    state = [s for s, _ in kept.bwt.state() if s]
    assert kept.runs() == sum(1 for i, s in enumerate(state) if not i or state[i - 1] != s)
    # a random stream's maximiser is short, so the counted lengths reach the certificate
    assert sketch.certified() and sketch.bound() <= 16


def test_chunked_text_and_late_rows(spark, tmp_path):
    schema = "id string, seq bigint, text string"
    source = str(tmp_path / "in")

    def put(*rows):
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(source)

    put(("a", 2, "cd"), ("a", 1, "ab"), ("b", 5, "x"))
    put(("a", 4, "ef"), ("a", 2, "late"), ("b", 6, None), ("a", 1, "later"))
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(source)
    rows = streams.run_to_table(streams.stream_sketch(stream, ["seq"], n_max=100, lengths=[1, 2], cd="exact"), "chunks")
    last = {r["id"]: r for r in streams.latest(rows).collect()}
    assert last["a"]["n"] == 6 and {p["k"]: p["d"] for p in last["a"]["profile"]} == {1: 6, 2: 5}
    assert last["b"]["n"] == 1 and last["a"]["bound"] == 1 and last["a"]["certified"]
    assert sorted(map(tuple, streams.late_rows(rows).collect())) == [("a", 1, "later"), ("a", 2, "late")]


def test_memory_of_a_long_chunk_follows_the_window():
    import tracemalloc

    import numpy as np

    stream = np.random.default_rng(3).integers(0, 4, 1 << 21)
    sketch = StreamSketch(1 << 22, [1, 2, 4, 8, 16, 256], window=256, m=256, transform=False)
    tracemalloc.start()
    sketch.extend(stream)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 16 * stream.nbytes / 4  # the whole chunk's fingerprints alone took 16 bytes a symbol for each power of two
    parts = StreamSketch(1 << 22, [1, 2, 4, 8, 16, 256], window=256, m=256, transform=False)
    for i in range(0, len(stream), 100_000):
        parts.extend(stream[i : i + 100_000])
    assert parts.profile() == sketch.profile() and parts.adds == sketch.adds and (parts.recent == sketch.recent).all()
    texts = ["ab" * 200_000, None, "", "c" * 300_000, "\U0001f600"]
    whole = StreamSketch(1 << 20, [1, 2, 5], window=8, cd="exact", transform=False)
    assert whole.extend_texts(texts).profile() == StreamSketch(1 << 20, [1, 2, 5], window=8, cd="exact", transform=False).extend(map(ord, "".join(t or "" for t in texts))).profile()


def test_words_of_one_large_source_stay_within_the_window(spark, tmp_path):
    import random as r

    from repetix import workloads

    rng = r.Random(6)
    rows = [(i, "".join(rng.choice("abcd ") for _ in range(40_000)), "en", "s" if i % 8 else None, 40_000) for i in range(16)]
    spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint").repartition(4).write.parquet(f"{tmp_path}/documents.parquet")
    got = {(x["id"], x["n"], x["within"]) for x in workloads.queries()["stream_state_size"](spark, str(tmp_path)).collect()}
    assert got == {("s", 14 * 40_000, True), ("", 2 * 40_000, True)}


@pytest.mark.parametrize("constant", [8.0, 0.008])
@pytest.mark.parametrize("letters", [1, 2, 5])
def test_sorting_a_chunk_is_growing_by_symbols(monkeypatch, letters, constant):
    rng = random.Random(letters)
    stream = [rng.randint(0, letters - 1) for _ in range(1500)]
    stream = stream + stream[:700] + [letters] + stream[300:900]
    options = {"lengths": [1, 2, 4, 8, 16, 33, 64, 257, 2000], "window": 8, "discard_constant": constant, "cd": "exact"}
    sketches = []
    for least in (1 << 30, 1):
        monkeypatch.setattr(streams, "LEAST", least)
        monkeypatch.setattr(streams, "PIECE", 300)
        sketch, at = StreamSketch(4000, **options), 0
        for step in (40, 700, 1, 900, 60, len(stream)):
            sketch = StreamSketch.loads(sketch.extend(stream[at : at + step]).dumps())
            at += step
        sketches.append(sketch)
    a, b = sketches
    assert (a.dropped_at is not None) == (constant < 1 and letters > 1) and a.dropped_at == b.dropped_at
    assert a.profile() == b.profile() and (a.n, a.adds, a.prints, a.whole, a.runs(), a.words()) == (b.n, b.adds, b.prints, b.whole, b.runs(), b.words())
    if a.bwt is not None:
        assert a.bwt.state() == b.bwt.state() and a.marks.places == b.marks.places
        assert (a.bwt.spelt() - 1).tolist() == stream


def test_a_long_chunk_with_the_transform_takes_microseconds_a_symbol():
    import time

    rng = random.Random(7)
    stream = [rng.randint(0, 3) for _ in range(60_000)]
    begin = time.process_time()
    sketch = StreamSketch(1 << 20, [1, 2, 4, 65_536, 131_072], window=20_000).extend(stream)
    assert sketch.bwt is not None and time.process_time() - begin < 60_000 * 8e-6


def test_rows_are_put_in_order_in_parts(monkeypatch):  # F20
    import tracemalloc

    import pandas as pd

    rng = random.Random(4)
    order = list(range(4000))
    rng.shuffle(order)

    def frames(width):
        for i in range(0, len(order), 100):
            yield pd.DataFrame({"id": "s", "text": [None if n % 7 == 0 else chr(97 + n % 26) * (n % width) for n in order[i : i + 100]], "doc_id": [n // 2 for n in order[i : i + 100]]})

    whole = pd.concat(list(frames(40))).sort_values("doc_id", kind="stable")
    monkeypatch.setattr(streams, "PART", 5000)
    monkeypatch.setattr(streams, "PIECE", 700)
    parts = list(streams.in_order(frames(40), ["doc_id"], "text"))
    assert len(parts) > 20 and list(pd.concat(parts).itertuples(index=False, name=None)) == list(whole.itertuples(index=False, name=None))
    nulls = pd.DataFrame({"text": ["x"] * 6000, "doc_id": [None, 2.0, 1.0] * 2000})
    found = pd.concat(streams.in_order(iter([nulls, nulls]), ["doc_id"], "text"))["doc_id"]
    assert found[:8000].is_monotonic_increasing and found[8000:].isna().all()
    monkeypatch.setattr(streams, "PART", 1 << 18)
    monkeypatch.setattr(streams, "PIECE", 1 << 14)
    tracemalloc.start()
    symbols = sum(len(t or "") for part in streams.in_order(frames(20_000), ["doc_id"], "text") for t in part["text"])
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert symbols > 6_000_000 and peak < symbols / 2  # the whole batch was held


def test_pieces_have_the_windows_of_the_whole_stream():  # F20
    import numpy as np

    from repetix.functions.fingerprint import FingerprintParams, Prefixes, remainder, window_fingerprints

    q = FingerprintParams().moduli
    edges = np.array([0, *(x + d for p in (*q, 1_500_000_001, 1 << 31) for x in (p, 2 * p) for d in (-1, 0, 1)), (1 << 62) + (1 << 31), (1 << 63) - 1])
    for p in (*q, 1_500_000_001):
        assert (remainder(edges, p) == edges % p).all()
    for params in (FingerprintParams(), FingerprintParams((q[0],))):
        stream, prefixes = np.random.default_rng(2).integers(0, 1_114_112, 3000), Prefixes(params, 600)
        for a, b in ((0, 0), (0, 1), (1, 4), (4, 1000), (1000, 1001), (1001, 3000)):
            prefixes.extend(stream[a:b])
            oldest = b + 1 - len(prefixes.held[0])
            for k in (1, 2, 7, 64, 600):
                first = max(0, a - k + 1)
                got = np.concatenate([np.empty(0, np.int64), *prefixes.windows(k, first - oldest, 128)])
                assert (got == window_fingerprints(stream[:b], params)(k)[first:]).all()
            prefixes.trim()
