import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from repetix.operators import distance, longstring, phylogeny, profile, sketch
from repetix.operators.distinct import FAMILY, F0, Exact, Hll, count_distinct, window_rows


@pytest.fixture(scope="module")
def texts():
    rng = random.Random(4)
    return [(i, "".join(rng.choice("abcde" + "xyz" * (i % 2)) for _ in range(rng.randint(0, 300)))) for i in range(30)]


@pytest.fixture(scope="module")
def strings(spark, texts):
    return spark.createDataFrame(texts, "id bigint, text string")


def brute(s, lengths):
    return {k: len({s[i : i + k] for i in range(len(s) - k + 1)}) for k in lengths}


LENGTHS = (1, 2, 3, 5, 9)


@pytest.mark.parametrize("kind", list(FAMILY))
def test_families_estimate(strings, texts, kind):
    cd = count_distinct(kind)
    got = {(r["id"], r["k"]): r["d"] for r in cd.estimates(sketch.build_sketch(strings, cd=cd, lengths=LENGTHS), ["id", "k"]).collect()}
    for i, s in texts:
        for k, d in brute(s, LENGTHS).items():
            if d:
                assert got[i, k] == pytest.approx(d, rel=0 if kind == "exact" else 0.15, abs=0 if kind == "exact" else 2)


@pytest.mark.parametrize("kind", ["exact", "kmv", "f0", "hll", "theta", "linear"])
def test_merging_is_the_sketch_of_the_union(strings, kind):
    cd = count_distinct(kind)
    rows = strings.withColumn("id", F.col("id") % 3)
    whole = cd.estimates(sketch.build_sketch(rows, cd=cd, lengths=LENGTHS), ["id", "k"])
    parts = sketch.build_sketch(strings, cd=cd, lengths=LENGTHS).withColumn("id", F.col("id") % 3)
    merged = cd.estimates(cd.merge(parts, ["id", "k"]), ["id", "k"])
    again = cd.estimates(cd.merge(cd.merge(parts.unionByName(parts), ["id", "k"]), ["id", "k"]), ["id", "k"])
    a, b, c = ({(r["id"], r["k"]): r["d"] for r in x.collect()} for x in (whole, merged, again))
    assert a.keys() == b.keys() == c.keys()
    assert all(a[x] == pytest.approx(b[x], rel=0.02) and b[x] == pytest.approx(c[x], rel=0.02) for x in a)


def test_registers_don_t_depend_on_partitions(strings):
    one, many = (F0(128).build(window_rows(strings.repartition(n), LENGTHS), ["id", "k"]).collect() for n in (1, 7))
    assert sorted(map(tuple, one)) == sorted(map(tuple, many))


def test_extend(spark, texts):
    cd = Exact()
    rows = spark.createDataFrame([(i, s[:100], s[100:]) for i, s in texts], "id bigint, a string, b string")
    first = rows.select("id", F.col("a").alias("text"))
    start = sketch.build_sketch(first, cd=cd, lengths=LENGTHS)
    tails = first.select("id", F.right("text", F.lit(max(LENGTHS) - 1)).alias("tail"))
    done, tails = sketch.extend_sketch(start, tails, rows.select("id", F.col("b").alias("text")), LENGTHS, cd)
    got = {(r["id"], r["k"]): r["d"] for r in cd.estimates(done, ["id", "k"]).collect()}
    for i, s in texts:
        for k, d in brute(s, LENGTHS).items():
            assert got.get((i, k), 0) == d
    assert {r["id"]: r["tail"] for r in tails.collect()} == {i: s[-(max(LENGTHS) - 1) :] for i, s in texts}


def test_nulls_and_empty_tables(spark):
    rows = spark.createDataFrame([(1, None), (2, ""), (None, "ab"), (3, "a")], "id bigint, text string")
    got = {r["id"]: (r["n"], r["delta"], r["k_hat"]) for r in profile.exact_delta(rows).collect()}
    assert got == {1: (0, 0.0, 0), 2: (0, 0.0, 0), None: (2, 2.0, 1), 3: (1, 1.0, 1)}
    empty = rows.where("false")
    assert profile.exact_delta(empty).count() == 0
    assert sketch.estimate_delta(sketch.build_sketch(empty, lengths=[1, 2])).count() == 0


@pytest.mark.parametrize("n_chunks,size", [(1, 7), (5, 7), (40, 16), (9, 64)])
def test_long_strings(spark, n_chunks, size):
    rng = random.Random(n_chunks)
    chunks = ["".join(rng.choice("abé") for _ in range(rng.randint(0, 12))) for _ in range(n_chunks)]
    whole = "".join(chunks)
    df = longstring.chunk_table(spark.createDataFrame(list(enumerate(chunks)), "at bigint, text string"), "at")
    lengths = (1, 2, 3, 8, 20)
    expected = {k: d for k, d in brute(whole, lengths).items() if d}
    for rows in (longstring.halo_windows(df, lengths), longstring.block_shift_windows(df, lengths, size=size)):
        assert {r["k"]: r["d"] for r in rows.groupBy("k").agg(F.count_distinct("fp").alias("d")).collect()} == expected


def test_distances(spark):
    rows = spark.createDataFrame([(1, "abcabc"), (2, "abcabc"), (3, "zzzzzzyx")], "id bigint, text string")
    found = {(r["id_a"], r["id_b"]): r["dist"] for r in distance.all_pairs_distance(rows, "delta", lengths=range(1, 9)).collect()}
    assert found[1, 2] == 0 and found[1, 3] == pytest.approx(1)
    near = {(r["id_a"], r["id_b"]): r["dist"] for r in distance.all_pairs_distance(rows, "sketch").collect()}
    assert near[1, 2] == pytest.approx(0, abs=0.01) and near[1, 3] == pytest.approx(1, abs=0.05)
    assert {r["id"]: r["other"] for r in distance.nearest(distance.all_pairs_distance(rows, "xz")).collect()}[1] == 2


def test_trees(spark):
    # ((a,b),(c,d)) with an inner edge of 3
    full = np.array([[0, 3, 7, 8], [3, 0, 8, 9], [7, 8, 0, 5], [8, 9, 5, 0]], float)
    assert phylogeny.splits(phylogeny.neighbour_joining(full)) == {frozenset({2, 3})}
    five = np.array([[0, 2, 9, 9, 9], [2, 0, 9, 9, 9], [9, 9, 0, 4, 6], [9, 9, 4, 0, 6], [9, 9, 6, 6, 0]], float)
    for build in (phylogeny.neighbour_joining, phylogeny.average_linkage):
        assert phylogeny.splits(build(five)) == {frozenset({2, 3}), frozenset({2, 3, 4})}
    ids = list("abcde")
    other = five[np.ix_([0, 2, 1, 3, 4], [0, 2, 1, 3, 4])]
    tables = [phylogeny.split_table(spark, n, ids, phylogeny.average_linkage(m)) for n, m in (("x", five), ("y", five), ("z", other))]
    rf = {(r["tree_a"], r["tree_b"]): r["rf"] for r in phylogeny.robinson_foulds(tables[0].unionByName(tables[1]).unionByName(tables[2])).collect()}
    assert rf["x", "y"] == 0 and rf["x", "z"] > 0


def test_store(spark, strings, tmp_path):
    made = sketch.build_sketch(strings, cd=Hll(), lengths=LENGTHS)
    sketch.save_sketch(made, str(tmp_path / "store"), 1.25, "hll")
    back, cd = sketch.load_sketch(spark, str(tmp_path / "store"), 1.25, "hll")
    assert sorted(map(tuple, sketch.estimate_delta(back, cd=cd).collect())) == sorted(map(tuple, sketch.estimate_delta(made).collect()))


def test_ordered_blocks(spark, tmp_path):
    from repetix.sources.ordered_blocks import OrderedBlocks

    raw = bytes(range(256)) * 20
    (tmp_path / "x.bin").write_bytes(raw)
    spark.dataSource.register(OrderedBlocks)
    rows = spark.read.format("ordered_blocks").option("block_bytes", 1000).option("blocks_a_task", 2).load(str(tmp_path)).orderBy("block").collect()
    assert b"".join(bytes(r["bytes"]) for r in rows) == raw and len(rows) == 6


def test_packed_registers(spark, strings, texts):
    from repetix.operators import packed

    cd = packed.Packed(1024)
    made = cd.from_strings(strings.withColumn("g", F.col("id") % 2).repartition(5), ["g"], LENGTHS)
    got = {(r["g"], r["k"]): r["d"] for r in cd.estimates(made, ["g", "k"]).collect()}
    for g in (0, 1):
        for k in LENGTHS:
            exact = len({s[i : i + k] for j, s in texts if j % 2 == g for i in range(len(s) - k + 1)})
            assert got[g, k] == pytest.approx(exact, rel=0.15, abs=2)
    near = {r["id"]: r["delta"] for r in packed.estimate_strings(strings, range(1, 12)).collect()}
    exact = {r["id"]: r["delta"] for r in profile.exact_delta(strings).collect()}
    assert near == pytest.approx(exact)


def test_packed_long_string(spark):
    from repetix.operators import packed

    rng = random.Random(6)
    chunks = ["".join(rng.choice("abcd") for _ in range(rng.randint(0, 60))) for _ in range(80)]
    whole = "".join(chunks)
    df = longstring.chunk_table(spark.createDataFrame(list(enumerate(chunks)), "at bigint, text string"), "at")
    cd = packed.Packed(4096)
    got = {r["k"]: r["d"] for r in cd.estimates(packed.long_string_sketch(df, [1, 3, 6, 30], cd), ["id", "k"]).collect()}
    for k, d in got.items():
        assert d == pytest.approx(len({whole[i : i + k] for i in range(len(whole) - k + 1)}), rel=0.06, abs=1)


def test_rollup_is_the_union(strings):
    made = sketch.build_sketch(strings.withColumn("a", F.col("id") % 2).withColumn("b", F.col("id") % 3), by=("a", "b"), lengths=LENGTHS)
    got = {(r["a"], r["b"]): r["delta"] for r in sketch.estimate_delta(sketch.rollup_sketch(made, ["a", "b"]), by=("a", "b")).collect()}
    assert len(got) == 6 + 2 + 1
    assert max(d for (a, b), d in got.items() if b is not None) <= got[None, None] * 1.05


def test_block_stream(spark, tmp_path):
    from repetix.sources.ordered_blocks import OrderedBlocks

    raw = bytes(range(200)) * 10
    (tmp_path / "in").mkdir()
    (tmp_path / "in" / "x.bin").write_bytes(raw)
    spark.dataSource.register(OrderedBlocks)
    stream = spark.readStream.format("ordered_blocks").option("block_bytes", 300).load(str(tmp_path / "in"))
    q = stream.writeStream.format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "state")).start()
    q.processAllAvailable()
    q.stop()
    rows = spark.read.parquet(str(tmp_path / "out")).orderBy("block").collect()
    assert b"".join(bytes(r["bytes"]) for r in rows) == raw
