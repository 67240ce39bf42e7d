import hashlib
import random
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from repetix.llm import ring_sharding
from repetix.llm.exact_dedup import DigestIndex, deduplicate
from repetix.llm.ring_sharding import assign_shards, capacities, plan_segments
from repetix.llm.simhash_trie import fingerprint, near_duplicates, near_links, trie_links

SCHEMA = "doc_id bigint, text string, row_no string, digest string, fp string, keep_id string, bytes string"


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty and long texts, ties, repeated rows, and columns named like the operators' own."""
    rows = [(1, "Ab c"), (2, "aB C"), (3, None), (4, ""), (5, "Äb"), (6, "äb"), (7, "word " * 60000), (8, "word " * 60000), (9, "one two three"), (9, "one two three"), (None, "ab c"), (None, "lonely")]
    return spark.createDataFrame([(*r, "x", "x", "x", "x", "x") for r in rows], SCHEMA)


def lower(s):
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in s or "")


def test_exact_dedup(odd):
    got = deduplicate(odd).collect()
    rows = [(r["doc_id"], r["text"]) for r in odd.collect()]
    assert len(got) == len(rows)
    by = defaultdict(list)
    for i, t in rows:
        by[hashlib.sha256(lower(t).encode()).hexdigest()].append(i)
    for r in got:
        group = by[r["text_sha256"]]
        ids = [i for i in group if i is not None]
        assert r["group_size"] == len(group) and r["keep_id"] == (max(ids) if ids else None)
    kept = Counter(r["text_sha256"] for r in got if r["kept"])
    assert set(kept.values()) == {1} and set(kept) == set(by)


def test_index_persists_over_batches(spark, odd):
    index = DigestIndex(spark, buckets=3)
    assert deduplicate(odd, index).where("kept").count() == 7
    assert deduplicate(odd, index).where("kept").count() == 0
    index.drop()
    again = DigestIndex(spark, path=index.path)
    assert again.buckets == 3
    new = spark.createDataFrame([(100, "AB C"), (101, "new")], "doc_id bigint, text string")
    got = {r["doc_id"]: (r["kept"], r["keep_id"]) for r in deduplicate(new, again).collect()}
    assert got == {100: (False, 2), 101: (True, 101)}
    assert again.entries().count() == 8
    with pytest.raises(ValueError):
        DigestIndex(spark, path=index.path, buckets=4)


@pytest.mark.parametrize("later", [4, 16])
def test_an_index_is_reopened_with_other_shuffle_partitions(spark, later):
    texts = spark.range(200).select(F.col("id").alias("doc_id"), F.concat(F.lit("t"), "id").alias("text"))
    before = spark.conf.get("spark.sql.shuffle.partitions")
    try:
        spark.conf.set("spark.sql.shuffle.partitions", "8")
        index = DigestIndex(spark)
        assert deduplicate(texts, index).where("kept").count() == 200
        spark.conf.set("spark.sql.shuffle.partitions", str(later))
        got = deduplicate(texts, DigestIndex(spark, path=index.path))
        assert got.count() == 200 and got.where("kept").count() == 0
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)


def test_a_batch_is_appended_once(spark, odd):
    index = DigestIndex(spark, buckets=2)
    first = deduplicate(odd, index, batch="monday")
    expected = sorted(map(str, first.collect()))
    assert sorted(map(str, deduplicate(odd, index, batch="monday").collect())) == expected
    assert index.entries().count() == 7
    # entries of an append that failed before it was finished
    spark.sql(f"INSERT INTO {index.table} VALUES (unhex('00'), 1, 1, 'half'), (unhex('01'), 2, 1, 'half')")
    assert index.entries().count() == 7
    new = spark.createDataFrame([(1, "n")], "doc_id bigint, text string")
    assert deduplicate(new, index, batch="tuesday").where("kept").count() == 1


def test_a_small_batch_on_a_skewed_index(spark):
    """Entries of large groups of an earlier batch are no broadcast of a later one, and a digest that is hot only now is."""
    index = DigestIndex(spark, buckets=2)
    old = spark.range(6000).select(F.col("id").alias("doc_id"), F.concat(F.lit("t"), F.col("id") % 3).alias("text"))
    assert deduplicate(old, index).where("kept").count() == 3
    new = spark.range(3000).select(F.col("id").alias("doc_id"), F.when(F.col("id") < 2500, "hot now").when(F.col("id") < 2600, "t1").otherwise(F.concat(F.lit("u"), "id")).alias("text"))
    got = deduplicate(new, index)
    assert got.count() == 3000 and got.where("kept").count() == 401
    assert {tuple(r) for r in got.where("kept AND doc_id < 2600").select("doc_id", "group_size").collect()} == {(2499, 2500)}
    assert {r["group_size"] for r in got.where("doc_id >= 2500 AND doc_id < 2600").collect()} == {2000}


def test_anti_join_is_sort_merge_on_buckets(spark, odd):
    index = DigestIndex(spark, buckets=3)
    deduplicate(odd, index)
    rows = spark.createDataFrame([(b"x",)], "digest binary")
    plan = rows.join(index.entries().select("digest").hint("merge"), "digest", "left_anti")._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and plan.count("Exchange") <= 1


def test_shards(odd):
    got = assign_shards(odd, 5, vnodes=8).collect()
    rows = odd.collect()
    assert len(got) == len(rows)
    sizes = Counter((r["doc_id"], len((r["text"] or "").encode()) + 16, zlib.crc32((r["text"] or "").encode())) for r in rows)
    assert sizes == Counter((r["doc_id"], r["size"], r["text_crc32"]) for r in got)
    by = defaultdict(list)
    for r in got:
        by[r["shard"]].append(r["slot"])
    assert all(sorted(s) == list(range(len(s))) for s in by.values())
    assert max(map(len, by.values())) - min(len(by.get(s, [])) for s in range(5)) <= 1


def test_shards_with_slack_move_little(spark):
    docs = spark.range(4000).select(F.col("id").alias("doc_id"), F.lit("t").alias("text"))
    a = {r["doc_id"]: r["shard"] for r in assign_shards(docs, 10, slack=0.25).collect()}
    b = {r["doc_id"]: r["shard"] for r in assign_shards(docs, 11, slack=0.25).collect()}
    assert max(Counter(a.values()).values()) <= 500
    moved = sum(a[i] != b[i] for i in a)
    assert moved < 0.3 * len(a)


def test_a_repeated_row_is_no_hot_key(spark):
    docs = spark.range(3000).select(F.lit(7).cast("bigint").alias("doc_id"), F.lit("same").alias("text"))
    got = assign_shards(docs, 6, vnodes=4)
    assert {r["shard"]: r["count"] for r in got.groupBy("shard").count().collect()} == dict.fromkeys(range(6), 500)


@pytest.mark.parametrize("slack", [None, 0.1])
def test_shards_equal_a_walk_key_by_key(spark, slack):
    """Every key is put on the ring by itself: home shards first, then clockwise to the first shard with room."""
    shards, vnodes = 5, 6
    rows = [(i % 50, f"text {i % 70}") for i in range(400)] + [(7, f"hot {i}") for i in range(200)] + [(None, "t")] * 30 + [(8, "same")] * 90
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    position = lambda *what: ring_sharding._position(*what)
    points = spark.range(shards * vnodes).select(F.col("id") % shards, position(F.lit("ring point"), F.col("id") % shards, F.floor(F.col("id") / shards))).collect()
    points = sorted((at, shard) for shard, at in points)
    size, crc = (F.octet_length("text").cast("long") + 16).alias("size"), F.crc32(F.col("text").cast("binary")).alias("crc")
    keyed = docs.select("doc_id", size, crc).select("doc_id", "size", "crc", position(F.lit("key"), "doc_id").alias("at"), position(F.lit("turn"), "doc_id", "size", "crc").alias("turn"))
    on_arc = defaultdict(list)
    for r in keyed.collect():
        on_arc[next((i for i, (at, _) in enumerate(points) if at >= r["at"]), len(points))].append((r["turn"], r["doc_id"], r["size"], r["crc"]))
    free = capacities(len(rows), shards, slack)
    ring = [*(s for _, s in points), points[0][1]]
    landed, waiting, over = defaultdict(list), [], {}
    for arc, shard in enumerate(ring):
        for key in sorted(on_arc[arc], key=lambda k: k[0]):
            if free[shard]:
                free[shard] -= 1
                landed[key[1:]].append(shard)
            else:
                over.setdefault(arc, []).append(key)
    for lap in range(2):
        for arc, shard in enumerate(ring):
            while waiting and free[shard]:
                free[shard] -= 1
                landed[waiting.pop(0)[1:]].append(shard)
            waiting += over.get(arc, []) if lap == 0 else []
    assert not waiting
    for window_rows, chunk in ((10**6, 10**6), (7, 4)):
        got = defaultdict(list)
        for r in assign_shards(docs, shards, vnodes, slack, window_rows=window_rows, chunk=chunk).collect():
            got[r["doc_id"], r["size"], r["text_crc32"]].append(r["shard"])
        assert {k: sorted(v) for k, v in got.items()} == {k: sorted(v) for k, v in landed.items()}


def test_segments_are_gapless():
    rng = random.Random(3)
    arcs = [(i, i % 4, rng.randint(0, 9)) for i in range(24)]
    n = sum(a[2] for a in arcs)
    found = plan_segments(arcs, capacities(n, 4, None))
    for arc, _, count in arcs:
        assert sorted(x for s in found if s[0] == arc for x in range(s[1], s[2])) == list(range(count))
    for shard, most in capacities(n, 4, None).items():
        assert sorted(x for s in found if s[3] == shard for x in range(s[4], s[4] + s[2] - s[1])) == list(range(most))


def brute_fingerprint(text):
    words = [w for w in __import__("re").findall("[^\x20\x09-\x0d]+", lower(text))]
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


@pytest.mark.parametrize("text", [None, "", " \t", "One", "one TWO", "a b c", "a b c d e f a b c d", "É x\xa0y z\x1cw v"])
def test_fingerprint(text):
    assert fingerprint(text) == brute_fingerprint(text)


def roots(ids, fps, budget=3):
    parent = {i: i for i in ids}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in ids:
        for j in ids:
            if i < j and bin(fps[i] ^ fps[j]).count("1") <= budget:
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    return {i: find(i) for i in ids}


def test_near_duplicates(spark):
    rng = random.Random(0)
    base = ["".join(rng.choice("abcdefgh") for _ in range(5)) for _ in range(200)]
    texts = []
    for _ in range(20):
        words = rng.sample(base, 80)
        texts.append(" ".join(words))
        for _ in range(3):
            words = list(words)
            words[rng.randrange(80)] = rng.choice(base)
            texts.append(" ".join(words))
    texts += [None, "", " ", "x", texts[0]]
    docs = spark.createDataFrame([(i, t, "x", "x") for i, t in enumerate(texts)], "doc_id bigint, text string, fp string, root string")
    got = near_duplicates(docs).collect()
    expected = roots(range(len(texts)), [brute_fingerprint(t) for t in texts])
    assert len(got) == len(texts)
    assert {r["doc_id"]: r["component_id"] for r in got} == expected
    assert len({r["component_id"] for r in got}) < len(texts)
    assert near_duplicates(docs.where("false")).count() == 0


@pytest.mark.parametrize("budget", [2, 3, 5])
def test_large_groups_are_split_exactly(spark, budget):
    rng = random.Random(budget)
    seeds = [rng.getrandbits(64) for _ in range(6)]
    fps = set()
    while len(fps) < 150:
        fp = rng.choice(seeds)
        for _ in range(rng.randint(0, 6)):
            fp ^= 1 << rng.randrange(64)
        fps.add(fp)
    fps = sorted(fps)
    signed = [f - (1 << 64) if f >> 63 else f for f in fps]
    table = spark.createDataFrame([(f,) for f in signed], "fp bigint")
    expected = roots(range(len(fps)), fps, budget)
    at = {f: i for i, f in enumerate(signed)}
    for most in (1, 3, 10**6):
        parent = list(range(len(fps)))

        def find(x, parent=parent):
            while parent[x] != x:
                x = parent[x]
            return x

        for r in near_links(table, budget, most).collect():
            assert bin(fps[at[r["fp_a"]]] ^ fps[at[r["fp_b"]]]).count("1") <= budget
            a, b = find(at[r["fp_a"]]), find(at[r["fp_b"]])
            parent[max(a, b)] = min(a, b)
        assert {i: find(i) for i in range(len(fps))} == expected


@pytest.mark.parametrize("leaf,chunk", [(1, 7), (16, 1 << 18)])
def test_trie_walk_finds_all_components(leaf, chunk):
    rng = np.random.default_rng(leaf)
    seeds = rng.integers(0, 1 << 63, 12, dtype=np.uint64)
    bits = np.unique(np.concatenate([seeds, seeds[rng.integers(0, 12, 300)] ^ (np.uint64(1) << rng.integers(0, 64, 300, dtype=np.uint64))]))
    a, b, d = trie_links(np.zeros(len(bits), np.int64), bits, 0, 3, leaf, chunk)
    assert (d <= 3).all() and len(a) < len(bits)
    fps = [int(x) for x in bits]
    expected = roots(range(len(fps)), fps)
    parent = list(range(len(fps)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, j in zip(a.tolist(), b.tolist(), strict=True):
        i, j = find(i), find(j)
        parent[max(i, j)] = min(i, j)
    assert [find(i) for i in range(len(fps))] == [expected[i] for i in range(len(fps))]
