"""Pairs of strings are met without broadcasting what has no known size."""

import random

from repetix.operators import distance


def plan_of(df) -> str:
    return df._jdf.queryExecution().toString()


def strings_of(spark, n=12, size=300):
    rng = random.Random(3)
    rows = [(i, "".join(rng.choice("abcd") for _ in range(size))) for i in range(n)]
    return spark.createDataFrame(rows, "id bigint, text string")


def test_pairs_are_met_without_broadcasting_strings(spark):  # F1, F5
    rows = strings_of(spark)
    for df in (distance.pair_profile(rows, None, [1, 2, 3]), distance.all_pairs_codec(rows, "gzip")):
        plan = plan_of(df).split("== Physical Plan ==")[1]
        assert "SortMergeJoin" in plan and "BroadcastHashJoin" not in plan


def test_pair_profile_counts_unions(spark):  # F1, F5
    rows = strings_of(spark, 5, 60)
    texts = dict(map(tuple, rows.collect()))
    sets = lambda t, k: {t[i : i + k] for i in range(len(t) - k + 1)}
    got = {(r["id_a"], r["id_b"], r["k"]): r["d"] for r in distance.pair_profile(rows, None, [1, 4, 99]).collect()}
    assert got == {(a, b, k): len(sets(texts[a], k) | sets(texts[b], k)) for a in texts for b in texts if a < b for k in (1, 4, 99)}


def test_registers_lose_no_near_pair_and_most_others(spark, sf_dir, monkeypatch):
    from repetix.operators import distance, sketch
    from repetix.operators.distinct import Hll
    from repetix.workloads.common import docs

    monkeypatch.setattr(distance, "CROWD", 16)  # several buckets
    strings = docs(spark, sf_dir)
    sketches = sketch.build_sketch(strings, one_each=True).cache()
    single = sketch.estimate_delta(sketches).select("id", "delta")
    every = distance.pairs_within(single, 0.25)
    near = {tuple(r) for r in distance.all_pairs_sketch(sketches, pairs=every).where("dist <= 0.25").select("id_a", "id_b").collect()}
    kept = {tuple(r) for r in distance.pairs_by_registers(strings, single, 0.25, Hll()).collect()}
    assert near and near <= kept and len(kept) < every.count() / 4


def nodes(plan):
    yield plan
    name = plan.nodeName()
    below = [plan.executedPlan()] if name == "AdaptiveSparkPlan" else [plan.plan()] if name.endswith("QueryStage") else []
    kids = plan.children()
    for child in below + [kids.apply(i) for i in range(kids.size())]:
        yield from nodes(child)


def test_no_string_or_set_of_the_trees_is_broadcast(spark, sf_dir):  # F5
    from repetix.workloads import experiments

    sent = set()
    for df in experiments.tree_distances(spark, sf_dir).values():
        df.collect()
        for node in nodes(df._jdf.queryExecution().executedPlan()):
            if node.nodeName() == "BroadcastExchange":
                columns = node.output()
                sent |= {columns.apply(i).dataType().typeName() for i in range(columns.size()) if columns.apply(i).name().startswith(("text", "__text", "cd", "fps", "__cd", "__fps"))}
    assert not sent
