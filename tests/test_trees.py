"""What the driver holds for trees: a few matrices, not an object for each pair, and one table of all splits."""

import tracemalloc

import numpy as np
import pytest

from repetix.operators import phylogeny


def distances(n, seed=5, levels=None):
    x = np.random.default_rng(seed).random((n, n))
    x = np.triu(np.round(x * levels) / levels if levels else x, 1)
    return x + x.T


def peak_of(f, *args):
    tracemalloc.start()
    try:
        f(*args)
        return tracemalloc.get_traced_memory()[1]
    finally:
        tracemalloc.stop()


@pytest.mark.parametrize("build", [phylogeny.neighbour_joining, phylogeny.average_linkage])
def test_a_tree_takes_a_few_matrices(build):  # F5
    full = distances(120)
    assert peak_of(build, full) < 12 * full.nbytes


def test_average_linkage_takes_the_first_of_equal_pairs():
    for seed in range(20):
        full = distances(12, seed, levels=3)
        i, j = min(((i, j) for i in range(12) for j in range(i + 1, 12)), key=lambda p: (full[p], p))
        first, second = phylogeny.average_linkage(full)[:2]
        assert (first[0], second[0], first[2]) == (i, j, full[i, j] / 2)


def test_matrix_takes_no_object_for_each_pair(spark):  # F5
    n = 200
    pairs = spark.range(n * n).selectExpr(f"id div {n} AS x", f"id % {n} AS y").where("x < y")
    pairs = pairs.selectExpr("concat('s', lpad(x, 3, '0')) AS id_a", "concat('s', lpad(y, 3, '0')) AS id_b", "(x * 1000 + y) / 7 AS dist")
    got, full = phylogeny.matrix(pairs)
    assert got == [f"s{i:03}" for i in range(n)]
    assert all(full[i, j] == (min(i, j) * 1000 + max(i, j)) / 7 if i != j else full[i, j] == 0 for i in range(n) for j in range(n))
    assert peak_of(phylogeny.matrix, pairs) < 6 * full.nbytes


def test_more_leaves_than_can_be_held_are_refused(spark, monkeypatch):
    monkeypatch.setattr(phylogeny, "MOST_LEAVES", 4)
    pairs = spark.range(9).selectExpr("id AS id_a", "id + 1 AS id_b", "1D AS dist")
    with pytest.raises(ValueError):
        phylogeny.matrix(pairs)
    assert phylogeny.matrix(pairs.limit(8))[0]


def test_trees_by_key_are_those_one_by_one(spark):  # F5
    ids = [f"s{i}" for i in range(9)]
    trees = {(b, m): (ids, build(distances(9, seed))) for b, build in (("nj", phylogeny.neighbour_joining), ("al", phylogeny.average_linkage)) for seed, m in enumerate("xyz")}
    met = phylogeny.robinson_foulds(phylogeny.forest_table(spark, trees, ["builder"]), ["builder"])
    got = {(r["builder"], r["tree_a"], r["tree_b"]): r["rf"] for r in met.collect()}
    assert len(got) == 6
    for (b, x, y), rf in got.items():
        a, c = (phylogeny.splits(trees[b, m][1]) for m in (x, y))
        assert rf == len(a ^ c) / (2 * (9 - 3))


def test_the_plan_of_tree_distance_has_one_table_of_splits(spark, sf_dir):  # F5
    from repetix.workloads import experiments

    plan = experiments.tree_distance(spark, sf_dir)._jdf.queryExecution().sparkPlan().toString()
    assert 0 < plan.count("Scan ExistingRDD") <= 4
