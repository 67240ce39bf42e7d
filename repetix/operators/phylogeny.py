"""Trees from distances, and how far two trees differ.

A tree has as many leaves as the workload has sequences, a few thousand at most, so it is made
on the driver from the collected distances; comparing many trees is a join of their splits.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Leaves of a tree at most: distances of all pairs are held on the driver.
MOST_LEAVES = 4000

Edges = list[tuple[int, int | None, float, int | None]]


def matrix(distances: DataFrame) -> tuple[list, np.ndarray]:
    """(ids in order, symmetric matrix) of (id_a, id_b, dist)."""
    most = MOST_LEAVES * MOST_LEAVES // 2
    rows = distances.select("id_a", "id_b", "dist").limit(most + 1).toArrow()  # columns: a Row for each pair takes many times its bytes
    if rows.num_rows > most:
        raise ValueError(f"more than {MOST_LEAVES} leaves")
    a, b = (rows.column(c).combine_chunks() for c in ("id_a", "id_b"))
    ids = sorted({*pc.unique(a).to_pylist(), *pc.unique(b).to_pylist()})
    i, j = (pc.index_in(x, value_set=pa.array(ids, x.type)).to_numpy(zero_copy_only=False) for x in (a, b))
    full = np.zeros((len(ids), len(ids)))
    full[i, j] = full[j, i] = rows.column("dist").to_numpy()
    return ids, full


def joined(d: np.ndarray, a: int, b: int, to_new: np.ndarray) -> np.ndarray:
    """`d` without a and b, with a node that has the distances `to_new` from the others as the last."""
    rest = np.delete(np.arange(len(d)), [a, b])
    out = np.zeros((len(rest) + 1, len(rest) + 1))
    out[:-1, :-1] = d[np.ix_(rest, rest)]
    out[-1, :-1] = out[:-1, -1] = to_new[rest]
    return out


def neighbour_joining(full: np.ndarray) -> Edges:
    """(node, parent, length, leaf) rows; the last node has no parent."""
    n = len(full)
    live, nodes, edges, d = list(range(n)), n, [], np.array(full, float)
    while len(live) > 2:
        m = len(live)
        sums = d.sum(1)
        q = (m - 2) * d - sums[:, None] - sums[None, :]
        np.fill_diagonal(q, np.inf)
        a, b = divmod(int(np.argmin(q)), m)
        i, j = live[a], live[b]
        to_i = d[a, b] / 2 + (sums[a] - sums[b]) / (2 * (m - 2))
        edges += [(i, nodes, to_i, i if i < n else None), (j, nodes, d[a, b] - to_i, j if j < n else None)]
        d = joined(d, a, b, (d[a] + d[b] - d[a, b]) / 2)
        live = [x for x in live if x not in (i, j)] + [nodes]
        nodes += 1
    if len(live) == 2:
        i, j = live
        edges += [(i, j, d[0, 1], i if i < n else None), (j, None, 0.0, j if j < n else None)]
    elif live:
        edges.append((live[0], None, 0.0, live[0]))
    return edges


def average_linkage(full: np.ndarray) -> Edges:
    """The same rows for a rooted tree that joins the two nearest clusters, with mean distances."""
    n = len(full)
    live, height, size, edges, nodes = list(range(n)), dict.fromkeys(range(n), 0.0), dict.fromkeys(range(n), 1), [], n
    d = np.array(full, float)
    while len(live) > 1:
        np.fill_diagonal(d, np.inf)
        a, b = divmod(int(np.argmin(d)), len(live))  # of equally near ones the first pair, as `live` is in order
        i, j = live[a], live[b]
        half = d[a, b] / 2
        for x in (i, j):
            edges.append((x, nodes, half - height[x], x if x < n else None))
        d = joined(d, a, b, (size[i] * d[a] + size[j] * d[b]) / (size[i] + size[j]))
        live = [x for x in live if x not in (i, j)] + [nodes]
        height[nodes], size[nodes] = half, size[i] + size[j]
        nodes += 1
    if live:
        edges.append((live[0], None, 0.0, live[0] if live[0] < n else None))
    return edges


def splits(edges: Edges) -> set[frozenset[int]]:
    """Of every inner edge the side without leaf 0, with 2 leaves at least on both sides."""
    children: dict[int, list[int]] = {}
    for node, parent, _, _ in edges:
        children.setdefault(parent, []).append(node)
    leaf = {node: x for node, _, _, x in edges}
    everyone = frozenset(x for x in leaf.values() if x is not None)
    found: set[frozenset[int]] = set()

    def below(node: int) -> frozenset[int]:
        own = frozenset() if leaf.get(node) is None else frozenset([leaf[node]])
        side = own.union(*map(below, children.get(node, [])))
        if 1 < len(side) < len(everyone) - 1:
            found.add(everyone - side if 0 in side else side)
        return side

    for root in children.get(None, []):
        below(root)
    return found


def tree_table(spark: SparkSession, tree: str, ids: list, edges: Edges) -> DataFrame:
    rows = [(tree, node, parent, float(length), None if leaf is None else str(ids[leaf])) for node, parent, length, leaf in edges]
    return spark.createDataFrame(rows, "tree string, node int, parent int, length double, leaf_id string")


def split_table(spark: SparkSession, tree: str, ids: list, edges: Edges) -> DataFrame:
    return forest_table(spark, {(tree,): (ids, edges)})


def forest_table(spark: SparkSession, trees: dict[tuple, tuple[list, Edges]], by: Sequence[str] = ()) -> DataFrame:
    """(by, tree, leaves, split) of many trees in one table: its plan doesn't grow with the trees."""
    rows = [(*key, len(ids), sorted(str(ids[i]) for i in s)) for key, (ids, edges) in trees.items() for s in splits(edges)]
    return spark.createDataFrame(rows, ", ".join([*(f"`{c}` string" for c in by), "tree string, leaves int, split array<string>"]))


def robinson_foulds(all_splits: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """(by, tree_a, tree_b, rf) of the trees with the same `by`: splits that one of the trees lacks, as a share of 2 (leaves - 3)."""
    by = list(by)
    sizes = all_splits.groupBy(*by, "tree").agg(F.count("*").alias("n"), F.max("leaves").alias("leaves"))
    a = all_splits.select(*by, F.col("tree").alias("tree_a"), "split")
    shared = a.join(all_splits.select(*by, F.col("tree").alias("tree_b"), "split"), [*by, "split"]).where("tree_a < tree_b").groupBy(*by, "tree_a", "tree_b").agg(F.count("*").alias("shared"))
    first, other = sizes.toDF(*by, "tree_a", "na", "leaves"), sizes.select(*by, F.col("tree").alias("tree_b"), F.col("n").alias("nb"))
    pairs = first.join(other, by).where("tree_a < tree_b") if by else first.join(other, F.col("tree_a") < F.col("tree_b"))
    met = pairs.join(shared, [*by, "tree_a", "tree_b"], "left")
    return met.select(*by, "tree_a", "tree_b", ((F.col("na") + F.col("nb") - 2 * F.coalesce("shared", F.lit(0))) / (2 * (F.col("leaves") - 3))).alias("rf"))
