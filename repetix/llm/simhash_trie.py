"""SimHash near-dedup by a binary trie self-join.

Fingerprints are dealt by their blocks of bits: two that differ in at most `budget` bits agree
in a whole block out of budget + 1, so every link is found where that block is shared. There
the fingerprints, the shared block's bits first, are a binary trie laid out as a sorted array.
Pairs of its nodes are walked together from the root, differing bits add up, and a pair of
nodes goes when the budget is exceeded. A task reports links that join its own components only,
so a group of copies never yields all its pairs; components over all tasks follow by rounds of
star contraction over the links.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import attach, checked, materialise, numbered, partitions, written_no

BITS = 64
SEED = 42
#: Distinct fingerprints of a group that one task walks.
GROUP = 2_000_000
LOWER = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")


def fingerprint(text: str | None, shingle: int = 3) -> int:
    """Bits set in over half of the hashes of all shingles of `shingle` words, repeats included; zero without words."""
    words = (text or "").encode("utf-8", "surrogatepass").translate(LOWER).split()  # bytes split at exactly the six ASCII spaces
    if not words:
        return 0
    joined = b" ".join(words)
    if len(words) <= shingle:
        return xxhash.xxh64_intdigest(joined, SEED)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    digest = xxhash.xxh64_intdigest
    hashes = np.fromiter(
        (digest(joined[a:b], SEED) for a, b in zip(starts[: 1 - shingle].tolist(), ends[shingle - 1 :].tolist(), strict=True)), np.uint64, len(words) - shingle + 1
    )
    ones = np.zeros(BITS, np.int64)
    for at in range(0, len(hashes), 4096):
        ones += np.unpackbits(hashes[at : at + 4096].astype(">u8").view(np.uint8)).reshape(-1, BITS).sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(ones * 2 > len(hashes)).tobytes(), "big")


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """row_no, doc_id, fp bigint (the fingerprint's 64 bits as a signed number) of numbered rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps = np.fromiter((fingerprint(t.as_py()) for t in batch.column(text_col)), np.uint64, batch.num_rows)
            yield pa.RecordBatch.from_arrays([batch.column("row_no"), batch.column(id_col), pa.array(fps.view(np.int64))], names=["row_no", "doc_id", "fp"])

    return docs.mapInArrow(run, f"row_no bigint, doc_id {dict(docs.dtypes)[id_col]}, fp bigint")


class Components:
    """Union of array positions; every position ends at the least of its component."""

    def __init__(self, n: int):
        self.root = np.arange(n)

    def join(self, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Unite a[i] with b[i]; returns links that span what was united by them."""
        kept_a, kept_b = [], []
        while len(a):
            ra, rb = self.root[a], self.root[b]
            apart = ra != rb
            a, b, ra, rb = a[apart], b[apart], ra[apart], rb[apart]
            if not len(a):
                break
            high, low = np.maximum(ra, rb), np.minimum(ra, rb)
            _, first = np.unique(high, return_index=True)  # each root is hung once a round
            kept_a.append(a[first])
            kept_b.append(b[first])
            self.root[high[first]] = low[first]
            while True:
                up = self.root[self.root]
                if np.array_equal(up, self.root):
                    break
                self.root = up
        if not kept_a:
            return np.empty(0, np.int64), np.empty(0, np.int64)
        return np.concatenate(kept_a), np.concatenate(kept_b)


def trie_links(group: np.ndarray, bits: np.ndarray, skip: int, budget: int, leaf_pairs: int = 16, chunk: int = 1 << 18) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Self-join of the tries of many groups at once.

    group, bits: sorted by (group, bits); the first `skip` bits are alike in a group. Returns
    positions a, b of links with at most `budget` differing bits that span every component
    inside each group, and their distances. A node is a range of positions and a depth; the
    walk takes pairs of nodes depth first, in chunks, so memory stays bounded.
    """
    n = len(bits)
    if n < 2:
        return (np.empty(0, np.int64),) * 3
    edges = np.flatnonzero(np.concatenate(([True], group[1:] != group[:-1], [True])))
    lo, hi = edges[:-1], edges[1:]
    big = hi - lo > 1
    lo, hi = lo[big], hi[big]
    united = Components(n)
    out_a, out_b = [], []

    def middle(lo: np.ndarray, hi: np.ndarray, depth: int) -> np.ndarray:
        """Where the nodes' second children begin, by bisection over all nodes at once."""
        left, right = lo.copy(), hi.copy()
        while (open_ := left < right).any():
            mid = (left + right) >> 1
            one = (bits[np.minimum(mid, n - 1)] >> np.uint64(BITS - 1 - depth)) & np.uint64(1) == 1
            right = np.where(open_ & one, mid, right)
            left = np.where(open_ & ~one, mid + 1, left)
        return left

    stack = [(skip, lo, hi, lo, hi, np.full(len(lo), budget))]
    while stack:
        depth, alo, ahi, blo, bhi, left = stack.pop()
        if len(alo) > chunk:
            half = len(alo) // 2
            stack += [(depth, alo[:half], ahi[:half], blo[:half], bhi[:half], left[:half]), (depth, alo[half:], ahi[half:], blo[half:], bhi[half:], left[half:])]
            continue
        sizes = (ahi - alo) * (bhi - blo)
        small = sizes <= leaf_pairs if depth < BITS else np.ones(len(alo), bool)
        if small.any():
            many = sizes[small]
            which = np.repeat(np.flatnonzero(small), many)
            nth = np.arange(len(which)) - np.repeat(np.cumsum(many) - many, many)
            width = (bhi - blo)[which]
            a, b = alo[which] + nth // width, blo[which] + nth % width
            near = (a < b) & (np.bitwise_count(bits[a] ^ bits[b]) <= budget)
            a, b = united.join(a[near], b[near])
            out_a.append(a)
            out_b.append(b)
        if small.all():
            continue
        alo, ahi, blo, bhi, left = (x[~small] for x in (alo, ahi, blo, bhi, left))
        same = alo == blo
        amid, bmid = middle(alo, ahi, depth), middle(blo, bhi, depth)
        pairs = [
            (alo, amid, blo, bmid, left, np.ones(len(alo), bool)),
            (amid, ahi, bmid, bhi, left, np.ones(len(alo), bool)),
            (alo, amid, bmid, bhi, left - 1, np.ones(len(alo), bool)),
            (amid, ahi, blo, bmid, left - 1, ~same),
        ]
        nodes = [np.concatenate(x) for x in zip(*pairs, strict=True)]
        keep = nodes[5] & (nodes[4] >= 0) & (nodes[0] < nodes[1]) & (nodes[2] < nodes[3])
        keep &= ~((nodes[0] == nodes[2]) & (nodes[1] - nodes[0] == 1))
        if keep.any():
            stack.append((depth + 1, *(x[keep] for x in nodes[:5])))
    a = np.concatenate(out_a) if out_a else np.empty(0, np.int64)
    b = np.concatenate(out_b) if out_b else np.empty(0, np.int64)
    return a, b, np.bitwise_count(bits[a] ^ bits[b]).astype(np.int64)


def near_links(distinct: DataFrame, budget: int = 3, most: int = GROUP) -> DataFrame:
    """fp_a, fp_b bigint: links of at most `budget` differing bits that span all near groups of the fingerprints in `distinct` (fp).

    A group is a block's number and value. One of over `most` fingerprints is split: within it
    the bits outside the block differ in at most `budget` places too, so that two near ones
    agree in a whole part out of budget + 1 of these bits, and the groups are by part as well.
    """
    blocks = budget + 1
    width = BITS // blocks
    part = (BITS - width) // blocks
    # rotate each block to the front; the group is the block's number and value
    rotated = distinct.select(
        "fp", F.explode(F.array(*[F.struct(F.lit(i).alias("block"), _rotate("fp", i * width).alias("bits")) for i in range(blocks)])).alias("r")
    ).select("fp", "r.block", "r.bits", F.shiftrightunsigned("r.bits", BITS - width).alias("value"))
    large = rotated.groupBy("block", "value").agg(F.count("*").alias("n")).where(F.col("n") > most).select("block", "value", F.lit(True).alias("large"))  # blocks * 2^width keys at most
    cut = lambda i: F.struct(F.lit(i).alias("part"), F.shiftrightunsigned(F.shiftleft("bits", width + i * part), BITS - part).alias("at"))
    # the last part is the longer one if the bits don't divide
    last = F.struct(F.lit(blocks - 1).alias("part"), F.col("bits").bitwiseAND(F.lit((1 << (BITS - width - (blocks - 1) * part)) - 1)).alias("at"))
    parts = F.when(F.col("large"), F.array(*[cut(i) for i in range(blocks - 1)], last)).otherwise(F.array(F.struct(F.lit(-1).alias("part"), F.lit(0).cast("bigint").alias("at"))))
    keyed = rotated.join(F.broadcast(large), ["block", "value"], "left").withColumn("p", F.explode(parts)).select("fp", "block", "bits", "value", "p.part", "p.at")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        batches = [b for b in batches if b.num_rows]
        if not batches:
            return
        table = pa.Table.from_batches(batches)  # one partition of the deal
        fp, bits = table.column("fp").to_numpy(), table.column("bits").to_numpy().view(np.uint64)
        keys = [table.column(c).to_numpy() for c in ("block", "value", "part", "at")]
        order = np.lexsort((bits, *reversed(keys)))
        fp, bits, keys = fp[order], bits[order], [k[order] for k in keys]
        new = np.zeros(len(fp), bool)
        for k in keys:
            new[1:] |= k[1:] != k[:-1]
        a, b, _ = trie_links(np.cumsum(new), bits, width, budget)
        yield pa.RecordBatch.from_arrays([pa.array(fp[a]), pa.array(fp[b])], names=["fp_a", "fp_b"])

    dealt = keyed.repartition(partitions(distinct.sparkSession) * blocks, "block", "value", "part", "at")
    return dealt.mapInArrow(run, "fp_a bigint, fp_b bigint")


def _rotate(col: str, by: int) -> F.Column:
    return F.col(col) if by == 0 else F.shiftleft(col, by).bitwiseOR(F.shiftrightunsigned(col, BITS - by))


def components(links: DataFrame, a: str, b: str) -> DataFrame:
    """(node, root): every node of the links with the least node of its component.

    Rounds of large-star and small-star contraction; each round is written to the shared
    folder. Nodes without links have no row.
    """
    pairs = links.select(F.greatest(a, b).alias("v"), F.least(a, b).alias("u")).where("u < v").distinct()
    pairs = materialise(pairs, "links")
    before = None
    while True:
        both = pairs.select("v", "u").union(pairs.select(F.col("u"), F.col("v"))).toDF("v", "u")
        least = both.groupBy("v").agg(F.min("u").alias("least")).withColumn("least", F.least("least", "v"))
        large = pairs_of(both.where("u > v").join(least, "v").select(F.col("u").alias("v"), F.col("least").alias("u")))
        down = large.groupBy("v").agg(F.min("u").alias("least"))
        small = large.join(down, "v").select(F.explode(F.array(F.struct(F.col("v"), F.col("least").alias("u")), F.struct(F.col("u").alias("v"), F.col("least").alias("u")))).alias("p"))
        pairs = materialise(pairs_of(small.select("p.v", "p.u")), "links")
        row = pairs.agg(F.count("*").alias("n"), F.count_distinct("v").alias("nodes"), F.bit_xor(F.xxhash64("v", "u")).alias("sum")).first()
        state = (row["n"], row["sum"])
        if row["n"] == row["nodes"] and state == before or row["n"] == 0:
            break
        before = state
    roots = pairs.select("u").distinct().select(F.col("u").alias("node"), F.col("u").alias("root"))
    return pairs.select(F.col("v").alias("node"), F.col("u").alias("root")).union(roots)


def pairs_of(df: DataFrame) -> DataFrame:
    return df.where("u < v").distinct()


def near_duplicates(docs: DataFrame, budget: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each row of `docs`: row_no, doc_id, fp, group_size (rows of this fingerprint), component_id (the least doc_id
    reachable over links) and keep_row (the row_no of a row with that id).

    Null and empty texts and those of blanks have fingerprint zero and are linked like others;
    equal fingerprints are linked. A null doc_id never names a component unless all its ids
    are null. An empty table gives no rows.
    """
    rows = materialise(fingerprints(numbered(checked(docs, id_col, text_col, *written_no(docs))), id_col, text_col), "fingerprints")
    least = F.min(F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "row_no"))
    groups = materialise(rows.groupBy("fp").agg(least.alias("least"), F.count("*").alias("group_size")), "distinct-fingerprints")
    linked = components(near_links(groups.select("fp"), budget), "fp_a", "fp_b")
    rooted = groups.join(linked.withColumnRenamed("node", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    named = materialise(rooted.groupBy("root").agg(F.min("least").alias("keep"), F.count("*").alias("members")), "components-named")
    table = attach(rooted, named, "root", "members", groups.count()).select("fp", "group_size", F.col("keep.doc_id").alias("component_id"), F.col("keep.row_no").alias("keep_row"))
    return attach(rows, materialise(table, "components"), "fp", "group_size", rows.count())


def op4_simhash_trie(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
