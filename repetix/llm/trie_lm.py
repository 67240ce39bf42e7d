"""LM scoring with sharded Elias-Fano n-gram tries (order three).

Probabilities are smoothed by a prior of the next lower order: after a context c that training
has C times, a word has (count + m * lower) / (C + m), where lower is its probability after the
context without its first word, and in the end the additive unigram estimate; m is PRIOR_2 or
PRIOR_3. Contexts of two words that training has once have no level of their own: there the
lower order stands. The probabilities of all words and the end after a context sum to one. The
tries store them quantised, each off by under 1.4 per cent (2.8 at order three, whose lower
probability is read from a code), so that the sum over a context is off by as much at most.

No task and no broadcast holds the model. Texts become blocks of word numbers, written once.
A block asks word shards for its words' counts, then pair shards for its pairs, then triple
shards for its triples. A shard adds up the training counts of all blocks, builds the trie
level of its contexts in a memory-mapped file, and answers with codes by a successor search
inside the context's pointers. A pair's answer names its place in the level, which is the
context of its triples. Questions and answers are packed arrays, one row for each block and
shard. A frequent context is spread over shards by word, and an n-gram appears once in a
block's question however often the block has it. Shards grow in number with the tokens.
"""

from __future__ import annotations

import ctypes
import functools
import itertools
import time
import uuid
import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import checked, drop_table, fresh_path, materialise, partitions, remove
from .elias_fano import Quantiser, TrieLevel
from .rank_array_bpe import slices

END = b""
BLOCK_BYTES = 4_000_000
#: Weights of the lower order, in tokens.
PRIOR_2, PRIOR_3 = 1000.0, 30.0
#: Contexts of two words with fewer training tokens have no successors.
LEAST_CONTEXT = 2
#: Pieces that a context's successors are spread over: every pair context, and pairs of words with more than HOT tokens.
PIECES = 64
HOT = 100_000
#: Questions or answers of a record batch.
LOT = 48
#: Training tokens for each pair shard, beyond the session's partitions.
SHARD_TOKENS = 4_000_000


@functools.cache
def _codec() -> tuple:
    """One compressor and one decompressor for a worker."""
    return zstandard.ZstdCompressor(level=1), zstandard.ZstdDecompressor()


def packed(values: np.ndarray) -> bytes:
    """Compressed, the bytes of like weight together, since the high ones are mostly alike."""
    values = np.ascontiguousarray(values)
    return _codec()[0].compress(values.view(np.uint8).reshape(-1, values.itemsize).T.tobytes())


def unpacked(raw: bytes, dtype) -> np.ndarray:
    width = np.dtype(dtype).itemsize
    return np.ascontiguousarray(np.frombuffer(_codec()[1].decompress(raw), np.uint8).reshape(width, -1).T).reshape(-1).view(dtype)


def in_lots(rows: Iterable[tuple], schema: str) -> Iterator[pa.RecordBatch]:
    """Record batches of a few dozen rows each."""
    kinds = {"int": pa.int32(), "bigint": pa.int64(), "binary": pa.binary()}
    names, types = zip(*((f.split()[0], kinds[f.split()[1]]) for f in schema.split(", ")), strict=True)
    rows = iter(rows)
    while lot := list(itertools.islice(rows, LOT)):
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*lot, strict=True), types, strict=True)], names=list(names))


def let_go() -> None:
    """Give freed memory back to the system, as the workers of an executor share its limit."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def distinct(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(ascending distinct keys, a place of each, the number of each place's key)."""
    order = np.argsort(keys)
    ascending = keys[order]
    new = np.ones(len(keys), bool)
    np.not_equal(ascending[1:], ascending[:-1], out=new[1:])
    number = np.empty(len(keys), np.int32)
    number[order] = np.cumsum(new, dtype=np.int32) - 1
    return ascending[new], order[new], number


def by_shard(shard: np.ndarray, shards: int) -> tuple[np.ndarray, np.ndarray]:
    """(places in the order of the shards, where each shard's begin); few shards are sorted by counting."""
    order = np.argsort(shard.astype(np.uint16 if shards < 1 << 16 else np.int64), kind="stable")
    return order, np.concatenate(([0], np.cumsum(np.bincount(shard.astype(np.int64), minlength=shards))))


def in_training(doc_id) -> bool:
    return doc_id is None or zlib.crc32(str(doc_id).encode()) % 5 != 1


def text_blocks(docs: DataFrame, id_col: str, text_col: str, shards: int, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """Two rows for each run of texts. Part 0: block, doc_ids, lengths (tokens), train, tokens (numbers of words), home (each word's shard); part 1: block, words (hashes), counts (training)."""

    def numbered(texts: pa.Array) -> tuple[list[bytes], np.ndarray, np.ndarray]:
        """(words, lengths, numbers of the tokens); the last word is the end. All in Arrow: splits at the six ASCII blanks, lowers A-Z."""
        split = pc.ascii_split_whitespace(pc.ascii_lower(pc.fill_null(texts.cast(pa.large_string()), "")))
        parts = split.flatten()
        there = pc.not_equal(parts, "")
        kept = np.concatenate(([0], np.cumsum(there.to_numpy(zero_copy_only=False))))
        offsets = split.offsets.to_numpy()
        lengths = np.diff(kept[offsets - offsets[0]]) + 1
        words = parts.filter(there).dictionary_encode()
        tokens = np.full(int(lengths.sum()), len(words.dictionary), np.int64)
        ends = np.zeros(len(tokens), bool)
        ends[np.cumsum(lengths) - 1] = True
        tokens[~ends] = words.indices.to_numpy()
        return [*words.dictionary.cast(pa.large_binary()).to_pylist(), END], lengths, tokens

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first = TaskContext.get().partitionId() << 32
        made = size = 0
        ids: list = []
        texts: list[pa.Array] = []

        def close() -> pa.RecordBatch:
            nonlocal made, size
            words, lengths, tokens = numbered(pa.concat_arrays(texts))
            train = np.fromiter(map(in_training, ids), bool, len(ids))
            counts = np.bincount(tokens[np.repeat(train, lengths)], minlength=len(words))
            hashes = np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))
            home = (hashes % np.uint64(shards)).astype("<u4")
            columns = {
                "block": pa.array([first + made] * 2, pa.int64()), "part": pa.array([0, 1], pa.int32()), "doc_ids": pa.array([ids, None], pa.list_(pa.int64())),
                **{name: pa.array([packed(x), None], pa.binary()) for name, x in (("lengths", lengths.astype("<u4")), ("train", train), ("tokens", tokens.astype("<u4")), ("home", home))},
                "words": pa.array([None, hashes.tobytes()], pa.binary()), "counts": pa.array([None, packed(counts.astype("<u4"))], pa.binary()),
            }
            made, size = made + 1, 0
            ids.clear()
            texts.clear()
            del words, lengths, tokens, counts, hashes
            let_go()
            return pa.RecordBatch.from_arrays(list(columns.values()), names=list(columns))

        for batch in batches:
            for part in slices(batch, text_col, block_bytes):
                ids += part.column(id_col).to_pylist()
                texts.append(part.column(text_col))
                size += pc.sum(pc.binary_length(part.column(text_col))).as_py() or 0
                if size >= block_bytes // 2:
                    yield close()
        if ids:
            yield close()

    schema = "block bigint, part int, doc_ids array<bigint>, lengths binary, train binary, tokens binary, home binary, words binary, counts binary"
    return checked(docs, id_col, text_col).select(F.col(id_col).cast("bigint").alias(id_col), text_col).mapInArrow(run, schema)


def _bucketed(rows: DataFrame, buckets: int, name: str, made: list[tuple[str, str]], parts: bool = False) -> DataFrame:
    """The rows in the shared folder, bucketed by block so that later joins on the block don't move them. `made` lists tables to drop."""
    spark = rows.sparkSession
    table, path = f"lm_{name}_{uuid.uuid4().hex}", fresh_path(spark, f"lm-{name}")
    writer = rows.write.partitionBy("part") if parts else rows.repartition(buckets, "block").write
    writer.bucketBy(buckets, "block").sortBy("block").option("path", path).option("compression", "uncompressed").saveAsTable(table)
    made.append((table, path))
    return spark.table(table)


def _sweep(spark: SparkSession) -> None:
    """Let the context cleaner delete the shuffle files of steps that are over; it goes by the driver's garbage collection."""
    for _ in range(2):
        spark.sparkContext._jvm.System.gc()
        time.sleep(0.2)


def deal_keys(spark: SparkSession, shards: int) -> list[int]:
    """For each shard a key that repartition() by it puts into a partition of its own, where a plain number would share one with others by chance."""
    found: dict[int, int] = {}
    tried = 0
    while len(found) < shards:
        key = F.col("id").cast("int")
        part = F.pmod(F.hash(key), F.lit(shards))
        for r in spark.range(tried, tried + 16 * shards).groupBy(part.alias("part")).agg(F.min(key).alias("key")).collect():  # a row for each shard
            found.setdefault(r["part"], r["key"])
        tried += 16 * shards
    return [found[s] for s in range(shards)]


def _rows(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
    for batch in batches:
        for i in range(batch.num_rows):
            yield {name: column[i].as_py() for name, column in zip(batch.schema.names, batch.columns, strict=True)}


def word_questions(blocks: DataFrame, shards: int, deal: list[int]) -> DataFrame:
    """(shard, deal, block, words, counts): each block's words by home shard, in the block's order."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in _rows(batches):
            words, counts = np.frombuffer(row["words"], np.uint64), unpacked(row["counts"], "<u4")
            home = (words % np.uint64(shards)).astype(np.int64)
            order, edges = by_shard(home, shards)
            parts = [(s, order[a:b]) for s, (a, b) in enumerate(zip(edges, edges[1:], strict=False)) if a < b]
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array([s for s, _ in parts], pa.int32()), pa.array([deal[s] for s, _ in parts], pa.int32()), pa.array([row["block"]] * len(parts), pa.int64()),
                    pa.array([words[at].tobytes() for _, at in parts]), pa.array([packed(counts[at]) for _, at in parts]),
                ],
                names=["shard", "deal", "block", "words", "counts"],
            )

    return blocks.where("part = 1").select("block", "words", "counts").mapInArrow(run, "shard int, deal int, block bigint, words binary, counts binary")


def word_answers(questions: DataFrame, shards: int) -> DataFrame:
    """(shard, block, ids, counts) with numbers of words by frequency within a shard, and a row of sums, (block -1, n, v), for each task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = list(_rows(batches))
        if not rows:
            return
        asked = [np.frombuffer(r["words"], np.uint64) for r in rows]
        lengths = [len(a) for a in asked]
        words, _, inverse = distinct(np.concatenate(asked))
        totals = np.bincount(inverse, weights=np.concatenate([unpacked(r["counts"], "<u4") for r in rows]), minlength=len(words)).astype(np.int64)
        rank = np.empty(len(words), np.uint32)
        rank[np.argsort(-totals, kind="stable")] = np.arange(len(words))
        place = TaskContext.get().partitionId()
        ends = np.cumsum(lengths)
        for row, start, stop in zip(rows, ends - lengths, ends, strict=True):
            mine = inverse[start:stop]
            yield answer(row["shard"], row["block"], place, packed(rank[mine]), packed(totals[mine].astype("<u8")), 0, 0)
        yield answer(-1, -1, place, b"", b"", int(totals.sum()), int((totals > 0).sum()))

    def answer(*values) -> pa.RecordBatch:
        types = [pa.int32(), pa.int64(), pa.int32(), pa.binary(), pa.binary(), pa.int64(), pa.int64()]
        return pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip(values, types, strict=True)], names=["shard", "block", "place", "ranks", "counts", "n", "v"])

    return questions.repartition(shards, "deal").mapInArrow(run, "shard int, block bigint, place int, ranks binary, counts binary, n bigint, v bigint")


def _told(blocks: DataFrame, answers: DataFrame, columns: list[str], name: str, *fields: str) -> DataFrame:
    """`blocks` with the answers to each, an array of structs; both are bucketed by block."""
    given = answers.where("block >= 0").groupBy("block").agg(F.collect_list(F.struct(*fields)).alias(name))
    return blocks.select(*columns).join(given, "block", "left")


class Block:
    """A block's n-grams in the order of the words' global ids, and where the questions to each shard stand."""

    def __init__(self, row: dict, word_shards: int, shards: int, n: int, v: int, hot: int = HOT):
        home = unpacked(row["home"], "<u4")
        ids, counts = np.zeros(len(home), np.int64), np.zeros(len(home), np.int64)
        order, edges = by_shard(home, word_shards)
        for part in row["told"]:
            at = order[edges[part["shard"]] : edges[part["shard"] + 1]]
            ids[at] = (part["place"] << 32) | unpacked(part["ranks"], "<u4").astype(np.int64)
            counts[at] = unpacked(part["counts"], "<u8").astype(np.int64)
        by_id = np.argsort(ids)
        renumbered = np.empty(len(ids), np.int64)
        renumbered[by_id] = np.arange(len(ids))
        self.ids, self.counts, self.shards, self.hot = ids[by_id], counts[by_id], shards, hot
        self.tokens = renumbered[unpacked(row["tokens"], "<u4")]
        self.lengths = unpacked(row["lengths"], "<u4").astype(np.int64)
        self.starts = np.cumsum(self.lengths) - self.lengths
        self.train = np.repeat(unpacked(row["train"], bool), self.lengths)
        self.unigram = (self.counts + 0.5) / (n + 0.5 * (v + 1))
        end = self.tokens[self.lengths[0] - 1]
        keys = np.concatenate(([end], self.tokens[:-1])) * len(ids) + self.tokens  # the context of a text's first word is the end
        pairs, _, self.pair_of = distinct(keys)
        self.a, self.b = (pairs // len(ids)).astype(np.int32), (pairs % len(ids)).astype(np.int32)
        ask = np.flatnonzero((self.counts[self.a] > 0) & (self.counts[self.b] > 0))
        v_id, w_id = self.ids[self.a[ask]].astype(np.uint64), self.ids[self.b[ask]]
        mixed = (v_id * np.uint64(0x9E3779B97F4A7C15)) ^ ((w_id % PIECES).astype(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F))
        self.asked, self.edges = self._dealt(ask, ((mixed ^ mixed >> np.uint64(29)) * np.uint64(0xBF58476D1CE4E5B9) >> np.uint64(33)) % np.uint64(shards))

    def _dealt(self, ask: np.ndarray, shard: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        order, edges = by_shard(shard, self.shards)
        return ask[order], edges

    def pair_questions(self) -> Iterator[tuple]:
        seen = np.bincount(self.pair_of[self.train], minlength=len(self.a))
        low = Quantiser.codes(np.log10(self.unigram))
        for s in range(self.shards):
            mine = self.asked[self.edges[s] : self.edges[s + 1]]
            if len(mine):
                yield s, self.ids[self.a[mine]], self.counts[self.a[mine]], self.ids[self.b[mine]], seen[mine], low[self.b[mine]]

    def hear_pairs(self, told: list[dict]) -> None:
        """From the answers: each pair's probability, training count and place, and the triples of contexts that have successors."""
        codes, total, node = np.zeros(len(self.a), np.uint16), np.zeros(len(self.a), np.int64), np.zeros(len(self.a), np.int64)
        for part in told or []:
            at = self.asked[self.edges[part["shard"]] : self.edges[part["shard"] + 1]]
            codes[at], total[at] = unpacked(part["codes"], "<u2"), unpacked(part["totals"], "<u4")
            node[at] = (part["place"] << 32) | np.cumsum(unpacked(part["steps"], "<u4"), dtype=np.int64)
        self.codes, self.total = codes, total
        self.pair = np.where(codes > 0, Quantiser.probabilities()[codes], PRIOR_2 * self.unigram[self.b] / (self.counts[self.a] + PRIOR_2))
        follows = np.ones(len(self.tokens), bool)
        follows[self.starts] = False
        self.at = np.flatnonzero(follows & (np.concatenate(([0], total[self.pair_of[:-1]])) >= LEAST_CONTEXT))
        context = self.pair_of[self.at - 1]
        triples, first, self.triple_of = distinct(context.astype(np.int64) * len(self.ids) + self.tokens[self.at])
        self.context, self.last = (triples // len(self.ids)).astype(np.int32), (triples % len(self.ids)).astype(np.int32)
        self.lower = self.pair_of[self.at[first]]  # the pair of the triple's last two words
        ask = np.flatnonzero(codes[self.lower] > 0)
        turn = np.empty(len(node), np.int64)
        turn[np.argsort(node)] = np.arange(len(node))
        ask = ask[np.argsort(turn[self.context[ask]] * len(self.ids) + self.last[ask])]  # by node, then word
        piece = np.where(total[self.context[ask]] > self.hot, self.ids[self.last[ask]] % PIECES, 0)
        self.node = node
        self.asked_3, self.edges_3 = self._dealt(ask, ((node[self.context[ask]] >> 32) + piece * 7919) % self.shards)

    def triple_questions(self) -> Iterator[tuple]:
        seen = np.bincount(self.triple_of[self.train[self.at]], minlength=len(self.context))
        for s in range(self.shards):
            mine = self.asked_3[self.edges_3[s] : self.edges_3[s + 1]]
            if len(mine):
                yield s, self.node[self.context[mine]], self.total[self.context[mine]], self.ids[self.last[mine]], seen[mine], self.codes[self.lower[mine]]

    def log10(self, told: list[dict]) -> np.ndarray:
        """Of every token's probability, from the answers to the triples."""
        codes = np.zeros(len(self.context), np.uint16)
        for part in told or []:
            codes[self.asked_3[self.edges_3[part["shard"]] : self.edges_3[part["shard"] + 1]]] = unpacked(part["codes"], "<u2")
        unseen = PRIOR_3 * self.pair[self.lower] / (self.total[self.context] + PRIOR_3)
        triple = np.where(codes > 0, Quantiser.probabilities()[codes], unseen)
        out = np.log10(self.pair)[self.pair_of]
        out[self.at] = np.log10(triple)[self.triple_of]
        return out


QUESTION = "shard int, deal int, block bigint, contexts binary, context_counts binary, of binary, words binary, high binary, counts binary, lower binary"


def _asked(block: int, question: tuple, deal: list[int]) -> tuple:
    shard, context, context_count, word, seen, lower = question
    new = np.flatnonzero(np.concatenate(([True], context[1:] != context[:-1])))
    return (
        shard, deal[shard], block, packed(np.diff(context[new], prepend=0)), packed(context_count[new].astype("<u8")), packed(np.diff(np.append(new, len(context))).astype("<u4")),
        packed(word.astype("<u4")), packed((word >> 32).astype("<u4")), packed(seen.astype("<u4")), packed(lower.astype("<u2")),
    )


def pair_questions(joined: DataFrame, word_shards: int, shards: int, n: int, v: int, deal: list[int]) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in _rows(batches):
            block = Block(row, word_shards, shards, n, v)
            yield from in_lots((_asked(row["block"], question, deal) for question in block.pair_questions()), QUESTION)
            del block
            let_go()

    return joined.mapInArrow(run, QUESTION)


def triple_questions(joined: DataFrame, word_shards: int, shards: int, n: int, v: int, hot: int, deal: list[int]) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in _rows(batches):
            block = Block(row, word_shards, shards, n, v, hot)
            block.hear_pairs(row["pairs"])
            yield from in_lots((_asked(row["block"], question, deal) for question in block.triple_questions()), QUESTION)
            del block
            let_go()

    return joined.mapInArrow(run, QUESTION)


ANSWER = "shard int, block bigint, place int, codes binary, totals binary, steps binary"


def answers(questions: DataFrame, shards: int, prior: float, places: bool) -> DataFrame:
    """(shard, block, place, codes, totals, steps): for each question the codes, and with `places` the training counts and the steps from place to place."""

    def build(c: np.ndarray, n_contexts: int, n_words: int, keys: np.ndarray, total: np.ndarray, lower: np.ndarray) -> TrieLevel:
        trained = np.flatnonzero(total > 0)
        of, word, total = keys[trained] // n_words, keys[trained] % n_words, total[trained]
        smoothed = (total + prior * Quantiser.probabilities()[lower[trained]]) / (c[of] + prior)
        return TrieLevel(n_contexts, of, word, np.log10(smoothed), total).map_to_file()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        asked, heads, head_counts, of, word, seen, lower = [], [], [], [], [], [], []
        for row in _rows(batches):
            asked.append((row["shard"], row["block"]))
            heads.append(np.cumsum(unpacked(row["contexts"], np.int64)))
            head_counts.append(unpacked(row["context_counts"], "<u8").astype(np.int64))
            of.append(unpacked(row["of"], "<u4"))
            word.append(unpacked(row["words"], "<u4").astype(np.int64) | unpacked(row["high"], "<u4").astype(np.int64) << 32)
            seen.append(unpacked(row["counts"], "<u4"))
            lower.append(unpacked(row["lower"], "<u2"))
        if not asked:
            return
        lengths = [len(w) for w in word]
        contexts, first, head_no = distinct(np.concatenate(heads))
        c = np.concatenate(head_counts)[first]
        del heads, head_counts
        words, _, word_no = distinct(np.concatenate(word))
        del word
        keys, first, no = distinct(np.repeat(head_no, np.concatenate(of)).astype(np.int64) * len(words) + word_no)
        del of, word_no, head_no
        total = np.bincount(no, weights=np.concatenate(seen), minlength=len(keys)).astype(np.int64)
        level = build(c, len(contexts), len(words), keys, total, np.concatenate(lower)[first])
        found = level.places(keys // len(words), keys % len(words))
        del keys, first, total
        let_go()
        has = found >= 0
        codes, totals = np.zeros(len(has), np.uint16), np.zeros(len(has), np.int64)
        codes[has], totals[has] = level.codes[found[has]], level.totals[found[has]]
        place = TaskContext.get().partitionId()
        ends = np.cumsum(lengths)

        def told() -> Iterator[tuple]:
            for (shard, block), start, stop in zip(asked, ends - lengths, ends, strict=True):
                mine = no[start:stop]
                near = np.maximum.accumulate(np.maximum(found[mine], 0))  # the question ascends, so its places do
                more = (packed(totals[mine].astype("<u4")), packed(np.diff(near, prepend=0).astype("<u4"))) if places else (b"", b"")
                yield (shard, block, place, packed(codes[mine]), *more)

        yield from in_lots(told(), ANSWER)

    return questions.repartition(shards, "deal").mapInArrow(run, ANSWER)


def text_scores(joined: DataFrame, word_shards: int, shards: int, n: int, v: int, hot: int) -> DataFrame:
    """The result rows from blocks with all their answers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in _rows(batches):
            block = Block(row, word_shards, shards, n, v, hot)
            block.hear_pairs(row["pairs"])
            score = block.log10(row["triples"])
            held_out = [not in_training(i) for i in row["doc_ids"]]
            summed = lambda x, at=block.starts: pa.array(np.add.reduceat(x, at))
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(row["doc_ids"], pa.int64()), pa.array(held_out), pa.array(block.lengths), summed((block.counts > 0)[block.tokens].astype(np.int64)),
                    pa.array(np.full(len(block.lengths), n, np.int64)), summed(np.log10(block.unigram)[block.tokens]), summed(score),
                ],
                names=["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"],
            )

    return joined.mapInArrow(run, "doc_id bigint, held_out boolean, n_tokens bigint, n_known bigint, train_tokens bigint, base_score double, score double")


def train_and_score(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", block_bytes: int = BLOCK_BYTES, hot: int = HOT) -> DataFrame:
    """Train on texts whose crc32(id) mod 5 is not 1 and score all texts: one row for each row.

    Null texts count as empty (one token, the end), a null id as one of training. Repeated rows
    count and score as often as they occur. An empty table gives no rows. Ids are integers.
    """
    spark = docs.sparkSession
    buckets = shards = partitions(spark)
    made: list[tuple[str, str]] = []
    blocks = _bucketed(text_blocks(docs, id_col, text_col, shards, block_bytes), buckets, "blocks", made, parts=True)
    words = _bucketed(word_answers(word_questions(blocks, shards, deal_keys(spark, shards)), shards), buckets, "words", made)
    remove(spark, f"{made[0][1]}/part=1")
    _sweep(spark)
    n, v = words.where("block < 0").agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.sum("v"), F.lit(0))).first()
    pair_shards = max(2 * shards, n // SHARD_TOKENS)  # a text has more pairs than words
    deal = deal_keys(spark, pair_shards)
    columns = ["block", "doc_ids", "home", "tokens", "lengths", "train"]
    told = _told(blocks.where("part = 0"), words, columns, "told", "shard", "place", "ranks", "counts")
    pairs = _bucketed(answers(pair_questions(told, shards, pair_shards, n, v, deal), pair_shards, PRIOR_2, True), buckets, "pairs", made)
    _sweep(spark)
    heard = _told(told, pairs, ["*"], "pairs", "shard", "place", "codes", "totals", "steps")
    triples = _bucketed(answers(triple_questions(heard, shards, pair_shards, n, v, hot, deal), pair_shards, PRIOR_3, False), buckets, "triples", made)
    _sweep(spark)
    scores = materialise(text_scores(_told(heard, triples, ["*"], "triples", "shard", "codes"), shards, pair_shards, n, v, hot), "lm-scores")
    for table, path in made:
        drop_table(spark, table, path)
    return scores


def op3_trie_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return train_and_score(spark.read.parquet(f"{sf_dir}/documents.parquet"))
