"""Quality classifier: votes of the nearest labelled texts in a latent semantic space.

Terms are hashed words, the shapes of words (runs of letter classes with their punctuation)
and a few levels of whole-text measures such as repetition. A bounded sample of labelled texts
gives term weights, a truncated singular value decomposition and the labelled vectors; these
have a fixed size and are broadcast. Every text is folded in, its cosines with all labelled
vectors come from one blocked product, and the labels of the nearest are weighted by them.
"""

from __future__ import annotations

import math
import re
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import checked

TERMS = 1 << 13
RANK = 64
NEIGHBOURS = 25
#: Labelled texts in the fit at most; they are the least by hash of the id.
SAMPLE = 4096
BLOCK = 512
REMEMBERED = 200_000
#: Longer words, as texts without blanks have, are cut into consecutive pieces of so many characters, each with its own terms.
PIECE = 64

_CLASSES = [(re.compile(r"[^\W\d_]+"), "a"), (re.compile(r"\d+"), "0")]


def shape(word: str) -> str:
    """Letters become a, A or Aa by case, digits 0; other characters stay, runs of one shortened to three."""

    def letters(m: re.Match) -> str:
        run = m[0]
        return "a" if run.islower() else "A" if run.isupper() else "Aa" if run[0].isupper() else "aA"

    out = _CLASSES[1][0].sub("0", re.sub(r"[^\W\d_]+", letters, word))
    return re.sub(r"(.)\1{3,}", r"\1\1\1", out)


def _slot(term: str) -> int:
    return zlib.crc32(term.encode("utf-8", "surrogatepass")) % TERMS


def term_counter():
    """text -> (slots, weights) of its terms; words are remembered within a bound."""
    seen: dict[str, tuple[int, int]] = {}

    def count(text: str) -> tuple[np.ndarray, np.ndarray]:
        words = text.split()
        weight: dict[int, float] = {}
        counted = Counter(words)
        pieces = counted
        if max(map(len, counted), default=0) > PIECE:
            pieces = Counter()
            for word, n in counted.items():
                for at in range(0, len(word), PIECE):
                    pieces[word[at : at + PIECE]] += n
        total = pieces.total()
        for word, n in pieces.items():
            slots = seen.get(word)
            if slots is None:
                if len(seen) > REMEMBERED:
                    seen.clear()
                slots = seen[word] = (_slot("w " + word.lower()), _slot("s " + shape(word)))
            weight[slots[0]] = weight.get(slots[0], 0.0) + n
            weight[slots[1]] = weight.get(slots[1], 0.0) + n
        found = {s: math.log1p(100 * w / total) / 8 for s, w in weight.items()}
        for name, level in _levels(text, words, counted):
            for step in range(level + 1):  # near levels share terms
                slot = _slot(f"m {name} {step}")
                found[slot] = found.get(slot, 0.0) + 0.5
        return np.fromiter(found, np.int32, len(found)), np.fromiter(found.values(), np.float32, len(found))

    return count


def _levels(text: str, words: list[str], counted: Counter) -> list[tuple[str, int]]:
    if not words:
        return [("empty", 0)]
    total = len(words)
    raw = text.encode("utf-8", "surrogatepass")
    lines = text.split("\n")
    share = lambda part, whole, steps: min(steps - 1, int(steps * part / max(1, whole)))
    return [
        ("length", min(9, int(math.log2(total)) // 2)),
        ("most common", share(counted.most_common(1)[0][1], total, 8)),
        ("repeated neighbours", share(sum(map(str.__eq__, words, words[1:])), total, 8)),
        ("repeated lines", share(len(lines) - len(set(lines)), len(lines), 8)),
        ("capitals", share(sum(w.isupper() for w in counted), len(counted), 8)),
        ("bare marks", share(sum(n for w, n in counted.items() if not any(map(str.isalnum, w))), total, 8)),
        ("packed", share(len(zlib.compress(raw, 1)), len(raw), 8)),
    ]


@dataclass
class LatentVotes:
    """What the fit leaves: at most TERMS * RANK + SAMPLE * (RANK + 1) numbers."""

    fold: np.ndarray
    vectors: np.ndarray
    labels: np.ndarray
    prior: float

    @classmethod
    def fit(cls, rows: list[tuple[np.ndarray, np.ndarray, int]], rank: int = RANK, seed: int = 7) -> LatentVotes:
        if not rows:
            return cls(np.zeros((TERMS, 1), np.float32), np.zeros((0, 1), np.float32), np.zeros(0, np.float32), 0.5)
        matrix = dense([r[:2] for r in rows])
        labels = np.array([r[2] for r in rows], np.float32)
        idf = np.log((1 + len(rows)) / (1 + (matrix > 0).sum(0))).astype(np.float32) + 0.1
        matrix *= idf
        matrix /= np.maximum(np.linalg.norm(matrix, axis=1, keepdims=True), 1e-9)
        basis = np.random.default_rng(seed).standard_normal((TERMS, min(rank + 16, len(rows)))).astype(np.float32)
        for _ in range(4):  # subspace iteration
            basis, _ = np.linalg.qr(matrix.T @ (matrix @ basis))
        _, _, right = np.linalg.svd(matrix @ basis, full_matrices=False)
        fold = idf[:, None] * (basis @ right[:rank].T)
        vectors = unit(dense([r[:2] for r in rows]) @ fold)
        return cls(fold.astype(np.float32), vectors, labels, float(labels.mean()))

    def score(self, rows: list[tuple[np.ndarray, np.ndarray]], neighbours: int = NEIGHBOURS) -> np.ndarray:
        """Weighted share of label 1 among the nearest; the prior where nothing is alike."""
        out = np.full(len(rows), self.prior)
        k = min(neighbours, len(self.labels))
        if not k:
            return out
        for at in range(0, len(rows), BLOCK):
            cosine = unit(dense(rows[at : at + BLOCK]) @ self.fold) @ self.vectors.T
            near = np.argpartition(cosine, -k, axis=1)[:, -k:]
            weight = np.maximum(np.take_along_axis(cosine, near, 1), 0).astype(np.float64) ** 4
            total = weight.sum(1)
            voted = (weight * self.labels[near]).sum(1)
            out[at : at + BLOCK] = np.where(total > 1e-12, voted / np.maximum(total, 1e-12), self.prior)
        return np.clip(out, 0, 1)


def dense(rows: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
    out = np.zeros((len(rows), TERMS), np.float32)
    for i, (slots, weights) in enumerate(rows):
        out[i, slots] = weights
    return out


def unit(vectors: np.ndarray) -> np.ndarray:
    return vectors / np.maximum(np.linalg.norm(vectors, axis=1, keepdims=True), 1e-9)


def fold_of(doc_id: str | Column, folds: int) -> Column:
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % folds


def fit_votes(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality") -> LatentVotes:
    """Fit on at most `sample` labelled texts whose crc32(id) mod 3 is not 1: those of least xxhash64(id).

    Rows of one id with different labels count as the lower; null labels and ids are left out.
    An id with several texts counts once, and its rows are made one before anything is collected.
    """
    usable = checked(labels, id_col, label_col).where(F.col(id_col).isNotNull() & F.col(label_col).isNotNull() & (fold_of(id_col, 3) != 1))
    chosen = usable.groupBy(id_col).agg(F.min(label_col).cast("int").alias("label")).orderBy(F.xxhash64(id_col), id_col).limit(sample)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = term_counter()
        for batch in batches:
            rows = [count(t.as_py() or "") for t in batch.column(text_col)]
            yield pa.RecordBatch.from_arrays(
                [batch.column(id_col), batch.column("label"), pa.array([s.tobytes() for s, _ in rows], pa.binary()), pa.array([w.tobytes() for _, w in rows], pa.binary())],
                names=[id_col, "label", "slots", "weights"],
            )

    labelled = checked(docs, id_col, text_col).join(F.broadcast(chosen), id_col)
    kept = labelled.select(id_col, "label", text_col)
    counted = kept.mapInArrow(run, f"`{id_col}` {dict(kept.dtypes)[id_col]}, label int, slots binary, weights binary")
    once = counted.groupBy(id_col).agg(F.max(F.struct("slots", "weights", "label")).alias("of"))  # a repeated id counts once; `sample` rows at most
    found = once.select(id_col, "of.*").orderBy(id_col).collect()
    return LatentVotes.fit([(np.frombuffer(r["slots"], np.int32), np.frombuffer(r["weights"], np.float32), r["label"]) for r in found])


def score_documents(docs: DataFrame, model: LatentVotes, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """id, the columns in `keep` and score (0 to 1) of every row. Null texts count as empty; any length is read whole."""
    sent = docs.sparkSession.sparkContext.broadcast((model.fold, model.vectors, model.labels, model.prior))
    kept = checked(docs, *dict.fromkeys([id_col, *keep, text_col]))
    names = [c for c in kept.columns if c in (id_col, *keep)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count, model = term_counter(), LatentVotes(*sent.value)
        for batch in batches:
            for at in range(0, batch.num_rows, BLOCK):
                part = batch.slice(at, BLOCK)
                scores = model.score([count(t.as_py() or "") for t in part.column(text_col)])
                yield pa.RecordBatch.from_arrays([*(part.column(c) for c in names), pa.array(scores)], names=[*names, "score"])

    types = dict(kept.dtypes)
    return kept.mapInArrow(run, ", ".join([*(f"`{c}` {types[c]}" for c in names), "score double"]))


def op1_latent_votes(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = fit_votes(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    scored = score_documents(docs, model)
    return scored.select(
        "doc_id", F.coalesce(fold_of("doc_id", 3) == 1, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted")
    )
