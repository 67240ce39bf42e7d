"""Token counts by a linear longest-match automaton over a word-piece vocabulary.

The vocabulary is a trie: pieces that begin a word hang below the root, pieces that continue
one below a second root. Where no child fits, a failure link leads to the node that stands
for what is left after the pieces that greedy longest match would have taken, and the number
of these pieces is kept on the link. So each character is read once and the pieces themselves
are never built.
"""

from __future__ import annotations

import functools
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import checked

#: Words, and bytes of words, that a worker remembers; beyond either the memory starts anew, which changes no result.
REMEMBERED = 200_000
REMEMBERED_BYTES = 128 << 20


class LongestMatchCounter:
    """Counts greedy word pieces; a word that they can't cover is one unknown token."""

    DEAD = -1

    def __init__(self, heads: Iterable[str], tails: Iterable[str]):
        self.child: list[dict[str, int]] = [{}, {}]
        whole = [False, False]
        for root, pieces in ((0, heads), (1, tails)):
            for piece in pieces:
                node = root
                for c in piece:
                    if c not in self.child[node]:
                        self.child[node][c] = len(self.child)
                        self.child.append({})
                        whole.append(False)
                    node = self.child[node][c]
                whole[node] |= bool(piece)
        #: where a node goes when no child fits, and how many pieces are popped on the way
        self.fail = [self.DEAD] * len(self.child)
        self.popped = [0] * len(self.child)
        level = [(node, root, c) for root in (0, 1) for c, node in self.child[root].items()]
        while level:  # breadth first: a failure link leads to a less deep node
            for node, parent, c in level:
                if whole[node]:
                    self.fail[node], self.popped[node] = 1, 1
                    continue
                at, pops = self.fail[parent], self.popped[parent]
                while at != self.DEAD and c not in self.child[at]:
                    pops += self.popped[at]
                    at = self.fail[at]
                if at != self.DEAD:
                    self.fail[node], self.popped[node] = self.child[at][c], pops
            level = [(below, node, c) for node, _, _ in level for c, below in self.child[node].items()]

    def count(self, word: str) -> tuple[int, bool]:
        """(tokens, known) of one word; (0, True) of the empty one."""
        at = pieces = 0
        for c in word:
            while c not in self.child[at]:
                pieces += self.popped[at]
                at = self.fail[at]
                if at == self.DEAD:
                    return 1, False
            at = self.child[at][c]
        while at > 1:  # what is still open is popped at the end
            pieces += self.popped[at]
            at = self.fail[at]
            if at == self.DEAD:
                return 1, False
        return pieces, True


def sentencepiece_vocabulary(path: str) -> tuple[list[str], list[str]]:
    """(head pieces, tail pieces) of a sentencepiece file: pieces with the word mark begin a word, the rest continue one."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    pieces = [model.id_to_piece(i) for i in range(model.get_piece_size()) if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i))]
    mark = "▁"
    return [p[1:] for p in pieces if p[0] == mark and len(p) > 1], [p for p in pieces if p[0] != mark]


@functools.lru_cache(maxsize=1)
def word_coder(vocabulary: str):
    """words -> tokens of each, -1 for an unknown one; words are remembered, for all tasks of a worker."""
    counter = LongestMatchCounter(*sentencepiece_vocabulary(vocabulary))
    known: dict[str, int] = {}
    held = 0

    def coded(words: list[str]) -> list[int]:
        nonlocal held
        try:
            return [known[w] for w in words]
        except KeyError:
            if len(known) > REMEMBERED or held > REMEMBERED_BYTES:
                known.clear()
                held = 0
            for w in set(words).difference(known):
                n, fits = counter.count(w)
                known[w] = n if fits else -1
                held += 4 * len(w)
            return [known[w] for w in words]

    return coded


def count_tokens(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_words, n_tokens, n_unknown (words counted as one unknown token): one row for each row.

    Words are what white space separates. Null and empty texts have none, null ids and rows
    repeated whole stay as they are; texts and words of any length are read whole. An empty
    table gives no rows. `vocabulary` is the path of the file, readable on every executor.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coded = word_coder(vocabulary)
        for batch in batches:
            rows = []
            for text in batch.column(text_col):
                codes = np.array(coded((text.as_py() or "").split()), np.int64)
                rows.append((len(codes), int(np.abs(codes).sum()), int((codes < 0).sum())))
            counts = np.array(rows, np.int64).reshape(-1, 3)
            yield pa.RecordBatch.from_arrays([batch.column(id_col), *(pa.array(counts[:, i]) for i in range(3))], names=["doc_id", "n_words", "n_tokens", "n_unknown"])

    kept = checked(docs, id_col, text_col)
    return kept.mapInArrow(run, f"doc_id {dict(kept.dtypes)[id_col]}, n_words bigint, n_tokens bigint, n_unknown bigint")


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def op8_longest_match(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_tokens(spark.read.parquet(f"{sf_dir}/documents.parquet"), default_vocabulary())
