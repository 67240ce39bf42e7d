"""Benchmark decontamination with a generalised suffix automaton over words.

The automaton holds every run of words of every test item. A training text streams through it
and keeps the length of the longest run that ends at each word; wherever that reaches the
window, the window's words are hit. Only stretches of words that all occur in some item and
are as long as the shortest window need the walk, as no other stretch can hold one.

The items of one automaton are bounded in words. A larger benchmark is dealt to several
automata, each broadcast for a pass of its own over the texts and then let go; the hits of all
passes are united. So neither a broadcast nor a task's memory grows with the benchmark.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import WRITTEN_NO, checked, materialise, with_row_numbers

WINDOW = 13
#: Words of one automaton at most: about 300 bytes each on an executor.
AUTOMATON_WORDS = 1_000_000

#: Lower-cases A-Z and turns all that is no digit, letter or byte of a longer character into blanks.
WORD_BYTES = bytes(
    b + 32 if 0x41 <= b <= 0x5A else b if 0x30 <= b <= 0x39 or 0x61 <= b <= 0x7A or b >= 0x80 else 32 for b in range(256)
)


def words_of(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").translate(WORD_BYTES).split()


class SuffixAutomaton:
    """Generalised automaton of items (id, words) with the windows' owners on its states."""

    def __init__(self, items: Iterable[tuple[str, list[bytes]]], window: int = WINDOW):
        self.window = window
        self.word_no: dict[bytes, int] = {}
        self.next: list[dict[int, int]] = [{}]
        self.link, self.length = [-1], [0]
        listed = [(item, [self.word_no.setdefault(w, len(self.word_no)) for w in words]) for item, words in items if words]
        for _, nos in listed:
            last = 0
            for no in nos:
                last = self._extend(last, no)
        #: state -> items with a window of full length that ends there; state -> [(words, item)] of shorter items
        self.full: dict[int, set[str]] = {}
        self.short: dict[int, list[tuple[int, str]]] = {}
        self.least = min([window, *(len(nos) for _, nos in listed)], default=window)
        for item, nos in listed:
            for end, (state, length) in enumerate(self._walk(nos)):
                if len(nos) >= window and length >= window:
                    self.full.setdefault(self._shortened(state, window), set()).add(item)
                elif len(nos) < window and end == len(nos) - 1:
                    self.short.setdefault(self._shortened(state, len(nos)), []).append((len(nos), item))
        #: nearest state on the way up, itself included, that marks something
        self.marked = [-1] * len(self.link)
        for state in sorted(range(1, len(self.link)), key=self.length.__getitem__):
            own = state in self.full or state in self.short
            self.marked[state] = state if own else self.marked[self.link[state]]

    def _copy(self, state: int, length: int) -> int:
        self.next.append(dict(self.next[state]))
        self.link.append(self.link[state])
        self.length.append(length)
        return len(self.link) - 1

    def _split(self, state: int, target: int, no: int) -> int:
        """The state of the shorter runs that reach `target` from `state` and above."""
        if self.length[target] == self.length[state] + 1:
            return target
        copy = self._copy(target, self.length[state] + 1)
        self.link[target] = copy
        while state >= 0 and self.next[state].get(no) == target:
            self.next[state][no] = copy
            state = self.link[state]
        return copy

    def _extend(self, last: int, no: int) -> int:
        if no in self.next[last]:
            return self._split(last, self.next[last][no], no)
        new = len(self.link)
        self.next.append({})
        self.link.append(0)
        self.length.append(self.length[last] + 1)
        state = last
        while state >= 0 and no not in self.next[state]:
            self.next[state][no] = new
            state = self.link[state]
        if state >= 0:
            self.link[new] = self._split(state, self.next[state][no], no)
        return new

    def _shortened(self, state: int, length: int) -> int:
        """The state of the last `length` words of a run that ends in `state`."""
        while self.length[self.link[state]] >= length:
            state = self.link[state]
        return state

    def _walk(self, nos: Iterable[int]) -> Iterator[tuple[int, int]]:
        """After each word the state and length of the longest run of items that ends there."""
        state = length = 0
        for no in nos:
            while state and no not in self.next[state]:
                state = self.link[state]
                length = self.length[state]
            if no in self.next[state]:
                state = self.next[state][no]
                length += 1
            yield state, length

    def hits(self, words: list[bytes]) -> tuple[list[tuple[int, int]], set[str]]:
        """Spans [from, to) of words inside occurrences of windows, and the items that own these windows."""
        spans: list[tuple[int, int]] = []
        owners: set[str] = set()
        if len(words) < self.least:
            return spans, owners
        get = self.word_no.get
        nos = np.fromiter((get(w, -1) for w in words), np.int32, len(words))
        known = np.diff(np.concatenate(([0], (nos >= 0).astype(np.int8), [0])))
        starts, stops = np.flatnonzero(known == 1), np.flatnonzero(known == -1)
        long = stops - starts >= self.least
        for start, stop in zip(starts[long].tolist(), stops[long].tolist(), strict=True):
            for end, (state, length) in enumerate(self._walk(nos[start:stop].tolist()), start + 1):
                if length < self.least:
                    continue
                widest = 0
                mark = self.marked[state]
                while mark > 0:
                    if mark in self.full and length >= self.window:
                        owners |= self.full[mark]
                        widest = self.window
                    for size, item in self.short.get(mark, ()):
                        if length >= size:
                            owners.add(item)
                            widest = max(widest, size)
                    mark = self.marked[self.link[mark]]
                if widest:
                    if spans and spans[-1][1] >= end - widest:
                        first = min(spans.pop()[0], end - widest)
                        while spans and spans[-1][1] >= first:
                            first = min(spans.pop()[0], first)
                        spans.append((first, end))
                    else:
                        spans.append((end - widest, end))
        return spans, owners


def automata(benchmark: DataFrame, window: int = WINDOW, most: int = AUTOMATON_WORDS, item_col: str = "item_id", text_col: str = "text") -> Iterator[list[tuple[str, list[bytes]]]]:
    """The items in lots of `most` words, streamed to the driver one partition at a time."""
    lot, size = [], 0
    for row in checked(benchmark, item_col, text_col).select(F.col(item_col).cast("string").alias("item"), F.col(text_col).alias("text")).toLocalIterator():
        words = words_of(row["text"])
        if lot and size + len(words) > most:
            yield lot
            lot, size = [], 0
        lot.append((row["item"] or "", words))
        size += len(words)
    if lot:
        yield lot


def find_hits(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, most: int = AUTOMATON_WORDS, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = (), cut: int | None = None) -> DataFrame:
    """doc_id, the columns in `keep`, n_words, n_hit, items array<string>; with `cut` also cleaned, the text without hit spans of so many words.

    One row for each row. Null texts have no words; items without words are no windows; an
    item id that occurs twice counts once. Cutting takes a span's bytes from its first to its
    last word and leaves all other characters. Empty and very long texts, repeated rows and null
    ids are rows like others; an empty table gives no rows.
    """
    lots = automata(benchmark, window, most)
    first, second = next(lots, []), next(lots, None)
    kept = checked(docs, *dict.fromkeys([id_col, *keep, text_col]))
    names = [c for c in kept.columns if c in (id_col, *keep)]
    if second is None:
        return _summed(kept, names, text_col, cut, _hits_of(docs.sparkSession, first, window), None)
    rows = with_row_numbers(kept)
    passes = None
    for lot in itertools.chain((first, second), lots):
        sent = _hits_of(docs.sparkSession, lot, window)
        found = materialise(_spans(rows, text_col, sent), "hits")
        sent[0].destroy()
        passes = found if passes is None else passes.unionByName(found)
    met = passes.groupBy("row_no").agg(F.flatten(F.collect_list("spans")).alias("__spans"), F.array_distinct(F.flatten(F.collect_list("items"))).alias("__items"))  # of one text
    joined = rows.join(met, rows[WRITTEN_NO] == met["row_no"], "left").drop("row_no")
    return _summed(joined, names, text_col, cut, None, ("__spans", "__items"))


def _hits_of(spark: SparkSession, lot: list[tuple[str, list[bytes]]], window: int) -> tuple:
    """(broadcast, function): the function gives a task's own automaton of the items that were sent."""
    sent = spark.sparkContext.broadcast(lot)
    return sent, lambda: SuffixAutomaton(sent.value, window)


def _spans(rows: DataFrame, text_col: str, sent: tuple) -> DataFrame:
    """(row_no, spans, items) of the rows that one automaton hits."""
    make = sent[1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        automaton = make()
        for batch in batches:
            found = [automaton.hits(words_of(t.as_py())) for t in batch.column(text_col)]
            at = [i for i, (spans, _) in enumerate(found) if spans]
            spans = pa.array([[list(s) for s in found[i][0]] for i in at], pa.list_(pa.list_(pa.int64())))
            yield pa.RecordBatch.from_arrays([batch.column(WRITTEN_NO).take(pa.array(at, pa.int64())), spans, pa.array([sorted(found[i][1]) for i in at], pa.list_(pa.string()))], names=["row_no", "spans", "items"])

    return rows.select(WRITTEN_NO, text_col).mapInArrow(run, "row_no bigint, spans array<array<bigint>>, items array<string>")


def _summed(rows: DataFrame, names: list[str], text_col: str, cut: int | None, sent: tuple | None, told: tuple[str, str] | None) -> DataFrame:
    """The result rows, from an automaton that was sent or from spans and items that stand beside the texts."""
    make = sent[1] if sent else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        automaton = make() if make else None
        for batch in batches:
            texts = batch.column(text_col)
            counts, found = [], []
            for i, text in enumerate(texts):
                words = words_of(text.as_py())
                counts.append(len(words))
                if automaton:
                    found.append(automaton.hits(words))
                else:
                    spans, items = (batch.column(c)[i].as_py() or [] for c in told)
                    found.append((united([tuple(s) for s in spans]), items))
            columns = {c: batch.column(c) for c in names}
            columns |= {
                "n_words": pa.array(counts, pa.int64()),
                "n_hit": pa.array([sum(b - a for a, b in spans) for spans, _ in found], pa.int64()),
                "items": pa.array([sorted(owners) for _, owners in found], pa.list_(pa.string())),
            }
            if cut is not None:
                long = [[s for s in spans if s[1] - s[0] >= cut] for spans, _ in found]
                columns["cleaned"] = pa.array([without(t.as_py(), spans) if spans else t.as_py() for t, spans in zip(texts, long, strict=True)], pa.string())
            yield pa.RecordBatch.from_arrays(list(columns.values()), names=list(columns))

    types = dict(rows.dtypes)
    schema = [*(f"`{c}` {types[c]}" for c in names), "n_words bigint", "n_hit bigint", "items array<string>", *["cleaned string"] * (cut is not None)]
    return rows.select(*dict.fromkeys([*names, text_col, *(told or ())])).mapInArrow(run, ", ".join(schema))


def united(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def without(text: str, spans: list[tuple[int, int]]) -> str:
    """`text` without the bytes of these spans of words."""
    raw = text.encode("utf-8", "surrogatepass")
    word = np.frombuffer(raw.translate(WORD_BYTES), np.uint8) != 32
    edge = np.diff(np.concatenate(([0], word.astype(np.int8), [0])))
    starts, stops = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    out, at = [], 0
    for a, b in spans:
        out.append(raw[at : starts[a]])
        at = stops[b - 1]
    return b"".join([*out, raw[at:]]).decode("utf-8", "surrogatepass")


def is_contaminated(n_hit: str = "n_hit", n_words: str = "n_words") -> F.Column:
    """Coverage of a twentieth of the words or more."""
    return (F.col(n_hit) > 0) & (20 * F.col(n_hit) >= F.col(n_words))


def decontaminate(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, longest: int = WINDOW, **options) -> DataFrame:
    """find_hits() plus contaminated (the coverage limit: such a document goes whole) and cleaned (without spans of `longest` words or more)."""
    return find_hits(docs, benchmark, window, cut=longest, **options).withColumn("contaminated", is_contaminated())


def op6_suffix_decontam(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = find_hits(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    return found.select(
        "doc_id",
        "n_words",
        "n_hit",
        F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("items_sha256"),
        is_contaminated().alias("contaminated"),
    )


ORACLE = r"""
WITH iw AS (
  SELECT item_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
  FROM benchmark WHERE text IS NOT NULL
), win AS (
  SELECT DISTINCT item_id, array_to_string(list_slice(w, i, i + least(len(w), 13) - 1), ' ') AS g, least(len(w), 13) AS size
  FROM (SELECT item_id, w, unnest(generate_series(1, greatest(len(w) - 12, 1))) AS i FROM iw WHERE len(w) > 0)
), dw AS (
  SELECT doc_id, coalesce(regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'), []) AS w
  FROM documents
), sizes AS (SELECT DISTINCT size FROM win), dg AS (
  SELECT doc_id, size, i, array_to_string(list_slice(w, i, i + size - 1), ' ') AS g
  FROM (SELECT doc_id, w, size, unnest(generate_series(1, len(w) - size + 1)) AS i FROM dw, sizes WHERE len(w) >= size)
), met AS (
  SELECT DISTINCT doc_id, i, dg.size, item_id FROM dg JOIN win ON dg.g = win.g AND dg.size = win.size
), hit AS (
  SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(generate_series(i, i + size - 1)) AS p FROM met) GROUP BY doc_id
), owner AS (
  SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items
  FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS item FROM met) GROUP BY doc_id
)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items,
       sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM dw d LEFT JOIN hit USING (doc_id) LEFT JOIN owner USING (doc_id)
"""
