"""One-pass sketches of symbol streams.

`StreamSketch` keeps, for every sampled length, a count-distinct state and what is needed to
find the windows that end in new symbols. Lengths up to K come from the last K symbols; longer
ones from a run-length transform of the reversed stream with a bookmark for each length, until
the transform has so many runs that no longer length can be the maximiser, when it is dropped
and the longer lengths stand still. Without the transform only lengths up to K are counted.
Count-distinct states are registers of a fixed size by default, so that the whole state is
sub-linear in the stream; `exact` keeps the sets themselves, for tests.
"""

from __future__ import annotations

import heapq
import pickle
import tempfile
from collections.abc import Iterable, Iterator, Sequence
from dataclasses import dataclass, field
from typing import BinaryIO

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from repetix.functions.fingerprint import SHIFT, FingerprintParams, Prefixes, window_fingerprints
from repetix.functions.hashing import hash_array
from repetix.functions.symbols import encode
from repetix.plans.accuracy import drop_threshold, should_drop, window_length
from repetix.session import fresh_path, passing

from .run_length_bwt import Bookmarks, RunLengthBwt, grown_transform

#: Symbols that are fingerprinted at once, besides those of the window.
PIECE = 1 << 18
#: Symbols and rows of a micro-batch that are put in order at once.
PART = 1 << 23
#: Symbols of a chunk at least and of its stream at most for which the stream is sorted.
LEAST, SORTED = 1 << 10, 1 << 23


class DistinctState:
    """exact: the set of fingerprints; kmv: the m least hashes; f0: m registers of greatest levels."""

    def __init__(self, kind: str = "exact", m: int = 1024):
        self.kind, self.m = kind, m
        self.values = np.full(m, -1, np.int8) if kind == "f0" else np.empty(0, np.int64)

    def add(self, fps: np.ndarray) -> None:
        if not len(fps):
            return
        if self.kind == "exact":
            self.values = np.union1d(self.values, fps)
        elif self.kind == "kmv":
            self.values = np.union1d(self.values, hash_array(fps, "order"))[: self.m]
        else:
            level = hash_array(fps, "level")
            least = int(self.values.min()) + 1  # lower ones change no register
            if least:
                able = np.flatnonzero(level & ((1 << least) - 1) == 0)
                level, fps = level[able], fps[able]
            zeros = np.bitwise_count((level ^ (level - 1)).astype(np.uint64)).astype(np.int8) - 1
            np.maximum.at(self.values, hash_array(fps, "bucket") % self.m, zeros)

    def estimate(self) -> float:
        if self.kind == "exact" or self.kind == "kmv" and len(self.values) < self.m:
            return float(len(self.values))
        if self.kind == "kmv":
            return (self.m - 1) * float((1 << 31) - 1) / float(self.values[-1])
        for low in range(32):
            taken = int((self.values >= low).sum())
            if taken <= 0.7 * self.m:
                return 2.0**low * np.log(1 - taken / self.m) / np.log(1 - 1 / self.m)
        return float("inf")


@dataclass
class StreamSketch:
    """n_max bounds the stream's length; window None means sqrt(n_max) * log2(n_max). cd: f0 (m registers), kmv (m hashes) or exact (not sub-linear)."""

    n_max: int
    lengths: Sequence[int]
    window: int | None = None
    transform: bool = True
    discard_constant: float = 8.0
    cd: str = "f0"
    m: int = 1024
    params: FingerprintParams = FingerprintParams()
    n: int = 0
    adds: int = 0
    dropped_at: int | None = None
    recent: np.ndarray = field(default_factory=lambda: np.empty(0, np.int64))

    def __post_init__(self):
        self.window = self.window or window_length(self.n_max)
        self.short = [k for k in self.lengths if k <= self.window]
        self.long = [k for k in self.lengths if k > self.window]
        self.states = {k: DistinctState(self.cd, self.m) for k in self.lengths}
        self.bwt = RunLengthBwt() if self.transform else None
        self.marks = Bookmarks(self.long)
        self.prefixes: Prefixes | None = None  # made anew of the recent symbols where a state is read
        self.prints: dict[int, list[int]] = {}
        self.whole = [0] * len(self.params.moduli)
        self.weights = {k: self.params.weight(k - 1) for k in self.long}

    def extend(self, symbols: Iterable[int]) -> StreamSketch:
        """Append symbols. Windows up to K are found for a piece of PIECE symbols at once, so that memory follows K and not the chunk.

        Longer ones are found symbol by symbol in the transform, or, where the chunk is not much shorter than the stream
        before it, by sorting the stream that the transform spells: the state after it is the same.
        """
        chunk = np.asarray(symbols if isinstance(symbols, np.ndarray) else list(symbols), np.int64)
        if self.n + len(chunk) > self.n_max:
            raise ValueError("the stream is longer than n_max")
        n = self.n
        for begin in range(0, len(chunk), PIECE):
            self._extend_short(chunk[begin : begin + PIECE])
        if self.bwt is not None and len(chunk) >= LEAST and 8 * len(chunk) >= n and n + len(chunk) <= SORTED:
            self._extend_long_at_once(chunk)
        elif self.bwt is not None:
            for begin in range(0, len(chunk), PIECE):
                made: dict[int, list[int]] = {k: [] for k in self.long}
                for a in chunk[begin : begin + PIECE].tolist():
                    self._extend_long(a, made)
                    if self.bwt is None:
                        break
                for k, fps in made.items():
                    self.states[k].add(np.array(fps, np.int64))
                    self.adds += len(fps)
                if self.bwt is None:
                    break
        self.n = n + len(chunk)
        return self

    def extend_texts(self, texts: Iterable[str | None]) -> StreamSketch:
        """Append the code points of texts as one stream, PIECE symbols or a text at a time."""
        held, size = [], 0
        for text in texts:
            if text:
                held.append(text)
                size += len(text)
            if size >= PIECE:
                self.extend(encode("".join(held)))
                held, size = [], 0
        return self.extend(encode("".join(held)))

    def _extend_short(self, chunk: np.ndarray) -> None:
        if self.prefixes is None:
            self.prefixes = Prefixes(self.params, self.window)
            self.prefixes.extend(self.recent)
        before, size = len(self.recent), len(self.recent) + len(chunk)
        self.prefixes.extend(chunk)
        for k in self.short:
            first = max(0, before - k + 1)
            parts = self.prefixes.windows(k, first)
            if self.cd != "f0":
                parts = [np.concatenate([np.empty(0, np.int64), *parts])]
            for fps in parts:
                self.states[k].add(fps)
            self.adds += max(0, size - k + 1 - first)
        self.prefixes.trim()
        self.recent = (chunk if len(chunk) >= self.window else np.concatenate((self.recent, chunk)))[-max(1, self.window) :].copy()

    def _extend_long_at_once(self, chunk: np.ndarray) -> None:
        """What `_extend_long` does for all symbols of the chunk."""
        n = self.n
        stream = np.concatenate((self.bwt.spelt() - 1, chunk))
        order, grown = grown_transform(stream)
        runs = self.bwt.runs(marker=False) + np.cumsum(grown[n:])
        over = np.flatnonzero(runs >= drop_threshold(self.n_max, self.window, self.discard_constant))
        end = n + int(over[0]) + 1 if len(over) else len(stream)
        residues = lambda fp: [fp >> SHIFT, fp & ((1 << SHIFT) - 1)] if len(self.params.moduli) > 1 else [fp]
        for begin in range(n, end, PIECE):
            stop = min(begin + PIECE, end)
            part = stream[begin:stop]
            whole = residues(int(window_fingerprints(part, self.params)(len(part))[0]))
            self.whole = [(w * g + f) % q for w, g, f, q in zip(self.whole, self.params.weight(len(part)), whole, self.params.moduli, strict=True)]
            if not self.long or stop < self.long[0]:
                continue
            first = max(0, begin - self.long[-1] + 1)
            of = window_fingerprints(stream[first:stop], self.params)
            for k in self.long:
                fps = of(k)[max(0, begin - k + 1 - first) :]
                if len(fps):
                    self.states[k].add(fps)
                    self.adds += len(fps)
                    self.prints[k] = residues(int(fps[-1]))
        if len(over):
            self.bwt, self.dropped_at = None, end
            return
        place = np.empty(len(stream) + 1, np.int64)
        place[order] = np.arange(len(order))
        self.marks.places.update({k: int(place[end - k]) for k in self.long if end >= k})
        follows = np.where(order < end, np.append(stream, -1)[order] + 1, 0)
        begins = np.flatnonzero(np.diff(follows, prepend=-1))
        self.bwt = RunLengthBwt.restore(list(zip(follows[begins].tolist(), np.diff(np.append(begins, len(follows))).tolist(), strict=True)))

    def _extend_long(self, a: int, made: dict[int, list[int]]) -> None:
        place = self.bwt.extend(a + 1)
        q, base = self.params.moduli, self.params.base
        leaving: dict[int, int] = {}
        for k in self.long:
            if self.n >= k:  # the bookmark stands at the symbol that leaves, moved if the marker came before it
                at = self.marks.places[k]
                leaving[k] = self.bwt.access(at + (at >= place)) - 1
        self.whole = [(w * base + a) % p for w, p in zip(self.whole, q, strict=True)]
        self.n += 1
        for k in self.long:
            if self.n == k:
                self.prints[k] = list(self.whole)
            elif self.n > k:
                self.prints[k] = [((f - leaving[k] * w) % p * base + a) % p for f, w, p in zip(self.prints[k], self.weights[k], q, strict=True)]
            else:
                continue
            f = self.prints[k]
            made[k].append(f[0] if len(f) == 1 else f[0] << SHIFT | f[1])
        self.marks.advance(self.bwt, place, self.n)
        if should_drop(self.bwt.runs(marker=False), self.n_max, self.window, self.discard_constant):
            self.bwt, self.dropped_at = None, self.n

    def runs(self) -> int | None:
        return self.bwt.runs(marker=False) if self.bwt is not None else None

    def frozen(self) -> list[int]:
        """Lengths that stand still; their counts are lower bounds."""
        return [] if self.bwt is not None else self.long

    def profile(self) -> list[tuple[int, float]]:
        return [(k, self.states[k].estimate()) for k in self.lengths]

    def estimate(self) -> tuple[float, int]:
        best = max(((d / k, -k) for k, d in self.profile()), default=(0.0, 0))
        return best[0], -best[1] if best[0] else 0

    def bound(self) -> int:
        """Certificate: no maximiser is longer than n / delta (as far as delta is estimated well)."""
        delta = self.estimate()[0]
        return int(self.n / delta) if delta > 0 else 0

    def certified(self) -> bool:
        """Whether the lengths that are counted to the end reach the certificate, so that no longer one could win."""
        counted = self.short if self.bwt is None else self.lengths
        return bool(counted) and self.bound() <= max(counted)

    def registers(self) -> list[tuple[int, int, int]]:
        """(k, bucket, level) of the taken registers of f0 states."""
        return [(k, int(b), int(s.values[b])) for k, s in self.states.items() for b in np.flatnonzero(s.values >= 0)]

    def words(self) -> int:
        """Words of 8 bytes held: window, runs, bookmarks, fingerprints and count-distinct states."""
        held = len(self.recent) + len(self.prints) * 2 + sum(-(-s.values.nbytes // 8) for s in self.states.values())
        return held + (2 * len(self.bwt.state()) + len(self.marks.places) if self.bwt is not None else 0)

    def dumps(self) -> bytes:
        kept = {k: v for k, v in self.__dict__.items() if k not in ("bwt", "marks", "states", "params", "prefixes")}
        kept |= {"runs_held": self.bwt.state() if self.bwt is not None else None, "places": self.marks.places, "values": {k: s.values for k, s in self.states.items()}}
        return pickle.dumps((kept, self.params.moduli, self.params.base))

    @classmethod
    def loads(cls, raw: bytes) -> StreamSketch:
        kept, moduli, base = pickle.loads(raw)
        out = cls(kept["n_max"], kept["lengths"], kept["window"], kept["transform"], kept["discard_constant"], kept["cd"], kept["m"], FingerprintParams(moduli, base))
        held, places, values = kept.pop("runs_held"), kept.pop("places"), kept.pop("values")
        out.__dict__.update(kept)
        out.bwt = RunLengthBwt.restore(held) if held is not None else None
        out.marks = Bookmarks(out.long, places)
        for k, v in values.items():
            out.states[k].values = v
        return out


OUTPUT = (
    "id {kind}, n bigint, delta double, k_hat int, bound bigint, certified boolean, runs bigint, dropped_at bigint, dropped boolean, adds bigint, words bigint, state_bytes bigint, "
    "profile array<struct<k:int,d:double>>, registers array<struct<k:int,bucket:int,level:int>>, late array<struct<{late}>>"
)


def in_order(frames: Iterator[pd.DataFrame], order: list[str], value: str) -> Iterator[pd.DataFrame]:
    """The rows of all frames, sorted by `order`, in frames with indexes of their own.

    Up to PART symbols and rows they are sorted at once; beyond that in parts, which go to files without a name in the
    worker's temporary folder and are merged a block at a time, so that memory doesn't follow the micro-batch.
    """
    held, size, parts = [], 0, []
    for frame in frames:
        held.append(frame)
        size += len(frame) + (sum(len(t) for t in frame[value] if t) if value == "text" else 0)
        if size >= PART:
            parts.append(_put_aside(_sorted(held, order), size))
            held, size = [], 0
    if not parts:
        yield _sorted(held, order)
        return
    if held:
        parts.append(_put_aside(_sorted(held, order), size))
    held, size, columns = [], 0, frame.columns
    del frame
    place = [columns.get_loc(c) for c in order]
    key = lambda row: [(bool(pd.isna(row[i])), row[i]) for i in place]
    at = columns.get_loc(value)
    for row in heapq.merge(*map(_read_back, parts), key=key):
        held.append(row)
        size += 1 + (len(row[at]) if value == "text" and row[at] else 0)
        if size >= PIECE:
            yield pd.DataFrame(held, columns=columns)
            held, size = [], 0
    if held:
        yield pd.DataFrame(held, columns=columns)


def _sorted(frames: list[pd.DataFrame], order: list[str]) -> pd.DataFrame:
    return pd.concat(frames, ignore_index=True).sort_values(order, kind="stable", ignore_index=True)


def _put_aside(batch: pd.DataFrame, size: int) -> BinaryIO:
    out = tempfile.TemporaryFile()
    table = pa.Table.from_pandas(batch, preserve_index=False)
    with pa.ipc.new_stream(out, table.schema, options=pa.ipc.IpcWriteOptions(compression="lz4")) as writer:
        writer.write_table(table, max_chunksize=max(1, len(batch) * PIECE // size))
    out.seek(0)
    return out


def _read_back(part: BinaryIO) -> Iterator[tuple]:
    with part, pa.ipc.open_stream(part) as blocks:
        for block in blocks:
            yield from block.to_pandas().itertuples(index=False, name=None)


class SketchProcessor(StatefulProcessor):
    """One state for each stream; rows of a micro-batch are put in order before they are read.

    A symbol can't be put into a stream afterwards, so a row that is not beyond the last one read is late: it comes out in `late` and changes nothing.
    """

    def __init__(self, options: dict, order: list[str], value: str, registers: bool):
        self.options, self.order, self.value, self.registers = options, order, value, registers

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("sketch", "raw binary")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        held = self.state.get()
        sketch, last = StreamSketch(**self.options), None
        if held is not None:
            raw, last = pickle.loads(bytes(held[0]))
            sketch = StreamSketch.loads(raw)
        late, before = [], last

        def on_time() -> Iterator[pd.DataFrame]:
            nonlocal last
            for batch in in_order(rows, self.order, self.value):
                places = list(batch[self.order].itertuples(index=False, name=None))
                after = [before is None or p > before for p in places]
                late.extend(batch.loc[[not t for t in after], [*self.order, self.value]].to_dict("records"))
                if any(after):
                    last = places[-1]
                    yield batch[after]

        if self.value == "text":
            sketch.extend_texts(text for batch in on_time() for text in batch["text"])
        else:
            for batch in on_time():
                sketch.extend(batch["symbol"])
        raw = sketch.dumps()
        self.state.update((pickle.dumps((raw, last)),))
        delta, k_hat = sketch.estimate()
        yield pd.DataFrame(
            {
                "id": [key[0]], "n": [sketch.n], "delta": [delta], "k_hat": [k_hat], "bound": [sketch.bound()], "certified": [sketch.certified()],
                "runs": pd.array([sketch.runs()], "Int64"), "dropped_at": pd.array([sketch.dropped_at], "Int64"), "dropped": [sketch.dropped_at is not None],
                "adds": [sketch.adds], "words": [sketch.words()], "state_bytes": [len(raw)], "profile": [[{"k": k, "d": d} for k, d in sketch.profile()]],
                "registers": [[{"k": k, "bucket": b, "level": x} for k, b, x in sketch.registers()] if self.registers else None],
                "late": [late],
            }
        )

    def close(self) -> None:
        pass


def stream_sketch(stream: DataFrame, order: Sequence[str], registers: bool = False, **options) -> DataFrame:
    """Streaming rows of OUTPUT from a streaming (id, symbol int, order columns...), or (id, text, order columns...) that arrives in pieces.

    After every micro-batch a row for each stream that met rows; `late` has the rows that came
    too late, of which `late_rows` makes a table. `registers` adds those of f0 states.
    """
    spark = stream.sparkSession
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    value = "text" if "text" in stream.columns else "symbol"
    kept = stream.select("id", value, *order)
    types = dict(kept.dtypes)
    schema = OUTPUT.format(kind=types["id"], late=", ".join(f"{c}: {types[c]}" for c in [*order, value]))
    return kept.groupBy("id").transformWithStateInPandas(SketchProcessor(options, list(order), value, registers), schema, outputMode="Append", timeMode="None")


def late_rows(rows: DataFrame) -> DataFrame:
    """(id, order columns..., value): the side table of the rows that came too late."""
    return rows.select("id", F.explode("late").alias("late")).select("id", "late.*")


def on_time(stream: DataFrame, ts_col: str, delay: str) -> DataFrame:
    """With a watermark, so that rows later than `delay` are dropped by operators that follow."""
    return stream.withWatermark(ts_col, delay)


def run_to_table(stream: DataFrame, name: str) -> DataFrame:
    """Run a stream over what its source has now, into Parquet in the shared folder, and read that."""
    spark = stream.sparkSession
    out, state = fresh_path(spark, name), fresh_path(spark, f"{name}-state")
    query = stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", state).outputMode("append").trigger(availableNow=True).start()
    query.awaitTermination()
    passing(spark, state)
    return spark.read.schema(stream.schema).parquet(passing(spark, out))


def latest(rows: DataFrame) -> DataFrame:
    """The last row of every stream."""
    return rows.groupBy("id").agg(F.max_by(F.struct(*[c for c in rows.columns if c != "id"]), "n").alias("last")).select("id", "last.*")


def windowed_profile(events: DataFrame, ts_col: str, window, by: Sequence[str], lengths: Sequence[int], cd=None) -> DataFrame:
    """(start, by, k, d): distinct symbol windows of the strings in each time window, batch or streaming.

    events: (id, ts_col, text, by...), a string for each row; `window` is F.window(...) or
    F.session_window(...) of the time column.
    """
    from repetix.operators.distinct import Exact, Hll, window_rows

    rows = window_rows(events, lengths, [ts_col, *by])
    grouped = rows.groupBy(window.alias("w"), *by, "k")
    counted = grouped.agg(F.count_distinct("fp").cast("double").alias("d")) if isinstance(cd or Exact(), Exact) else grouped.agg(F.hll_sketch_estimate(F.hll_sketch_agg("fp", F.lit((cd or Hll()).lg_k))).cast("double").alias("d"))
    return counted.select(F.col("w.start").alias("start"), *by, "k", "d")
