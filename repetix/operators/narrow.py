"""Count-distinct of strings made where their windows are, so that no window is shuffled.

`per_key` is for keys of one string each: nothing leaves the task but a sketch or a number for
each string and length. `hll_of_sets` merges inside each task first. Both put strings together
up to CHUNK symbols, so that vector operations don't run over short arrays. HyperLogLog sketches
are images that Spark's functions read, of the same coupons and registers as `hll_sketch_agg` makes;
those of one string have the running estimate (HIP) over its windows from left to right, those of sets
are marked as out of order, as merged sketches are.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from repetix.functions.fingerprint import FingerprintParams, Prefixes, window_fingerprints
from repetix.functions.hashing import hash_array
from repetix.functions.symbols import encode

#: Symbols and strings of a chunk, about; a longer string is a chunk of its own.
CHUNK, STRINGS = 1 << 14, 256
#: Symbols of a set's strings that wait for each other.
SET_CHUNK = 1 << 16
C1, C2 = np.uint64(0x87C37B91114253D5), np.uint64(0x4CF5AD432745937F)
SEED = np.uint64(9001)

#: kernel(owners, fingerprints, strings): (owners, values) of a length
Kernel = Callable[[np.ndarray, np.ndarray, int], tuple[np.ndarray, pa.Array]]


def _mixed(h: np.ndarray) -> np.ndarray:
    h ^= h >> np.uint64(33)
    h *= np.uint64(0xFF51AFD7ED558CCD)
    h ^= h >> np.uint64(33)
    h *= np.uint64(0xC4CEB9FE1A85EC53)
    h ^= h >> np.uint64(33)
    return h


def murmur(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Both halves of the 128-bit hash that Spark's HyperLogLog and Theta sketches take of a BIGINT."""
    k = values.astype(np.int64, copy=False).view(np.uint64) * C1
    high = k >> np.uint64(33)
    k <<= np.uint64(31)
    k |= high
    k *= C2
    b = SEED ^ np.uint64(8)
    k ^= b
    k += b
    a, b = k, k + b
    a, b = _mixed(a), _mixed(b)
    a += b
    b += a
    return a, b


def coupons(fps: np.ndarray, able: np.ndarray | None = None, least: int = 1) -> np.ndarray:
    """(levels << 26 | address) of each value, as int64; of those only that are `able` and have a level of `least` at least."""
    a, b = murmur(fps)
    if able is not None or least > 1:
        high = b < np.uint64(1 << (65 - least)) if least > 1 else able
        found = np.flatnonzero(high if able is None or least <= 1 else high & able)
        a, b = a[found], b[found]
    top = (b >> np.uint64(12)).astype(np.float64)
    zeros = 51 - ((top.view(np.int64) >> 52) - 1023)
    for i in np.flatnonzero(top == 0):
        zeros[i] = min(62, 64 - int(b[i]).bit_length())
    return (zeros + 1) << 26 | (a & np.uint64((1 << 26) - 1)).astype(np.int64)


def coupon_limit(lg_k: int) -> int:
    """Distinct coupons that are still kept as such."""
    return 7 if lg_k < 8 else 3 << (lg_k - 5)


def registers_of(rows: np.ndarray, found: np.ndarray, n: int, m: int) -> tuple[np.ndarray, np.ndarray]:
    """(n rows of m registers, running estimates) of coupons, rows in order."""
    bits = max(1, len(found).bit_length())
    key = np.sort(((rows * m + (found & (m - 1))) << bits | np.arange(len(found))) << 6 | found >> 26)
    best = key >> (bits + 6)
    best <<= 6
    best |= key & 63
    np.maximum.accumulate(best, out=best)  # of each place, from left to right
    grows = np.flatnonzero(np.diff(best, prepend=-1))
    best, after = best[grows], key[grows] >> 6 & ((1 << bits) - 1)
    place, level = best >> 6, best & 63
    before = np.where(np.diff(place, prepend=-1) == 0, np.concatenate(([0], level[:-1])), 0)
    registers = np.zeros(n * m, np.uint8)
    registers[place] = level  # the last of a place is its greatest
    order = np.argsort(after)
    part = np.ldexp(1.0, -np.arange(64))
    row, change = place[order] // m, (part[level] - part[before])[order]
    total = np.concatenate(([0.0], np.cumsum(change)))
    begin = np.searchsorted(row, np.arange(n))
    share = m + total[:-1] - total[begin[row]]
    return registers.reshape(n, m), np.bincount(row, m / share, minlength=n)


def register_images(registers: np.ndarray, running: np.ndarray | None = None) -> np.ndarray:
    """A row of bytes for each row of registers."""
    n, m = registers.shape
    out = np.zeros((n, 40 + m), np.uint8)
    out[:, :8] = [10, 1, 7, m.bit_length() - 1, 0, 16 if running is None else 0, 0, 10]
    if running is not None:
        out[:, 8:16] = running.astype("<f8").view(np.uint8).reshape(n, 8)
    shares = np.ldexp(1.0, -registers.astype(np.int32))
    low = registers < 32
    out[:, 16:24] = np.where(low, shares, 0).sum(1).astype("<f8").view(np.uint8).reshape(n, 8)
    out[:, 24:32] = np.where(low, 0, shares).sum(1).astype("<f8").view(np.uint8).reshape(n, 8)
    out[:, 32:36] = (registers == 0).sum(1).astype("<i4").view(np.uint8).reshape(n, 4)
    out[:, 40:] = registers
    return out


def coupon_images(owners: np.ndarray, found: np.ndarray, lg_k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(owners, bytes, sizes) of distinct coupons, owners in order: lists below eight, else hash sets."""
    names, begins, counts = np.unique(owners, return_index=True, return_counts=True)
    tables = np.where(counts < 8, 3, 5 + np.searchsorted([24 << i for i in range(max(0, lg_k - 8))], counts))
    heads = np.where(counts < 8, 2, 3)
    sizes = heads + (1 << tables)
    starts = np.cumsum(sizes) - sizes
    ints = np.zeros(int(sizes.sum()), np.int64)
    ints[starts] = (lg_k << 24 | 7 << 16 | 1 << 8) + heads
    ints[starts + 1] = np.where(counts < 8, 8 << 24 | counts << 16, 9 << 24) | tables
    sets = counts >= 8
    ints[starts[sets] + 2] = counts[sets]
    of = np.repeat(np.arange(len(names)), counts)
    base, mask = (starts + heads)[of], (1 << tables[of]) - 1
    at = np.where(sets[of], found & mask, np.arange(len(found)) - begins[of])
    step = (found & ((1 << 26) - 1)) >> tables[of] | 1
    left = np.arange(len(found))
    while len(left):
        place = base[left] + at[left]
        free = ints[place] == 0
        ints[place[free]] = found[left[free]]
        left = left[ints[place] != found[left]]
        at[left] = (at[left] + step[left]) & mask[left]
    return names, ints.astype("<u4").view(np.uint8), 4 * sizes


def binaries(data: np.ndarray, sizes: np.ndarray) -> pa.Array:
    offsets = np.concatenate(([0], np.cumsum(sizes))).astype(np.int32)
    return pa.Array.from_buffers(pa.binary(), len(sizes), [None, pa.py_buffer(offsets.tobytes()), pa.py_buffer(data.tobytes())])


def distinct(values: np.ndarray) -> np.ndarray:
    """In order; a sort of integers is many times faster than `np.unique`."""
    order = np.sort(values)
    return order[np.append(True, order[1:] != order[:-1])] if len(order) else order


def _registers_and_coupons(owners: np.ndarray, fps: np.ndarray, n: int, lg_k: int):
    """(owners of registers, registers, running estimates, owners of coupons, coupons): strings of few distinct coupons have no registers."""
    m, most = 1 << lg_k, coupon_limit(lg_k)
    found = coupons(fps)
    many = np.flatnonzero(np.bincount(owners, minlength=n) > most)  # few windows, few coupons
    row = np.full(n, -1)
    row[many] = np.arange(len(many))
    of = row[owners]
    big = of >= 0 if len(many) < len(row) else slice(None)
    registers, running = registers_of(of[big], found[big], len(many), m) if len(many) else (np.zeros((0, m), np.uint8), np.zeros(0))
    for x in many[np.count_nonzero(registers, axis=1) <= most]:
        if len(distinct(found[owners == x])) <= most:
            row[x] = -1
    large = np.flatnonzero(row >= 0)
    few = row[owners] < 0 if len(large) < n else slice(0)
    pairs = distinct(owners[few] << 32 | found[few])
    return large, registers[row[large]], running[row[large]], pairs >> 32, pairs & ((1 << 32) - 1)


def hll_images(lg_k: int) -> Kernel:
    m = 1 << lg_k

    def kernel(owners: np.ndarray, fps: np.ndarray, n: int) -> tuple[np.ndarray, pa.Array]:
        large, registers, running, of, found = _registers_and_coupons(owners, fps, n, lg_k)
        images = register_images(registers, running)
        names, data, sizes = coupon_images(of, found, lg_k)
        return np.concatenate((large, names)), binaries(np.concatenate((images.reshape(-1), data)), np.concatenate((np.full(len(large), 40 + m), sizes)))

    return kernel


def hll_counts(lg_k: int) -> Kernel:
    """The estimates that `hll_sketch_estimate` gives of `hll_images`."""

    def kernel(owners: np.ndarray, fps: np.ndarray, n: int) -> tuple[np.ndarray, pa.Array]:
        large, _, running, of, _ = _registers_and_coupons(owners, fps, n, lg_k)
        names, counts = np.unique(of, return_counts=True)
        return np.concatenate((large, names)), pa.array(np.concatenate((np.floor(running + 0.5), counts)), pa.float64())

    return kernel


def each(count: Callable[[np.ndarray], float], hashed: Callable[[np.ndarray], np.ndarray] = lambda fps: fps) -> Kernel:
    """A number for each string, of the distinct hashes of its windows in order."""

    def kernel(owners: np.ndarray, fps: np.ndarray, n: int) -> tuple[np.ndarray, pa.Array]:
        hashes = hashed(fps)
        begins = np.flatnonzero(np.diff(owners, prepend=-1))  # owners are in order
        ends = [*begins[1:].tolist(), len(owners)]
        return owners[begins], pa.array([float(count(distinct(hashes[a:b]))) for a, b in zip(begins.tolist(), ends, strict=True)], pa.float64())

    return kernel


def greatest(owners: np.ndarray, buckets: np.ndarray, levels: np.ndarray, m: int) -> tuple[np.ndarray, np.ndarray]:
    """(owners, levels): the greatest level, below 64, of each taken bucket of each owner."""
    key = np.sort((owners * m + buckets) << 6 | levels)
    last = np.append(key[1:] >> 6 != key[:-1] >> 6, True) if len(key) else np.zeros(0, bool)
    key = key[last]
    return (key >> 6) // m, key & 63


def f0_levels(m: int, copies: Sequence[int], fill: float) -> Kernel:
    """The median over copies of the estimates of `distinct.F0`, from the same registers."""

    def of_copy(owners: np.ndarray, fps: np.ndarray, n: int, copy: int) -> np.ndarray:
        level = hash_array(fps, "level", copy)
        zeros = np.bitwise_count((level ^ (level - 1)).astype(np.uint64)).astype(np.int64) - 1
        owner, taken = greatest(owners, hash_array(fps, "bucket", copy) % m, zeros, m)
        at_least = np.bincount(owner * 32 + taken, minlength=32 * n).reshape(n, 32)[:, ::-1].cumsum(1)[:, ::-1]
        first = np.argmax(at_least <= int(fill * m), axis=1)
        taken = at_least[np.arange(n), first]
        return np.exp2(first) * np.log(1 - taken / m) / math.log(1 - 1 / m)

    def kernel(owners: np.ndarray, fps: np.ndarray, n: int) -> tuple[np.ndarray, pa.Array]:
        names, own = np.unique(owners, return_inverse=True)
        found = [of_copy(own, fps, len(names), c) for c in copies]
        return names, pa.array(np.median(found, axis=0), pa.float64())

    return kernel


def spark_hash(values: np.ndarray) -> np.ndarray:
    """Spark's xxhash64 of a BIGINT, as unsigned."""
    one, two, three, four, five = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))
    turned = lambda x, r: x << np.uint64(r) | x >> np.uint64(64 - r)
    h = (np.uint64(42 + 8) + five) ^ turned(values.astype(np.int64).view(np.uint64) * two, 31) * one
    h = turned(h, 27) * one + four
    h = (h ^ h >> np.uint64(33)) * two
    h = (h ^ h >> np.uint64(29)) * three
    return h ^ h >> np.uint64(32)


def approx_counts(raw: np.ndarray, bias: np.ndarray, threshold: float, p: int) -> Kernel:
    """What `approx_count_distinct` gives, from Spark's tables of `approx_tables`."""
    m, near = 1 << p, 6

    def corrected(e: float) -> float:
        if e >= 5.0 * m:
            return e
        low = max(int(np.searchsorted(raw, e)) - near + 1, 0)
        high = min(low + near, len(raw))
        while high < len(raw) and (e - raw[high]) ** 2 < (e - raw[low]) ** 2:
            low, high = low + 1, high + 1
        return e - float(bias[low:high].sum()) / (high - low)

    def kernel(owners: np.ndarray, fps: np.ndarray, n: int) -> tuple[np.ndarray, pa.Array]:
        h = spark_hash(fps)
        rest = h << np.uint64(p) | np.uint64(1 << (p - 1))
        level = 54 - np.frexp((rest >> np.uint64(11)).astype(np.float64))[1].astype(np.int64)
        owner, taken = greatest(owners, (h >> np.uint64(64 - p)).astype(np.int64), level, m)
        names, counts = np.unique(owner, return_counts=True)
        zeros = m - counts
        raws = 0.7213 / (1 + 1.079 / m) * m * m / (np.bincount(owner, np.ldexp(1.0, -taken), minlength=n)[names] + zeros)
        out = []
        for e, v in zip(raws.tolist(), zeros.tolist(), strict=True):
            linear = m * math.log(m / v) if v else math.inf
            out.append(linear if v and (linear <= threshold or e <= 2.5 * m) else corrected(e))
        return names, pa.array(np.floor(np.array(out) + 0.5), pa.float64())

    return kernel


def approx_tables(spark, rsd: float = 0.02) -> tuple[np.ndarray, np.ndarray, float, int]:
    """(raw estimates, biases, the threshold of linear counting, the binary logarithm of registers) of Spark's `approx_count_distinct`."""
    helper = spark._jvm.org.apache.spark.sql.catalyst.util.HyperLogLogPlusPlusHelper
    p = math.ceil(2 * math.log(1.106 / rsd) / math.log(2))
    return np.array(list(helper.RAW_ESTIMATE_DATA()[p - 4])), np.array(list(helper.BIAS_DATA()[p - 4])), float(helper.THRESHOLDS()[p - 4]), p


def set_errors(df: DataFrame, grids: dict[float, Sequence[int]], kernels: dict[str, Kernel], params: FingerprintParams = FingerprintParams()) -> DataFrame:
    """(cd, alpha, error) of each row of (texts array<string>) as a set of strings, against the exact maximum over all lengths of the grids.

    A set ends where no kernel's estimate could beat its best of any grid, were it twice the number of windows.
    """
    wanted = sorted({k for ks in grids.values() for k in ks})
    has = {k: [i for i, ks in enumerate(grids.values()) if k in ks] for k in wanted}

    def gathered(batch: pa.RecordBatch) -> Iterator[tuple[list[np.ndarray], list[int]]]:
        strings, rows, size, row = [], [], 0, 0
        for texts in batch.column(0).to_pylist():
            own = [encode(t) for t in texts if t]
            if strings and size + sum(map(len, own)) > CHUNK:
                yield strings, rows
                strings, rows, size, row = [], [], 0, 0
            strings += own
            rows += [row] * len(own)
            row += bool(own)
            size += sum(map(len, own))
        if strings:
            yield strings, rows

    def of_chunk(strings: list[np.ndarray], rows: list[int]) -> np.ndarray:
        sizes, row, n = np.array([len(s) for s in strings]), np.array(rows), rows[-1] + 1
        best, true = np.zeros((len(kernels), len(grids), n)), np.zeros(n)
        live, parts = np.arange(len(strings)), cut(strings, params)
        for k in wanted:
            windows_of = np.bincount(row, np.maximum(sizes - k + 1, 0), minlength=n)
            going = (2 * windows_of / k > np.minimum(best.min((0, 1)), true)) & (windows_of > 0)
            if not going.any():
                break
            keep = np.flatnonzero(going[row])
            if 2 * sizes[keep].sum() <= sizes[live].sum():
                live, parts = keep, cut([strings[i] for i in keep], params)
            owners, fps = parts(k)
            owners = row[live][owners]
            names = np.flatnonzero(going)
            begins, ends = np.searchsorted(owners, names), np.searchsorted(owners, names, "right")
            sets = [np.unique(fps[a:b]) for a, b in zip(begins.tolist(), ends.tolist(), strict=True)]
            counts = np.array([len(x) for x in sets])
            true[names] = np.maximum(true[names], counts / k)
            owners, fps = np.repeat(names, counts), np.concatenate(sets)
            for j, kernel in enumerate(kernels.values()):
                found, values = kernel(owners, fps, n)
                ratio = np.zeros(n)
                ratio[found] = values.to_numpy() / k
                for i in has[k]:
                    np.maximum(best[j, i], ratio, out=best[j, i])
        return np.abs(best - true) / true

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for strings, rows in gathered(batch):
                errors = of_chunk(strings, rows)
                n = errors.shape[2]
                names = np.repeat(np.array(list(kernels), object), len(grids) * n)
                ratios = np.tile(np.repeat(np.array(list(grids), float), n), len(kernels))
                yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array(ratios), pa.array(errors.reshape(-1))], names=["cd", "alpha", "error"])

    return df.select("texts").mapInArrow(run, "cd string, alpha double, error double")


def chunks(batch: pa.RecordBatch, column: str, unit: str) -> Iterator[tuple[int, list[np.ndarray]]]:
    """(place of the first, strings) in chunks."""
    first, held, size = 0, [], 0
    for i, value in enumerate(batch.column(column)):
        symbols = encode(value.as_py(), unit)
        if held and (size + len(symbols) > CHUNK or len(held) >= STRINGS):
            yield first, held
            first, held, size = i, [], 0
        held.append(symbols)
        size += len(symbols)
    if held:
        yield first, held


def cut(strings: list[np.ndarray], params: FingerprintParams) -> Callable[[int], tuple[np.ndarray, np.ndarray]]:
    """A function of k that gives (owners, fingerprints) of all windows that lie in one of the strings."""
    sizes = np.array([len(s) for s in strings])
    owner = np.repeat(np.arange(len(strings)), sizes)
    room = np.repeat(np.cumsum(sizes), sizes) - np.arange(len(owner))
    of = window_fingerprints(np.concatenate(strings), params)

    def windows_of(k: int) -> tuple[np.ndarray, np.ndarray]:
        fps = of(k)
        if len(strings) == 1:
            return owner[: len(fps)], fps
        inside = room[: len(fps)] >= k
        return owner[: len(fps)][inside], fps[inside]

    return windows_of


def windows(strings: list[np.ndarray], lengths: Sequence[int], params: FingerprintParams) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(k, owners, fingerprints) for the lengths that any of the strings has."""
    of, longest = cut(strings, params), max(map(len, strings))
    for k in lengths:
        if k > longest:
            break
        yield k, *of(k)


def _kept(df: DataFrame, by: Sequence[str], text_col: str, unit: str | None) -> tuple[DataFrame, dict, str]:
    kept = df.select(*by, df[text_col].alias("__text"))
    types = dict(kept.dtypes)
    return kept, types, unit or {"string": "codepoint", "binary": "byte"}.get(types["__text"], "symbol")


def per_key(df: DataFrame, by: Sequence[str], lengths: Sequence[int], kernel: Kernel, field: str, text_col: str = "text", unit: str | None = None, params: FingerprintParams = FingerprintParams()) -> DataFrame:
    """(by, k, field) where each key has one string."""
    by, wanted = list(by), sorted(set(lengths))
    kept, types, unit = _kept(df, by, text_col, unit)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, strings in chunks(batch, "__text", unit):
                for k, owners, fps in windows(strings, wanted, params):
                    names, values = kernel(owners, fps, len(strings))
                    places = pa.array(names + first)
                    yield pa.RecordBatch.from_arrays([*(batch.column(c).take(places) for c in by), pa.array(np.full(len(names), k, np.int32)), values], names=[*by, "k", field.split()[0]])

    return kept.mapInArrow(run, ", ".join([*(f"`{c}` {types[c]}" for c in by), "k int", field]))


def per_key_of_grids(
    df: DataFrame, by: Sequence[str], grids: Sequence[Sequence[int]], kernel: Kernel, most: Callable[[np.ndarray], np.ndarray], text_col: str = "text", unit: str | None = None, params: FingerprintParams = FingerprintParams()
) -> DataFrame:
    """(by, k, d) where each key has one string: estimates of every length that may be the maximiser of a grid that holds it.

    `most` gives the greatest estimate of so many members; a length is passed over in a string where that is no more than
    the best of each of its grids so far, so the greatest d / k of every grid is that over all of its lengths. A string has at
    most as many members of length k as windows, and at most t - k more than of the next power of two, t. Lengths 1 and 2,
    which seldom win, come last: their members are counted before they are estimated.
    """
    by, wanted, counts = list(by), sorted({k for ks in grids for k in ks}), each(len)
    order = sorted(wanted, key=lambda k: (k < 3, k))
    has = {k: [g for g, ks in enumerate(map(set, grids)) if k in ks] for k in wanted}
    kept, types, unit = _kept(df, by, text_col, unit)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, strings in chunks(batch, "__text", unit):
                sizes, live, parts = np.array([len(s) for s in strings]), np.arange(len(strings)), cut(strings, params)
                best, top, cap = np.zeros((len(grids), len(strings))), 8, np.full(len(strings), np.inf)
                found: list[tuple[int, np.ndarray, np.ndarray]] = []
                whole, ended = parts, False
                for k in order:
                    if k > 2 and ended:
                        continue
                    over = np.maximum(sizes - k + 1, 0)
                    going = most(over) / k > best.min(0)
                    ended = not going.any()
                    if ended:
                        continue
                    if k < 3:
                        live, parts, top = np.arange(len(strings)), whole, 0
                    elif 2 * sizes[going].sum() <= sizes[live].sum():  # the others needn't be gone through any more
                        live = np.flatnonzero(going)
                        parts = cut([strings[i] for i in live], params)
                    if k > top:
                        top, cap = 1 << (k - 1).bit_length(), np.full(len(strings), np.inf)
                        names, members = counts(*parts(top), len(live))
                        cap[live[names]] = members.to_numpy() + top
                    able = most(np.minimum(over, cap - k)) / k > best[has[k]].min(0)
                    if not able.any():
                        continue
                    owners, fps = parts(k)
                    if not able[live].all():
                        inside = able[live][owners]
                        owners, fps = owners[inside], fps[inside]
                    names, values = kernel(owners, fps, len(live))
                    at, d = live[names], values.to_numpy()
                    for g in has[k]:
                        best[g, at] = np.maximum(best[g, at], d / k)
                    found.append((k, at, d))
                if found:
                    places, ks = pa.array(np.concatenate([at for _, at, _ in found]) + first), np.repeat(np.array([k for k, _, _ in found], np.int32), [len(at) for _, at, _ in found])
                    yield pa.RecordBatch.from_arrays([*(batch.column(c).take(places) for c in by), pa.array(ks), pa.array(np.concatenate([d for _, _, d in found]))], names=[*by, "k", "d"])

    return kept.mapInArrow(run, ", ".join([*(f"`{c}` {types[c]}" for c in by), "k int, d double"]))


def deltas(df: DataFrame, by: Sequence[str], lengths: Sequence[int], kernel: Kernel, text_col: str = "text", unit: str | None = None, params: FingerprintParams = FingerprintParams()) -> DataFrame:
    """(by, delta, k_hat) where each key has one string: a string stops where it has too few windows for any longer length to win."""
    by, wanted = list(by), sorted(set(lengths))
    kept, types, unit = _kept(df, by, text_col, unit)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, strings in chunks(batch, "__text", unit):
                sizes = np.array([len(s) for s in strings])
                best, best_k, going = np.zeros(len(strings)), np.zeros(len(strings), np.int32), np.ones(len(strings), bool)
                for k in wanted:
                    going &= (sizes >= k) & ((sizes - k + 1) / k > best)
                    if not going.any():
                        break
                    if k == wanted[0] or going.sum() * 2 <= len(live):  # the others needn't be gone through any more
                        live = np.flatnonzero(going)
                        parts = cut([strings[i] for i in live], params)
                    owners, fps = parts(k)
                    inside = going[live][owners]
                    names, values = kernel(owners[inside], fps[inside], len(live))
                    ratio, at = values.to_numpy() / k, live[names]
                    higher = ratio > best[at]
                    best[at[higher]], best_k[at[higher]] = ratio[higher], k
                places = np.flatnonzero(best_k)
                yield pa.RecordBatch.from_arrays([*(batch.column(c).take(pa.array(places + first)) for c in by), pa.array(best[places]), pa.array(best_k[places])], names=[*by, "delta", "k_hat"])

    return kept.mapInArrow(run, ", ".join([*(f"`{c}` {types[c]}" for c in by), "delta double", "k_hat int"]))


def hll_of_sets(df: DataFrame, by: Sequence[str], lengths: Sequence[int], lg_k: int, text_col: str = "text", unit: str | None = None, params: FingerprintParams = FingerprintParams()) -> DataFrame:
    """(by, k, cd): a sketch for each key and length that a task meets; keys may come from several tasks and are to be merged."""
    by, wanted, m, most = list(by), sorted(set(lengths)), 1 << lg_k, coupon_limit(lg_k)
    kept, types, unit = _kept(df, by, text_col, unit)

    def images(arrow: list, held: dict[tuple, np.ndarray]) -> Iterator[pa.RecordBatch]:
        for key, state in held.items():
            data = register_images(state[None])[0] if state.dtype == np.uint8 else coupon_images(np.zeros(len(state), np.int64), state, lg_k)[1]
            yield pa.RecordBatch.from_arrays([*(pa.array([v], t) for v, t in zip(key, arrow, strict=False)), pa.array([key[-1]], pa.int32()), binaries(data, np.array([len(data)]))], names=[*by, "k", "cd"])

    def put(held: dict[tuple, np.ndarray], key: tuple, strings: list[np.ndarray]) -> None:
        sizes = np.array([len(x) for x in strings])
        room = np.repeat(np.cumsum(sizes), sizes) - np.arange(int(sizes.sum()))
        prefixes = Prefixes(params, 0)
        prefixes.extend(np.concatenate(strings))
        for k in wanted:
            if k > sizes.max():
                break
            at, state = 0, held.get((*key, k))
            for fps in prefixes.windows(k, 0):
                inside = room[at : at + len(fps)] >= k if k > 1 and len(strings) > 1 else None
                at += len(fps)
                if state is not None and state.dtype == np.uint8:
                    found = coupons(fps, inside, int(state.min()) + 1)  # lower ones change no register
                    np.maximum.at(state, found & (m - 1), (found >> 26).astype(np.uint8))
                    continue
                found = coupons(fps, inside)
                if state is not None:
                    found = np.concatenate((state, found))
                state = np.zeros(m, np.uint8)
                np.maximum.at(state, found & (m - 1), (found >> 26).astype(np.uint8))
                if np.count_nonzero(state) <= most and len(few := np.unique(found)) <= most:
                    state = few
            held[(*key, k)] = state

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple, np.ndarray] = {}
        waiting: dict[tuple, list[np.ndarray]] = {}
        sizes: dict[tuple, int] = {}
        arrow: list = []
        for batch in batches:
            arrow = [batch.column(c).type for c in by]
            of_rows = zip(*(batch.column(c).to_pylist() for c in by), strict=True) if by else [()] * batch.num_rows
            for key, text in zip(of_rows, batch.column("__text"), strict=True):
                symbols = encode(text.as_py(), unit)
                if not len(symbols):
                    continue
                waiting.setdefault(key, []).append(symbols)
                sizes[key] = sizes.get(key, 0) + len(symbols)
                if sizes[key] >= SET_CHUNK:
                    put(held, key, waiting.pop(key))
                    del sizes[key]
                elif len(waiting) > 64 and sum(sizes.values()) >= 64 * SET_CHUNK:
                    for other, strings in waiting.items():
                        put(held, other, strings)
                    waiting, sizes = {}, {}
                if len(held) > 20_000:
                    yield from images(arrow, held)
                    held.clear()
        for key, strings in waiting.items():
            put(held, key, strings)
        yield from images(arrow, held)

    return kept.mapInArrow(run, ", ".join([*(f"`{c}` {types[c]}" for c in by), "k int", "cd binary"]))
