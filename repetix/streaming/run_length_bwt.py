"""The transform of a reversed stream, grown symbol by symbol, in runs; and marks that follow the stream at a distance.

The runs, without the marker, are the leaves of a balanced tree of bounded fan-out whose nodes
hold lengths and symbol counts, so a place, a rank and an insertion each cost one way down. The
number of runs is kept up to date from the two neighbours of each new symbol.
"""

from __future__ import annotations

from bisect import insort

import numpy as np

from repetix.functions.suffixes import suffix_array

#: Runs of a leaf and children of a node at most.
FANOUT = 32


class _Node:
    __slots__ = ("children", "counts", "runs", "size")

    def __init__(self, runs: list[list[int]] | None = None, children: list[_Node] | None = None):
        self.runs, self.children = runs, children
        self.counts: dict[int, int] = {}
        if runs is not None:
            self.size = sum(n for _, n in runs)
            for s, n in runs:
                self.counts[s] = self.counts.get(s, 0) + n
        else:
            self.size = sum(c.size for c in children)
            for c in children:
                for s, n in c.counts.items():
                    self.counts[s] = self.counts.get(s, 0) + n

    def halved(self) -> _Node | None:
        """The new right neighbour of a node that has grown too wide."""
        mine = self.runs if self.runs is not None else self.children
        if len(mine) <= FANOUT:
            return None
        left, right = mine[: len(mine) // 2], mine[len(mine) // 2 :]
        if self.runs is not None:
            other = _Node(right)
            self.__init__(left)
        else:
            other = _Node(children=right)
            self.__init__(children=left)
        return other

    def insert(self, place: int, symbol: int) -> _Node | None:
        if self.runs is None:
            for i, c in enumerate(self.children):
                if place <= c.size:
                    break
                place -= c.size
            new = c.insert(place, symbol)
            if new is not None:
                self.children.insert(i + 1, new)
        else:
            runs = self.runs
            for i, (s, n) in enumerate(runs):
                if s == symbol and place <= n:
                    runs[i][1] += 1
                    break
                if place < n:
                    runs[i : i + 1] = [[s, place], [symbol, 1], [s, n - place]] if place else [[symbol, 1], [s, n]]
                    break
                place -= n
                if not place and i + 1 < len(runs) and runs[i + 1][0] != symbol:
                    runs.insert(i + 1, [symbol, 1])
                    break
            else:
                runs.append([symbol, 1])
        self.size += 1
        self.counts[symbol] = self.counts.get(symbol, 0) + 1
        return self.halved()


class RunLengthBwt:
    """Places count from 0. Symbols are integers from 1; 0 is the marker, which sorts first and stands once."""

    def __init__(self):
        self.root = _Node([])
        self.order: list[int] = []
        self.marker = 0
        self.kept = 0  # runs without the marker

    @classmethod
    def restore(cls, runs: list[tuple[int, int]]) -> RunLengthBwt:
        out, at, plain = cls(), 0, []
        for s, n in runs:
            if s == 0:
                out.marker = at
            elif plain and plain[-1][0] == s:
                plain[-1][1] += n
            else:
                plain.append([s, n])
            at += n
        level = [_Node(plain[i : i + FANOUT // 2]) for i in range(0, len(plain), FANOUT // 2)] or [_Node([])]
        while len(level) > 1:
            level = [_Node(children=level[i : i + FANOUT // 2]) for i in range(0, len(level), FANOUT // 2)]
        out.root, out.kept, out.order = level[0], len(plain), sorted(level[0].counts)
        return out

    def spelt(self) -> np.ndarray:
        """The stream, from its first symbol to its last: the marker's way from the place of the empty string."""
        runs = self.state()
        rows = np.repeat(np.array([s for s, _ in runs], np.int64), np.array([n for _, n in runs]))
        after = np.empty(len(rows), np.int64)
        after[np.argsort(rows, kind="stable")] = np.arange(len(rows))
        steps, place, out = after.tolist(), 0, np.empty(len(rows) - 1, np.int64)
        for i in range(len(out)):
            out[i] = place
            place = steps[place]
        return rows[out]

    def _plain(self) -> list[list[int]]:
        """The runs without the marker; neighbours differ, also from leaf to leaf."""
        merged: list[list[int]] = []
        stack = [self.root]
        while stack:
            node = stack.pop()
            if node.runs is None:
                stack += reversed(node.children)
                continue
            for s, n in node.runs:
                if merged and merged[-1][0] == s:
                    merged[-1][1] += n
                else:
                    merged.append([s, n])
        return merged

    def state(self) -> list[tuple[int, int]]:
        out, at, put = [], 0, False
        for s, n in self._plain():
            if not put and at <= self.marker < at + n:
                out += [(s, self.marker - at)] * (self.marker > at) + [(0, 1), (s, at + n - self.marker)]
                put = True
            else:
                out.append((s, n))
            at += n
        return out if put else [*out, (0, 1)]

    def __len__(self) -> int:
        return self.root.size + 1

    def runs(self, marker: bool = True) -> int:
        if not marker:
            return self.kept
        return self.kept + 1 + (0 < self.marker < self.root.size and self._at(self.marker - 1) == self._at(self.marker))

    def _at(self, place: int) -> int:
        """The symbol at a place of the sequence without the marker."""
        node = self.root
        while node.runs is None:
            for c in node.children:
                if place < c.size:
                    break
                place -= c.size
            node = c
        for s, n in node.runs:
            if place < n:
                return s
            place -= n
        raise IndexError(place)

    def access(self, place: int) -> int:
        return 0 if place == self.marker else self._at(place - (place > self.marker))

    def _rank(self, symbol: int, place: int) -> int:
        found, node = 0, self.root
        while node.runs is None:
            for c in node.children:
                if place <= c.size:
                    break
                found += c.counts.get(symbol, 0)
                place -= c.size
            node = c
        for s, n in node.runs:
            if place <= 0:
                break
            found += min(n, place) if s == symbol else 0
            place -= n
        return found

    def rank(self, symbol: int, place: int) -> int:
        """Occurrences of the symbol before the place."""
        if symbol == 0:
            return int(place > self.marker)
        return self._rank(symbol, place - (place > self.marker))

    def smaller(self, symbol: int) -> int:
        counts, total = self.root.counts, int(symbol > 0)
        for s in self.order:
            if s >= symbol:
                break
            total += counts[s]
        return total

    def lf(self, place: int) -> int:
        symbol = self.access(place)
        return self.smaller(symbol) + self.rank(symbol, place)

    def extend(self, symbol: int) -> int:
        """Append to the stream; returns the marker's new place."""
        at, size = self.marker, self.root.size
        left, right = self._at(at - 1) if at else None, self._at(at) if at < size else None
        if symbol not in (left, right):
            self.kept += 2 if left == right and left is not None else 1
        if symbol not in self.root.counts:
            insort(self.order, symbol)
        beside = self.root.insert(at, symbol)
        if beside is not None:
            self.root = _Node(children=[self.root, beside])
        self.marker = self.smaller(symbol) + self._rank(symbol, at)
        return self.marker


def grown_transform(stream: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(the number of symbols before each row of the reversed stream's transform, the runs without the marker that each symbol adds as the transform grows).

    A row's rank among the others never changes, so a symbol meets the nearest rows on both sides that are older than its own.
    """
    n = len(stream)
    order = np.concatenate(([0], n - suffix_array(stream[::-1])[0]))
    follows = [*stream.tolist(), None]
    left, held = [None] * (n + 1), []
    right = [None] * (n + 1)
    for row in order.tolist():
        while held and held[-1] > row:
            right[held.pop()] = follows[row]
        left[row] = follows[held[-1]] if held else None
        held.append(row)
    adds = [0 if s == a or s == b else 2 if a == b and a is not None else 1 for s, a, b in zip(follows, left, right, strict=True)]
    return order, np.array(adds[:n], np.int64)


class Bookmarks:
    """One place in the transform for each length k: there stands the k-th most recent symbol."""

    def __init__(self, lengths: list[int], places: dict[int, int] | None = None):
        self.lengths = lengths
        self.places: dict[int, int] = dict(places or {})

    def advance(self, bwt: RunLengthBwt, inserted: int, n: int) -> None:
        """After a symbol was appended and the marker inserted; n counts the stream's symbols."""
        for k in self.lengths:
            if n == k:
                self.places[k] = bwt.lf(inserted)
            elif n > k:
                place = self.places[k]
                self.places[k] = bwt.lf(place + (place >= inserted))

    def symbol(self, bwt: RunLengthBwt, k: int) -> int:
        return bwt.access(self.places[k])
