"""An FM-index over word sequences: Burrows-Wheeler transform in a wavelet matrix, searched backwards.

The index is made for patterns up to ``depth`` symbols: suffixes are sorted by that many symbols,
which backward search of shorter or equal patterns needs and no more. What is kept is compressed: packed bit vectors with a
count of set bits for each 64, for the transform and for where groups of suffixes with equal first symbols begin. The suffix array is
gone once the transform and the least owner of each group are made. Searching is vectorised over many patterns.
"""

from __future__ import annotations

import numpy as np


class BitVector:
    """Packed bits with rank."""

    def __init__(self, bits: np.ndarray):
        words = np.packbits(np.concatenate([bits, np.zeros(-len(bits) % 64 + 64, bits.dtype)]).astype(np.uint8), bitorder="little").view(np.uint64)
        self.words = words
        self.before = np.concatenate([[0], np.cumsum(np.bitwise_count(words), dtype=np.int64)[:-1]]).astype(np.int32)
        self.zeros = int(len(bits) - bits.sum())

    def rank(self, i: np.ndarray) -> np.ndarray:
        """Set bits before each position."""
        w = i >> 6
        mask = (np.uint64(1) << (i & 63).astype(np.uint64)) - np.uint64(1)
        return self.before[w] + np.bitwise_count(self.words[w] & mask)


class WaveletMatrix:
    """A sequence of small integers with rank of any symbol, one bit vector for each bit of a symbol."""

    def __init__(self, symbols: np.ndarray, size: int):
        self.levels: list[tuple[int, BitVector]] = []
        now = symbols
        for bit in range(max(1, int(size - 1).bit_length()) - 1, -1, -1):
            bits = (now >> bit) & 1
            self.levels.append((bit, BitVector(bits)))
            now = np.concatenate([now[bits == 0], now[bits == 1]])
        every = np.arange(size)
        self.first = self._down(every, np.zeros(size, np.int64))

    def _down(self, c: np.ndarray, i: np.ndarray) -> np.ndarray:
        for bit, vector in self.levels:
            ones = vector.rank(i)
            i = np.where((c >> bit) & 1, vector.zeros + ones, i - ones)
        return i

    def rank(self, c: np.ndarray, i: np.ndarray) -> np.ndarray:
        return self._down(c, i) - self.first[c]


class FMIndex:
    """Index of many word sequences; symbol 0 ends each of them and is never searched for."""

    def __init__(self, sequences: list[np.ndarray], depth: int = 50, owners: np.ndarray | None = None):
        """``sequences``: arrays of positive integers, dense from 1. ``owners``: a value for each; of every group of suffixes
        that share ``depth`` symbols ``least`` is the least one."""
        self.depth = depth
        lengths = np.array([len(s) for s in sequences], np.int64)
        starts = np.concatenate([[0], np.cumsum(lengths + 1)[:-1]]) if len(lengths) else np.zeros(0, np.int64)
        text = np.concatenate([x for s in sequences for x in (s, [0])]).astype(np.int64) if sequences else np.zeros(1, np.int64)
        n, self.size = len(text), int(text.max()) + 1
        rank, reach = text.copy(), 1
        while reach < depth:
            step = min(reach, depth - reach)
            tail = np.concatenate([rank[step:] + 1, np.zeros(step, np.int64)])
            rank = np.unique(rank * (n + self.size + 2) + tail, return_inverse=True)[1]
            reach += step
        suffixes = np.argsort(rank, kind="stable")
        first = np.concatenate([[True], np.diff(rank[suffixes]) != 0])
        del rank
        self.group_bits, self.group_start = BitVector(first), np.append(np.flatnonzero(first), n).astype(np.int32)
        self.least = None
        if owners is not None and len(starts):
            self.least = np.minimum.reduceat(owners[np.searchsorted(starts, suffixes, "right") - 1], self.group_start[:-1])
        self.bwt = WaveletMatrix(text[suffixes - 1], self.size)
        self.below = np.concatenate([[0], np.cumsum(np.bincount(text, minlength=self.size))[:-1]])
        self.n = n

    def group(self, at: np.ndarray) -> np.ndarray:
        """The group of the suffix at each place of the order."""
        return self.group_bits.rank(at + 1) - 1

    def extend(self, c: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Intervals of the patterns with ``c`` put in front."""
        both = self.bwt.rank(np.concatenate([c, c]), np.concatenate([lo, hi]))
        base = self.below[c]
        return base + both[: len(c)], base + both[len(c) :]

    def count(self, pattern: np.ndarray) -> int:
        """Occurrences of a pattern of at most ``depth`` symbols."""
        if len(pattern) > self.depth:
            raise ValueError("longer than the index is sorted for")
        lo, hi = np.array([0]), np.array([self.n])
        for c in pattern[::-1]:
            if not 0 < c < self.size:
                return 0
            lo, hi = self.extend(np.array([c]), lo, hi)
            if lo[0] >= hi[0]:
                return 0
        return int(hi[0] - lo[0])

    def matched_groups(self, streams: list[np.ndarray]) -> list[np.ndarray]:
        """For each stream and place the group that its next ``depth`` symbols belong to, or -1 if they aren't in the index.

        Streams go in from their ends, all at once. The statistic of a place is the length matched
        there, up to ``depth``; a place that reaches it widens its interval to the group, which drops
        the last symbol. Where nothing matches, the state goes back to the empty pattern and the places
        that the mismatch covers stay below ``depth``; places between are found by another pass from
        the end just before the mismatch.
        """
        out = [np.full(len(s), -1, np.int64) for s in streams]
        todo = [(k, len(s)) for k, s in enumerate(streams) if len(s) >= self.depth]
        while todo:
            todo.sort(key=lambda x: -x[1])
            of = np.array([k for k, _ in todo])
            end = np.array([e for _, e in todo])
            ends = np.concatenate([[0], np.cumsum(end)])
            flat = np.concatenate([streams[k][:e] for k, e in todo])
            lo, hi, length = np.zeros(len(todo), np.int64), np.full(len(todo), self.n), np.zeros(len(todo), np.int64)
            again, live = [], np.arange(len(todo))
            for t in range(int(end[0])):
                live = live[end[live] > t]
                if not len(live):
                    break
                at = end[live] - 1 - t
                c = flat[ends[live] + at]
                known = (c > 0) & (c < self.size)
                a, b = self.extend(np.where(known, c, 0), lo[live], hi[live])
                ok = known & (a < b)
                for x, place in zip(live[~ok], at[~ok]):
                    # The match of a later end can still cross this place: end it one symbol earlier.
                    stop = place if not known[np.searchsorted(live, x)] else place + length[x]
                    if stop >= self.depth:
                        again.append((int(of[x]), int(stop)))
                live, at, a, b = live[ok], at[ok], a[ok], b[ok]
                length[live] = np.minimum(length[live] + 1, self.depth)
                full = length[live] == self.depth
                group = self.group(a[full])
                a[full], b[full] = self.group_start[group], self.group_start[group + 1]
                lo[live], hi[live] = a, b
                for x, place, g in zip(live[full], at[full], group):
                    out[of[x]][place] = g
            todo = again
        return out
