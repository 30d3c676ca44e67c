"""Chroma fingerprints of audio: rectangle filters over pitch-class frames, packed integers, alignment.

A recording is cut into overlapping frames; the spectrum of each is folded into twelve pitch classes,
smoothed over neighbouring frames and scaled to unit length. An integral image over (frame, class)
gives the sum of any rectangle in four look-ups. Sixteen filters compare halves or thirds of rectangles that
differ in kind, first class, height and width; each answer is quantised to two bits (a Gray code), so a
frame gives one 32-bit integer.

Two recordings are aligned by the histogram of offsets between their equal integers; at the fullest
offset the share of bits that differ over the overlap is the error.

For a table, recordings with the same integers are one class, which its least id stands for. Classes are
dealt into groups by ranges of ids, and every two groups meet in a cell, which finds the fullest offset of all pairs that have an
equal integer and returns the best of each class. A pair's bits are compared only as long as its error may be the least:
integers that aren't equal differ by a bit each. Smaller ids come first, so a recording that agrees wholly with one over their overlap
is compared with no larger one of the cell, which could not be its best. No other pair is left out, so the work grows with the pairs; no task depends on how
frequent an integer is, as cells are dealt by class alone. A group is as large as a task's memory allows, since it travels
to as many cells as there are groups; what it meets passes piece by piece.

The media of a row is its column of bytes, read as unsigned 8-bit mono samples. Rows: null or too
short media have no integers and match nothing; constant media gives the integers of silence. Rows repeating
an id are fingerprinted one by one and never matched with each other. Matches of equal error go to the smaller id. Very long media count
whole. Other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shapeplan.llm import words as W
from shapeplan.runtime import ship, written

RATE, FRAME, HOP = 11_025, 1024, 64
LOW_HZ, HIGH_HZ = 28.0, 3520.0

#: Frames that the widest filter spans.
SPAN = 16

#: Frames averaged by the smoothing, and the thresholds of the quantiser.
SMOOTH, CUTS = 5, (-0.12, 0.0, 0.12)

#: The error up to which a recording counts as the same.
SAME = 0.35

#: Bytes of a fingerprint's digest.
DIGEST = 16

#: Frames whose spectra are taken at once, and frames folded into integers at once.
BLOCK, FRAMES_AT_ONCE = 128, 4096

#: What rounding may take from an answer that lies on a threshold, as those of repeating sound do.
ROUNDING = 1e-7

#: Least number of groups, integers of a group and of a piece at most on average, and integers that a recording counts for besides its own.
GROUPS, PER_GROUP, PER_PIECE, BESIDES = 8, 1 << 24, 1 << 19, 4

#: Equal integers aligned at once, and integers of an alignment compared before it is judged again.
AT_ONCE, STEPS = 1 << 21, (4, 12, 48)

#: No match: no id is below another one and this large.
NONE = np.iinfo(np.int64).max


def filters() -> list[tuple[int, int, int, int]]:
    """Kind, first class, height, width: every kind at several scales, classes spread over the octave."""
    return [(k % 4, (5 * k) % 12 // 2, 2 + 2 * (k % 3), (4, 8, 12, SPAN)[k // 4]) for k in range(16)]


def _fold() -> np.ndarray:
    hz = np.arange(FRAME // 2 + 1) * RATE / FRAME
    at = np.flatnonzero((hz >= LOW_HZ) & (hz <= HIGH_HZ))
    out = np.zeros((len(hz), 12))
    out[at, np.round(12 * np.log2(hz[at] / 440.0)).astype(int) % 12] = 1.0
    return out


_FOLD, _HANN = _fold(), np.hanning(FRAME)
_HEARD = slice(int(np.flatnonzero(_FOLD.any(axis=1))[0]), int(np.flatnonzero(_FOLD.any(axis=1))[-1]) + 1)


def energies(recordings: list[np.ndarray], counts: np.ndarray) -> np.ndarray:
    """Energy of the twelve pitch classes in all frames of recordings (samples in [-1, 1]), which have ``counts`` of them, end to end."""
    out, block, used, done = np.zeros((int(counts.sum()), 12)), np.empty((BLOCK, FRAME)), 0, 0
    for samples, count in zip(recordings, counts.tolist()):
        frames = np.ndarray((count, FRAME), float, samples, strides=(8 * HOP, 8))
        while len(frames):
            some = frames[: BLOCK - used]
            np.multiply(some, _HANN, out=block[used : used + len(some)])
            frames, used = frames[len(some) :], used + len(some)
            if used == BLOCK or done + used == len(out):
                z = np.fft.rfft(block[:used], axis=1)[:, _HEARD]
                out[done : done + used] = (z.real**2 + z.imag**2) @ _FOLD[_HEARD]
                used, done = 0, done + used
    return out


def chroma(energy: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Pitch-class frames, of unit length or zero, from energies (recordings by frames by 12; zeros after a recording's last frame)."""
    edge, total = np.arange(energy.shape[1]), np.zeros((len(energy), energy.shape[1] + 1, 12))
    np.cumsum(energy, axis=1, out=total[:, 1:])
    lo, hi = np.maximum(edge - SMOOTH // 2, 0), np.minimum(edge + SMOOTH // 2 + 1, len(edge))
    out = (total[:, hi] - total[:, lo]) / np.maximum(np.minimum(hi, counts[:, None]) - lo, 1)[:, :, None]
    norm = np.linalg.norm(out, axis=2, keepdims=True)
    return np.where(norm > 1e-9, out / np.maximum(norm, 1e-9), 0.0)


def codes(frames: np.ndarray) -> np.ndarray:
    """One 32-bit integer for each frame that the widest filter fits after: recordings by frames."""
    n = frames.shape[1] - SPAN + 1
    image = np.zeros((13, len(frames), frames.shape[1] + 1))
    image[1:, :, 1:] = np.moveaxis(frames.cumsum(axis=1).cumsum(axis=2), 2, 0)

    def area(t: int, y: int, w: int, h: int) -> np.ndarray:
        a, b = image[:, :, t : t + n], image[:, :, t + w : t + w + n]
        return b[y + h] - b[y] - a[y + h] + a[y]

    out = np.zeros((len(frames), n), np.uint32)
    for kind, y, h, w in filters():
        whole = area(0, y, w, h)
        if kind == 0:  # lower against upper classes
            part = area(0, y, w, h // 2)
        elif kind == 1:  # earlier against later frames
            part = area(0, y, w // 2, h)
        elif kind == 2:  # opposite quarters against the others
            part = area(0, y, w // 2, h // 2) + area(w // 2, y + h // 2, w - w // 2, h - h // 2)
        else:  # the middle of the time against its sides, twice as wide
            part = area(w // 4, y, w // 2, h)
        ratio = (2 * part - whole) / (np.abs(whole) + 1e-3)
        level = sum((ratio >= cut - ROUNDING).view(np.uint8) for cut in CUTS)
        out = (out << np.uint32(2)) | (level ^ (level >> 1))
    return out


def fingerprinted(media: list[bytes | None]) -> list[np.ndarray]:
    """The integers of recordings; those of like length are worked on together."""
    raw = [np.frombuffer(m or b"", np.uint8) for m in media]
    counts = np.array([max(0, (len(r) - FRAME) // HOP + 1) for r in raw], int)
    order, out = np.argsort(counts, kind="stable"), [np.zeros(0, np.uint32)] * len(raw)
    order = order[counts[order] >= SPAN]
    while len(order):
        some = order[-max(1, FRAMES_AT_ONCE // int(counts[order[-1]])) :]
        order, n = order[: -len(some)], counts[some]
        energy = np.zeros((len(some), int(n[-1]), 12))
        energy[np.arange(n[-1]) < n[:, None]] = energies([raw[k].astype(float) / 127.5 - 1.0 for k in some.tolist()], n)
        for k, own, size in zip(some.tolist(), codes(chroma(energy, n)), (n - SPAN + 1).tolist()):
            out[k] = own[:size].copy()
    return out


def fingerprint(media: bytes | None) -> np.ndarray:
    return fingerprinted([media])[0]


def align(a: np.ndarray, b: np.ndarray) -> tuple[int | None, float | None]:
    """Frames by which ``b`` starts later within ``a``, and the share of differing bits there; nulls if no integer is equal."""
    u, at = np.unique(a, return_inverse=True)
    order = np.argsort(at, kind="stable")
    ends = np.concatenate([[0], np.cumsum(np.bincount(at, minlength=len(u)))])
    k = np.minimum(np.searchsorted(u, b), max(len(u) - 1, 0)) if len(u) else np.zeros(len(b), int)
    hist = np.zeros(len(a) + len(b), np.int64)
    for j in np.flatnonzero(u[k] == b) if len(u) else ():
        hist[order[ends[k[j]] : ends[k[j] + 1]] - j + len(b)] += 1
    if not hist.any():
        return None, None
    offset = int(np.argmax(hist)) - len(b)
    i, j = max(offset, 0), max(-offset, 0)
    n = min(len(a) - i, len(b) - j)
    return offset, float(np.bitwise_count(a[i : i + n] ^ b[j : j + n]).sum() / (32 * n))


@W.tidy
def _prints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in W.slices(batches, "media", 4 << 20):
        rows, media = [], W.texts(batch, "media")
        for doc, media, own in zip(W.column(batch, "doc_id"), media, fingerprinted(media)):
            packed = own.astype("<u4").tobytes()
            node = hashlib.blake2b(packed, digest_size=DIGEST).digest() if packed and doc is not None else None
            rows.append((doc, len(media or b""), len(own), zlib.crc32(packed), packed, node))
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.binary())
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names=["doc_id", "n_samples", "n_codes", "codes_crc32", "codes", "node"])


def _runs(begin: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The whole numbers from each ``begin`` on, ``size`` of them, run after run."""
    ends = np.cumsum(size)
    return np.repeat(begin - (ends - size), size) + np.arange(int(ends[-1]) if len(ends) else 0)


class Recordings:
    """Recordings end to end, and of each the best alignment so far: error, smaller id (``NONE``: none yet), offset."""

    def __init__(self, ids: np.ndarray, sizes: np.ndarray, flat: np.ndarray, same: float):
        self.ids, self.n, self.first, self.flat = ids, sizes, np.cumsum(sizes) - sizes, flat
        self.error, self.other, self.offset = np.full(len(ids), float(same)), np.full(len(ids), NONE), np.zeros(len(ids), np.int64)

    def improve(self, own: np.ndarray, error: np.ndarray, other: np.ndarray, offset: np.ndarray) -> None:
        """Take the least error, then the least id, then the least offset."""
        keep = error <= self.error[own]
        own, error, other, offset = own[keep], error[keep], other[keep], offset[keep]
        order = np.lexsort((offset, other, error, own))
        order = order[np.diff(own[order], prepend=-1) != 0]
        own, error, other, offset = own[order], error[order], other[order], offset[order]
        ahead = (error < self.error[own]) | (other < self.other[own]) | ((other == self.other[own]) & (offset < self.offset[own]))
        own = own[ahead]
        self.error[own], self.other[own], self.offset[own] = error[ahead], other[ahead], offset[ahead]

    def closed(self, least: int) -> np.ndarray:
        """Whether nothing better is left among ids from ``least`` on."""
        return (self.error == 0) & (self.other < least)

    def found(self) -> np.ndarray:
        return np.flatnonzero(self.other != NONE)


class Places:
    """The integers of recordings in ascending order, each with its recording and its place there."""

    def __init__(self, codes: np.ndarray, rec: np.ndarray, pos: np.ndarray):
        self.codes, self.rec, self.pos = codes, rec, pos

    @classmethod
    def of(cls, recordings: Recordings) -> Places:
        both = recordings.flat.astype(np.uint64)
        both <<= np.uint64(32)
        both |= np.arange(len(both), dtype=np.uint32)
        both.sort()
        pos = both.astype(np.uint32)
        both >>= np.uint64(32)
        codes = both.astype(np.uint32)
        del both
        rec = np.repeat(np.arange(len(recordings.n), dtype=np.int32), recordings.n)[pos]
        pos -= recordings.first.astype(np.uint32)[rec]
        return cls(codes, rec, pos.view(np.int32))

    def without(self, closed: np.ndarray) -> Places:
        """Leave out closed recordings, once they are many."""
        keep = ~closed[self.rec]
        return Places(self.codes[keep], self.rec[keep], self.pos[keep]) if np.count_nonzero(keep) < 0.8 * len(keep) else self


def _bits(left: np.ndarray, a: np.ndarray, right: np.ndarray, b: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Differing bits of runs of ``n`` integers that start at ``a`` of ``left`` and at ``b`` of ``right``."""
    out, ends, start = np.zeros(len(n), np.int64), np.cumsum(n), 0
    while start < len(n):
        floor = ends[start - 1] if start else 0
        stop = max(start + 1, int(np.searchsorted(ends, floor + AT_ONCE, "right")))
        size = n[start:stop]
        bits = np.bitwise_count(left[_runs(a[start:stop], size)] ^ right[_runs(b[start:stop], size)])
        out[start:stop] = np.add.reduceat(bits, np.cumsum(size) - size, dtype=np.int64)
        start = stop
    return out


def _settle(left: Recordings, right: Recordings, x: np.ndarray, y: np.ndarray, shift: np.ndarray, votes: np.ndarray) -> None:
    """Compare recordings ``x`` of ``left`` with ``y`` of ``right``, ``shift`` later in ``left``, where ``votes`` integers are equal.

    A pair is given up as soon as it can't be a recording's best: an integer that isn't equal differs by a bit at least.
    """
    swap, i, j = left.ids[x] > right.ids[y], np.maximum(shift, 0), np.maximum(-shift, 0)
    n, i, j = np.minimum(left.n[x] - i, right.n[y] - j), left.first[x] + i, right.first[y] + j
    bits, odd, done = np.zeros(len(x), np.int64), np.zeros(len(x), np.int64), 0
    for step in (*STEPS, None):
        keep = (bits + np.maximum(n - votes - odd, 0)) / (32 * n) <= np.where(swap, left.error[x], right.error[y])
        x, y, shift, votes, swap, i, j, n, bits, odd = (c[keep] for c in (x, y, shift, votes, swap, i, j, n, bits, odd))
        if not len(x):
            return
        if step:
            at = np.arange(done, done + step)
            inside = at < n[:, None]
            apart = left.flat[np.where(inside, i[:, None] + at, 0)] ^ right.flat[np.where(inside, j[:, None] + at, 0)]
            apart[~inside] = 0
            bits, odd, done = bits + np.bitwise_count(apart).sum(axis=1, dtype=np.int64), odd + np.count_nonzero(apart, axis=1), done + step
            over = n <= done
        else:
            bits, over = bits + _bits(left.flat, i + done, right.flat, j + done, n - done), np.ones(len(n), bool)
        of_left, of_right, error = over & swap, over & ~swap, bits / (32 * n)
        right.improve(y[of_right], error[of_right], left.ids[x[of_right]], shift[of_right])
        left.improve(x[of_left], error[of_left], right.ids[y[of_left]], -shift[of_left])
        x, y, shift, votes, swap, i, j, n, bits, odd = (c[~over] for c in (x, y, shift, votes, swap, i, j, n, bits, odd))


def _fullest(left: Recordings, right: Recordings, key: np.ndarray, start: int, for_x: int, for_shift: int, longest: int) -> None:
    """Settle each pair at the fullest offset, the least of several, from sorted keys of all equal integers: right, left, shift."""
    at = np.concatenate([np.zeros(min(len(key), 1), int), np.flatnonzero(key[1:] != key[:-1]) + 1])
    votes, key = np.diff(at, append=len(key)), key[at]
    pair, low = key >> for_shift, (1 << for_shift) - 1
    x, y, place = pair & ((1 << for_x) - 1), (pair >> for_x) + start, key & low
    first = np.flatnonzero(np.diff(pair, prepend=-1))
    if not len(first):
        return
    swap = left.ids[x] > right.ids[y]  # seen from the smaller id, the shift has the other sign
    top = np.maximum.reduceat((votes << for_shift) | np.where(swap, place, low - place), first)
    x, y, place = x[first], y[first], top & low
    shift, votes = np.where(swap[first], place, low - place) - longest, top >> for_shift
    ours = np.flatnonzero(left.ids[x] != right.ids[y])
    some = max(1, AT_ONCE // 32)
    for k in range(0, len(ours), some):
        _settle(left, right, *(c[ours[k : k + some]] for c in (x, y, shift, votes)))


def _alone(left: Recordings, places: Places, right: Recordings, one: int, begin: np.ndarray, size: np.ndarray, upward: bool) -> None:
    """A recording with many equal integers: met by a part of the others at a time, one by one by those that repeat with it."""
    begin, at, times = np.unique(begin[size > 0], return_index=True, return_counts=True)
    size = size[size > 0][at]
    held = _runs(begin, size)
    rec = places.rec[held]
    equal = np.bincount(rec, np.repeat(times, size), len(left.ids)).astype(np.int64)
    equal[left.ids <= right.ids[one] if upward else left.ids == right.ids[one]] = 0
    for x in np.flatnonzero(equal > AT_ONCE).tolist():
        a, b = (r.flat[r.first[k] : r.first[k] + r.n[k]] for r, k in ((left, x), (right, one)))
        swap = left.ids[x] > right.ids[one]
        offset, error = align(b, a) if swap else align(a, b)
        own, k, other = (left, x, right.ids[one]) if swap else (right, one, left.ids[x])
        own.improve(*(np.array([c]) for c in (k, error, other, offset)))
    equal[equal > AT_ONCE] = 0
    part = np.where(equal > 0, np.cumsum(equal) // AT_ONCE, -1)
    order = np.argsort(part[rec], kind="stable")
    edges = np.flatnonzero(np.diff(part[rec][order], prepend=-1, append=part.max(initial=-1) + 1))
    for lo, hi in zip(edges[:-1].tolist(), edges[1:].tolist()):
        some = held[order[lo:hi]]
        _meet(left, Places(places.codes[some], places.rec[some], places.pos[some]), right, slice(one, one + 1), upward, True)


def _meet(left: Recordings, places: Places, right: Recordings, these: slice, upward: bool, part_of: bool = False) -> None:
    """Align recordings of ``right`` with all of ``left`` that have an equal integer.

    ``upward``: only with those of larger ids; ``right`` is in order of ids, so what agrees wholly with one of them is closed to the rest.

    ``part_of``: the places are those that one recording meets at once, whatever their number.
    """
    first, n = right.first[these], right.n[these]
    whole = slice(int(first[0]), int(first[-1] + n[-1]))
    distinct, which = np.unique(right.flat[whole], return_inverse=True)
    begin = np.searchsorted(places.codes, distinct, "left")
    size = (np.searchsorted(places.codes, distinct, "right") - begin)[which]
    begin, first, longest = begin[which], first - whole.start, int(n.max())
    ends = np.cumsum(np.add.reduceat(size, first))
    for_x, for_shift = len(left.n).bit_length(), (int(left.n.max()) + longest).bit_length()
    most, k = 1 << max(0, 62 - for_x - for_shift), 0
    while k < len(ends):
        floor = ends[k - 1] if k else 0
        to = min(k + most, max(k + 1, int(np.searchsorted(ends, floor + AT_ONCE, "right"))))
        part = slice(int(first[k]), int(first[to - 1] + n[to - 1]))
        if ends[to - 1] - floor > AT_ONCE and not part_of:
            _alone(left, places, right, these.start + k, begin[part], size[part], upward)
        elif ends[to - 1] > floor:
            own = np.repeat(np.arange(to - k), n[k:to])
            base = (own << (for_x + for_shift)) + longest - (np.arange(part.start, part.stop) - first[k + own])
            at = _runs(begin[part], size[part])
            key = places.rec[at].astype(np.int64)
            keep = slice(None)
            if upward:
                reach = np.where(left.closed(right.ids[these.start + k]), np.iinfo(np.int64).min, left.ids)
                keep = np.flatnonzero(reach[key] > np.repeat(right.ids[these][k + own], size[part]))
                at, key = at[keep], key[keep]
            key <<= for_shift
            key += places.pos[at]
            key += np.repeat(base, size[part])[keep]
            key.sort()
            _fullest(left, right, key, these.start + k, for_x, for_shift, longest)
        k = to


def best_in_cell(ids: np.ndarray, codes: list[np.ndarray], left: np.ndarray, right: np.ndarray, same: float) -> tuple:
    """Place, error, smaller id and offset of the best alignment of recordings, over all pairs of ``left`` and ``right``, equal or apart."""
    upward = np.array_equal(left, right)
    right = right[np.argsort(ids[right], kind="stable")] if upward else right
    a, b = (Recordings(ids[side], np.array([len(codes[k]) for k in side]), np.concatenate([codes[k] for k in side]), same) for side in (left, right))
    _meet(a, Places.of(a), b, slice(0, len(right)), upward)
    found = [(side[r.found()], *(c[r.found()] for c in (r.error, r.other, r.offset))) for r, side in ((a, left), (b, right))]
    return tuple(np.concatenate(c) for c in zip(*found))


def bundle(ids: np.ndarray, nodes: list[bytes], codes: list[np.ndarray]) -> bytes:
    """A group's recordings in few bytes: of neighbouring integers the bits that change, by byte planes, compressed."""
    flat = np.concatenate(codes).astype("<u4")
    flat[1:] ^= flat[:-1].copy()
    planes = lambda x: np.ascontiguousarray(x).view(np.uint8).reshape(len(x), x.itemsize).T.tobytes()
    head, n = np.array([len(ids), len(flat)], "<i8").tobytes(), np.array([len(c) for c in codes], "<i8")
    return zstandard.ZstdCompressor(level=1).compress(b"".join([head, planes(ids.astype("<i8")), planes(n), *nodes, planes(flat)]))


def _opened(data: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Ids, digests, sizes and integers of a bundle, end to end."""
    raw = zstandard.ZstdDecompressor().decompress(data)
    n, total = np.frombuffer(raw, "<i8", 2).tolist()
    whole = lambda at, kind, n: np.ascontiguousarray(np.frombuffer(raw, np.uint8, n * np.dtype(kind).itemsize, at).reshape(-1, n).T).reshape(-1).view(kind)
    at = 16 + 16 * n
    return whole(16, "<i8", n), np.frombuffer(raw, f"V{DIGEST}", n, at), whole(16 + 8 * n, "<i8", n), np.bitwise_xor.accumulate(whole(at + DIGEST * n, "<u4", total))


def unbundle(data: bytes) -> tuple[np.ndarray, list[bytes], list[np.ndarray]]:
    ids, nodes, sizes, flat = _opened(data)
    return ids, [x.tobytes() for x in nodes], np.split(flat, np.cumsum(sizes)[:-1])


@W.tidy
def _bundles(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Pieces of rows that come in order of ids: least id, weight and bundle."""

    def piece() -> pa.RecordBatch:
        ids, nodes, codes = zip(*held)
        data = bundle(np.array(ids, np.int64), list(nodes), [np.frombuffer(c, "<u4") for c in codes])
        return pa.RecordBatch.from_arrays([pa.array([ids[0]], pa.int64()), pa.array([weight], pa.int64()), pa.array([data], pa.binary())], names=["least", "weight", "data"])

    held, weight = [], 0
    for batch in batches:
        for row in zip(*(W.column(batch, name) for name in ("id", "node", "codes"))):
            held.append(row)
            weight += len(row[2]) // 4 + BESIDES
            if weight >= PER_PIECE:
                yield piece()
                held, weight = [], 0
    if held:
        yield piece()


def _cell(cell: pa.Table, same: float) -> pa.Table:
    """All pairs of two groups, or of one with itself: the one of larger ids is laid out by integer, the pieces of the other pass by in order of ids."""
    low, high = cell.column("low")[0].as_py(), cell.column("high")[0].as_py()
    group, least, data = cell.column("own_group").to_numpy(), cell.column("least").to_numpy(), cell.column("data")
    theirs, ours = (np.flatnonzero(group == g) for g in (low, high))
    form = pa.schema([("node", pa.binary()), ("bit_error", pa.float64()), ("match_id", pa.int64()), ("match_offset", pa.int64())])
    if not len(ours) or not len(theirs):
        return form.empty_table()
    ids, nodes, sizes, flat = (np.concatenate(c) for c in zip(*(_opened(data[k].as_py()) for k in ours.tolist())))
    left = Recordings(ids, sizes, flat, same)
    places = Places.of(left)
    for k in theirs[np.argsort(least[theirs], kind="stable")].tolist():
        ids, _, sizes, flat = _opened(data[k].as_py())
        places = places.without(left.closed(int(ids[0])) | (left.ids <= ids[0]))
        _meet(left, places, Recordings(ids, sizes, flat, same), slice(0, len(ids)), True)
    own = left.found()
    digests = pa.Array.from_buffers(pa.binary(DIGEST), len(own), [None, pa.py_buffer(nodes[own].tobytes())]).cast(pa.binary())
    return pa.table([digests, *(pa.array(c[own]) for c in (left.error, left.other, left.offset))], schema=form)


def fingerprints(media: DataFrame) -> DataFrame:
    """From ``doc_id``, ``media`` (bytes): sizes, checksum, the packed integers and their digest ``node``; null without any or without an id."""
    ship(media.sparkSession)
    rows = media.select("doc_id", F.col("media").cast("binary").alias("media"))
    return rows.mapInArrow(_prints, "doc_id long, n_samples long, n_codes long, codes_crc32 long, codes binary, node binary")


def matched(media: DataFrame, *, same: float = SAME) -> DataFrame:
    """Fingerprint digests with the best-aligned recording of smaller id: ``match_id``, ``match_offset``, ``bit_error`` or nulls."""
    prints = written(fingerprints(media), "prints")
    nodes = written(prints.where("node is not null").groupBy("node").agg(F.min("doc_id").alias("id"), F.first("codes").alias("codes")), "nodes")
    total = int(nodes.agg(F.sum(F.octet_length("codes") / 4 + BESIDES)).first()[0] or 0)
    groups = max(GROUPS, -(-total // PER_GROUP))
    ranges = 4 * groups * max(1, -(-total // (groups * PER_PIECE)))
    pieces = nodes.repartitionByRange(ranges, "id").sortWithinPartitions("id").mapInArrow(_bundles, "least long, weight long, data binary")
    pieces = written(pieces, "pieces")
    # Groups are ranges of ids of about equal weight; each travels to all its cells as small bundles.
    sizes = pieces.select("least", "weight").orderBy("least").collect()
    weights = np.array([r.weight for r in sizes], np.int64)
    at = (np.cumsum(weights) - weights // 2) * groups // max(total, 1)
    starts = [sizes[k + 1].least for k in np.flatnonzero(np.diff(at)).tolist()]
    own = F.size(F.filter(F.array(*map(F.lit, starts)).cast("array<bigint>"), lambda start: start <= F.col("least"))).cast("long")
    groups = len(starts) + 1
    dealt = pieces.select("least", "data", own.alias("own_group")).withColumn("g", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(groups - 1).cast("long"))))
    cells = dealt.select("own_group", "least", "data", F.least("own_group", "g").alias("low"), F.greatest("own_group", "g").alias("high"))
    cells = cells.repartition(min(2 * groups * (groups + 1), 10_000), "low", "high").groupBy("low", "high")
    found = cells.applyInArrow(lambda group: _cell(group, same), "node binary, bit_error double, match_id long, match_offset long")
    best = found.groupBy("node").agg(F.min(F.struct("bit_error", "match_id", "match_offset")).alias("m"))
    # Copies of a class's least id match that id without error, unless one below it does so too.
    of = nodes.select("node", "id").join(best, "node", "left")
    copy = (F.col("doc_id") > F.col("id")) & ~F.coalesce(F.col("m.bit_error") == 0, F.lit(False))
    itself = F.struct(F.lit(0.0).alias("bit_error"), F.col("id").alias("match_id"), F.lit(0).cast("long").alias("match_offset"))
    of = prints.where("node is not null").join(of, "node").withColumn("m", F.when(copy, itself).otherwise(F.col("m")))
    rest = prints.where("node is null").withColumn("m", F.lit(None).cast(of.schema["m"].dataType))  # apart, as a join would send them all to one task
    cols = ["doc_id", "n_samples", "n_codes", "codes_crc32", "m.match_id", "m.match_offset", "m.bit_error"]
    return of.select(*cols).unionByName(rest.select(*cols))
