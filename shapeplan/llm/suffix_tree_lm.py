"""Language-model scoring with a probabilistic suffix tree over words.

A document is its lower-cased words and one end symbol. The tree holds contexts of up to ``depth``
words. A context is a state if it was seen ``least`` times, its suffix is a state, and it passes a
divergence test: what its next-symbol distribution gains over that of its suffix, in nats over all
its occurrences, must exceed ``penalty`` for each distinct next symbol; one-word contexts are tested against
the root. Distributions are smoothed by an absolute discount whose mass is spread as the next shorter
state says, at the root by add-one counts of all training tokens with one place for all unknown words, so
every distribution sums to one. A position is scored from the longest state that is a suffix of its history.

Texts are read once, into slices: word hashes and indexes into them, written as a table. Words are counted and numbered first, and
each slice gets the counts and numbers of its words, ascending in order of their hashes so that they pack well. Then a slice deals its distinct histories, with counts, to buckets by
their last word, as all contexts that end in a word belong to its subtree. A bucket builds its subtrees from the histories of
all slices and sends back one probability for each history that a slice sent. So what is shuffled follows the
distinct histories of slices, and never the number of documents times that of buckets. Number of buckets and
of slices follow the input.

A word that is the last one of more than ``hot`` histories has buckets of its own, by the word before (after the start
symbol, which has nothing before it, by the next word). The pair counts that these buckets share are summed in a
pass before, so each tests and smooths with the counts of all.

Rows: a null text counts as empty (one end symbol), a very long one is a slice by itself. Rows repeating a
``doc_id`` are scored one by one. A null id counts as the empty string in the fold rule. Other columns are ignored,
whatever their names; an empty table gives an empty result. A score has no ties.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shapeplan.llm import words as W
from shapeplan.runtime import bucketed, ship, written

DISCOUNT = 0.75

#: Distinct histories scored at a time, and at least all that end in the same two words.
CHUNK = 400_000

#: Bytes of text in a slice, and bytes of all texts for each bucket.
SLICE, BUCKET = 24 << 20, 18 << 20

#: Hashes of the two symbols that are no words, and their places in a slice's dictionary.
START, END = xxhash.xxh3_64_intdigest(b"\x00start"), xxhash.xxh3_64_intdigest(b"\x00end")
AT_START, AT_END = 0, 1

#: The bucket of a row that holds a slice itself; rows with its words' counts come below, by the bucket that counted them.
SELF, COUNTS = -1, -2


#: Rows that slices and buckets exchange, and the result.
FORM = pa.schema([("slice", pa.int64()), ("bucket", pa.int64()), ("data", pa.binary())])
OUT = pa.schema([
    ("doc_id", pa.int64()), ("held_out", pa.bool_()), *((c, pa.int64()) for c in ("n_tokens", "n_known", "train_tokens")), ("base_score", pa.float64()),
    ("score", pa.float64()),
])


def held_out(doc_id: int | None, folds: int = 7, fold: int = 2) -> bool:
    return zlib.crc32(b"" if doc_id is None else str(doc_id).encode()) % folds == fold


class _Local(dict):
    """Words in order of first sight; the two symbols come first."""

    def __missing__(self, word: bytes) -> int:
        i = self[word] = len(self) + 2
        return i


def _pack(*arrays: np.ndarray) -> bytes:
    """Arrays by byte planes (first bytes of all items, second bytes, ...), compressed."""
    raw = b"".join(struct.pack("<cq", a.dtype.char.encode(), len(a)) + np.ascontiguousarray(a).view(np.uint8).reshape(len(a), a.itemsize).T.tobytes() for a in arrays)
    return zstandard.ZstdCompressor(level=3).compress(raw)


def _unpack(data: bytes) -> list[np.ndarray]:
    raw, out, at = zstandard.ZstdDecompressor().decompress(data), [], 0
    while at < len(raw):
        kind, n = struct.unpack_from("<cq", raw, at)
        t = np.dtype(kind.decode())
        a = np.ascontiguousarray(np.frombuffer(raw, np.uint8, n * t.itemsize, at + 9).reshape(t.itemsize, n).T).reshape(-1).view(t)
        out.append(a)
        at += 9 + a.nbytes
    return out


def _small(x: np.ndarray) -> np.ndarray:
    top = int(x.max(initial=0))
    return x.astype(np.uint16 if top < 1 << 16 else np.uint32 if top < 1 << 32 else np.uint64)


def _distinct(key: np.ndarray, *counts: np.ndarray) -> tuple[np.ndarray, ...]:
    """As ``np.unique`` with index (any place of a key) and inverse, and the sums of counts, in half of its memory."""
    order = np.argsort(key)
    own = key[order]
    new = np.ones(len(key), bool)
    np.not_equal(own[1:], own[:-1], out=new[1:])
    own, starts = own[new], np.flatnonzero(new)
    sums = [np.add.reduceat(c[order], starts, dtype=np.int64) if len(c) else np.zeros(0, np.int64) for c in counts]
    number = np.cumsum(new, dtype=np.int32)
    number -= 1
    at = np.empty(len(key), np.int32)
    at[order] = number
    return own, order[starts], at, *sums


def _types(symbols: list[np.ndarray], size: int) -> tuple[np.ndarray, np.ndarray]:
    """Where each distinct tuple of symbols below ``size`` is first seen, and the number of each place's tuple."""
    key, span = np.zeros(len(symbols[0]), np.int64), 1
    for s in symbols:
        if span > (1 << 62) // max(size, 1):
            seen, key = np.unique(key, return_inverse=True)
            span = len(seen)
        key, span = key * size + s, span * size
    _, first, kind = np.unique(key, return_index=True, return_inverse=True)
    return first, kind


def _rows(names: str, *columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c) for c in columns], names=names.split())


@W.tidy
def _slices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Texts as one stream of dictionary places, an end after each, with the documents' rows, ids and folds."""
    for batch in W.slices(batches, "text", SLICE):
        ids, local, parts = W.column(batch, "doc_id"), _Local(), []
        for text in W.texts(batch, "text"):
            words = W.split(text, lower=True)
            parts.append(np.append(np.fromiter(map(local.__getitem__, words), np.int32, len(words)), np.int32(AT_END)))
        hashes = np.fromiter([START, END, *map(xxhash.xxh3_64_intdigest, local)], np.uint64, len(local) + 2)
        meta = np.array([i or 0 for i in ids], np.int64), np.array([i is None for i in ids], np.int8), np.array([held_out(i) for i in ids], np.int8)
        data = _pack(hashes, _small(np.concatenate(parts)), _small(np.array([len(p) for p in parts])), *meta)
        yield _rows("slice bucket data", np.array([W.column(batch, "uid")[0]], np.int64), np.array([SELF], np.int64), pa.array([data], pa.binary()))


class _Slice:
    """A slice and, once they are known, its words' numbers and counts: in training and in all documents."""

    def __init__(self, data: bytes):
        self.hashes, stream, lengths, self.ids, self.no_id, self.held = _unpack(data)
        self.stream, self.lengths = stream.astype(np.int32), lengths.astype(np.int64)
        self.doc = np.repeat(np.arange(len(self.lengths), dtype=np.int32), self.lengths)
        self.train = self.held[self.doc] == 0
        self.number = self.learned = self.every = np.zeros(0, np.int64)

    def by_hash(self, buckets: int) -> Iterator[tuple[int, np.ndarray]]:
        """Dictionary places by the bucket that counts them, in order of hashes."""
        where = (self.hashes % np.uint64(buckets)).astype(np.int64)
        order = np.lexsort((self.hashes, where))
        for own in np.split(order, np.flatnonzero(np.diff(where[order])) + 1):
            yield int(where[own[0]]), own

    def words(self) -> tuple[np.ndarray, np.ndarray]:
        """How often each dictionary entry is a token; the start counts once a document, like the end."""
        n = len(self.hashes)
        learned, every = (np.bincount(s, minlength=n) for s in (self.stream[self.train], self.stream))
        learned[AT_START], every[AT_START] = learned[AT_END], every[AT_END]
        return learned, every

    def take(self, rows: dict[int, bytes], buckets: int) -> None:
        self.number, self.learned, self.every = (np.zeros(len(self.hashes), np.int64) for _ in range(3))
        for bucket, own in self.by_hash(buckets):
            steps, self.learned[own], self.every[own] = _unpack(rows[COUNTS - bucket])
            self.number[own] = (bucket << 32) + np.cumsum(steps.astype(np.int64))

    def symbols(self, depth: int) -> list[np.ndarray]:
        """The symbol of each position, then its history from the last word back, the start before each document."""
        begin, out = np.cumsum(self.lengths) - self.lengths, [self.stream]
        for k in range(1, depth + 1):
            # The last but k, which is the one before of the last but k - 1; a document's first ones have the start instead.
            back = np.empty_like(self.stream)
            back[1:] = out[-1][:-1]
            back[begin] = AT_START
            out.append(back)
        return out

    def packs(self, depth: int, buckets: int, hot: int, only_hot: bool = False) -> Iterator[tuple[int, list[np.ndarray], np.ndarray, np.ndarray, np.ndarray]]:
        """By bucket: its positions' symbols, these positions, the first position of each distinct history, and the history of each position."""
        symbols = self.symbols(depth)
        last, before = symbols[1], symbols[2] if depth > 1 else symbols[0]
        parts = -(-self.every // hot)
        # Buckets by small numbers, in order of their names, as these make small arrays.
        names, where = np.arange(buckets), _small(self.hashes % np.uint64(buckets))[last]
        at = np.flatnonzero((parts > 1)[last])
        if len(at):
            by = self.hashes[np.where(last[at] == AT_START, symbols[0][at], before[at])]
            own = W.mix(self.hashes[last[at]] + W.mix(by) % parts[last[at]].astype(np.uint64)) >> np.uint64(2)
            more, own = np.unique(own.astype(np.int64) + buckets, return_inverse=True)
            names = np.append(names, more)
            where = where.astype(_small(np.array([len(names)])).dtype)
            where[at] = own + buckets
        if only_hot:
            order = at[np.argsort(where[at], kind="stable")]
        else:
            order = np.argsort(where, kind="stable")
        ends = np.flatnonzero(np.diff(where[order])) + 1 if len(order) else np.zeros(0, np.int64)
        for pick in np.split(order, ends) if len(order) else ():
            own = [s[pick] for s in symbols]
            first, kind = _types([*own[1:], own[0]], len(self.hashes))
            yield int(names[where[pick[0]]]), own, pick, first, kind


@W.tidy
def _words(batches: Iterator[pa.RecordBatch], buckets: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for name, data in zip(W.column(batch, "slice"), W.column(batch, "data")):
            own = _Slice(data)
            learned, every = own.words()
            for bucket, at in own.by_hash(buckets):
                out = _pack(own.hashes[at], _small(learned[at]), _small(every[at]))
                yield _rows("slice bucket data", np.array([name], np.int64), np.array([bucket], np.int64), pa.array([out], pa.binary()))


def _number(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Numbers and counts for each slice's words of a bucket, and the bucket's sums: tokens, words, largest count."""
    group = pa.Table.from_batches(batches)
    bucket, packs = group["bucket"][0].as_py(), [_unpack(x.as_py()) for x in group["data"]]
    hashes, inverse = np.unique(np.concatenate([p[0] for p in packs]), return_inverse=True)
    learned, every = (np.bincount(inverse, weights=np.concatenate([p[k] for p in packs])).astype(np.int64) for k in (1, 2))
    token = hashes != np.uint64(START)
    sums = [int(learned[token].sum()), int((learned[token] > 0).sum()), int(every.max())]
    ends = np.cumsum([len(p[0]) for p in packs])
    for name, own in zip(group["slice"].to_pylist(), np.split(inverse, ends[:-1])):
        data = _pack(_small(np.diff(own, prepend=0)), _small(learned[own]), _small(every[own]))
        yield _rows(
            "slice bucket data tokens words most", *(np.array([x], np.int64) for x in (name, COUNTS - bucket)), pa.array([data], pa.binary()),
            *(np.array([x], np.int64) for x in sums),
        )
        sums[:2] = 0, 0


def _known(one: pa.Table, sent: pa.Table, buckets: int) -> tuple[_Slice, np.ndarray, dict[int, bytes]]:
    """A slice with its words' counts, its number, and what else was sent to it, by bucket."""
    own, rows = _Slice(one["data"][0].as_py()), {k: x.as_py() for k, x in zip(sent["bucket"].to_pylist(), sent["data"])}
    own.take(rows, buckets)
    return own, one["slice"].to_numpy()[:1], {k: x for k, x in rows.items() if k >= 0}


def _histories(place: np.ndarray) -> np.ndarray:
    """Histories in the order in which they travel: of their last word, then of the words before it, then of the symbol."""
    return np.lexsort((place[0], *place[:0:-1]))


def _ranked(own: _Slice, symbols: list[np.ndarray], first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A pack's words, the most frequent first, equally frequent ones by number, and its distinct histories as places among them."""
    used, inverse = np.unique(np.concatenate([s[first] for s in symbols]), return_inverse=True)
    order = np.lexsort((own.number[used], -own.learned[used]))
    rank = np.empty(len(used), np.int64)
    rank[order] = np.arange(len(used))
    return used[order], rank[inverse].reshape(len(symbols), -1)


def _steps(x: np.ndarray) -> np.ndarray:
    """Differences of neighbours, backward ones wrapped around."""
    return np.diff(x, prepend=0).view(np.uint64)


def _deal(one: pa.Table, sent: pa.Table, depth: int, buckets: int, hot: int, only_hot: bool) -> Iterator[pa.RecordBatch]:
    own, name, _ = _known(one, sent, buckets)
    for bucket, symbols, pick, first, kind in own.packs(depth, buckets, hot, only_hot):
        used, place = _ranked(own, symbols, first)
        order = _histories(place)
        learned = np.bincount(kind, weights=own.train[pick], minlength=len(first)).astype(np.int64)
        data = _pack(_steps(own.number[used]), _steps(own.learned[used]), np.flatnonzero(used == AT_START), _small(learned[order]), *(_small(p[order]) for p in place))
        yield _rows("slice bucket data", name, np.array([bucket], np.int64), pa.array([data], pa.binary()))


class _Bucket:
    """The distinct histories of all slices' packs, in order of their last word: symbols, training counts, counts of the symbols.

    The packs are taken out of their list one by one, as they would lie beside what is made of them.
    """

    def __init__(self, packs: list[list[np.ndarray]], depth: int):
        self.starts = np.cumsum([0, *(len(p[3]) for p in packs)])
        shift = np.cumsum([0, *(len(p[0]) for p in packs)])
        self.number, at, words = _distinct(np.concatenate([np.cumsum(p[0]).view(np.int64) for p in packs]))
        self.count = np.concatenate([np.cumsum(p[1]).view(np.int64) for p in packs])[at]
        self.start = next((int(words[a + p[2][0]]) for a, p in zip(shift, packs) if len(p[2])), -1)
        size, n = len(self.number), int(self.starts[-1])
        # A history as one integer: its last word, the words before it and the symbol.
        whole = size ** (depth + 1) < 1 << 62
        key = np.zeros(n if whole else 0, np.int64)
        symbols = [np.empty(0 if whole else n, np.int32) for _ in range(depth + 1)]
        learned = np.empty(n, np.result_type(np.uint16, *(p[3] for p in packs)))
        while packs:
            p, k = packs.pop(), len(packs)
            own, to = words[shift[k] : shift[k + 1]], slice(self.starts[k], self.starts[k + 1])
            learned[to] = p[3]
            for j in (*range(1, depth + 1), 0):
                if whole:
                    key[to] *= size
                    key[to] += own[p[4 + j]]
                else:
                    symbols[j][to] = own[p[4 + j]]
        del p, own, words
        if whole:
            key, _, self.kind, self.learned = _distinct(key, learned)
            self.symbols = [(key // size**e % size).astype(np.int32) for e in (0, *range(depth, 0, -1))]
        else:
            first, kind = _types([*symbols[1:], symbols[0]], size)
            self.kind, self.symbols = kind.astype(np.int32), [x[first] for x in symbols]
            self.learned = np.bincount(kind, weights=learned, minlength=len(first)).astype(np.int64)

    def chunks(self, shared: tuple | None, root: np.ndarray) -> Iterator[tuple[int, int, tuple | None]]:
        """Ranges of histories that are scored together, and what is known of their one last word: whole subtrees, some at a time.

        A subtree that is longer is cut by the word before, once the pairs of its last word are counted.
        """
        last, n = self.symbols[1], len(self.symbols[1])
        ends, a = np.append(np.flatnonzero(last[1:] != last[:-1]) + 1, n), 0
        while a < n:
            b = int(ends[max(np.searchsorted(ends, a + CHUNK, "right") - 1, 0)])
            if a < b <= a + CHUNK:
                yield a, b, shared
                a = b
                continue
            b = int(ends[np.searchsorted(ends, a, "right")])
            known = self.pairs(a, b, root) if shared is None else shared
            back = self.symbols[2][a:b] if len(self.symbols) > 2 else np.arange(b - a)
            cuts = np.append(np.flatnonzero(back[1:] != back[:-1]) + 1, b - a) + a
            while a < b:
                to = int(cuts[max(np.searchsorted(cuts, a + CHUNK, "right") - 1, 0)])
                to = to if to > a else int(cuts[np.searchsorted(cuts, a, "right")])
                yield a, to, known
                a = to

    def pairs(self, a: int, b: int, root: np.ndarray) -> tuple[np.ndarray, float, float, float]:
        """Of the last word of a subtree: by symbol its count after that word, the word's occurrences, distinct next symbols and gain."""
        after = np.bincount(self.symbols[0][a:b], weights=self.learned[a:b], minlength=len(self.number))
        seen = np.flatnonzero(after)
        total = after.sum()
        return after, total, float(len(seen)), float((after[seen] * (np.log(after[seen] / total) - np.log(root[seen]))).sum())


def _hot_pairs(batches: Iterator[pa.RecordBatch], depth: int) -> Iterator[pa.RecordBatch]:
    """Pairs of a hot word's bucket: the last word, the symbol after it, their count there and the symbol's own."""
    group = pa.Table.from_batches(batches)
    own = _Bucket([_unpack(x.as_py()) for x in group["data"]], depth)
    words, inverse = np.unique(own.symbols[0], return_inverse=True)
    n = np.bincount(inverse, weights=own.learned).astype(np.int64)
    fill = lambda x: np.full(len(words), x, np.int64)
    yield _rows("bucket last word n c", fill(group["bucket"][0].as_py()), fill(own.number[own.symbols[1][0]]), own.number[words], n, own.count[words])


def _hot_packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Counts of all of a hot word's pairs that a bucket has, and the word's figures: occurrences, distinct next symbols, gain."""
    group = pa.Table.from_batches(batches)
    pairs, head = group.filter(pa.compute.is_valid(group["word"])), group.filter(pa.compute.is_null(group["word"]))
    data = _pack(np.array(head["figures"][0].as_py(), float), pairs["word"].to_numpy(), pairs["n"].to_numpy())
    yield _rows("slice bucket data", pa.array([None], pa.int64()), group["bucket"].to_numpy()[:1], pa.array([data], pa.binary()))


def _counts(keys: np.ndarray, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct keys among those of some weight, the sums of their weights, and for each key its index or -1."""
    among = weight > 0
    u, inverse = np.unique(keys[among], return_inverse=True)
    if not len(u):
        return u, u, np.full(len(keys), -1)
    c = np.bincount(inverse, weights=weight[among])
    i = np.minimum(np.searchsorted(u, keys), len(u) - 1)
    return u, c, np.where(u[i] == keys, i, -1)


def tree_probabilities(symbols: list[np.ndarray], learned: np.ndarray, root: np.ndarray, least: int, penalty: float, start: int = -1, shared: tuple | None = None) -> np.ndarray:
    """Probability of each position by the tree that the positions make.

    ``symbols``: the symbol of each position, then its history from the last one back, as small integers.
    ``learned``: how many training positions each stands for; positions may be given one by one or as distinct ones.
    ``root``: each symbol's probability without a context. ``start``: the number of the start symbol, before which is nothing.
    ``shared``: where all have one last word, of which other buckets have a part: by symbol its count after that word, then
    the word's occurrences, distinct next symbols and gain.
    """
    word, size = symbols[0].astype(np.int64), 1 + max(int(s.max(initial=0)) for s in symbols)
    p, n, weight = root[word].astype(float), len(word), learned.astype(np.int64)
    context, state = np.zeros(n, np.int64), np.ones(n, bool)
    for level, back in enumerate(symbols[1:]):
        if level == 0 and shared is not None:
            after, total, kinds, gain = shared
            if total < least or gain <= penalty * kinds:
                break
            p = np.maximum(after[word] - DISCOUNT, 0) / total + DISCOUNT * kinds / total * p
            continue
        if level:
            state = state & (symbols[level] != start)
        _, cc, ci = _counts(context * size + back, weight * state)
        ok = state & (ci >= 0) & (cc[np.maximum(ci, 0)] >= least) if len(cc) else np.zeros(n, bool)
        if not ok.any():
            break
        ci = np.where(ok, ci, 0)
        total = np.where(ok, cc[ci], 1)
        pu, pc, pi = _counts(ci * size + word, weight * ok)
        count = np.where(ok & (pi >= 0), pc[np.maximum(pi, 0)], 0)
        kinds = np.bincount(pu // size, minlength=len(cc))[ci]
        del pi, pu, pc
        # Gain over the suffix: training positions all have a probability there.
        known = ok & (weight > 0)
        gain = np.bincount(ci[known], weights=weight[known] * (np.log(count[known] / total[known]) - np.log(p[known])), minlength=len(cc))
        ok &= gain[ci] > penalty * kinds
        p = np.where(ok, np.maximum(count - DISCOUNT, 0) / total + DISCOUNT * kinds / total * p, p)
        context, state = np.where(ok, ci, 0), ok
    return p


def _score(batches: Iterator[pa.RecordBatch], depth: int, least: int, penalty: float, norm: float) -> Iterator[pa.RecordBatch]:
    """For each pack the log10 probabilities of its histories."""
    group = pa.Table.from_batches(batches)
    bucket, names = group["bucket"][0].as_py(), group["slice"].to_pylist()
    data = [_unpack(x.as_py()) for x in group["data"]]
    del group
    shared = next((d for d, s in zip(data, names) if s is None), None)
    data, names = [d for d, s in zip(data, names) if s is not None], [s for s in names if s is not None]
    own = _Bucket(data, depth)
    root = (own.count + 1.0) / norm
    if shared is not None:
        (total, kinds, gain), words, n = shared
        after = np.zeros(len(own.number))
        after[np.searchsorted(own.number, words)] = n
        shared = after, total, kinds, gain
    p = np.ones(len(own.learned))
    for a, b, known in own.chunks(shared, root):
        p[a:b] = tree_probabilities([s[a:b] for s in own.symbols], own.learned[a:b], root, least, penalty, own.start, known)
    logs = np.log10(p).astype(np.float32)
    for k, name in enumerate(names):
        out = _pack(logs[own.kind[own.starts[k] : own.starts[k + 1]]])
        yield _rows("slice bucket data", np.array([name], np.int64), np.array([bucket], np.int64), pa.array([out], pa.binary()))


def _sum(one: pa.Table, sent: pa.Table, depth: int, buckets: int, hot: int, norm: float, tokens: int) -> Iterator[pa.RecordBatch]:
    """The documents of a slice, from what the buckets sent back."""
    own, _, found = _known(one, sent, buckets)
    score, base, n = np.zeros(len(own.lengths)), np.log10((own.learned + 1.0) / norm), len(own.lengths)
    for bucket, symbols, pick, first, kind in own.packs(depth, buckets, hot):
        logs = np.zeros(len(first))
        logs[_histories(_ranked(own, symbols, first)[1])] = _unpack(found.pop(bucket))[0]
        score += np.bincount(own.doc[pick], weights=logs[kind], minlength=n)
    begin = np.cumsum(own.lengths) - own.lengths
    sums = lambda x: np.add.reduceat(x[own.stream], begin)
    columns = pa.array(own.ids, mask=own.no_id != 0), own.held != 0, own.lengths, sums((own.learned > 0).astype(np.int64)), np.full(n, tokens, np.int64), sums(base), score
    yield _rows(" ".join(OUT.names), *columns)


def _hot_shares(dealt: DataFrame, depth: int, norm: float) -> DataFrame:
    """What the buckets of hot words have to know of each other's pairs, a row a bucket."""
    pairs = written(dealt.groupBy("bucket").applyInArrow(W.grouped(_hot_pairs, depth=depth), "bucket long, last long, word long, n long, c long"), "pairs")
    all_of = written(pairs.groupBy("last", "word").agg(F.sum("n").alias("n"), F.max("c").alias("c")), "pair_counts")
    seen = all_of.where("n > 0")
    per = seen.groupBy("last").agg(
        F.sum("n").cast("double").alias("total"), F.count(F.lit(1)).cast("double").alias("kinds"),
        F.sum(F.col("n") * (F.ln("n") - F.ln((F.col("c") + 1.0) / F.lit(norm)))).alias("cross"),
    )
    figures = per.select("last", F.array("total", "kinds", F.col("cross") - F.col("total") * F.ln("total")).alias("figures"))
    heads = pairs.select("bucket", "last").distinct().join(figures, "last", "left")
    none = F.array(*[F.lit(0.0)] * 3)
    heads = heads.select("bucket", F.lit(None).cast("long").alias("word"), F.lit(0).cast("long").alias("n"), F.coalesce("figures", none).alias("figures"))
    rows = pairs.select("bucket", "last", "word").join(all_of.select("last", "word", "n"), ["last", "word"]).select(
        "bucket", "word", "n", F.lit(None).cast("array<double>").alias("figures"),
    )
    return rows.unionByName(heads).groupBy("bucket").applyInArrow(W.grouped(_hot_packed), "slice long, bucket long, data binary")


def lm_scores(docs: DataFrame, *, depth: int = 2, least: int = 8, penalty: float = 1.5, buckets: int | None = None, hot: int = 4_000_000) -> DataFrame:
    """Per document: ``doc_id``, ``held_out``, ``n_tokens``, ``n_known``, ``train_tokens``, ``base_score``, ``score``.

    ``base_score`` is the add-one unigram score, ``score`` that of the tree; both are log10
    probabilities of the whole text with its end symbol. Documents of the held-out fold are scored but
    not learned from. Histories travel back as single-precision logarithms and are summed in double precision.
    """
    spark = docs.sparkSession
    ship(spark)
    form, out = "slice long, bucket long, data binary", "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    if buckets is None:
        size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
        buckets = max(1, -(-size // BUCKET))
    rows = docs.select("doc_id", "text").withColumn("uid", F.monotonically_increasing_id())
    slices = bucketed(rows.mapInArrow(_slices, form), "slices", "slice", parts)
    seen = slices.mapInArrow(partial(_words, buckets=buckets), form)
    counts = bucketed(seen.groupBy("bucket").applyInArrow(W.grouped(_number), f"{form}, tokens long, words long, most long"), "counts", "slice", parts)
    total = counts.agg(F.sum("tokens").alias("n"), F.sum("words").alias("v"), F.max("most").alias("most")).first()
    tokens = total["n"] or 0
    norm = float(tokens + (total["v"] or 0) + 1)
    counts = counts.select("slice", "bucket", "data")
    of = slices.groupBy("slice")

    def deal(only_hot: bool) -> DataFrame:
        return of.cogroup(counts.groupBy("slice")).applyInArrow(W.paired(_deal, FORM, depth=depth, buckets=buckets, hot=hot, only_hot=only_hot), form)

    dealt = deal(False)
    if (total["most"] or 0) > hot:
        dealt = dealt.unionByName(written(_hot_shares(deal(True), depth, norm), "shares"))
    scored = dealt.groupBy("bucket").applyInArrow(W.grouped(_score, depth=depth, least=least, penalty=penalty, norm=norm), form)
    back = counts.unionByName(scored).groupBy("slice")
    return of.cogroup(back).applyInArrow(W.paired(_sum, OUT, depth=depth, buckets=buckets, hot=hot, norm=norm, tokens=tokens), out)
