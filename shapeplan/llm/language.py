"""Language identification by unigrams over pieces, marginalised over all segmentations.

Every language has a probability for each piece of a fixed public vocabulary. The probability of a
word is the sum, over all ways to cut it into pieces, of the product of their probabilities: a forward
pass over its characters, whatever its length. Short words of equal length go through it together, in products that
cannot leave the range of a double; long ones go alone, in logarithms. A text's languages are compared by the product over its words.

Learning: two passes of expectation maximisation over the whole texts of labelled rows, of which a
parameter bounds the number a label. Both count on the
executors and return at most one row a language and piece, a table bounded by the vocabulary; the
first starts from equal probabilities for pieces of equal length. Words repeat, so each worker cuts
each distinct word of a batch once.

Rows: a null text, or one without a letter, is ``und`` with score 0. Ties go to the label that sorts
first. If nothing is labelled all is ``und``. Rows repeating an id are judged one by one. Very long texts and words count whole. An
empty table gives an empty result. Other columns are ignored.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter
from collections.abc import Iterator
from functools import partial
from itertools import islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from shapeplan.llm import words as W
from shapeplan.runtime import ship

#: Labels that one model may have, so that the table of a model is bounded by labels times pieces.
MOST_LABELS = 512

LETTER = re.compile(r"[^\W\d_]")
SPACE = "▁"
_models: dict = {}


def vocabulary(model: str) -> list[str]:
    """The pieces of a public sentence-piece vocabulary, by id; control and byte pieces are blank."""
    if model not in _models:
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=model)
        _models[model] = ["" if sp.IsControl(i) or sp.IsUnknown(i) or sp.IsByte(i) else sp.IdToPiece(i) for i in range(sp.GetPieceSize())]
    return _models[model]


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


#: Factor a character that keeps the products of a short word within the range of a double, and the characters of one.
LIFT, SHORT = 5.0, 64

_BASE = np.uint64(0x100000001B3 * 2 + 0x5BD1E995)


def _prefix_hashes(codes: np.ndarray) -> np.ndarray:
    """Polynomial hashes of all prefixes of equally long words (rows of code points)."""
    out = np.zeros((codes.shape[1] + 1, len(codes)), np.uint64)
    for j in range(codes.shape[1]):
        out[j + 1] = out[j] * _BASE + codes[:, j]
    return out


def _codes(words: list[str], n: int) -> np.ndarray:
    return np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), np.uint32).reshape(-1, n).astype(np.uint64) + np.uint64(1)


class Lattice:
    """All segmentations of words under one probability vector a piece; works on equally long words at once."""

    def __init__(self, pieces: list[str], logp: np.ndarray):
        """``logp``: pieces by languages; the last row is for a character that is no piece."""
        named = [(p, i) for i, p in enumerate(pieces) if p]
        self.longest = max((len(p) for p, _ in named), default=1)
        hashes = np.zeros(len(named), np.uint64)
        at = {n: [k for k, (p, _) in enumerate(named) if len(p) == n] for n in {len(p) for p, _ in named}}
        for n, ks in at.items():
            hashes[ks] = _prefix_hashes(_codes([named[k][0] for k in ks], n))[n] ^ np.uint64(n)
        order = np.argsort(hashes)
        self.hashes, self.ids = hashes[order], np.array([i for _, i in named], np.int64)[order]
        self.other, self.none = len(pieces), len(pieces) + 1
        length = np.array([len(p) for p in pieces] + [1])
        self.p = np.vstack([np.exp(logp.astype(float) + LIFT * length[:, None]), np.zeros((1, logp.shape[1]))])
        self.logp = np.vstack([logp.astype(float), np.full((1, logp.shape[1]), -np.inf)])

    def arcs(self, words: list[str], n: int) -> dict[tuple[int, int], np.ndarray]:
        """For each (start, end) the piece of each word there, or the row of zeros; lone unknown characters count as one."""
        h = _prefix_hashes(_codes(words, n))
        power = [np.uint64(1)]
        for _ in range(n):
            with np.errstate(over="ignore"):
                power.append(power[-1] * _BASE)
        out = {}
        for j in range(1, n + 1):
            for i in range(max(0, j - self.longest), j):
                sub = (h[j] - h[i] * power[j - i]) ^ np.uint64(j - i)
                k = np.minimum(np.searchsorted(self.hashes, sub), len(self.hashes) - 1)
                ids = np.where(self.hashes[k] == sub, self.ids[k], self.other if j == i + 1 else self.none)
                if j == i + 1 or (ids != self.none).any():
                    out[i, j] = ids
        return out

    def forward(self, arcs, n: int, size: int) -> np.ndarray:
        alpha = np.zeros((n + 1, size, self.p.shape[1]))
        alpha[0] = 1.0
        for (i, j), ids in sorted(arcs.items(), key=lambda x: x[0][1]):
            alpha[j] += alpha[i] * self.p[ids]
        return alpha

    def log_probability(self, words: list[str]) -> np.ndarray:
        """Words by languages, for words of any lengths."""
        out = np.zeros((len(words), self.p.shape[1]))
        for n, at, part in _by_length(words):
            out[at] = np.log(self.forward(self.arcs(part, n), n, len(part))[n]) - LIFT * n
        for at in _long(words):
            out[at] = self.sweep(self.ends(words[at]))[-1]
        return out

    def ends(self, word: str) -> np.ndarray:
        """Of one word the piece that ends before each place (rows from the second on) with each length (columns), or the row of zeros."""
        n, size = len(word), min(self.longest, len(word))
        codes = _codes([word], n)[0]
        out = np.full((n + 1, size + 1), self.none, np.int64)
        h = np.zeros(n, np.uint64)  # of the last d characters before each place
        power = np.uint64(1)
        for d in range(1, size + 1):
            with np.errstate(over="ignore"):
                h[d - 1 :] = h[d - 1 :] + codes[: n - d + 1] * power
                power = power * _BASE
            sub = h[d - 1 :] ^ np.uint64(d)
            k = np.minimum(np.searchsorted(self.hashes, sub), len(self.hashes) - 1)
            out[d:, d] = np.where(self.hashes[k] == sub, self.ids[k], self.other if d == 1 else self.none)
        return out

    def sweep(self, ends: np.ndarray) -> np.ndarray:
        """Log of the sum over all segmentations of each prefix, by languages."""
        n, size = ends.shape[0] - 1, ends.shape[1] - 1
        out = np.full((n + 1, self.p.shape[1]), -np.inf)
        out[0] = 0.0
        for j in range(1, n + 1):
            d = min(j, size)
            parts = out[j - d : j][::-1] + self.logp[ends[j, 1 : d + 1]]
            top = parts.max(axis=0)
            out[j] = top + np.log(np.exp(parts - top).sum(axis=0))
        return out

    def sweep_back(self, ends: np.ndarray) -> np.ndarray:
        """The same for each suffix."""
        n, size = ends.shape[0] - 1, ends.shape[1] - 1
        out = np.full((n + 1, self.p.shape[1]), -np.inf)
        out[n] = 0.0
        for i in range(n - 1, -1, -1):
            d = np.arange(1, min(n - i, size) + 1)
            parts = out[i + d] + self.logp[ends[i + d, d]]
            top = parts.max(axis=0)
            out[i] = top + np.log(np.exp(parts - top).sum(axis=0))
        return out

    def expected(self, words: list[str], weights: np.ndarray) -> np.ndarray:
        """How often each piece is expected in the words, of which language k has ``weights[:, k]``."""
        counts = np.zeros((len(self.p), self.p.shape[1]))
        for n, at, part in _by_length(words):
            arcs = self.arcs(part, n)
            alpha = self.forward(arcs, n, len(part))
            beta = np.zeros_like(alpha)
            beta[n] = 1.0
            for (i, j), ids in sorted(arcs.items(), key=lambda x: -x[0][0]):
                beta[i] += self.p[ids] * beta[j]
            share = weights[at] / alpha[n]
            for (i, j), ids in arcs.items():
                now = alpha[i] * self.p[ids] * beta[j] * share
                for k in range(counts.shape[1]):
                    counts[:, k] += np.bincount(ids, weights=now[:, k], minlength=len(counts))
        for at in _long(words):
            ends = self.ends(words[at])
            front, back = self.sweep(ends), self.sweep_back(ends)
            for d in range(1, ends.shape[1]):
                ids = ends[d:, d]
                now = np.exp(front[: len(front) - d] + self.logp[ids] + back[d:] - front[-1]) * weights[at]
                for k in range(counts.shape[1]):
                    counts[:, k] += np.bincount(ids, weights=now[:, k], minlength=len(counts))
        return counts[: self.none]


#: Words that go through a lattice together.
TOGETHER = 2048


def _by_length(words: list[str]) -> Iterator[tuple[int, np.ndarray, list[str]]]:
    """Short words by length: the length, their places and the words."""
    by: dict[int, list[int]] = {}
    for at, word in enumerate(words):
        if len(word) <= SHORT:
            by.setdefault(len(word), []).append(at)
    for n, at in by.items():
        for i in range(0, len(at), TOGETHER):
            own = at[i : i + TOGETHER]
            yield n, np.array(own), [words[k] for k in own]


def _long(words: list[str]) -> list[int]:
    return [at for at, word in enumerate(words) if len(word) > SHORT]


def tokens(text: str) -> list[str]:
    return [SPACE + w for w in text.lower().split()]


@W.tidy
def _learn(batches: Iterator[pa.RecordBatch], model: str, labels: list[str], logp: np.ndarray) -> Iterator[pa.RecordBatch]:
    pieces, place = vocabulary(model), {x: i for i, x in enumerate(labels)}
    lattice, counts = Lattice(pieces, logp), np.zeros((len(pieces) + 1, len(labels)))
    for batch in W.slices(batches, "text", 8 << 20):
        seen: dict[str, Counter] = {}
        for text, lang in zip(W.column(batch, "text"), W.column(batch, "lang")):
            seen.setdefault(lang, Counter()).update(tokens(text or ""))
        by_word: dict[str, int] = {}
        for words in seen.values():
            for word in words:
                by_word.setdefault(word, len(by_word))
        weights = np.zeros((len(by_word), len(labels)))
        for lang, words in seen.items():
            weights[[by_word[w] for w in words], place[lang]] = list(words.values())
        counts += lattice.expected(list(by_word), weights)
    at, lang = np.nonzero(counts)
    yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(lang.astype(np.int32)), pa.array(counts[at, lang])], names=["piece", "lang_at", "n"])


def fit(labelled: DataFrame, *, model: str | None = None, rounds: int = 2, smoothing: float = 0.05, sample: int | None = 2000) -> tuple[list[str], np.ndarray]:
    """Labels and the log probabilities (pieces and one more by labels) learned from columns ``doc_id``, ``text``, ``lang``.

    ``sample`` bounds the rows of a label that are learned from: rows are drawn by a hash of the id, in
    the share that makes that many expected. None learns from all.
    """
    ship(labelled.sparkSession)
    model = model or default_vocabulary()
    labelled = labelled.where("lang is not null and text is not null").select("doc_id", "text", "lang")
    sizes = dict(labelled.groupBy("lang").count().limit(MOST_LABELS + 1).collect())
    labels = sorted(sizes)
    if len(labels) > MOST_LABELS:
        raise ValueError(f"more than {MOST_LABELS} labels")
    if sample is not None and labels:
        share = F.create_map(*[F.lit(x) for k in labels for x in (k, min(1.0, sample / sizes[k]))])
        labelled = labelled.where(F.pmod(F.xxhash64("doc_id", F.lit(7)), F.lit(1 << 30)) < share[F.col("lang")] * (1 << 30))
    labelled = labelled.select("text", "lang")
    pieces = vocabulary(model)
    start = np.array([-3.0 - 1.5 * len(p) for p in pieces] + [-14.0])
    logp = np.repeat(start[:, None], max(len(labels), 1), axis=1)
    for _ in range(rounds if labels else 0):
        counted = labelled.mapInArrow(
            partial(_learn, model=model, labels=labels, logp=logp.astype(np.float32)), "piece int, lang_at int, n double",
        ).groupBy("piece", "lang_at").agg(F.sum("n").alias("n")).toArrow()
        counts = np.full((len(pieces) + 1, len(labels)), smoothing)
        np.add.at(counts, (counted["piece"].to_numpy(), counted["lang_at"].to_numpy()), counted["n"].to_numpy())
        logp = np.log(counts / counts.sum(axis=0))
    return labels, logp


class _Numbers(dict):
    """A number for each word, in order of first sight."""

    def __missing__(self, word: str) -> int:
        i = self[word] = len(self)
        return i


@W.tidy
def _predict(batches: Iterator[pa.RecordBatch], model: str, labels: list[str], logp: np.ndarray, whole: bool = False, most: int = 300_000) -> Iterator[pa.RecordBatch]:
    lattice = Lattice(vocabulary(model), logp)
    numbers, known = _Numbers(), np.zeros((0, len(labels)))
    for batch in W.slices(batches, "text", 8 << 20):
        if len(numbers) > most:
            numbers, known = _Numbers(), known[:0]
        ids = []
        for text in W.column(batch, "text"):
            words = tokens(text) if text and labels and LETTER.search(text) else []
            ids.append(np.fromiter(map(numbers.__getitem__, words), np.int64, len(words)))
        if len(numbers) > len(known):
            known = np.vstack([known, lattice.log_probability(list(islice(numbers, len(known), None)))])
        best, sure = [], []
        for own in ids:
            if not len(own):
                best.append("und")
                sure.append(0.0)
                continue
            total = known[own].sum(axis=0)
            p = np.exp(total - total.max())
            p /= p.sum()
            k = int(np.argmax(p))
            best.append(labels[k])
            sure.append(float(p[k]))
        keep = [i for i, name in enumerate(batch.schema.names) if whole or name != "text"]
        yield pa.RecordBatch.from_arrays(
            [*(batch.column(i) for i in keep), pa.array(best, pa.string()), pa.array(sure, pa.float64())],
            names=[*(batch.schema.names[i] for i in keep), "lang_pred", "score"],
        )


def predict(docs: DataFrame, labels: list[str], logp: np.ndarray, *, model: str | None = None, whole: bool = False) -> DataFrame:
    """``doc_id`` with ``lang_pred`` and ``score`` (the posterior of that label under equal priors); ``whole`` keeps all columns."""
    ship(docs.sparkSession)
    rows = docs if whole else docs.select("doc_id", "text")
    schema = T.StructType([*(f for f in rows.schema.fields if whole or f.name != "text"), T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())])
    return rows.mapInArrow(partial(_predict, model=model or default_vocabulary(), labels=labels, logp=logp.astype(np.float32), whole=whole), schema)


def fold(doc_id) -> object:
    """crc32 of the id as text, modulo 4, as a column."""
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(4))


def identify(docs: DataFrame, **how) -> DataFrame:
    """Per document ``doc_id``, ``held_out``, ``lang_pred``, ``score``; documents of fold 2 are not learned from."""
    labels, logp = fit(docs.where(fold(F.col("doc_id")) != 2), **how)
    out = predict(docs, labels, logp)
    return out.select("doc_id", (fold(F.col("doc_id")) == 2).alias("held_out"), "lang_pred", "score")
