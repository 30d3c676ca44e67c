"""Removing long passages that an earlier document has, with FM-indexes over shards of segments.

A window is ``window`` words in a row. Windows with equal words must meet in one shard, whatever else their
documents hold. So a document is cut into segments, runs of windows with the same least k-gram
hash, and segments go where that hash says. Only hashes that occur in two documents matter, and of
equal segments only one copy is indexed, with the least id of its holders: what all others hold of it
is removed as it stands. A shard concatenates its segments into an FM-index; every segment is
streamed through it backwards, and each window reports the interval of its occurrences and so the least id
that has them. The number of shards follows the indexed words. A hash with very many different
segments is split further by the first and last k-grams of its windows.

Texts are shuffled twice, to fetch the words of indexed segments and to apply what is removed;
all else is hashes and spans.

Rows: a null or short text loses nothing. Windows are judged on the input. A null id neither removes
nor loses. Rows repeating an id count as that id; none removes from another. Very long texts count whole, in segments of at most
``RUN`` windows. Other columns are ignored, or carried along where they are named. An empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shapeplan.llm import words as W
from shapeplan.llm.fm_index import FMIndex
from shapeplan.runtime import ship, written

GRAM = 8

#: Words that a shard indexes, as expected.
SHARD_WORDS = 1 << 19

#: Different segments of one least hash beyond which its windows are dealt out one by one.
HOT = 8192

#: Windows of a segment, at most.
RUN = 64

def least_grams(h: np.ndarray, window: int) -> np.ndarray:
    """For each window the least of its k-gram hashes."""
    if len(h) < window:
        return np.zeros(0, np.uint64)
    now, reach, span = W.ngram_hashes(h, GRAM), 1, window - GRAM + 1
    while reach < span:
        step = min(reach, span - reach)
        now = np.minimum(now[: len(now) - step], now[step:])
        reach += step
    return now


def segments(h: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, number of windows and least hash of each segment of a document."""
    low = least_grams(h, window)
    if not len(low):
        return (np.zeros(0, np.int64),) * 2 + (low,)
    new = np.concatenate([[True], low[1:] != low[:-1]])
    start = np.flatnonzero(new)
    place = np.arange(len(low)) - start[np.cumsum(new) - 1]
    start = np.flatnonzero(place % RUN == 0)
    return start, np.diff(np.concatenate([start, [len(low)]])), low[start]


@W.tidy
def _segments(batches: Iterator[pa.RecordBatch], window: int) -> Iterator[pa.RecordBatch]:
    for batch in W.slices(batches, "text"):
        ids, starts, runs, lows, names = [], [], [], [], []
        for doc, text in zip(W.column(batch, "doc_id"), W.texts(batch, "text")):
            h = W.hashes.of(W.split(text))
            start, run, low = segments(h, window)
            ids.extend([doc] * len(start))
            starts.append(start)
            runs.append(run)
            lows.append(low)
            raw = memoryview(h.tobytes())
            names.extend(hashlib.blake2b(raw[8 * a : 8 * (a + n + window - 1)], digest_size=16).digest() for a, n in zip(start.tolist(), run.tolist()))
        cat = lambda x, kind: np.concatenate([np.zeros(0, kind), *x]).astype(kind)
        yield pa.RecordBatch.from_arrays(
            [pa.array(ids, pa.int64()), pa.array(cat(starts, np.int32)), pa.array(cat(runs, np.int32)), pa.array(W.signed(cat(lows, np.uint64))), pa.array(names, pa.binary())],
            names=["doc_id", "start", "windows", "low", "segment"],
        )


@W.tidy
def _fetch(batches: Iterator[pa.RecordBatch], window: int, shards: int) -> Iterator[pa.RecordBatch]:
    """The words of wanted segments, dealt out to shards."""
    for batch in W.slices(batches, "text"):
        rows = []
        for doc, text, wanted in zip(W.column(batch, "doc_id"), W.texts(batch, "text"), W.column(batch, "wanted")):
            h = W.hashes.of(W.split(text))
            for w in wanted:
                own = h[w["start"] : w["start"] + w["windows"] + window - 1]
                if hashlib.blake2b(own.tobytes(), digest_size=16).digest() != w["segment"]:
                    continue  # another row with this id
                if not w["hot"]:
                    rows.append((w["low"] % shards, w["segment"], 0, doc, own.tobytes()))
                    continue
                grams = W.ngram_hashes(own, GRAM)
                with np.errstate(over="ignore"):
                    to = W.mix(grams[: w["windows"]] * np.uint64(3) + grams[window - GRAM :][: w["windows"]]) % np.uint64(shards)
                rows.extend((int(to[k]), w["segment"], k, doc, own[k : k + window].tobytes()) for k in range(w["windows"]))
        cols = list(zip(*rows)) or [()] * 5
        yield pa.RecordBatch.from_arrays(
            [pa.array(c, t) for c, t in zip(cols, (pa.int32(), pa.binary(), pa.int32(), pa.int64(), pa.binary()))],
            names=["shard", "segment", "at", "doc_id", "data"],
        )


def first_holders(streams: list[np.ndarray], ids: np.ndarray, window: int) -> list[np.ndarray]:
    """For each window of each stream the least id of the streams that have it, from an FM-index over all of them."""
    used, inverse = np.unique(np.concatenate(streams), return_inverse=True)
    ends = np.cumsum([0, *map(len, streams)])
    local = [inverse[a:b] + 1 for a, b in zip(ends[:-1], ends[1:])]
    index = FMIndex(local, window, ids)
    return [index.least[g[: len(g) - window + 1]] for g in index.matched_groups(local)]


def _search(group: pa.Table, window: int) -> pa.Table:
    out = _found(group, window)
    W.release()
    return out


def _found(group: pa.Table, window: int) -> pa.Table:
    ids = group.column("doc_id").to_numpy()
    first = first_holders([np.frombuffer(x, np.uint64) for x in group.column("data").to_pylist()], ids, window)
    seg, at, lo, hi = group.column("segment").to_pylist(), group.column("at").to_pylist(), [], []
    names = []
    for k, own in enumerate(first):
        edges = np.flatnonzero(np.diff(np.concatenate([[0], (own < ids[k]).astype(np.int8), [0]])))
        for a, b in zip(edges[::2].tolist(), edges[1::2].tolist()):
            names.append(seg[k])
            lo.append(at[k] + a)
            hi.append(at[k] + b + window - 1)
    return pa.table([pa.array(names, pa.binary()), pa.array(lo, pa.int32()), pa.array(hi, pa.int32())], names=["segment", "lo", "hi"])


def repeated_spans(docs: DataFrame, *, window: int = 50, hot: int = HOT) -> DataFrame:
    """Spans of words (``doc_id``, ``lo``, ``hi``) that documents with a smaller id have; spans may overlap."""
    ship(docs.sparkSession)
    docs = docs.select("doc_id", "text").where("doc_id is not null")
    segs = written(docs.mapInArrow(partial(_segments, window=window), "doc_id long, start int, windows int, low long, segment binary"), "segments")
    both = segs.groupBy("low").agg(F.min("doc_id").alias("a"), F.max("doc_id").alias("b")).where("a < b").select("low")
    shared = written(segs.join(both, "low"), "shared")
    least = written(
        shared.groupBy("segment").agg(F.min("doc_id").alias("first"), F.min_by(F.struct("start", "windows", "low"), F.struct("doc_id", "start")).alias("w")).select("segment", "first", "w.*"),
        "firsts",
    )
    copies = shared.join(least.select("segment", "first"), "segment").where("doc_id > first").select(
        "doc_id", F.col("start").alias("lo"), (F.col("start") + F.col("windows") + (window - 1)).alias("hi"),
    )
    # A hash with one segment alone has nothing left to find.
    several = least.groupBy("low").agg(F.count(F.lit(1)).alias("k")).where("k > 1").select("low", (F.col("k") > hot).alias("hot"))
    indexed = written(least.join(several, "low"), "indexed")
    words = indexed.agg(F.sum(F.when(F.col("hot"), F.col("windows") * window).otherwise(F.col("windows") + window - 1)).alias("n")).first()["n"] or 0
    shards = max(1, -(-words // SHARD_WORDS))
    wanted = indexed.groupBy(F.col("first").alias("doc_id")).agg(F.collect_list(F.struct("segment", "start", "windows", "low", "hot")).alias("wanted"))
    fetched = docs.join(wanted, "doc_id").mapInArrow(
        partial(_fetch, window=window, shards=shards), "shard int, segment binary, at int, doc_id long, data binary",
    ).dropDuplicates(["segment", "at"])
    found = fetched.groupBy("shard").applyInArrow(lambda group: _search(group, window), "segment binary, lo int, hi int")
    own = shared.join(least.select("segment", F.col("first").alias("doc_id")), ["segment", "doc_id"]).select("segment", "doc_id", "start")
    parts = found.join(own, "segment").select("doc_id", (F.col("start") + F.col("lo")).alias("lo"), (F.col("start") + F.col("hi")).alias("hi"))
    return copies.unionByName(parts)


@W.tidy
def _apply(batches: Iterator[pa.RecordBatch], text: bool) -> Iterator[pa.RecordBatch]:
    for batch in W.slices(batches, "text"):
        n, gone, kept = [], [], []
        for raw, spans in zip(W.texts(batch, "text"), W.column(batch, "spans")):
            words = W.split(raw)
            keep = np.ones(len(words), bool)
            for s in spans or ():
                keep[s["lo"] : s["hi"]] = False
            left = int(keep.sum())
            n.append(len(words))
            gone.append(len(words) - left)
            if text:
                kept.append(raw if left == len(words) else b" ".join(w for w, k in zip(words, keep) if k))
            else:
                kept.append(hashlib.sha256(b" ".join(words if left == len(words) else [w for w, k in zip(words, keep) if k])).hexdigest())
        rest = [i for i, name in enumerate(batch.schema.names) if name not in ("text", "spans")]
        out = pa.array(kept, pa.binary()).cast(pa.string()) if text else pa.array(kept, pa.string())
        yield pa.RecordBatch.from_arrays(
            [*(batch.column(i) for i in rest), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), out],
            names=[*(batch.schema.names[i] for i in rest), "n_words", "n_removed", "kept"],
        )


def deduplicated(docs: DataFrame, *, window: int = 50, keep: tuple[str, ...] = (), text: bool = False, hot: int = HOT) -> DataFrame:
    """Per document ``n_words``, ``n_removed`` and ``kept``: the sha256 of what is left, or with ``text`` that itself.

    Kept words are joined by one space; with ``text``, a text that loses nothing stays as it was.
    ``keep`` names further columns to carry along.
    """
    spans = repeated_spans(docs, window=window, hot=hot).groupBy("doc_id").agg(F.collect_set(F.struct("lo", "hi")).alias("spans")).withColumnRenamed("doc_id", "span_of")
    rows = docs.select("doc_id", *keep, "text")
    at = rows.join(spans, rows["doc_id"] == spans["span_of"], "left").select("doc_id", *keep, "text", "spans")
    kinds = dict(docs.dtypes)
    schema = ", ".join(f"`{c}` {kinds[c]}" for c in ("doc_id", *keep)) + ", n_words long, n_removed long, kept string"
    return at.mapInArrow(partial(_apply, text=text), schema)
