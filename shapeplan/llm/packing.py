"""Packing documents into training sequences by minimum bin slack.

A document's ids are cut at every full window; whole windows are sequences of their own. Of the
remainders each sequence takes the longest one left and then the multiset of remaining lengths that
comes closest to the capacity: a subset-sum dynamic programme over bit sets, one shift and one "or"
for each power of two of a length's count, stopped as soon as the capacity is reached, with the counts
found by going back through the steps. A multiset that can be repeated is repeated at once.

Remainders are dealt out by a hash to groups of bounded size, so no task holds more than its group;
each group leaves at most a few sequences that aren't full. Only lengths and checksums are shuffled.

Rows: a null text counts as empty (the end id alone). Rows repeating an id, whole rows too, are packed one by one, and dealt out by
row, not by id. Very long texts are cut at full windows. Pieces of equal length are interchangeable; they go in order of id.
Other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import zlib
from collections import defaultdict
from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shapeplan.llm import words as W
from shapeplan.llm.tokens import Encoder
from shapeplan.runtime import ship, written

#: Remainders that a group holds, as expected.
GROUP = 4096


def fill(counts: dict[int, int], room: int) -> dict[int, int]:
    """The multiset of lengths (at most ``counts`` of each) whose sum comes closest to ``room`` without passing it."""
    mask, reach, steps = (1 << (room + 1)) - 1, 1, []
    for length in sorted((x for x in counts if x <= room), reverse=True):
        left, k = min(counts[length], room // length), 1
        while left > 0:
            k = min(k, left)
            steps.append((length, k, reach))
            reach |= (reach << (k * length)) & mask
            left -= k
            k *= 2
        if reach >> room & 1:
            break
    at, out = reach.bit_length() - 1, defaultdict(int)
    for length, k, before in reversed(steps):
        if not before >> at & 1:
            out[length] += k
            at -= k * length
    return dict(out)


def pack(lengths: list[int], capacity: int) -> list[list[int]]:
    """Sequences as lists of positions in ``lengths``; every position is in one of them."""
    stock: dict[int, list[int]] = defaultdict(list)
    for i in range(len(lengths) - 1, -1, -1):
        stock[lengths[i]].append(i)
    out = []
    while stock:
        seed = max(stock)
        counts = {n: len(v) for n, v in stock.items()}
        counts[seed] -= 1
        use = fill({n: c for n, c in counts.items() if c}, capacity - seed)
        use[seed] = use.get(seed, 0) + 1
        for _ in range(min(len(stock[n]) // k for n, k in use.items())):
            out.append([stock[n].pop() for n in sorted(use, reverse=True) for _ in range(use[n])])
        for n in use:
            if not stock[n]:
                del stock[n]
    return out


@W.tidy
def _pieces(batches: Iterator[pa.RecordBatch], vocabulary: str | None, end: int, capacity: int) -> Iterator[pa.RecordBatch]:
    encoder, last = Encoder(vocabulary), np.array([end], "<u4").tobytes()
    for batch in W.slices(batches, "text"):
        rows = []
        for doc, text in zip(W.column(batch, "doc_id"), W.column(batch, "text")):
            ids = memoryview(encoder.encode(text) + last)
            n = len(ids) // 4
            for at in range(0, n, capacity):
                rows.append((doc, at, min(capacity, n - at), zlib.crc32(ids[4 * at : 4 * (at + capacity)]), n))
        cols = list(zip(*rows)) or [()] * 5
        yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], names=["doc_id", "start", "length", "ids_crc32", "doc_tokens"])


def _pack_group(group: pa.Table, capacity: int) -> pa.Table:
    group = group.sort_by([(c, "ascending") for c in ("doc_id", "start", "ids_crc32")])
    lengths, of, offset = group.column("length").to_pylist(), np.zeros(group.num_rows, np.int64), np.zeros(group.num_rows, np.int64)
    number = int(group.column("grp")[0].as_py()) << 32
    for k, members in enumerate(pack(lengths, capacity)):
        at = 0
        for i in members:
            of[i], offset[i] = (number + k) * 2 + 1, at
            at += lengths[i]
    return group.drop_columns(["grp"]).append_column("sequence_id", pa.array(of)).append_column("offset", pa.array(offset))


def pieces(docs: DataFrame, *, vocabulary: str | None = None, end: int = 1, capacity: int = 2048) -> DataFrame:
    """Pieces of every whole text: ``doc_id``, ``start``, ``length``, ``ids_crc32``, ``doc_tokens``."""
    ship(docs.sparkSession)
    return docs.select("doc_id", "text").mapInArrow(
        partial(_pieces, vocabulary=vocabulary, end=end, capacity=capacity), "doc_id long, start long, length long, ids_crc32 long, doc_tokens long",
    )


def packed(docs: DataFrame, *, vocabulary: str | None = None, end: int = 1, capacity: int = 2048) -> DataFrame:
    """The pieces with ``sequence_id`` and ``offset``; ids of whole windows are even, those of packed sequences odd."""
    cut = written(pieces(docs, vocabulary=vocabulary, end=end, capacity=capacity), "pieces")
    parts = cut.where(F.col("length") < capacity)
    groups = max(1, -(-parts.count() // GROUP))
    cols = ["doc_id", "start", "length", "ids_crc32", "doc_tokens"]
    # By row: copies of a row would otherwise all go to one group.
    dealt = parts.withColumn("grp", F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(groups)).cast("int"))
    schema = ", ".join(f"{c} long" for c in [*cols, "sequence_id", "offset"])
    small = dealt.groupBy("grp").applyInArrow(lambda group: _pack_group(group, capacity), schema)
    full = cut.where(F.col("length") == capacity).select(*cols, (F.monotonically_increasing_id() * 2).alias("sequence_id"), F.lit(0).cast("long").alias("offset"))
    return small.unionByName(full)
