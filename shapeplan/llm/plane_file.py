"""A file format for token ids: blocks of ids as bit or byte planes, each compressed, with a chunk index.

A file is a run of pages, each whole documents in ascending id order; a page closes at the first
document end beyond ``page_ids`` ids. Within a page the ids are cut into blocks of a fixed size. A
block is transposed into planes (one for each bit, or each byte, of an id), and every plane is
compressed with zstandard on its own; a plane without a set bit takes no bytes. Ids below 65,536
leave half the planes empty, and the high planes of frequent ids are long runs.

A page starts with a magic number and counts, then the chunk index (compressed length of each plane of
each block), then the planes, then the index of documents. Pages are rows of a Parquet table, which any store
takes and Spark's committer makes whole: a lost executor leaves no half file. Reading needs no order
among pages; the page tells how many ids of its shard come before it.

Rows: a null text is the end id alone. Null ids come first; repeated ids are ordered by text. A very long text is a page by
itself. Other columns are ignored; an empty table gives an empty file and result.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from shapeplan.llm import words as W
from shapeplan.llm.tokens import Encoder
from shapeplan.runtime import scratch_path, ship

MAGIC = b"IDPLANE1"
_HEAD = struct.Struct("<8sBIQQ")
_NULL = -(2**63)


def planes(ids: np.ndarray, kind: str = "bit") -> list[bytes]:
    """The byte planes of ids, or their bit planes, lowest first; a plane of zeros is empty."""
    raw, out = np.ascontiguousarray(ids, "<u4").view(np.uint8).reshape(-1, 4), []
    for k in range(4):
        column = np.ascontiguousarray(raw[:, k])
        if not column.any():
            out.extend([b""] * (1 if kind == "byte" else 8))
        elif kind == "byte":
            out.append(column.tobytes())
        else:
            bits = np.ascontiguousarray(np.unpackbits(column, bitorder="little").reshape(-1, 8).T)
            out.extend(p.tobytes() if p.any() else b"" for p in np.packbits(bits, axis=1, bitorder="little"))
    return out


def unplanes(data: list[bytes], n: int, kind: str = "bit") -> np.ndarray:
    raw = np.zeros((n, 4), np.uint8)
    per = len(data) // 4
    for k in range(4):
        own = data[k * per : k * per + per]
        if not any(own):
            continue
        if kind == "byte":
            raw[:, k] = np.frombuffer(own[0], np.uint8)
        else:
            size = -(-n // 8)
            packed = np.stack([np.frombuffer(p, np.uint8) if p else np.zeros(size, np.uint8) for p in own])
            bits = np.ascontiguousarray(np.unpackbits(packed, axis=1, bitorder="little")[:, :n].T)
            raw[:, k] = np.packbits(bits, axis=1, bitorder="little")[:, 0]
    return raw.view("<u4").reshape(-1)


def write_page(ids: np.ndarray, doc_ids: list[int | None], counts: list[int], *, block: int = 65_536, kind: str = "bit", level: int = 1) -> bytes:
    z = zstandard.ZstdCompressor(level=level)
    lengths, chunks = [], []
    for at in range(0, len(ids), block):
        for plane in planes(ids[at : at + block], kind):
            data = z.compress(plane) if plane else b""
            lengths.append(len(data))
            chunks.append(data)
    docs = z.compress(np.array([[_NULL if d is None else d, n] for d, n in zip(doc_ids, counts)], "<i8").tobytes())
    return _HEAD.pack(MAGIC, kind == "byte", block, len(ids), len(doc_ids)) + np.array(lengths, "<u4").tobytes() + b"".join(chunks) + docs


def read_page(page: bytes) -> tuple[np.ndarray, list[int | None], list[int]]:
    magic, is_byte, block, n, n_docs = _HEAD.unpack_from(page)
    if magic != MAGIC:
        raise ValueError("not a page of this format")
    kind, per = ("byte", 4) if is_byte else ("bit", 32)
    blocks, z = -(-n // block), zstandard.ZstdDecompressor()
    lengths = np.frombuffer(page, "<u4", blocks * per, _HEAD.size)
    at = _HEAD.size + lengths.nbytes
    ends = at + np.cumsum([0, *lengths.tolist()])
    parts = []
    for b in range(blocks):
        data = [z.decompress(page[ends[k] : ends[k + 1]]) if lengths[k] else b"" for k in range(b * per, b * per + per)]
        parts.append(unplanes(data, min(block, n - b * block), kind))
    docs = np.frombuffer(z.decompress(page[int(ends[-1]) :]), "<i8").reshape(-1, 2) if n_docs else np.zeros((0, 2), np.int64)
    return np.concatenate(parts) if parts else np.zeros(0, "<u4"), [None if d == _NULL else d for d in docs[:, 0].tolist()], docs[:, 1].tolist()


@W.tidy
def _pages(batches: Iterator[pa.RecordBatch], vocabulary: str | None, end: int, page_ids: int, kind: str) -> Iterator[pa.RecordBatch]:
    encoder, shard = Encoder(vocabulary), TaskContext.get().partitionId()
    last = np.array([end], "<u4").tobytes()
    parts, docs, counts, held, before = [], [], [], 0, 0

    def page():
        ids = np.frombuffer(b"".join(parts), "<u4")
        return pa.RecordBatch.from_arrays(
            [pa.array([shard], pa.int32()), pa.array([before], pa.int64()), pa.array([len(ids)], pa.int64()), pa.array([write_page(ids, docs, counts, kind=kind)], pa.binary())],
            names=["shard", "before", "n_ids", "page"],
        )

    for batch in W.slices(batches, "text"):
        for doc, text in zip(W.column(batch, "doc_id"), W.column(batch, "text")):
            data = encoder.encode(text) + last
            parts.append(data)
            docs.append(doc)
            counts.append(len(data) // 4)
            held += counts[-1]
            if held >= page_ids:
                yield page()
                before += held
                parts, docs, counts, held = [], [], [], 0
    if docs:
        yield page()


def write_ids(docs: DataFrame, path: str, *, vocabulary: str | None = None, end: int = 0, page_ids: int = 1 << 20, kind: str = "bit") -> None:
    """Encode every whole text, append ``end``, and write the ids to ``path`` in ascending order of ``doc_id``."""
    ship(docs.sparkSession)
    ordered = docs.select("doc_id", "text").repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    ordered.mapInArrow(partial(_pages, vocabulary=vocabulary, end=end, page_ids=page_ids, kind=kind), "shard int, before long, n_ids long, page binary").write.parquet(path)


@W.tidy
def _documents(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for shard, before, page in zip(*(W.column(batch, c) for c in ("shard", "before", "page"))):
            ids, docs, counts = read_page(page)
            ends = np.cumsum([0, *counts])
            raw = memoryview(ids.tobytes())
            crc = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(ends[:-1].tolist(), ends[1:].tolist())]
            yield pa.RecordBatch.from_arrays(
                [pa.array([shard] * len(docs), pa.int32()), pa.array(docs, pa.int64()), pa.array(before + ends[:-1], pa.int64()), pa.array(counts, pa.int64()), pa.array(crc, pa.int64())],
                names=["shard", "doc_id", "own_start", "n_tokens", "ids_crc32"],
            )


def read_index(spark, path: str) -> DataFrame:
    """What the files hold of each document: ``doc_id``, ``start``, ``n_tokens``, ``ids_crc32``, decoded from the planes."""
    pages = spark.read.schema("shard int, before long, n_ids long, page binary").parquet(path)
    # One row a shard, as many as the writing stage had tasks.
    sizes = pages.groupBy("shard").agg(F.sum("n_ids").alias("n"))
    base = sizes.select("shard", (F.sum("n").over(Window.orderBy("shard")) - F.col("n")).alias("base"))
    found = pages.select("shard", "before", "page").mapInArrow(_documents, "shard int, doc_id long, own_start long, n_tokens long, ids_crc32 long")
    return found.join(F.broadcast(base), "shard").select("doc_id", (F.col("base") + F.col("own_start")).alias("start"), "n_tokens", "ids_crc32")


@W.tidy
def _ids(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for page in W.column(batch, "page"):
            ids, docs, counts = read_page(page)
            ends = np.cumsum([0, *counts]).astype(np.int32)
            yield pa.RecordBatch.from_arrays([pa.array(docs, pa.int64()), pa.ListArray.from_arrays(ends, pa.array(ids.astype(np.int32), pa.int32()))], names=["doc_id", "ids"])


def read_ids(spark, path: str) -> DataFrame:
    """The ids themselves: ``doc_id``, ``ids`` (with the end id)."""
    return spark.read.parquet(path).select("page").mapInArrow(_ids, "doc_id long, ids array<int>")


def round_trip(docs: DataFrame, **how) -> DataFrame:
    path = scratch_path(docs.sparkSession, "planes")
    write_ids(docs, path, **how)
    return read_index(docs.sparkSession, path)
