"""Nearest neighbours by largest inner product over several shifted space-filling curves.

Every vector is projected to a few dimensions by random orthogonal directions, shifted, and numbered along a
Hilbert curve; each of ``curves`` does so with directions and a shift of its own. Spark range-partitions the
numbers, which gives each vector a rank on every curve. A query's candidates are the vectors of its
own and the two neighbouring windows of ranks on each curve; the lists of all curves are merged and ranked by
the exact inner product of the original vectors.

How wide a window must be depends on the data: it is fitted so that a bounded sample of queries,
answered by brute force, finds ``recall`` of its neighbours. Vectors without structure (independent
directions in many dimensions) need windows that hold a fixed share of all rows; then this
method, like any other, saves little over scanning.

Equal vectors are one point with its least ``k + 1`` ids, which is all that ties can ask for, so a
vector that very many rows share costs no more than another.

Rows: vectors null, empty, zero, holding a null or a component that isn't finite take no part. Vectors of different lengths
compare by the components that both have, as if the shorter one went on with zeros. A null id takes no part. With fewer
candidates than ``k`` all are returned. Rows repeating an id and vector count once. Points that tie are kept in order of their least
ids wherever lists are cut, so ties go to smaller ids. Other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from shapeplan.llm import words as W
from shapeplan.llm.words import column
from shapeplan.runtime import ship, written

DIMS, BITS = 5, 12

#: Vectors of a window, and queries, that a task holds at once.
CHUNK = 16_384


def hilbert(coords: np.ndarray, bits: int) -> np.ndarray:
    """Numbers along a Hilbert curve of points with integer coordinates (rows), by Gray-code rotations from the top bit down."""
    x = coords.astype(np.int64).T.copy()
    n, top = len(x), 1 << (bits - 1)
    q = top
    while q > 1:
        low = q - 1
        for i in range(n):
            on = (x[i] & q) != 0
            swap = np.where(on, 0, (x[0] ^ x[i]) & low)
            x[0] = np.where(on, x[0] ^ low, x[0] ^ swap)
            x[i] ^= swap
        q >>= 1
    for i in range(1, n):
        x[i] ^= x[i - 1]
    flip = np.zeros_like(x[0])
    q = top
    while q > 1:
        flip = np.where((x[n - 1] & q) != 0, flip ^ (q - 1), flip)
        q >>= 1
    x ^= flip
    key = np.zeros_like(x[0])
    for b in range(bits - 1, -1, -1):
        for i in range(n):
            key = (key << 1) | ((x[i] >> b) & 1)
    return key


def directions(dim: int, curves: int, seed: int) -> tuple[list[np.ndarray], np.ndarray]:
    """Orthogonal directions and a shift for each curve."""
    rng = np.random.default_rng(seed)
    k = min(DIMS, dim)
    return [np.linalg.qr(rng.standard_normal((dim, dim)))[0][:, :k] for _ in range(curves)], rng.random((curves, k))


def _matrix(batch: pa.RecordBatch, dim: int, name: str = "embedding") -> np.ndarray:
    """Vectors as rows of ``dim`` components, shorter ones filled up with zeros."""
    a = batch.column(batch.schema.get_field_index(name))
    flat, sizes = a.flatten().to_numpy(zero_copy_only=False).astype(float), pa.compute.list_value_length(a).to_numpy(zero_copy_only=False).astype(np.int64)
    out = np.zeros((len(a), dim))
    out[np.arange(dim) < sizes[:, None]] = flat
    return out


@W.tidy
def _points(batches: Iterator[pa.RecordBatch], k: int, every: int, dim: int) -> Iterator[pa.RecordBatch]:
    """Distinct vectors of a partition's batches, with their least ids and whether a query has them."""
    for batch in batches:
        if not batch.num_rows:
            continue
        ids = np.array(column(batch, "vec_id"), np.int64)
        x = np.ascontiguousarray(_matrix(batch, dim)) + 0.0  # no negative zeros
        order = np.argsort(ids, kind="stable")
        by: dict[bytes, list[int]] = {}
        asks: dict[bytes, bool] = {}
        for i in order:
            key = x[i].tobytes()
            own = by.setdefault(key, [])
            if len(own) <= k and (not own or own[-1] != ids[i]):
                own.append(int(ids[i]))
            asks[key] = asks.get(key, False) or ids[i] % every == 0
        yield pa.RecordBatch.from_arrays(
            [pa.array(list(by), pa.binary()), pa.array(list(by.values()), pa.list_(pa.int64())), pa.array([asks[b] for b in by])],
            names=["point", "ids", "asks"],
        )


@W.tidy
def _truth(batches: Iterator[pa.RecordBatch], queries: np.ndarray, k: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        if batch.num_rows and len(queries):
            points, pids, least = (column(batch, c) for c in ("point", "pid", "least"))
            s = queries @ np.array([np.frombuffer(p) for p in points]).T
            top = np.argsort(-s, axis=1)[:, :k]
            q = np.repeat(np.arange(len(queries)), top.shape[1])
            yield pa.RecordBatch.from_arrays(
                [pa.array(q.astype(np.int32)), *(pa.array([c[i] for i in top.ravel()], pa.int64()) for c in (pids, least)), pa.array(np.take_along_axis(s, top, 1).ravel())],
                names=["q", "pid", "least", "score"],
            )


@W.tidy
def _numbered(batches: Iterator[pa.RecordBatch], axes, shifts, lo, hi) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        points, pids, asks, least = (column(batch, c) for c in ("point", "pid", "asks", "least"))
        if not points:
            continue
        x = np.array([np.frombuffer(p) for p in points])
        for c, axis in enumerate(axes):
            unit = np.clip((x @ axis - lo[c]) / np.maximum(hi[c] - lo[c], 1e-12), 0, 1)
            key = hilbert(((unit + shifts[c]) / 2 * ((1 << BITS) - 1)).astype(np.int64), BITS)
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.full(len(points), c, np.int32)), pa.array(key), pa.array(pids, pa.int64()), pa.array(asks), pa.array(least, pa.int64())],
                names=["curve", "number", "pid", "asks", "least"],
            )


def _window(group: pa.Table, k: int) -> pa.Table:
    asks, least, pid = (group.column(c).to_numpy() for c in ("asks", "least", "pid"))
    q, v = np.flatnonzero(asks), np.flatnonzero(~asks)
    out: list[list] = [[np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0)], [np.zeros(0, np.int64)]]
    x = np.array([np.frombuffer(p) for p in group.column("point").to_pylist()]) if len(q) and len(v) else None
    for at in range(0, len(q) if len(v) else 0, 256):
        own = q[at : at + 256]
        s = x[own] @ x[v].T
        n = min(k, len(v))
        # All that could be among the best, products of a matrix being a little off, then the best by score and least id.
        edge = np.partition(s, len(v) - n, axis=1)[:, len(v) - n]
        a, b = np.nonzero(s >= (edge - 1e-9 * (1 + np.abs(s).max(axis=1)))[:, None])
        score = np.einsum("ij,ij->i", x[own[a]], x[v[b]])
        order = np.lexsort((least[v[b]], -score, a))
        place = np.arange(len(order)) - np.searchsorted(a[order], a[order], "left")
        keep = order[place < n]
        for o, found in zip(out, (pid[own[a[keep]]], pid[v[b[keep]]], score[keep], least[v[b[keep]]])):
            o.append(found)
    return pa.table([pa.array(np.concatenate(o)) for o in out], names=["q", "pid", "score", "least"])


def usable(vectors: DataFrame) -> DataFrame:
    x = F.col("embedding")
    fine = F.forall(x, lambda v: F.coalesce((v == v) & (F.abs(v) < float("inf")) & ~F.isnan(v), F.lit(False))) & F.exists(x, lambda v: v != 0)
    return vectors.select("vec_id", "embedding").where(F.col("vec_id").isNotNull() & x.isNotNull()).where(fine)


def neighbours(vectors: DataFrame, *, k: int = 20, every: int = 20, curves: int = 6, recall: float = 0.97, sample: int = 128, seed: int = 5) -> DataFrame:
    """For each query (rows whose id ``every`` divides): ``query_id``, ``rank``, ``vec_id``, ``score``."""
    spark = vectors.sparkSession
    ship(spark)
    schema = "query_id long, rank int, vec_id long, score double"
    sized = usable(vectors).withColumn("dim", F.size("embedding"))
    dim = sized.agg(F.max("dim")).first()[0]
    if dim is None:
        return spark.createDataFrame([], schema)
    good = sized.select("vec_id", "embedding")
    least = F.slice(F.array_sort(F.array_distinct(F.flatten(F.collect_list("ids")))), 1, k + 1)
    points = good.mapInArrow(partial(_points, k=k, every=every, dim=dim), "point binary, ids array<long>, asks boolean")
    # Twice, so that a vector with very many copies isn't merged in one go.
    points = points.withColumn("salt", F.pmod(F.xxhash64("ids"), F.lit(64))).groupBy("point", "salt").agg(least.alias("ids"), F.max("asks").alias("asks"))
    points = points.groupBy("point").agg(least.alias("ids"), F.max("asks").alias("asks"))
    # Points go by a number of their own from here on, as a vector is some twenty times as long.
    points = written(points.withColumn("least", F.element_at("ids", 1)).withColumn("pid", F.monotonically_increasing_id()), "points")

    asked = points.where("asks").orderBy(F.xxhash64("point")).limit(sample).select("pid", "point").collect()
    queries = np.array([np.frombuffer(r["point"]) for r in asked]).reshape(len(asked), dim)
    ranked = Window.partitionBy("q").orderBy(F.desc("score"), "least")
    near = points.select("point", "pid", "least").mapInArrow(
        partial(_truth, queries=queries, k=k + 1), "q int, pid long, least long, score double",
    ).withColumn("r", F.row_number().over(ranked)).where(F.col("r") <= k + 1).select("q", "pid").collect()
    axes, shifts = directions(dim, curves, seed)
    seen = np.array([np.frombuffer(r[0]) for r in points.select("point").orderBy(F.xxhash64("point", F.lit(1))).limit(1024).collect()])
    lo, hi = [np.array([np.quantile(seen @ a, f, axis=0) for a in axes]) for f in (0.002, 0.998)]

    lined = points.select("point", "pid", "asks", "least").mapInArrow(
        partial(_numbered, axes=axes, shifts=shifts, lo=lo, hi=hi), "curve int, number long, pid long, asks boolean, least long",
    )
    along = ("curve", "number", "least", "pid")
    lined = written(lined.repartitionByRange(*along).sortWithinPartitions(*along).withColumn("at", F.monotonically_increasing_id()), "lined")
    runs = lined.groupBy("curve", F.shiftright("at", 33).alias("part")).agg(F.min("at").alias("least"), F.count(F.lit(1)).alias("n"))
    base = Window.partitionBy("curve").orderBy("part")
    runs = runs.select("curve", "part", (F.sum("n").over(base) - F.col("n") - F.col("least")).alias("shift"))
    ranks = written(
        lined.withColumn("part", F.shiftright("at", 33)).join(F.broadcast(runs), ["curve", "part"]).select("curve", "pid", "asks", "least", (F.col("at") + F.col("shift")).alias("rank")),
        "ranks",
    )

    wanted = {r["pid"] for r in asked} | {r["pid"] for r in near}
    place: dict[int, np.ndarray] = {}
    small = spark.createDataFrame([(p,) for p in wanted], "pid long") if wanted else points.select("pid").limit(0)
    for r in ranks.join(F.broadcast(small), "pid").select("curve", "pid", "rank").collect():
        place.setdefault(r["pid"], np.zeros(curves, np.int64))[r["curve"]] = r["rank"]
    gaps = np.sort([np.abs(place[asked[r["q"]]["pid"]] - place[r["pid"]]).min() for r in near]) if near else np.zeros(1, np.int64)
    width = max(256, int(gaps[min(len(gaps) - 1, int(np.ceil(recall * len(gaps))))]) + 1)

    block = F.floor(F.col("rank") / F.lit(width)).cast("long")
    most = ranks.where("asks").groupBy("curve", block).count().agg(F.max("count")).first()[0] or 0
    # A group has one piece of a window and one hand of the queries that look at it.
    pieces, hands = -(-width // CHUNK), max(1, -(-3 * most // CHUNK))
    every_of = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long")))
    held = ranks.select(
        "curve", block.alias("block"), F.floor(F.pmod("rank", F.lit(width)) / F.lit(CHUNK)).cast("long").alias("piece"), "pid", F.lit(False).alias("asks"), "least",
    ).join(points.select("pid", "point"), "pid").withColumn("hand", every_of(hands))
    sent = ranks.where("asks").join(points.where("asks").select("pid", "point"), "pid")
    sent = sent.select("curve", F.explode(F.array(block - 1, block, block + 1)).alias("block"), "pid", F.lit(True).alias("asks"), "least", "point")
    sent = sent.withColumn("piece", every_of(pieces)).withColumn("hand", F.pmod(F.xxhash64("pid"), F.lit(hands)).cast("long"))
    groups = held.unionByName(sent).groupBy("curve", "block", "piece", "hand")
    found = groups.applyInArrow(lambda group: _window(group, k + 1), "q long, pid long, score double, least long")
    best = found.groupBy("q", "pid").agg(F.max("score").alias("score"), F.min("least").alias("least"))
    order = lambda by: Window.partitionBy(by).orderBy(F.desc("score"), "vec_id")
    merged = best.withColumn("r", F.row_number().over(Window.partitionBy("q").orderBy(F.desc("score"), "least"))).where(F.col("r") <= k + 1)
    top = merged.join(points.select("pid", "ids"), "pid").select(
        "q", "score", F.explode("ids").alias("vec_id"),
    ).withColumn("r", F.row_number().over(order("q"))).where(F.col("r") <= k + 1).select(F.col("q").alias("pid"), "vec_id", "score")
    asks = good.where(F.col("vec_id") % every == 0).mapInArrow(partial(_named, dim=dim), "query_id long, point binary").distinct()
    asks = asks.join(points.where("asks").select("point", "pid"), "point").select("query_id", "pid")
    out = asks.join(top, "pid").where("query_id <> vec_id").withColumn("rank", F.row_number().over(order("query_id"))).where(F.col("rank") <= k)
    return out.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


@W.tidy
def _named(batches: Iterator[pa.RecordBatch], dim: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        if batch.num_rows:
            x = _matrix(batch, dim) + 0.0
            yield pa.RecordBatch.from_arrays([pa.array(column(batch, "vec_id"), pa.int64()), pa.array([r.tobytes() for r in x], pa.binary())], names=["query_id", "point"])
