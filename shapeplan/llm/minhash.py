"""Near-duplicate documents: one-permutation MinHash, banded buckets, star-shaped candidates.

Each shingle of a document is hashed once; the top bits pick one of ``bins`` bins and the rest is
the value, of which a bin keeps the least. An empty bin borrows from a filled one that a hash of
(bin, attempt) picks, the densification of least variance. ``rows`` bins in sequence make a band;
documents with an equal band share a bucket.

Within a bucket no pairs are listed. First every member is compared with the bucket's least member
(a star). Links found there are contracted into components. In a bucket whose members are already
one component nothing is left to learn; in the others the members outside the largest component
become centres in turn, a few per bucket at a time, more in each round, and are compared with
members of other components; the links found are contracted before the next round. So every pair of
a bucket that could change a component is compared, and the rows made per round follow the bucket.

Sets of few shingles fill few bins, and then bands depend on each other. Up to ``small`` shingles
the buckets are instead the shingles of the set's prefix in hash order, which meet for certain at
the given similarity; sets near the border have both kinds.

Copies with equal shingle sets are one node throughout, whatever their number. Every candidate is
confirmed on the full sets.

Rows: a null or blank text has no shingles and is linked with nothing. Rows repeating a ``doc_id``
are judged by their own texts. A null id keeps a row of its own, with a null component. Very long texts count whole. Other
columns are ignored, whatever their names. An empty table gives an empty result.
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
from shapeplan.llm.components import components
from shapeplan.runtime import ship, written

#: Members of a bucket that become centres in the first round after the star; each round takes eight times as many.
CENTRES = 8

#: Members of a bucket that are held together at once, besides its centres.
CHUNK = 256


def shingles(text: bytes | None, n: int) -> np.ndarray:
    """Sorted distinct hashes of the ``n``-word shingles of a lower-cased text."""
    return np.unique(W.ngram_hashes(W.hashes.of(W.split(text, lower=True)), n))


def signature(sh: np.ndarray, bins: int) -> np.ndarray:
    """One-permutation MinHash with optimal densification of a non-empty set."""
    shift = np.uint64(64 - int(np.log2(bins)))
    h = W.mix(sh)
    which = (h >> shift).astype(np.int64)
    sig = np.zeros(bins, np.uint64)
    full = np.zeros(bins, bool)
    order = np.argsort(h, kind="stable")
    first = np.unique(which[order], return_index=True)
    sig[first[0]] = h[order][first[1]]
    full[first[0]] = True
    empty = np.flatnonzero(~full)
    attempt = 1
    while len(empty):
        with np.errstate(over="ignore"):
            lent = (W.mix(empty.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(attempt)) >> shift).astype(np.int64)
        good = full[lent]
        sig[empty[good]] = sig[lent[good]]
        empty, attempt = empty[~good], attempt + 1
    return sig


def bands(sig: np.ndarray, rows: int) -> np.ndarray:
    """A key for each band; the band's number is part of it."""
    parts = sig.reshape(-1, rows)
    with np.errstate(over="ignore"):
        key = W.mix(np.arange(1, len(parts) + 1, dtype=np.uint64) * np.uint64(0xD6E8FEB86659FD93))
        for i in range(rows):
            key = W.mix(key * np.uint64(31) + parts[:, i])
    return key


def keys(sh: np.ndarray, sig: np.ndarray, rows: int, small: int, num: int, den: int) -> np.ndarray:
    """The buckets of a set: bands, and for small sets the shingles of its prefix."""
    n = len(sh)
    out = []
    if n * den >= small * num:
        out.append(bands(sig, rows))
    if n <= small:
        with np.errstate(over="ignore"):
            out.append(W.mix(np.sort(W.mix(sh))[: n - -(-n * num // den) + 1] + np.uint64(0xA5A5A5A5)))
    return np.concatenate(out)


@W.tidy
def _describe(batches: Iterator[pa.RecordBatch], n: int, bins: int, key: tuple[str, ...], **how) -> Iterator[pa.RecordBatch]:
    for batch in W.slices(batches, "text"):
        ids, node, size, buckets = W.column(batch, "doc_id"), [], [], []
        for text in W.texts(batch, "text"):
            sh = shingles(text, n)
            node.append(hashlib.blake2b(sh.tobytes(), digest_size=16).digest())
            size.append(len(sh))
            sig = signature(sh, bins) if len(sh) else np.zeros(bins, np.uint64)
            buckets.append(W.signed(keys(sh, sig, **how)) if len(sh) else sh.view(np.int64))
        flat = np.concatenate(buckets) if buckets else np.zeros(0, np.int64)
        ends = np.cumsum([0, *map(len, buckets)]).astype(np.int32)
        yield pa.RecordBatch.from_arrays(
            [pa.array(ids, pa.int64()), pa.array(node, pa.binary()), pa.array(size, pa.int64()), pa.ListArray.from_arrays(ends, pa.array(flat, pa.int64())), *(batch.column(k) for k in key)],
            names=["doc_id", "node", "n_shingles", "buckets", *key],
        )


@W.tidy
def _sets(batches: Iterator[pa.RecordBatch], n: int) -> Iterator[pa.RecordBatch]:
    for batch in W.slices(batches, "text"):
        node = batch.column(batch.schema.get_field_index("node")).to_pylist()
        own = [shingles(t, n) for t in W.texts(batch, "text")]
        keep = [i for i, sh in enumerate(own) if hashlib.blake2b(sh.tobytes(), digest_size=16).digest() == node[i]]
        ends = np.cumsum([0, *(len(own[i]) for i in keep)]).astype(np.int32)
        flat = np.concatenate([own[i] for i in keep]) if keep else np.zeros(0, np.uint64)
        yield pa.RecordBatch.from_arrays(
            [pa.array([node[i] for i in keep], pa.binary()), pa.ListArray.from_arrays(ends, pa.array(W.signed(flat), pa.int64()))], names=["node", "sh"],
        )


def describe(docs: DataFrame, *, n: int = 5, bins: int = 128, rows: int = 4, small: int = 80, num: int = 4, den: int = 5, key: tuple[str, ...] = ()) -> DataFrame:
    """Per document: ``node`` (a digest of its shingle set), ``n_shingles`` and its ``buckets``; ``key``: long columns to carry along."""
    ship(docs.sparkSession)
    how = dict(bins=bins, rows=rows, small=small, num=num, den=den)
    kinds = "".join(f", {k} long" for k in key)
    return docs.select("doc_id", "text", *key).mapInArrow(partial(_describe, n=n, key=key, **how), f"doc_id long, node binary, n_shingles long, buckets array<long>{kinds}")


def _similar(x: str, y: str, num: int, den: int):
    """Whether two sorted shingle sets reach the similarity; exact."""
    return F.size(F.array_intersect(x, y)) * (den + num) >= (F.size(x) + F.size(y)) * num


def _repeated(sets: DataFrame, num: int, den: int) -> DataFrame:
    """Those sets of which a share of ``num / den`` occurs in other sets of the table too; others link to none of it."""
    at = sets.select("node", F.explode("sh").alias("s"))
    lone = at.groupBy("s").agg(F.count(F.lit(1)).alias("k"), F.min("node").alias("node")).where("k = 1").groupBy("node").agg(F.count(F.lit(1)).alias("lone"))
    return sets.join(lone, "node", "left").where((F.size("sh") - F.coalesce("lone", F.lit(0))) * den >= F.size("sh") * num).drop("lone")


def _could(num: int, den: int):
    """Sizes of two sets that can be similar enough."""
    return F.least("na", "nb") * den >= F.greatest("na", "nb") * num


def _links(group: pa.Table, num: int, den: int) -> pa.Table:
    """Links between the centres and the other members of part of a bucket, one for each pair of components."""
    group = group.combine_chunks()
    node, comp, centre = (group.column(c).to_pylist() for c in ("node", "comp", "centre"))
    sh = group.column("sh").chunk(0) if group.num_rows else pa.array([], pa.list_(pa.int64()))
    n = np.diff(sh.offsets.to_numpy())
    local = np.unique(sh.flatten().to_numpy(), return_inverse=True)[1]
    ends = np.concatenate([[0], np.cumsum(n)])
    marks = np.zeros(int(local.max(initial=-1)) + 1, np.int32)
    found, known = [], set()
    for i in np.flatnonzero(centre):
        mine = local[ends[i] : ends[i + 1]]
        marks[mine] = 1
        common = np.add.reduceat(marks[local], ends[:-1])
        marks[mine] = 0
        for j in np.flatnonzero(common * (den + num) >= (n + n[i]) * num):
            pair = frozenset((comp[i], comp[j]))
            if len(pair) == 2 and pair not in known:
                known.add(pair)
                found.append((node[i], node[j]))
    return pa.table([pa.array([x[k] for x in found], pa.binary()) for k in (0, 1)], names=["a", "b"])


def near_duplicates(docs: DataFrame, *, n: int = 5, num: int = 4, den: int = 5, bins: int = 128, rows: int = 4, small: int = 80, key: tuple[str, ...] = ()) -> DataFrame:
    """Per document: ``doc_id``, ``n_shingles``, ``component_id``, ``kept`` and the long columns of ``key``.

    Documents are linked when their sets of ``n``-word shingles have a Jaccard similarity of
    ``num / den`` or more; ``component_id`` is the least id that links reach. With the defaults a
    linked pair just at 0.8 is missed by every band with a probability below 1e-7.
    """
    described = written(describe(docs, n=n, bins=bins, rows=rows, small=small, num=num, den=den, key=key), "described")
    nodes = written(
        described.where("n_shingles > 0 and doc_id is not null").groupBy("node").agg(F.min("doc_id").alias("min_doc"), F.first("n_shingles").alias("n"), F.first("buckets").alias("buckets")),
        "nodes",
    )
    member = nodes.select("node", "n", F.explode("buckets").alias("bucket"))
    shared = member.groupBy("bucket").agg(F.count(F.lit(1)).alias("m"), F.min("node").alias("centre"), F.min_by("n", "node").alias("nc")).where("m > 1")
    member = written(member.join(shared.select("bucket", "centre", "nc"), "bucket"), "members")

    wanted = member.select("node").distinct().join(nodes, "node").select("node", F.col("min_doc").alias("doc_id"))
    found = docs.select("doc_id", "text").join(wanted.select("node", "doc_id"), "doc_id").select("node", "text").mapInArrow(
        partial(_sets, n=n), "node binary, sh array<long>",
    ).dropDuplicates(["node"])
    sets = written(found, "sets")
    side = lambda x: [F.col(c).alias(f"{k}{x}") for c, k in (("node", ""), ("sh", "x"))]

    star = member.where("node <> centre").select(
        F.col("centre").alias("a"), F.col("node").alias("b"), F.col("nc").alias("na"), F.col("n").alias("nb"),
    ).where(_could(num, den)).select("a", "b").distinct()
    links = star.join(sets.select(*side("a")), "a").join(sets.select(*side("b")), "b").where(_similar("xa", "xb", num, den)).select("a", "b")
    label = written(components(links), "labels")

    # Of every bucket, its centre is done. The rest matters only where it is several components.
    rest = member.where("node <> centre").select("bucket", "node", "n")
    sets = written(_repeated(_open(rest, label).select("node").distinct().join(sets, "node"), num, den), "repeated")
    rest = written(rest.join(sets.select("node"), "node"), "rest")
    centres = CENTRES
    while True:
        among = written(_open(rest, label), "open")
        size = among.groupBy("bucket").agg(F.sum(F.col("stray").cast("long")).alias("k"), F.ceil(F.count(F.lit(1)) / F.lit(CHUNK)).alias("chunks"))
        turn = F.pmod(F.xxhash64("node", "bucket", F.lit(centres)), F.ceil(F.col("k") / F.lit(centres))) == 0
        chosen = written(among.where("stray").join(size, "bucket").where(turn).select("bucket", "chunks", "node", "comp"), "chosen")
        if chosen.isEmpty() and among.isEmpty():
            break
        own = among.join(size.select("bucket", "chunks"), "bucket").select(
            "bucket", F.pmod(F.xxhash64("node"), "chunks").alias("chunk"), F.lit(False).alias("centre"), "node", "comp",
        )
        sent = chosen.select("bucket", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)).alias("chunk"), F.lit(True).alias("centre"), "node", "comp")
        links = own.unionByName(sent).join(sets, "node").groupBy("bucket", "chunk").applyInArrow(lambda group: _links(group, num, den), "a binary, b binary")
        label = written(_joined(label, links.distinct()), "labels")
        rest = written(rest.join(chosen.select("bucket", "node"), ["bucket", "node"], "left_anti"), "rest")
        centres *= 8
    named = nodes.select("node", "min_doc").join(label, "node", "left").withColumn("label", F.coalesce("label", "node"))
    least = named.groupBy("label").agg(F.min("min_doc").alias("component_id"))
    of = named.join(least, "label").select("node", "component_id")
    out = described.select("doc_id", "n_shingles", *key, F.when((F.col("n_shingles") > 0) & F.col("doc_id").isNotNull(), F.col("node")).alias("node")).join(of, "node", "left")
    comp = F.coalesce("component_id", "doc_id")
    return out.select("doc_id", "n_shingles", comp.alias("component_id"), F.col("doc_id").eqNullSafe(comp).alias("kept"), *key)


def _joined(label: DataFrame, links: DataFrame) -> DataFrame:
    """Labels after further links: only the labels that the links touch are contracted."""
    own = lambda c: label.select(F.col("node").alias(c), F.col("label").alias(f"l{c}"))
    between = links.join(own("a"), "a", "left").join(own("b"), "b", "left").select(F.coalesce("la", "a").alias("a"), F.coalesce("lb", "b").alias("b"))
    moved = components(between).withColumnRenamed("label", "to")
    old = label.join(moved.select(F.col("node").alias("label"), "to"), "label", "left").select("node", F.coalesce("to", "label").alias("label"))
    new = moved.join(label.select("node"), "node", "left_anti").select("node", F.col("to").alias("label"))
    return old.unionByName(new)


def _open(member: DataFrame, label: DataFrame) -> DataFrame:
    """Members of buckets that still hold several components; ``stray``: outside the bucket's largest."""
    at = member.select("bucket", "node", "n").join(label, "node", "left").select("bucket", "node", "n", F.coalesce("label", "node").alias("comp"))
    per = at.groupBy("bucket", "comp").agg(F.count(F.lit(1)).alias("k"))
    top = per.groupBy("bucket").agg(F.count(F.lit(1)).alias("comps"), F.max_by("comp", F.struct("k", "comp")).alias("largest")).where("comps > 1")
    return at.join(top.select("bucket", "largest"), "bucket").select("bucket", "node", "n", "comp", (F.col("comp") != F.col("largest")).alias("stray"))
