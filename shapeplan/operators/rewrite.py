"""Rewrites of target and constraint queries with what decided shapes proved."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

from pyspark.ml.feature import Bucketizer
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from shapeplan.model import Count, Shape
from shapeplan.model.ast import leaves
from shapeplan.operators.compile import NodeList, as_list, conforming


@dataclass(frozen=True)
class RewriteConfig:
    """Which rewrites the planned engine makes; each can be switched off by itself."""

    #: Cut targets by what decided shapes proved.
    push: bool = True
    #: Fetch a target query in slices, and deliver each slice's verdicts when they are known.
    slice: bool = False
    #: Put a long list into several queries, or into none if these would be too many.
    split: bool = False
    #: The most selective constraint first.
    reorder: bool = True
    #: Drop an entity at its first violation.
    skip: bool = True
    #: ``smaller``: the smaller list, that of others only where no link leaves the domain; ``valid``, ``invalid``: always this one.
    lists: str = "smaller"


OFF = RewriteConfig(push=False, reorder=False, skip=False)


@dataclass(frozen=True)
class Limits:
    #: Most rows that one answer may have (None: no cap).
    answer_cap: int | None = None
    #: Rows of a slice (None: as many as an answer may have).
    slice_rows: int | None = None
    #: Most jobs that the slices of a shape take; more slices than that share jobs, as each job reads the child tables anew.
    slice_jobs: int = 8
    #: Longest list that goes into a query as literals.
    literal_items: int = 10
    #: Most bytes of a side that is broadcast; beyond them the join is shuffled.
    broadcast_bytes: int = 64 << 20
    #: Items a query of a split list, and most queries that a list is split into.
    max_filter_items: int = 10_000
    max_rewritten: int = 8


def choose_list(n_valid: int, n_invalid: int, closed: bool = True) -> str:
    """The smaller list; the valid one on a tie, and where links may lead out of the domain, as its complement then isn't all of the rest."""
    return "valid" if n_valid <= n_invalid or not closed else "invalid"


def can_push(c, decided: set[str]) -> bool:
    """Only a minimum of one or more with a decided reference justifies dropping targets."""
    return isinstance(c, Count) and c.kind == "min" and c.n >= 1 and c.ref in decided


def sized(side: DataFrame, size: int | None, limits: Limits) -> DataFrame:
    """A broadcast hint if the counted bytes allow it."""
    return F.broadcast(side) if size is not None and size <= limits.broadcast_bytes else side


def filter_edges(pairs: DataFrame, nodes: DataFrame, mode: str) -> DataFrame:
    """Pairs whose value is in (``valid``) or not in (``invalid``) the list."""
    return conforming(pairs, NodeList(mode, nodes))


def push_filter(graph, shape: Shape, targets: DataFrame, c: Count, known: DataFrame | NodeList, limits: Limits = Limits()) -> DataFrame:
    """Targets with a link over the path to a node that the list lets through.

    An exclusion list filters links, not entities: one good link is enough. On a single-valued path
    both are a join on the column itself, without a second look at the entity.
    """
    known = as_list(known)
    if graph.single(shape.entity_class, c.path):
        col = F.col(c.path)
        own = targets if c.path in targets.columns else targets.join(graph.frame(shape.entity_class, [c.path]), "entity")
        if known.n is not None and known.n <= limits.literal_items and known.within is None:
            items = [r[0] for r in known.nodes.select("entity").limit(limits.literal_items + 1).collect()]
            among = col.isin(items) if items else F.lit(False)
            return own.where(among if known.mode == "valid" else col.isNotNull() & ~among)
        own = own.where(col.isNotNull())
        for nodes, wanted in known.sides():
            own = own.join(nodes.select(F.col("entity").alias("_node")), col == F.col("_node"), "left_semi" if wanted else "left_anti")
        return own
    pairs = graph.edges(shape.entity_class, c.path)
    if c.test:
        pairs = pairs.where(c.test.sql)
    return targets.join(conforming(pairs, known).select("entity"), "entity", "left_semi")


def split_filter(pairs: DataFrame, nodes: DataFrame, n: int, mode: str, limits: Limits = Limits()) -> DataFrame:
    """Entities after a long list went in as several queries, one for each chunk of the list.

    An entity may link into two chunks, so answers of an inclusion list are united as a set. Chunks of an
    exclusion list apply to the same link one after the other; a union of theirs would let everything
    through. Beyond ``max_rewritten`` queries the list isn't split and one query is made.
    """
    queries = -(-max(n, 1) // limits.max_filter_items)
    if queries > limits.max_rewritten or queries == 1:
        return filter_edges(pairs, nodes, mode).select("entity").distinct()
    chunk = lambda i: nodes.where(F.pmod(F.xxhash64("entity"), F.lit(queries)) == i)
    if mode == "valid":
        return reduce(DataFrame.unionByName, [filter_edges(pairs, chunk(i), mode).select("entity") for i in range(queries)]).distinct()
    return reduce(lambda p, i: filter_edges(p, chunk(i), mode), range(queries), pairs).select("entity").distinct()


def sliced(rows: DataFrame, parts: int, strategy: str = "hash", key: str = "entity") -> DataFrame:
    """Rows with the number of their slice, ``slice``, of ``parts``: one look at each row, however many slices there are.

    Ranges come from one call for all quantiles, and a row finds its own by bisection; rows without a key go last.
    """
    if parts == 1:
        return rows.withColumn("slice", F.lit(0))
    if strategy == "hash":
        return rows.withColumn("slice", F.pmod(F.xxhash64(key), F.lit(parts)).cast("int"))
    edges = sorted(set(rows.approxQuantile(key, [k / parts for k in range(1, parts)], 1 / (8 * parts))))
    if not edges:  # no row has a key
        return rows.withColumn("slice", F.lit(0))
    found = Bucketizer(splits=[-math.inf, *edges, math.inf], inputCol=key, outputCol="slice", handleInvalid="keep").transform(rows)
    return found.withColumn("slice", F.col("slice").cast("int"))


def slices(rows: DataFrame, cap: int, n: int | None = None, strategy: str = "hash", key: str = "entity") -> Iterator[DataFrame]:
    """Parts of at most about ``cap`` rows whose union is the answer.

    ``offset`` sorts the whole answer for every slice, as an endpoint would; ``hash`` deals rows out by key and
    ``range`` by ranges of its values, both without a sort. Rows are counted where ``n`` isn't given; if they are more
    than the given ``n``, ``offset`` goes on until nothing is left, and the parts of the others are longer.
    """
    parts = max(1, -(-(rows.count() if n is None else n) // cap))
    for i in range(parts):
        if parts == 1 and strategy != "offset":
            yield rows
        elif strategy == "offset":
            yield rows.orderBy(key).offset(i * cap).limit(cap)
        else:
            dealt = sliced(rows, parts, strategy, key) if not i else dealt
            yield dealt.where(F.col("slice") == i).drop("slice")
    while strategy == "offset" and n is not None and not (more := rows.orderBy(key).offset(parts * cap).limit(cap)).isEmpty():
        yield more
        parts += 1


def hash_slices(rows: DataFrame, n: int, cap: int, key: str = "entity", jobs: int | None = None) -> tuple[int, list[Column]]:
    """The number of slices into which a hash of the key deals rows, each of ``cap`` rows at most, and a condition for each slice.

    Hashing is uneven, so the largest slice is counted, and there are more slices until it fits. With ``jobs`` there are at most so many
    conditions, each for a run of slices.
    """
    parts = max(1, -(-n // cap))
    while parts > 1 or n > cap:
        parts += max(1, parts // 8)
        part = F.pmod(F.xxhash64(key), F.lit(parts))
        if (rows.groupBy(part).count().agg(F.max("count")).first()[0] or 0) <= cap:
            runs = min(parts, jobs or parts)
            ends = [parts * i // runs for i in range(runs + 1)]
            return parts, [part.between(a, b - 1) for a, b in zip(ends, ends[1:])]
    return 1, [F.lit(True)]


def surviving(graph, shape: Shape, c, stats=None, share: dict[str, float] | None = None) -> float:
    """The estimated share of entities that pass a constraint, from statistics and from the shares of decided shapes that conform."""
    if not isinstance(c, Count):
        return 0.5
    cls = shape.entity_class
    known = stats.path(cls, c.path) if stats is not None else None
    per = known.n / max(known.n_subjects, 1) if known else 1.0
    some = known.n_subjects / max(stats.entities(cls), 1) if known else 0.9
    good = (1 / 3 if c.test else 1.0) * ((share or {}).get(c.ref, 0.5) if c.ref else 1.0)
    if c.kind == "min":
        return 1.0 if c.n == 0 else some * (1 - (1 - good) ** max(per, 1.0)) ** c.n
    if known and known.most <= c.n:
        return 1.0
    return 1 - some * good ** (c.n + 1) if c.n < per else 0.9


def order_constraints(graph, shape: Shape, parts: list, stats=None, share: dict[str, float] | None = None) -> list:
    """Tests of the entity's own row first, as they cost nothing, then by the share of entities that are expected to pass; ties as declared."""

    def rank(c) -> tuple:
        own = isinstance(c, Count) and not c.ref and graph.single(shape.entity_class, c.path)
        return not own, round(surviving(graph, shape, c, stats, share), 6), any(leaf.ref for leaf, _ in leaves(c))

    return sorted(parts, key=rank)
