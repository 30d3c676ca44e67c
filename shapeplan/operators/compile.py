"""Shapes as queries: targets, witnesses, counts, flags. Nothing here runs a job."""

from __future__ import annotations

from functools import reduce
from typing import NamedTuple

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from shapeplan.model import And, Count, Not, Or, Shape
from shapeplan.model.ast import leaves
from shapeplan.runtime import joinable


class NodeList(NamedTuple):
    """What is known of a decided shape, as a list for filters: of the nodes that conform, or of those that don't.

    A list of the others says nothing of nodes outside the shape's domain, which don't conform either. ``within`` is
    that domain; it may be left out only where no link leaves it.
    """

    mode: str  # valid, invalid
    nodes: DataFrame
    within: DataFrame | None = None
    #: Items and their bytes, where they are known.
    n: int | None = None
    size: int | None = None

    def sides(self) -> list[tuple[DataFrame, bool]]:
        """Sets of nodes, and whether a node must be in them."""
        return [(self.nodes, self.mode == "valid")] + ([(self.within, True)] if self.within is not None else [])


def as_list(known: DataFrame | NodeList) -> NodeList:
    return known if isinstance(known, NodeList) else NodeList("valid", known)


def conforming(pairs: DataFrame, known: DataFrame | NodeList) -> DataFrame:
    """Pairs whose value conforms. Never ``NOT IN``: that broadcasts whatever its size."""
    for nodes, wanted in as_list(known).sides():
        pairs = pairs.join(nodes.select(F.col("entity").alias("value")), "value", "left_semi" if wanted else "left_anti")
    return joinable(pairs.select("entity", "value"))


def target(graph, shape: Shape) -> DataFrame:
    """``entity`` of the shape's target class."""
    return graph.entities(shape.target)


def demanded(graph, schema, name: str) -> DataFrame | None:
    """Nodes that constraints of other shapes reach with a reference to this one."""
    parts = [graph.edges(
        s.entity_class, leaf.path,
    ).select(F.col("value").alias("entity")) for s in schema.shapes for c in s.body for leaf, _ in leaves(c) if leaf.ref == name and s.entity_class]
    return reduce(DataFrame.unionByName, parts).distinct() if parts else None


def domain(graph, schema, shape: Shape) -> DataFrame:
    """What must be judged: the targets, and referenced nodes outside them where these could conform.

    A node without a class row has no values, so it conforms only if the shape accepts a bare entity;
    for other shapes the targets are enough, as absent nodes count as not conforming.
    """
    own = graph.entities(shape.entity_class) if shape.entity_class else None
    if own is not None and not shape.accepts_bare:
        return own
    more = demanded(graph, schema, shape.name)
    parts = [p for p in (own, more) if p is not None]
    return reduce(DataFrame.unionByName, parts).distinct()


def witnesses(graph, shape: Shape, c: Count, valid: dict[str, DataFrame | NodeList] | None = None) -> DataFrame:
    """Distinct ``entity``, ``value`` that pass the constraint's test and, where ``valid`` has it, its reference."""
    pairs = graph.edges(shape.entity_class, c.path)
    if c.test:
        pairs = pairs.where(c.test.sql)
    if c.ref and c.ref in (valid or {}):
        pairs = conforming(pairs, valid[c.ref])
    return pairs.distinct()


def _subsets(pairs: DataFrame, n: int, stem: str) -> DataFrame:
    """All unordered ``n``-subsets of the values of each entity, as columns ``stem``1..n."""
    out = pairs.select("entity", F.col("value").alias(f"{stem}1"))
    for i in range(2, n + 1):
        nxt = pairs.select("entity", F.col("value").alias(f"{stem}{i}"))
        out = out.join(joinable(nxt), "entity").where(F.col(f"{stem}{i - 1}") < F.col(f"{stem}{i}"))
    return out


def min_query(graph, shape: Shape, valid: dict[str, DataFrame] | None = None) -> DataFrame:
    """One query for all minima: a row for each combination of witnesses, the product of the fan-outs."""
    out = target(graph, shape)
    for k, c in enumerate(shape.counts("min"), 1):
        if c.n:
            out = out.join(joinable(_subsets(witnesses(graph, shape, c, valid), c.n, f"m{k}_")), "entity")
    return out


def max_query(graph, shape: Shape, c: Count, valid: dict[str, DataFrame] | None = None) -> DataFrame:
    """One query for one maximum: a row for each set of ``n + 1`` witnesses, so any row is a violation."""
    return target(graph, shape).join(joinable(_subsets(witnesses(graph, shape, c, valid), c.n + 1, "x")), "entity")


def counts(graph, shape: Shape, valid: dict[str, DataFrame] | None = None) -> DataFrame:
    """``entity`` and for each top-level constraint its number of witnesses, ``c1``.., without combinations."""
    out = target(graph, shape)
    for k, c in enumerate(shape.counts(), 1):
        per = witnesses(graph, shape, c, valid).groupBy("entity").agg(F.count(F.lit(1)).alias(f"c{k}"))
        out = out.join(per, "entity", "left").withColumn(f"c{k}", F.coalesce(f"c{k}", F.lit(0)).cast("long"))
    return out


def holds(c: Count, n: Column) -> Column:
    return n >= c.n if c.kind == "min" else n <= c.n


def rows_of(graph, schema, shape: Shape, parts=None) -> DataFrame:
    """The domain of a shape, with the entity's own columns that the constraints look at."""
    cls = shape.entity_class
    found = (leaf for c in (shape.body if parts is None else parts) for leaf, _ in leaves(c))
    single = list(dict.fromkeys(c.path for c in found if graph.single(cls, c.path)))
    if single and not (shape.accepts_bare or shape.target is None):
        return graph.frame(cls, single)
    out = domain(graph, schema, shape)
    return out.join(joinable(graph.frame(cls, single)), "entity", "left") if single else out


class Flags:
    """Truth of all counts of a shape, with one aggregation for each child table instead of one a constraint.

    Single-valued predicates are columns of the class row. Values of one child table are counted together;
    bounds of one need no distinct count: there is a value if the least is not null, and one only if least
    and greatest agree. References are marked by a left join with the conforming entities.
    """

    def __init__(self, graph, schema, shape: Shape, valid: dict[str, DataFrame | NodeList], parts=None):
        self.graph, self.schema, self.shape = graph, schema, shape
        self.valid = {n: as_list(v) for n, v in valid.items()}
        self.parts = shape.body if parts is None else parts
        self.all = list(dict.fromkeys(leaf for c in self.parts for leaf, _ in leaves(c)))
        self.columns: dict[Count, Column] = {}
        self._marks: dict[tuple[str, str], Column] = {}

    def frame(self, only: DataFrame | None = None) -> DataFrame:
        """The domain (or the entities of ``only``) with whatever the flags need; fills ``columns``."""
        out = rows_of(self.graph, self.schema, self.shape, self.parts)
        if only is not None:
            out = out.join(joinable(only.select("entity")), "entity", "left_semi")
        return self.add(out)

    def add(self, out: DataFrame) -> DataFrame:
        """Rows that hold the entity's own columns, with whatever else the flags need."""
        grouped: dict[tuple, list[Count]] = {}
        for i, c in enumerate(self.all):
            if self.graph.single(self.shape.entity_class, c.path):
                out = self._single(out, i, c)
            else:
                grouped.setdefault(self._source(c), []).append(c)
        for j, (_, own) in enumerate(grouped.items()):
            out = self._multi(out, j, own)
        return out

    def _single(self, out: DataFrame, i: int, c: Count) -> DataFrame:
        has = F.col(c.path).isNotNull()
        if c.test:
            has = has & F.coalesce(F.expr(c.test.on(c.path)), F.lit(False))
        if c.ref:
            if (c.path, c.ref) not in self._marks:
                mark = F.lit(True)
                for k, (nodes, wanted) in enumerate(self.valid[c.ref].sides()):
                    at = f"_r{i}_{k}"
                    out = out.join(nodes.select(F.col("entity").alias(f"{at}v"), F.lit(True).alias(at)), F.col(c.path) == F.col(f"{at}v"), "left").drop(f"{at}v")
                    mark = mark & (F.col(at).isNotNull() if wanted else F.col(at).isNull())
                self._marks[c.path, c.ref] = mark
            has = has & self._marks[c.path, c.ref]
        self.columns[c] = holds(c, has.cast("int"))
        return out

    def _source(self, c: Count) -> tuple:
        edge = self.graph.base(self.shape.entity_class, c.path)
        if edge is None or c.ref or edge.where or " OVER " in edge.value or any(x.n > 1 for x in self.all if x.path == c.path):
            return ("path", c.path, c.test, c.ref)
        return ("table", edge.table, edge.entity)

    def _multi(self, out: DataFrame, j: int, own: list[Count]) -> DataFrame:
        g, cls = self.graph, self.shape.entity_class
        kinds = list(dict.fromkeys((c.path, c.test) for c in own))
        if self._source(own[0])[0] == "table":
            edge = g.base(cls, own[0].path)
            value = {}
            for k, (path, test) in enumerate(kinds):
                v = g.base(cls, path).value
                value[path, test] = f"_a{j}_{k}", F.expr(v if test is None else f"CASE WHEN {test.on(v)} THEN {v} END")
            rows = g.read(edge.table).select(F.expr(edge.entity).alias("entity"), *[v.alias(n) for n, v in value.values()]).where("entity IS NOT NULL")
            per = rows.groupBy("entity").agg(*[f(n).alias(f"{n}_{s}") for n, _ in value.values() for f, s in ((F.min, "lo"), (F.max, "hi"))])
            out = out.join(joinable(per), "entity", "left")
            for c in own:
                n = value[c.path, c.test][0]
                some, many = F.col(f"{n}_lo").isNotNull(), F.coalesce(F.col(f"{n}_lo") != F.col(f"{n}_hi"), F.lit(False))
                self.columns[c] = {("min", 0): F.lit(True), ("min", 1): some, ("max", 0): ~some, ("max", 1): ~many}[c.kind, c.n]
            return out
        c = own[0]
        need = min(max(x.n + (x.kind == "max") for x in own), 2)
        pairs = g.edges(cls, c.path)
        if c.test:
            pairs = pairs.where(c.test.sql)
        if c.ref:
            pairs = conforming(pairs, self.valid[c.ref])
        # Existence needs no distinct values.
        number = F.count(F.lit(1)) if need <= 1 else F.count_distinct("value")
        per = pairs.groupBy("entity").agg(number.alias(f"_n{j}"))
        out = out.join(joinable(per), "entity", "left")
        for x in own:
            self.columns[x] = holds(x, F.coalesce(f"_n{j}", F.lit(0)))
        return out

    def truth(self, c=None) -> Column:
        """The constraint as a column over ``frame``; the whole conjunction by default."""
        if c is None:
            return reduce(lambda a, b: a & b, map(self.truth, self.parts), F.lit(True))
        if isinstance(c, Count):
            return self.columns[c]
        if isinstance(c, Not):
            return ~self.truth(c.part)
        fold = (lambda a, b: a & b) if isinstance(c, And) else (lambda a, b: a | b)
        return reduce(fold, map(self.truth, c.parts))

    def reason(self) -> Column:
        """The first violated conjunct, null for conforming entities."""
        label = lambda c: c.label if isinstance(c, Count) else type(c).__name__.lower()
        return F.coalesce(*[F.when(~self.truth(c), F.lit(label(c))) for c in self.parts]) if self.parts else F.lit(None).cast("string")
