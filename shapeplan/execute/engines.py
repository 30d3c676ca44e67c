"""The engines. All give the same verdicts; they differ in what they read, join and keep.

``naive``: every target, minimum and maximum query unfiltered, combinations and all.
``naive_py``: the same rows, decided in Python workers.
``planned``: shapes in planned order, targets cut by what decided shapes proved, candidates shrinking
from constraint to constraint, deferred where a reference isn't decided yet.
``grounded``: rules made and saturated shape by shape in planned order (see ``grounding``).
``fused``: for each shape one aggregation a child table and one pass over the class rows.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from functools import reduce

import pandas as pd
from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from shapeplan.execute.endpoint import Endpoint
from shapeplan.measure.work import rules_of
from shapeplan.model import Count, Shape, ShapeSchema, UnsupportedFragment
from shapeplan.operators import compile as q
from shapeplan.operators.rewrite import Limits, RewriteConfig, can_push, choose_list, hash_slices, order_constraints, push_filter, sized, split_filter
from shapeplan.plans.depgraph import DepGraph, dependency_graph
from shapeplan.plans.order import PlanConfig, ValidationPlan, plan_validation
from shapeplan.runtime import SMALL_ROWS, joinable, settled, ship, shuffled, written
from shapeplan.sources.stats import GraphStats


@dataclass
class ValidationResult:
    schema: ShapeSchema
    #: The shapes as their verdicts were reached.
    order: list[str]
    #: Conforming entities by shape; those that only references reach included.
    valid: dict[str, DataFrame]
    targets: Callable[[str], DataFrame]
    measures: dict[str, dict] = field(default_factory=dict)
    #: Shape, seconds since the start, verdicts reached then.
    trace: list[tuple[str, float, int]] = field(default_factory=list)
    #: Whether verdicts come sorted by shape and entity.
    ordered: bool = False

    def of(self, shape: str) -> DataFrame:
        """``shape``, ``entity`` (as text), ``valid`` for each target of a shape."""
        mark = joinable(self.valid[shape].select("entity", F.lit(True).alias("ok")))
        return self.targets(shape).join(mark, "entity", "left").select(
            F.lit(shape).alias("shape"), F.col("entity").cast("string").alias("entity"), F.coalesce("ok", F.lit(False)).alias("valid"),
        )

    @property
    def reported(self) -> list[str]:
        """Decided shapes that have a target."""
        return [s.name for s in self.schema.shapes if s.target and s.name in self.valid]

    @property
    def verdicts(self) -> DataFrame:
        out = reduce(DataFrame.unionByName, map(self.of, self.reported))
        return out.orderBy("shape", "entity") if self.ordered else out

    def invalid(self, shape: str) -> DataFrame:
        return self.of(shape).where("not valid").select("entity")

    def summary(self) -> DataFrame:
        """As ``shape_report`` of the verdicts, by counting targets and conforming ones instead of joining them."""
        parts = []
        for name in self.reported:
            valid, targets = self.valid[name], self.targets(name)
            if self.schema[name].accepts_bare:  # then nodes outside the targets can conform too
                valid = valid.join(joinable(targets), "entity", "left_semi")
            one, none = F.count(F.lit(1)), F.lit(0).cast("long")
            parts.append(targets.agg(one.alias("n"), none.alias("ok")))
            parts[-1] = parts[-1].unionByName(valid.agg(none.alias("n"), one.alias("ok"))).select(F.lit(name).alias("shape"), "n", "ok")
        both = reduce(DataFrame.unionByName, parts).groupBy("shape").agg(F.sum("n").alias("n"), F.sum("ok").alias("n_valid")).where("n > 0")
        return both.select("shape", (F.col("n") == F.col("n_valid")).alias("all_valid"), "n_valid", (F.col("n") - F.col("n_valid")).alias("n_invalid"))


def shape_report(verdicts: DataFrame) -> DataFrame:
    """By shape: whether all targets conform, and how many do."""
    return verdicts.groupBy("shape").agg(F.bool_and("valid").alias("all_valid"), F.count_if("valid").alias("n_valid"), F.count_if(~F.col("valid")).alias("n_invalid"))


def equivalent(a: DataFrame, b: DataFrame) -> DataFrame:
    """Verdicts that only one of two results has; empty if they agree."""
    cols = ["shape", "entity", "valid"]
    return a.select(cols).exceptAll(b.select(cols)).withColumn("side", F.lit("a")).unionByName(b.select(cols).exceptAll(a.select(cols)).withColumn("side", F.lit("b")))


def decision_order(dep: DepGraph, order: list[str]) -> list[list[str]]:
    """The given order, but a shape waits for those that it refers to; shapes of one recursion come together."""
    part_of = {n: p for p in dep.components() for n in p}
    out, done = [], set()
    while len(done) < len(order):
        part = next(p for n in order if n not in done for p in [part_of[n]] if all(r in done or r in p for m in p for r in dep.out(m)))
        out.append(part)
        done |= set(part)
    return out


def _fused(graph, schema: ShapeSchema, shape: Shape, valid: dict[str, DataFrame], only: DataFrame | None = None) -> DataFrame:
    flags = q.Flags(graph, schema, shape, valid)
    rows = flags.frame(only)
    # What joins give has no hint, and its shuffle may look small enough for a broadcast while its hash table isn't.
    return joinable(rows.where(flags.truth()).select("entity"))


def _naive(graph, schema: ShapeSchema, shape: Shape, valid: dict[str, DataFrame], endpoint: Endpoint) -> DataFrame:
    rows = endpoint.answer(q.min_query(graph, shape))
    for k, c in enumerate(shape.counts("min"), 1):
        for i in range(1, c.n + 1) if c.ref else ():
            rows = rows.join(joinable(valid[c.ref].select(F.col("entity").alias(f"m{k}_{i}"))), f"m{k}_{i}", "left_semi")
    out = rows.select("entity").distinct()
    for c in shape.counts("max"):
        bad = endpoint.answer(q.max_query(graph, shape, c))
        for i in range(1, c.n + 2) if c.ref else ():
            bad = bad.join(joinable(valid[c.ref].select(F.col("entity").alias(f"x{i}"))), f"x{i}", "left_semi")
        out = out.join(joinable(bad.select("entity").distinct()), "entity", "left_anti")
    return out


def _decide(rules: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Saturation of grounded rules that come sorted by entity: some minimum rule holds and no maximum rule does."""
    held = None
    for pdf in rules:
        if held is not None:
            pdf = pd.concat([held, pdf])
        # The last entity may go on in the next batch.
        last = pdf["entity"].iloc[-1] if len(pdf) else None
        held, pdf = pdf[pdf["entity"] == last], pdf[pdf["entity"] != last]
        yield _conforming(pdf)
    if held is not None:
        yield _conforming(held)


def _conforming(pdf: pd.DataFrame) -> pd.DataFrame:
    true = pdf["body"].map(all).astype(bool)
    by = pd.DataFrame({"entity": pdf["entity"], "good": true & pdf["kind"].eq("min"), "bad": true & pdf["kind"].eq("max")}).groupby("entity", as_index=False).any()
    return by.loc[by["good"] & ~by["bad"], ["entity"]]


def _naive_py(graph, schema: ShapeSchema, shape: Shape, valid: dict[str, DataFrame], endpoint: Endpoint) -> DataFrame:
    def grounded(rows: DataFrame, kind: str, refs: list[tuple[str, str]]) -> DataFrame:
        for col, ref in refs:
            rows = rows.join(joinable(valid[ref].select(F.col("entity").alias(col), F.lit(True).alias(f"t_{col}"))), col, "left")
        body = F.array(F.lit(True), *[F.coalesce(F.col(f"t_{c}"), F.lit(False)) for c, _ in refs])
        return rows.select("entity", F.lit(kind).alias("kind"), body.alias("body"))

    mins = [(f"m{k}_{i}", c.ref) for k, c in enumerate(shape.counts("min"), 1) if c.ref for i in range(1, c.n + 1)]
    rules = grounded(endpoint.answer(q.min_query(graph, shape)), "min", mins)
    for c in shape.counts("max"):
        rules = rules.unionByName(grounded(endpoint.answer(q.max_query(graph, shape, c)), "max", [(f"x{i}", c.ref) for i in range(1, c.n + 2)] if c.ref else []))
    kind = dict(rules.dtypes)["entity"]
    ship(rules.sparkSession)
    return rules.repartition("entity").sortWithinPartitions("entity").mapInPandas(_decide, f"entity {kind}")


def _chain(shape: Shape) -> str | None:
    """The path over which a shape refers to itself, if that is the only way in which it does: one value that conforms."""
    own = {(leaf.path, leaf.kind, leaf.n, leaf.test, positive) for c in shape.body for leaf, positive in q.leaves(c) if leaf.ref == shape.name}
    path = next(iter(own))[0] if own else None
    return path if own == {(path, "min", 1, None, True)} else None


def _doubled(graph, schema: ShapeSchema, shape: Shape, path: str, valid: dict[str, DataFrame], unfounded: bool) -> DataFrame | None:
    """A recursion along chains, in as many rounds as the logarithm of the longest one; None if an entity has several next ones.

    An entity conforms for certain (``lo``), or if the one that it points to does (``hi``). A round lets each look through the one that
    it points to, so pointers reach twice as far. Entities that are open once pointers reach further than there are entities are on
    cycles or lead there.
    """
    links = q.witnesses(graph, shape, Count(path, "min", 1))
    if not links.groupBy("entity").count().where("count > 1").isEmpty():
        return None
    every = settled(q.domain(graph, schema, shape), "domain")
    none = every.limit(0)
    sure = _fused(graph, schema, shape, valid | {shape.name: none}).select("entity", F.lit(True).alias("lo"))
    may = _fused(graph, schema, shape, valid | {shape.name: q.NodeList("invalid", none, every)}).select("entity", F.lit(True).alias("hi"))
    rows = every.join(may, "entity", "left").join(sure, "entity", "left").join(joinable(links.withColumnRenamed("value", "next")), "entity", "left")
    rows = settled(rows.select("entity", F.coalesce("hi", F.lit(False)).alias("hi"), F.coalesce("lo", F.lit(False)).alias("lo"), "next"), "chains")
    undecided, n, reach = F.col("hi") & ~F.col("lo") & F.col("next").isNotNull(), every.count(), 1
    while reach <= 2 * n and not rows.where(undecided).isEmpty():
        there = rows.select(F.col("entity").alias("next"), F.col("hi").alias("hi2"), F.col("lo").alias("lo2"), F.col("next").alias("next2"))
        moved = rows.where(undecided).join(joinable(there), "next", "left")
        moved = moved.select("entity", F.coalesce("hi2", F.lit(False)).alias("hi"), F.coalesce("lo2", F.lit(False)).alias("lo"), F.col("next2").alias("next"))
        rows = settled(rows.where(~undecided).unionByName(moved), "chains")
        reach *= 2
    return rows.where(F.col("lo") | undecided if unfounded else F.col("lo")).select("entity")


def fixpoint(graph, schema: ShapeSchema, part: list[str], valid: dict[str, DataFrame], unfounded: bool = False) -> dict[str, DataFrame]:
    """The least solution of mutually recursive shapes, or the greatest if ``unfounded`` entities are to conform.

    For the least one entities are added until a round adds none, so entities that only support each other stay out;
    for the greatest they are taken away until a round takes none. A round looks only at entities that have a link to
    what the last one added or took; its result is written, so the plan doesn't grow. Each round decides something, so the rounds
    are at most as many as entities; a shape that refers only to itself, along chains, takes the logarithm of that.
    """
    path = _chain(schema[part[0]]) if len(part) == 1 else None
    if path and (chained := _doubled(graph, schema, schema[part[0]], path, valid, unfounded)) is not None:
        return {part[0]: settled(chained, "solution")}
    every = {n: settled(q.domain(graph, schema, schema[n]), "domain") for n in part}
    now = every if unfounded else {n: written(every[n].limit(0), "none") for n in part}
    fresh = None
    while True:
        known, new, moved = valid | now, {}, False
        for n in part:
            shape = schema[n]
            rest = now[n] if unfounded else every[n].join(now[n], "entity", "left_anti")
            if fresh is not None:
                touched = [q.witnesses(graph, shape, leaf, fresh).select("entity") for c in shape.body for leaf, _ in q.leaves(c) if leaf.ref in fresh]
                rest = rest.join(reduce(DataFrame.unionByName, touched).distinct(), "entity", "left_semi")
            seen, holds = Observation(), _fused(graph, schema, shape, known, rest)
            out = rest.join(holds, "entity", "left_anti") if unfounded else holds
            new[n] = written(out.observe(seen, F.count(F.lit(1)).alias("n")), "delta")
            new[n] = new[n] if seen.get["n"] <= SMALL_ROWS else shuffled(new[n])
            moved |= seen.get["n"] > 0
        if not moved:
            return now
        now = {n: settled(now[n].join(new[n], "entity", "left_anti") if unfounded else now[n].unionByName(new[n]), "solution") for n in part}
        fresh = new


#: Bytes that the driver needs for an entity of a broadcast list beside its own: its place in the hash table and its row, with the spare room of
#: tables that double, and their copy that is sent.
HASHED = 240


@dataclass
class _Decided:
    n_valid: int
    n_invalid: int
    #: Bytes of an entity in a broadcast list, on average.
    width: float
    invalid: DataFrame | None = None

    @property
    def share(self) -> float:
        return self.n_valid / max(1, self.n_valid + self.n_invalid)


@dataclass
class _Delivery:
    """Verdicts that became known together: a shape's, or those of the slices of its targets that shared a job."""

    shape: str
    where: Column | None
    valid: DataFrame
    n: int


class _Planned:
    """State of a planned run: what is decided, with counts, and who waits.

    The counts are observed while tables are written. They choose lists, joins and orders, and no verdict depends on them.
    """

    def __init__(self, graph, schema: ShapeSchema, plan: ValidationPlan, rewrite: RewriteConfig, limits: Limits, stats: GraphStats | None = None, adaptive: bool = False, count: bool = False, unfounded: bool = False):
        self.graph, self.schema, self.plan, self.rewrite, self.limits = graph, schema, plan, rewrite, limits
        self.stats, self.adaptive, self.count, self.unfounded = stats, adaptive, count, unfounded
        self.endpoint = Endpoint(limits.answer_cap)
        self.dep = dependency_graph(schema)
        self.loops = {n: p for p in self.dep.components() if self.dep.recursive(p) for n in p}
        self.valid: dict[str, DataFrame] = {}
        self.done: dict[str, _Decided] = {}
        #: Candidates of shapes that wait, and the constraints that are left.
        self.pending: dict[str, tuple[DataFrame, tuple]] = {}
        self.measures: dict[str, dict] = {}
        self.visited: list[str] = []
        self.totals: dict[str, int] = {}

    def run(self) -> Iterator[_Delivery]:
        """Verdicts as they are reached."""
        todo = list(self.plan.order)
        while todo:
            name = self._next(todo)
            todo.remove(name)
            self.visited.append(name)
            shape = self.schema[name]
            if all(r in self.valid for r in shape.refs):
                yield from self._decide(name, shape.body)
            else:
                now = tuple(c for c in shape.body if all(leaf.ref is None or leaf.ref in self.valid for leaf, _ in q.leaves(c)))
                found, self.totals[name] = [], 0
                for where in self._slices(name)[1]:
                    total, pushed = Observation(), Observation()
                    found.append(settled(self._candidates(name, now, self._rows(name, now, total, where), pushed), "pending"))
                    self.totals[name] += total.get["n"]
                    self._seen(name, total, pushed)
                self.pending[name] = reduce(DataFrame.unionByName, found), tuple(c for c in shape.body if c not in now)
            yield from self._wake()

    def _next(self, todo: list[str]) -> str:
        """The next shape of the plan; if replanning, the one that refers to the decided shape with the most invalid entities."""
        if not self.adaptive:
            return todo[0]
        return max(todo, key=lambda n: (max((1 - self.done[r].share for r in self.schema[n].refs if r in self.done), default=0.0), -todo.index(n)))

    def _seen(self, name: str, total: Observation, pushed: Observation) -> None:
        self.measures[name]["prefiltered"] += total.get["n"] - pushed.get["n"]
        self.measures[name]["rows"] += pushed.get["n"]

    def _wake(self) -> Iterator[_Delivery]:
        moved = True
        while moved:
            moved = False
            for name in list(self.pending):
                loop = self.loops.get(name, [name])
                if name not in self.pending:
                    continue
                if all(r in self.valid for r in self.schema[name].refs):
                    start, rest = self.pending.pop(name)
                    yield from self._decide(name, rest, start)
                    moved = True
                elif name in self.loops and all(n in self.pending and all(r in self.valid or r in loop for r in self.schema[n].refs) for n in loop):
                    for n, rows in fixpoint(self.graph, self.schema, loop, self.valid, self.unfounded).items():
                        self.pending.pop(n)
                        self._note(n)
                        yield self._close(n, [self._keep(n, rows)], self.totals[n])
                    moved = True

    def _note(self, name: str) -> dict:
        return self.measures.setdefault(name, {"queries": 0, "prefiltered": 0, "rows": 0, "pushed": [], "slices": 1})

    def _rows(self, name: str, parts: tuple, total: Observation, where: Column | None = None) -> DataFrame:
        """The shape's target query, the whole or a slice, through the endpoint; ``total`` sees its rows."""
        self._note(name)["queries"] += 1
        rows = q.rows_of(self.graph, self.schema, self.schema[name], parts)
        rows = self.endpoint.answer(rows) if where is None else rows.where(where)
        return rows.observe(total, F.count(F.lit(1)).alias("n"))

    def _slices(self, name: str) -> tuple[int, list[Column | None]]:
        """The number of slices, and the conditions of the jobs that fetch them."""
        size = self.limits.slice_rows or self.limits.answer_cap
        if not self.rewrite.slice or size is None:
            return 1, [None]
        rows = q.domain(self.graph, self.schema, self.schema[name])
        n = rows.count()
        return hash_slices(rows, n, min(size, self.limits.answer_cap or size), jobs=self.limits.slice_jobs) if n > size else (1, [None])

    def _decide(self, name: str, parts: tuple, start: DataFrame | None = None) -> Iterator[_Delivery]:
        n, slices = self._slices(name)
        self._note(name)["slices"] = n
        found, all_of = [], 0
        for where in slices:
            total, pushed = Observation(), Observation()
            rows = self._rows(name, parts, total, where)
            if start is not None:
                rows = rows.join(joinable(start), "entity", "left_semi")
            rows = self._candidates(name, parts, rows, pushed if start is None else None)
            kept = self._keep(name, rows)
            all_of += total.get["n"]
            if start is None:
                self._seen(name, total, pushed)
            found.append(kept)
            if len(slices) > 1:
                yield _Delivery(name, where, kept[0], total.get["n"])
        last = self._close(name, found, all_of)
        if len(slices) == 1:
            yield last

    def _keep(self, name: str, rows: DataFrame) -> tuple[DataFrame, int, int]:
        seen = Observation()
        out = written(rows.observe(seen, F.count(F.lit(1)).alias("n"), F.sum(F.octet_length(F.col("entity").cast("string"))).alias("size")), f"valid-{name}")
        return out if seen.get["n"] <= SMALL_ROWS else shuffled(out), seen.get["n"], seen.get["size"] or 0

    def _close(self, name: str, found: list[tuple[DataFrame, int, int]], total: int) -> _Delivery:
        self.valid[name] = found[0][0] if len(found) == 1 else joinable(reduce(DataFrame.unionByName, [f[0] for f in found]))
        n, size = (sum(f[k] for f in found) for k in (1, 2))
        self.done[name] = _Decided(n, total - n, HASHED + size / max(1, n))
        self.measures[name] |= {"n_valid": n, "n_invalid": total - n}
        return _Delivery(name, None, self.valid[name], total)

    def _list(self, shape: Shape, c: Count) -> q.NodeList:
        """What is known of a decided shape, as the list that the configuration asks for."""
        done, closed = self.done[c.ref], self.stats is not None and self.stats.closed(shape.entity_class, c.path)
        mode = choose_list(done.n_valid, done.n_invalid, closed) if self.rewrite.lists == "smaller" else self.rewrite.lists
        if mode == "valid":
            size = int(done.n_valid * done.width)
            return q.NodeList(mode, sized(self.valid[c.ref], size, self.limits), None, done.n_valid, size)
        domain = q.domain(self.graph, self.schema, self.schema[c.ref])
        if done.invalid is None:
            done.invalid = settled(domain.join(joinable(self.valid[c.ref]), "entity", "left_anti"), f"invalid-{c.ref}")
        size = int(done.n_invalid * done.width)
        return q.NodeList(mode, sized(done.invalid, size, self.limits), None if closed else domain, done.n_invalid, size)

    def _push(self, name: str, parts: tuple, rows: DataFrame) -> tuple[DataFrame, set]:
        """Targets cut by the lists of decided shapes, the list with the smallest share of conforming nodes first; constraints that this settles."""
        g, shape, done = self.graph, self.schema[name], set()
        ready = [c for c in parts if can_push(c, set(self.valid))]
        for c in sorted(ready, key=lambda c: self.done[c.ref].share):
            known = self._list(shape, c)
            queries = -(-max(known.n, 1) // self.limits.max_filter_items) if self.rewrite.split else 1
            if queries > self.limits.max_rewritten:
                self.measures[name]["pushed"].append((c.label, "none", known.n, queries))
                continue
            if queries > 1:
                pairs = g.edges(shape.entity_class, c.path)
                pairs = pairs.where(c.test.sql) if c.test else pairs
                linked = split_filter(pairs, known.nodes, known.n, known.mode, self.limits)
                if known.within is not None:
                    linked = linked.join(q.conforming(pairs, q.NodeList("valid", known.within)).select("entity"), "entity", "left_semi")
                rows = rows.join(joinable(linked), "entity", "left_semi")
            else:
                rows = push_filter(g, shape, rows, c, known, self.limits)
            self.measures[name]["pushed"].append((c.label, known.mode, known.n, queries))
            # A split exclusion list may have let through a link that leaves the domain beside one to an excluded node.
            exact = queries == 1 or known.within is None
            if c.n == 1 and exact and (c.test is None or not g.single(shape.entity_class, c.path)):
                done.add(c)
        return rows, done

    def _candidates(self, name: str, parts: tuple, rows: DataFrame, pushed: Observation | None = None) -> DataFrame:
        """Entities that pass the given conjuncts, fewer with each query."""
        g, shape, cls = self.graph, self.schema[name], self.schema[name].entity_class
        m, done = self._note(name), set()
        if self.rewrite.push:
            rows, done = self._push(name, parts, rows)
        if self.count and pushed is not None:
            m["rules"] = m.get("rules", 0) + rules_of(g, shape, rows.select("entity"), {r: self.valid[r] for r in shape.refs if r in self.valid}).first()["n"]
        if pushed is not None:
            rows = rows.observe(pushed, F.count(F.lit(1)).alias("n"))
        rest = [c for c in parts if c not in done]
        if self.rewrite.reorder:
            rest = order_constraints(g, shape, rest, self.stats, {r: d.share for r, d in self.done.items()})
        lists: dict[str, q.NodeList] = {}
        for c in (c for part in rest for c, _ in q.leaves(part) if c.ref in self.valid):
            known = self._list(shape, c)
            # Of several paths to one shape, the list that holds for the widest of them.
            if c.ref not in lists or known.mode == "valid" or known.within is not None:
                lists[c.ref] = known
        keep = rows.columns
        for step in self._steps(shape, rest):
            m["queries"] += 1
            flags = q.Flags(g, self.schema, shape, lists, tuple(step))
            rows = flags.add(rows)
            rows = rows.where(flags.truth()).select(*keep)
        return rows.select("entity")

    def _steps(self, shape: Shape, rest: list) -> list[list]:
        """Constraints that share a query: tests of the entity's own row, those over one path or one child table; all if none is to be skipped."""
        if not self.rewrite.skip:
            return [rest] if rest else []
        by: dict = {}
        probe = q.Flags(self.graph, self.schema, shape, {}, tuple(rest))
        for i, c in enumerate(rest):
            if not isinstance(c, Count):
                key = "one", i
            elif self.graph.single(shape.entity_class, c.path):
                key = ("own", c.path, c.ref) if c.ref else ("own",)
            else:
                key = probe._source(c)
                key = key[:2] if key[0] == "path" else key
            by.setdefault(key, []).append(c)
        return list(by.values())


def interleave(graph, schema: ShapeSchema, config: PlanConfig | int = 5, rewrite: RewriteConfig = RewriteConfig(), limits: Limits = Limits(), **how) -> Iterator[DataFrame]:
    """Verdicts of one shape, or of one slice of its targets, after the other, each as soon as it is decided."""
    run = _Planned(graph, schema, plan_validation(schema, config), rewrite, limits, **how)
    for d in run.run():
        if schema[d.shape].target:
            targets = graph.entities(schema[d.shape].target)
            part = targets if d.where is None else targets.where(d.where)
            yield ValidationResult(schema, run.visited, {d.shape: d.valid}, lambda n, part=part: part).of(d.shape)


#: Engines that decide one shape after the other from counts with targets alone.
BASELINES = {"naive": _naive, "naive_py": _naive_py}


def validate(
    graph, schema: ShapeSchema, engine: str = "planned", config: PlanConfig | int = 5, rewrite: RewriteConfig = RewriteConfig(), limits: Limits = Limits(), *,
    stats: GraphStats | None = None, adaptive: bool = False, count: bool = False, unfounded: str = "false", ordered: bool = False, stop_at_first_invalid: bool = False, traced: bool = False,
) -> ValidationResult:
    """Judge every target of every shape.

    ``fused`` stays lazy for non-recursive schemas unless ``traced``: then each shape is decided for itself, and the trace says when.
    ``naive`` and ``naive_py`` write what conforms to each shape before the next. The baselines have neither logic nor recursion and refuse such schemas.
    ``count``: count grounded rules while running. ``unfounded``: whether entities that only support each other conform (``valid``)
    or not (``false``). ``ordered``: verdicts come sorted.
    """
    plan, dep = plan_validation(schema, config), dependency_graph(schema)
    targets = lambda n: graph.entities(schema[n].target)
    began = time.monotonic()
    if engine == "planned":
        run = _Planned(graph, schema, plan, rewrite, limits, stats, adaptive, count, unfounded == "valid")
        result = ValidationResult(schema, run.visited, run.valid, targets, run.measures, ordered=ordered)
        for d in run.run():
            result.trace.append((d.shape, time.monotonic() - began, d.n))
            if stop_at_first_invalid and run.done.get(d.shape) and run.done[d.shape].n_invalid:
                break
        return result
    if engine == "grounded":
        from shapeplan.execute.grounding import grounded

        return grounded(graph, schema, plan, rewrite.push, targets, ordered)
    parts = decision_order(dep, list(plan.order))
    valid: dict[str, DataFrame] = {}
    result = ValidationResult(schema, [n for p in parts for n in p], valid, targets, ordered=ordered)
    for part in parts:
        shape, loop = schema[part[0]], dep.recursive(part)
        if engine in BASELINES:
            if loop or not shape.target or not all(isinstance(c, Count) for c in shape.body):
                raise UnsupportedFragment(f"{engine} has counts over targets only, not {shape.name}")
            found = BASELINES[engine](graph, schema, shape, valid, Endpoint(limits.answer_cap))
            # One job a shape: in one plan of all shapes their broadcasts would be on the driver together, and its plan grow by each reference.
            valid[shape.name] = settled(found, f"valid-{shape.name}")
        elif engine == "fused":
            valid |= fixpoint(graph, schema, part, valid, unfounded == "valid") if loop else {shape.name: _fused(graph, schema, shape, valid)}
        else:
            raise ValueError(f"no engine {engine}")
        for n in part if traced else ():
            if engine == "fused" and not loop:
                valid[n] = settled(valid[n], f"valid-{n}")
            result.trace.append((n, time.monotonic() - began, targets(n).count() if schema[n].target else 0))
    return result


def explain(graph, schema: ShapeSchema, result: ValidationResult, shape: str) -> DataFrame:
    """``entity``, ``reason``: the first violated constraint of each target that doesn't conform."""
    flags = q.Flags(graph, schema, schema[shape], result.valid)
    rows = flags.frame()
    return rows.where(~flags.truth()).select("entity", flags.reason().alias("reason"))


def cascade(graph, schema: ShapeSchema, result: ValidationResult) -> DataFrame:
    """``shape``, ``entity``, ``depth`` of all that doesn't conform: 0 if a constraint of its own is violated, else one more than the invalid neighbour that is nearest to such a one.

    For schemas without recursion. An entity whose links all lack an invalid end (none, or ends outside the domain) has depth 0.
    """
    depth: dict[str, DataFrame] = {}
    for part in dependency_graph(schema).components():
        if len(part) > 1 or part[0] in schema[part[0]].refs:
            raise UnsupportedFragment("depths are defined without recursion only")
        shape = schema[part[0]]
        own = tuple(c for c in shape.body if not any(leaf.ref for leaf, _ in q.leaves(c)))
        flags = q.Flags(graph, schema, shape, {}, own)
        bad = q.domain(graph, schema, shape).join(result.valid[shape.name], "entity", "left_anti")
        rows = flags.frame(bad).select("entity", (~flags.truth()).alias("own"))
        links = [graph.edges(shape.entity_class, leaf.path).join(
            depth[leaf.ref].select(F.col("entity").alias("value"), "depth"), "value",
        ).select("entity", "depth") for c in shape.body for leaf, _ in q.leaves(c) if leaf.ref]
        if links:
            near = reduce(DataFrame.unionByName, links).groupBy("entity").agg(F.min("depth").alias("near"))
            rows = rows.join(near, "entity", "left")
        else:
            rows = rows.withColumn("near", F.lit(None).cast("int"))
        rows = rows.select("entity", F.when(F.col("own") | F.col("near").isNull(), 0).otherwise(F.col("near") + 1).cast("int").alias("depth"))
        depth[shape.name] = written(rows, "depth")
    named = [d.select(F.lit(n).alias("shape"), F.col("entity").cast("string").alias("entity"), "depth") for n, d in depth.items() if schema[n].target]
    return reduce(DataFrame.unionByName, named)
