"""Grounding and saturation, interleaved shape by shape.

A rule is a conjunction of atoms, each a node and a shape that it must conform to, and speaks for an entity (``min``: one choice of
witnesses for all minima) or against it (``max``: witnesses beyond a maximum). Atoms that are known true when the rule is
grounded are left out of it, and choices with one that is known false aren't grounded at all. Saturation takes the atoms that were decided last,
strikes them from the open rules and drops rules with a false one. A rule without atoms left fires. An entity conforms once a
rule for it has fired and none against it is open or has; it doesn't once a rule against it has fired or none for it is
left. Newly decided entities are the next round's atoms, until a round decides nothing.

Every rule is a row, as many as the baseline makes, so this is the engine for small graphs, where the rules
themselves are wanted. Entities that are undecided at the end only support each other, and don't conform.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shapeplan.model import Count, Shape, ShapeSchema, UnsupportedFragment
from shapeplan.operators import compile as q
from shapeplan.operators.rewrite import can_push, push_filter
from shapeplan.plans.order import ValidationPlan
from shapeplan.runtime import written

RULE = "shape string, entity string, kind string, body array<struct<shape:string,node:string>>"


def ground(graph, shape: Shape, targets: DataFrame, known: dict[str, DataFrame]) -> DataFrame:
    """The rules of the given targets, a row each: ``shape``, ``entity``, ``kind``, ``body``.

    A target without minima is a rule for itself; with minima its own rule is implied by theirs and has no row.
    """

    def rules(rows: DataFrame, kind: str, refs: list[tuple[str, str]]) -> DataFrame:
        atoms = [F.struct(F.lit(ref).alias("shape"), F.col(col).cast("string").alias("node")) for col, ref in refs if ref not in known]
        body = F.array(*atoms) if atoms else F.array().cast("array<struct<shape:string,node:string>>")
        out = rows.join(targets, "entity", "left_semi")
        return out.select(F.lit(shape.name).alias("shape"), F.col("entity").cast("string").alias("entity"), F.lit(kind).alias("kind"), body.alias("body"))

    mins = [(f"m{k}_{i}", c.ref) for k, c in enumerate(shape.counts("min"), 1) if c.ref for i in range(1, c.n + 1)]
    out = rules(q.min_query(graph, shape, known), "min", mins)
    for c in shape.counts("max"):
        out = out.unionByName(rules(q.max_query(graph, shape, c, known), "max", [(f"x{i}", c.ref) for i in range(1, c.n + 2)] if c.ref else []))
    return out


def strike(rules: DataFrame, atoms: DataFrame) -> DataFrame:
    """Open rules after ``atoms`` (``shape``, ``node``, ``value``) were decided: true ones are gone from bodies, rules with a false one are gone."""
    keyed = rules.withColumn("rule", F.monotonically_increasing_id())
    keyed = written(keyed, "rules")
    at = keyed.select("rule", F.explode("body").alias("atom")).select("rule", F.col("atom.shape").alias("shape"), F.col("atom.node").alias("node"))
    hit = at.join(atoms, ["shape", "node"]).groupBy("rule").agg(F.bool_and("value").alias("alive"), F.collect_set(F.struct("shape", "node")).alias("known"))
    out = keyed.join(hit, "rule", "left").where(F.coalesce("alive", F.lit(True)))
    body = F.when(F.col("known").isNull(), F.col("body")).otherwise(F.filter("body", lambda a: ~F.array_contains("known", a)))
    return out.select("shape", "entity", "kind", body.alias("body"))


def settled(heads: DataFrame, rules: DataFrame) -> DataFrame:
    """``shape``, ``entity``, ``value`` of the undecided entities that the open rules decide."""
    fired = F.size("body") == 0
    per = rules.groupBy("shape", "entity").agg(
        F.count_if(F.col("kind") == "min").alias("fors"), F.count_if((F.col("kind") == "min") & fired).alias("fired"),
        F.count_if(F.col("kind") == "max").alias("againsts"), F.count_if((F.col("kind") == "max") & fired).alias("broken"),
    )
    at = heads.join(per, ["shape", "entity"], "left").na.fill(0)
    value = F.when((F.col("broken") > 0) | (F.col("fors") == 0), F.lit(False)).when((F.col("fired") > 0) & (F.col("againsts") == 0), F.lit(True))
    return at.select("shape", "entity", value.alias("value")).where("value is not null")


def grounded(graph, schema: ShapeSchema, plan: ValidationPlan, push: bool, targets: Callable[[str], DataFrame], ordered: bool = False):
    from shapeplan.execute.engines import ValidationResult

    spark = None
    began, valid, kinds, native = time.monotonic(), {}, {}, {}
    result = ValidationResult(schema, [], valid, targets, ordered=ordered)
    heads = rules = decided = None
    n_heads: dict[str, int] = {}
    todo = list(plan.order)

    def saturate(rules: DataFrame, heads: DataFrame, decided: DataFrame, fresh: DataFrame | None):
        while True:
            if fresh is not None:
                rules = written(strike(rules, fresh.select("shape", F.col("entity").alias("node"), "value")), "rules")
            fresh = written(settled(heads, rules), "atoms")
            if fresh.isEmpty():
                return rules, heads, decided
            decided = written(decided.unionByName(fresh), "decided")
            heads = written(heads.join(fresh, ["shape", "entity"], "left_anti"), "heads")
            rules = rules.join(fresh.select("shape", "entity"), ["shape", "entity"], "left_anti")

    def close(rest: set[str]) -> None:
        """Shapes of which no entity is undecided are known from now on."""
        left = {r.shape for r in heads.select("shape").distinct().collect()}
        for n in list(rest - left):
            out = decided.where((F.col("shape") == n) & F.col("value")).select(F.col("entity").cast(kinds[n]).alias("entity"))
            valid[n] = written(out, f"valid-{n}")
            result.order.append(n)
            result.trace.append((n, time.monotonic() - began, n_heads[n]))
            rest.discard(n)

    waiting: set[str] = set()
    for name in todo:
        shape = schema[name]
        if not shape.target or not all(isinstance(c, Count) for c in shape.body):
            raise UnsupportedFragment(f"rules are grounded for counts over targets only, not for {name}")
        own = graph.entities(shape.target)
        spark, kinds[name] = own.sparkSession, dict(own.dtypes)["entity"]
        known = {r: valid[r] for r in shape.refs if r in valid}
        rows = own
        for c in shape.counts() if push else ():
            if can_push(c, set(known)):
                rows = push_filter(graph, shape, rows, c, known[c.ref]).select("entity")
        rows = written(rows, "targets")
        new = written(ground(graph, shape, rows, known), "grounded")
        n_heads[name], n_rows = own.count(), rows.count()
        fors = new if any(c.n for c in shape.counts("min")) or shape.counts("min") else new.where("kind = 'max'")
        result.measures[name] = {"prefiltered": n_heads[name] - n_rows, "rules": n_rows + fors.count()}
        head = own.select(F.lit(name).alias("shape"), F.col("entity").cast("string").alias("entity"))
        if heads is None:
            heads, rules, decided = head, new, spark.createDataFrame([], "shape string, entity string, value boolean")
            fresh = None
        else:
            # Atoms that were decided before, though their shape isn't as a whole.
            fresh, heads, rules = decided, heads.unionByName(head), rules.unionByName(new)
        waiting.add(name)
        rules, heads, decided = saturate(rules, written(heads, "heads"), decided, fresh)
        close(waiting)
    # No rule will ever speak for nodes outside all heads.
    at = rules.select(F.explode("body").alias("a")).select(F.col("a.shape").alias("shape"), F.col("a.node").alias("entity")).distinct()
    bare = F.col("shape").isin([s.name for s in schema.shapes if s.accepts_bare])
    lone = at.join(heads.unionByName(decided.select("shape", "entity")), ["shape", "entity"], "left_anti").withColumn("value", bare)
    rules, heads, decided = saturate(rules, heads, decided, written(lone, "lone"))
    decided = written(decided.unionByName(heads.withColumn("value", F.lit(False))), "decided")
    heads = heads.limit(0)
    close(waiting)
    return result


def n_rules(result) -> int:
    """Rules that a run grounded, over all shapes."""
    return int(reduce(lambda a, m: a + m["rules"], result.measures.values(), 0))
