"""Work measures: grounded rules in closed form, retrieved and pre-filtered entities, checks."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from shapeplan.model import Shape, ShapeSchema
from shapeplan.operators import compile as q
from shapeplan.operators.rewrite import can_push


def choose(k: Column, n: int) -> Column:
    """Binomial coefficient of a column and a small number."""
    out = F.lit(1.0)
    for i in range(n):
        out = out * F.greatest(k - i, F.lit(0)) / (i + 1)
    return out


def rules_of(graph, shape: Shape, rows: DataFrame, known: dict[str, DataFrame]) -> DataFrame:
    """``n``: rules that the given targets ground: one each, the product of the minima's choices, and each maximum's.

    Witnesses of a decided reference must conform to it. Combinations are counted, never made.
    """
    terms: dict[str, list[Column]] = {"min": [], "max": []}
    for k, c in enumerate(shape.counts(), 1):
        per = q.witnesses(graph, shape, c, known).groupBy("entity").agg(F.count(F.lit(1)).alias(f"k{k}"))
        rows = rows.join(per, "entity", "left")
        n = F.coalesce(F.col(f"k{k}"), F.lit(0)).cast("double")
        terms[c.kind].append(choose(n, c.n + (c.kind == "max")))
    product = reduce(lambda a, b: a * b, terms["min"]) if terms["min"] else F.lit(0.0)
    return rows.select(reduce(lambda a, b: a + b, terms["max"], F.lit(1.0) + product).alias("n")).agg(F.coalesce(F.sum("n"), F.lit(0.0)).alias("n"))


def count_rules(graph, schema: ShapeSchema, order: list[str] | None = None, valid: dict[str, DataFrame] | None = None, push: bool = True) -> DataFrame:
    """``n_rules`` of a whole schema.

    Without ``order`` the naive count. With it, shapes come in that order and witnesses must conform to decided shapes, as
    rules with a false atom aren't grounded; with ``push`` targets are first cut by the valid lists of decided shapes.
    """
    parts, decided = [], set()
    for name in order or schema.names:
        shape = schema[name]
        known = {r: valid[r] for r in decided} if order else {}
        rows = graph.entities(shape.target)
        for c in shape.counts() if push else ():
            if can_push(c, set(known)):
                rows = rows.join(q.witnesses(graph, shape, c, known).select("entity").distinct(), "entity", "left_semi")
        parts.append(rules_of(graph, shape, rows, known))
        decided.add(name)
    return reduce(DataFrame.unionByName, parts).agg(F.sum("n").alias("n_rules"))


def retrieved(graph, schema: ShapeSchema) -> DataFrame:
    """By shape the distinct entities that its target and constraint queries return."""
    out = []
    for s in schema.shapes:
        rows = graph.entities(s.target).select(F.col("entity").cast("string").alias("e"))
        for c in s.counts():
            if c.ref:
                rows = rows.unionByName(q.witnesses(graph, s, c).select(F.concat(F.lit(f"{c.ref}/"), F.col("value").cast("string")).alias("e")))
        out.append(rows.agg(F.count_distinct("e").alias("n_retrieved")).select(F.lit(s.name).alias("shape"), "n_retrieved"))
    return reduce(DataFrame.unionByName, out)


def prefiltered(graph, schema: ShapeSchema, shape: str, path: str, valid: DataFrame) -> DataFrame:
    """Targets without a link over ``path`` to a conforming node: what a pushed valid list drops."""
    s = schema[shape]
    linked = graph.edges(s.entity_class, path).join(valid.select(F.col("entity").alias("value")), "value", "left_semi").select("entity")
    return graph.entities(s.target).join(linked, "entity", "left_anti").agg(F.count(F.lit(1)).alias("n_prefiltered"))


def checks(graph, schema: ShapeSchema) -> DataFrame:
    """``kind`` (inter, intra), ``n_constraints`` and the average number of checks of a constraint of that kind.

    A check is a pair of an entity and a candidate witness, or an entity without candidates.
    """
    out = []
    for s in schema.shapes:
        for k, c in enumerate(s.counts(), 1):
            per = q.witnesses(graph, s, c).groupBy("entity").agg(F.count(F.lit(1)).alias("n"))
            n = graph.entities(s.target).join(per, "entity", "left").agg(F.coalesce(F.sum(F.greatest(F.coalesce("n", F.lit(0)), F.lit(1))), F.lit(0)).alias("n"))
            out.append(n.select(F.lit("inter" if c.ref else "intra").alias("kind"), "n"))
    return reduce(DataFrame.unionByName, out).groupBy("kind").agg(F.count(F.lit(1)).alias("n_constraints"), F.avg("n").alias("avg_checks"))


def invalid_pct(verdicts: DataFrame) -> DataFrame:
    v = verdicts.agg(F.count(F.lit(1)).alias("n_entities"), F.count_if("valid").alias("n_valid"))
    return v.withColumn("invalid_pct", F.round(100.0 * (F.col("n_entities") - F.col("n_valid")) / F.col("n_entities"), 2))
