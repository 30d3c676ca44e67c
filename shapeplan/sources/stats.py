"""Statistics of a graph, and of a graph under a schema."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce
from typing import NamedTuple

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shapeplan.model import ShapeSchema
from shapeplan.model.ast import leaves


class PathStats(NamedTuple):
    n: int
    n_subjects: int
    most: int
    #: Links whose end is no entity of the class that a reference over the path is about; None if there is no such reference.
    dangling: int | None


@dataclass(frozen=True)
class GraphStats:
    """What the planner knows of a graph under a schema: a row for each class and path, on the driver."""

    classes: dict[str, int]
    paths: dict[tuple[str, str], PathStats] = field(hash=False)

    def entities(self, cls: str) -> int:
        return self.classes.get(cls, 0)

    def path(self, cls: str, path: str) -> PathStats | None:
        return self.paths.get((cls, path))

    def closed(self, cls: str, path: str) -> bool:
        """Whether every link over the path ends in the referred shape's class."""
        known = self.path(cls, path)
        return known is not None and known.dangling == 0


def graph_stats(graph, schema: ShapeSchema) -> GraphStats:
    """One job; the result has a row for each class and path of the schema, whatever the size of the graph."""
    rows = [d.select(
        F.lit(c).alias("cls"), F.lit(None).cast("string").alias("path"), F.col("n_entities").alias("n"),
        *[F.lit(None).cast("long").alias(x) for x in ("subjects", "most", "dangling")],
    ) for c in schema_classes(schema) for d in [class_stats(graph, [c])]]
    ends: dict[tuple[str, str], str | None] = {}
    for s in schema.shapes:
        for leaf, _ in (x for c in s.body for x in leaves(c)):
            to = schema[leaf.ref].entity_class if leaf.ref else None
            ends[s.entity_class, leaf.path] = ends.get((s.entity_class, leaf.path)) or to
    for (cls, path), to in ends.items():
        if cls is None:
            continue
        per = graph.edges(cls, path).distinct()
        if to:
            per = per.join(graph.entities(to).select(F.col("entity").alias("value"), F.lit(0).alias("out")), "value", "left")
        out = F.sum(F.coalesce("out", F.lit(1))) if to else F.lit(None)
        one = per.groupBy("entity").agg(F.count(F.lit(1)).alias("k"), out.cast("long").alias("d")).agg(
            F.coalesce(F.sum("k"), F.lit(0)).alias("n"), F.count(F.lit(1)).alias("subjects"), F.coalesce(F.max("k"), F.lit(0)).alias("most"),
            F.sum("d").alias("dangling"),
        )
        none = F.coalesce("dangling", F.lit(0)) if to else F.col("dangling")
        rows.append(one.select(F.lit(cls).alias("cls"), F.lit(path).alias("path"), "n", "subjects", "most", none.cast("long").alias("dangling")))
    found = reduce(DataFrame.unionByName, rows).collect()
    return GraphStats({r.cls: r.n for r in found if r.path is None}, {(r.cls, r.path): PathStats(r.n, r.subjects, r.most, r.dangling) for r in found if r.path is not None})


def class_stats(graph, classes: list[str]) -> DataFrame:
    """``cls``, ``n_entities``; column pruning leaves keys only."""
    return reduce(DataFrame.unionByName, [graph.entities(c).agg(F.count(F.lit(1)).alias("n_entities")).select(F.lit(c).alias("cls"), "n_entities") for c in classes])


def predicate_stats(graph, cls: str, paths: list[str]) -> DataFrame:
    """``path``, pairs, subjects, objects and the largest number of values of a subject; one aggregation a path."""

    def one(path: str) -> DataFrame:
        per = graph.edges(cls, path).distinct().groupBy("entity").agg(F.count(F.lit(1)).alias("k"))
        objects = graph.edges(cls, path).agg(F.count_distinct("value").alias("n_objects"))
        return per.agg(
            F.coalesce(F.sum("k"), F.lit(0)).alias("n"), F.count(F.lit(1)).alias("n_subjects"), F.coalesce(F.max("k"), F.lit(0)).alias("max_per_subject"),
        ).crossJoin(F.broadcast(objects)).select(F.lit(path).alias("path"), "n", "n_subjects", "n_objects", "max_per_subject")

    return reduce(DataFrame.unionByName, map(one, paths))


def graph_size(triples: DataFrame) -> DataFrame:
    return triples.agg(F.count(F.lit(1)).alias("n_triples"), F.count_distinct("s").alias("n_subjects"))


def schema_classes(schema: ShapeSchema) -> list[str]:
    return list(dict.fromkeys(s.entity_class for s in schema.shapes if s.entity_class))
