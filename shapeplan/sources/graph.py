"""Graph sources: wide class tables, the default, and triples partitioned by predicate."""

from __future__ import annotations

from collections.abc import Callable
from functools import cache, reduce
from typing import Protocol

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shapeplan.runtime import joinable, table
from shapeplan.sources.mapping import ClassMap, Mapping, corrupted, default_mapping


class GraphSource(Protocol):
    def entities(self, cls: str) -> DataFrame:
        """``entity`` of every instance of a class, once."""

    def frame(self, cls: str, predicates: list[str]) -> DataFrame:
        """``entity`` and the named single-valued predicates as columns."""

    def single(self, cls: str, path: str) -> bool:
        """Whether a path is one predicate that an entity has once at most."""

    def edges(self, cls: str, path: str) -> DataFrame:
        """Pairs ``entity``, ``value`` over a path; not null, may repeat."""


class _Paths:
    """Paths over single steps: sequences ``a/b``, alternatives ``a|b``, inverses ``^a``."""

    def edges(self, cls: str, path: str) -> DataFrame:
        if "|" in path:
            return reduce(DataFrame.unionByName, [self.edges(cls, p) for p in path.split("|")])
        first, *rest = path.split("/")
        out, at = self.step(cls, first), self.range_of(first)
        for p in rest:
            nxt = self.step(at, p).select(F.col("entity").alias("value"), F.col("value").alias("next"))
            # Intermediate pairs are a set, so that fan-outs don't multiply repeats.
            out = out.join(nxt, "value").select("entity", F.col("next").alias("value"))
            at = self.range_of(p)
        return out


class ClassTableSource(_Paths):
    """One row an entity for single-valued predicates, child tables for the others; keys stay native."""

    def __init__(self, read: Callable[[str], DataFrame], mapping: Mapping):
        self.read, self.mapping = read, mapping

    def _class(self, cls: str) -> ClassMap:
        return self.mapping.classes[cls]

    def entities(self, cls: str) -> DataFrame:
        c = self._class(cls)
        out = self.read(c.table).select(F.expr(c.key).alias("entity")).where("entity IS NOT NULL")
        return out.distinct() if c.distinct else out

    def frame(self, cls: str, predicates: list[str]) -> DataFrame:
        c = self._class(cls)
        out = self.read(c.table).select(F.expr(c.key).alias("entity"), *[F.expr(c.single[p]).alias(p) for p in predicates]).where("entity IS NOT NULL")
        return out.distinct() if c.distinct else out

    def single(self, cls: str, path: str) -> bool:
        return path in self._class(cls).single

    def range_of(self, predicate: str) -> str | None:
        return self.mapping.links.get(predicate)

    def step(self, cls: str, predicate: str) -> DataFrame:
        c = self._class(cls)
        if predicate in c.single:
            return self.frame(cls, [predicate]).select("entity", F.col(predicate).alias("value")).where("value IS NOT NULL")
        e = c.multi[predicate]
        rows = self.read(e.table) if e.where is None else self.read(e.table).where(e.where)
        return rows.select(F.expr(e.entity).alias("entity"), F.expr(e.value).alias("value")).where("value IS NOT NULL AND entity IS NOT NULL")

    def base(self, cls: str, predicate: str):
        """Where a multi-valued predicate comes from, so that several can be counted in one pass."""
        return self._class(cls).multi.get(predicate)

    def triples(self, classes: list[str] | None = None) -> DataFrame:
        """The long form: ``s``, ``p``, ``o`` (kind, iri, lex, dt), as a set.

        Rows are dealt out by entity before they become triples, so each row of a table is shuffled once and no triple is. Repeats are dropped
        from the rows, then from an entity's values of a predicate, so no triple is hashed or sorted either.
        """
        none = F.lit(None).cast("string")
        iri = lambda cls, c: F.concat(F.lit(f"{cls}/"), c.cast("string"))
        node = lambda name: F.struct(F.lit("iri").alias("kind"), name.alias("iri"), none.alias("lex"), none.alias("dt"))
        direct = {p for c in self.mapping.classes.values() for p in (*c.single, *c.multi) if not p.startswith("^")}
        parts = []
        for cls in dict.fromkeys(classes or self.mapping.classes):
            c = self._class(cls)
            # Predicates by the table, key and condition that their values come from; the triples of two sources differ in predicate.
            sources: dict[tuple, dict[str, str]] = {(c.table, c.key, None, None): dict(c.single)}
            for p, e in c.multi.items():
                if not p.startswith("^"):
                    sources.setdefault((e.table, e.entity, e.where, p if " OVER " in e.value else None), {})[p] = e.value
                elif p[1:] not in direct:
                    # A derived inverse: turns are the only entities at the far end of one.
                    pairs = self.step(cls, p).distinct()
                    parts.append(pairs.select(iri("Turn", F.col("value")).alias("s"), F.lit(p[1:]).alias("p"), node(iri(cls, F.col("entity"))).alias("o")))
            for k, ((name, key, where, _), values) in enumerate(sources.items()):
                rows = self.read(name) if where is None else self.read(name).where(where)
                rows = rows.select(F.expr(key).alias("entity"), *[F.expr(v).alias(f"v{i}") for i, v in enumerate(values.values())]).where("entity IS NOT NULL").repartition("entity")
                kinds = [rows.schema[f"v{i}"].dataType.simpleString() for i in range(len(values))]
                rows = rows.select("entity", *[F.col(f"v{i}").cast("string").alias(f"v{i}") for i in range(len(values))]).distinct()
                said = lambda p, to, dt, vs: F.struct(F.lit(p).alias("p"), F.lit(to).cast("string").alias("to"), F.lit(dt).cast("string").alias("dt"), vs.alias("vs"))
                each = [said("type", "", None, F.array(F.lit(cls)))] if not k else []
                if len(values) > 1 or values and each:
                    rows = rows.groupBy("entity").agg(F.collect_list(F.struct(*[f"v{i}" for i in range(len(values))])).alias("rows"))
                    held = [F.array_distinct(F.col("rows")[f"v{i}"]) for i in range(len(values))]
                else:
                    held = [F.array(f"v{i}") for i in range(len(values))]
                for p, dt, vs in zip(values, kinds, held):
                    to = self.range_of(p)
                    each.append(said(p, to and f"{to}/", None if to else dt, vs))
                pairs = rows.select("entity", F.explode(F.array(*each)).alias("t")).select("entity", "t.p", "t.to", "t.dt", F.explode("t.vs").alias("v")).where("v IS NOT NULL")
                linked = F.col("to").isNotNull()
                o = F.struct(F.when(linked, "iri").otherwise("literal").alias("kind"), F.concat("to", "v").alias("iri"), F.when(~linked, F.col("v")).alias("lex"), F.col("dt"))
                parts.append(pairs.select(iri(cls, F.col("entity")).alias("s"), "p", o.alias("o")))
        return reduce(DataFrame.unionByName, parts)


class TripleSource(_Paths):
    """Triples ``s``, ``p``, ``o``; every predicate may have many values."""

    def __init__(self, triples: DataFrame, links: dict[str, str] | None = None):
        self.triples, self.links = triples, links or {}

    def entities(self, cls: str) -> DataFrame:
        return self.triples.where((F.col("p") == "type") & (F.col("o.iri") == cls)).select(F.col("s").alias("entity")).distinct()

    def frame(self, cls: str, predicates: list[str]) -> DataFrame:
        return self.entities(cls)

    def single(self, cls: str, path: str) -> bool:
        return False

    def base(self, cls: str, predicate: str):
        return None

    def range_of(self, predicate: str) -> str | None:
        return self.links.get(predicate)

    def step(self, cls: str, predicate: str) -> DataFrame:
        node = F.coalesce("o.iri", "o.lex")
        if predicate.startswith("^"):
            return self.triples.where(F.col("p") == predicate[1:]).select(node.alias("entity"), F.col("s").alias("value")).distinct()
        return self.triples.where(F.col("p") == predicate).select(F.col("s").alias("entity"), node.alias("value")).distinct()


def class_tables(spark: SparkSession, sf_dir: str, mapping: Mapping | None = None) -> ClassTableSource:
    return ClassTableSource(cache(lambda name: joinable(table(spark, sf_dir, name))), mapping or default_mapping())


def corrupt(graph: ClassTableSource, level: str, wide: bool = False) -> ClassTableSource:
    return ClassTableSource(graph.read, corrupted(graph.mapping, level, wide))
