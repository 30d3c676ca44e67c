"""The dependency graph of a schema: signed edges, degrees, fragments, strata."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from shapeplan.model import Not, Or, ShapeSchema, UnsupportedFragment
from shapeplan.model.ast import leaves, references


@dataclass(frozen=True)
class DepGraph:
    schema: ShapeSchema
    #: (referrer, referred, sign): True if the reference is monotone.
    edges: frozenset[tuple[str, str, bool]]

    @property
    def names(self) -> list[str]:
        return self.schema.names

    def out(self, name: str) -> list[str]:
        return sorted({b for a, b, _ in self.edges if a == name})

    def into(self, name: str) -> list[str]:
        return sorted({a for a, b, _ in self.edges if b == name})

    def neighbours(self, name: str) -> list[str]:
        """Either way, by name; in declaration order if the schema asks for that."""
        both = {*self.out(name), *self.into(name)} - {name}
        return [n for n in self.names if n in both] if self.schema.options.get("neighbours") == "declared" else sorted(both)

    def components(self) -> list[list[str]]:
        """Strongly connected components, referred before referring."""
        index, low, stack, on, out = {}, {}, [], set(), []

        def visit(v: str) -> None:
            index[v] = low[v] = len(index)
            stack.append(v)
            on.add(v)
            for w in self.out(v):
                if w not in index:
                    visit(w)
                    low[v] = min(low[v], low[w])
                elif w in on:
                    low[v] = min(low[v], index[w])
            if low[v] == index[v]:
                part = []
                while True:
                    w = stack.pop()
                    on.discard(w)
                    part.append(w)
                    if w == v:
                        break
                out.append(sorted(part))

        for v in self.names:
            if v not in index:
                visit(v)
        return out

    def recursive(self, part: list[str]) -> bool:
        return len(part) > 1 or part[0] in self.out(part[0])


def dependency_graph(schema: ShapeSchema) -> DepGraph:
    return DepGraph(schema, frozenset((s.name, t, sign) for s in schema.shapes for c in s.body for t, sign in references(c)))


def dependencies(spark: SparkSession, schema: ShapeSchema) -> DataFrame:
    """``src``, ``dst``, ``path``, ``kind``, ``n`` of each reference."""
    rows = [(s.name, leaf.ref, leaf.path, leaf.kind, leaf.n) for s in schema.shapes for c in s.body for leaf, _ in leaves(c) if leaf.ref]
    return spark.createDataFrame(rows, "src string, dst string, path string, kind string, n long")


def degrees(spark: SparkSession, schema: ShapeSchema) -> DataFrame:
    g = dependency_graph(schema)
    rows = [(s.name, len(g.into(s.name)), len(g.out(s.name)), s.n_constraints, s.target is not None) for s in schema.shapes]
    return spark.createDataFrame(rows, "shape string, in_deg long, out_deg long, n_constraints long, has_target boolean")


def classify(schema: ShapeSchema) -> str:
    """``non-recursive``, ``positive`` (recursion without negation, disjunction allowed), ``stratified``, else an error."""
    g = dependency_graph(schema)
    loops = [p for p in g.components() if g.recursive(p)]
    if not loops:
        return "non-recursive"
    for part in loops:
        if any(a in part and b in part and not sign for a, b, sign in g.edges):
            raise UnsupportedFragment(f"negation through the recursion of {part}")
    negated = any(not sign for _, _, sign in g.edges) or any(_has(c, Not) for s in schema.shapes for c in s.body)
    return "stratified" if negated else "positive"


def _has(c, kind) -> bool:
    return isinstance(c, kind) or any(_has(p, kind) for p in getattr(c, "parts", ()) or ((c.part,) if isinstance(c, Not) else ()))


def has_disjunction(schema: ShapeSchema) -> bool:
    return any(_has(c, Or) for s in schema.shapes for c in s.body)


def strata(schema: ShapeSchema) -> dict[str, int]:
    """Levels such that a negative reference points to a lower one and a positive one never to a higher."""
    classify(schema)
    g, level = dependency_graph(schema), {}
    for part in g.components():
        own = [level[b] + (not sign) for a, b, sign in g.edges if a in part and b not in part]
        level |= dict.fromkeys(part, max(own, default=0))
    return level
