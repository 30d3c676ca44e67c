"""Schemas as DuckDB SQL, written independently of the engines: one table of conforming entities a shape."""

from __future__ import annotations

from shapeplan.model import And, Count, Not, Shape, ShapeSchema
from shapeplan.plans.depgraph import dependency_graph
from shapeplan.sources.mapping import Mapping


def entities(m: Mapping, cls: str) -> str:
    c = m.classes[cls]
    return f"(SELECT DISTINCT {c.key} AS entity FROM {c.table} WHERE ({c.key}) IS NOT NULL)"


def _step(m: Mapping, cls: str, p: str) -> str:
    c = m.classes[cls]
    if p in c.single:
        return f"(SELECT {c.key} AS entity, {c.single[p]} AS value FROM {c.table})"
    e = c.multi[p]
    return f"(SELECT {e.entity} AS entity, {e.value} AS value FROM {e.table}" + (f" WHERE {e.where}" if e.where else "") + ")"


def edges(m: Mapping, cls: str, path: str) -> str:
    if "|" in path:
        return "(" + " UNION ".join(f"SELECT * FROM {edges(m, cls, p)}" for p in path.split("|")) + ")"
    first, *rest = path.split("/")
    out, at = _step(m, cls, first), m.links.get(first)
    for p in rest:
        out = f"(SELECT a.entity, b.value FROM {out} a JOIN {_step(m, at, p)} b ON a.value = b.entity)"
        at = m.links.get(p)
    return out


def witnesses(m: Mapping, s: Shape, c: Count, judged: bool = True) -> str:
    where = ["value IS NOT NULL", "entity IS NOT NULL"]
    if c.test:
        where.append(f"({c.test.sql})")
    if c.ref and judged:
        where.append(f"value IN (SELECT entity FROM valid_{c.ref})")
    return f"(SELECT DISTINCT entity, value FROM {edges(m, s.entity_class, c.path)} WHERE {' AND '.join(where)})"


def _holds(m: Mapping, s: Shape, c) -> str:
    if isinstance(c, Count):
        bound = c.n if c.kind == "min" else c.n + 1
        some = f"entity IN (SELECT entity FROM {witnesses(m, s, c)} GROUP BY entity HAVING count(*) >= {bound})" if bound else "TRUE"
        return f"({some})" if c.kind == "min" else f"(NOT {some})"
    if isinstance(c, Not):
        return f"(NOT {_holds(m, s, c.part)})"
    return "(" + (" AND " if isinstance(c, And) else " OR ").join(_holds(m, s, p) for p in c.parts) + ")"


def valid_ctes(m: Mapping, schema: ShapeSchema, upto: str | None = None) -> str:
    """``WITH`` clause of the tables ``valid_<shape>``, referred shapes first."""
    names = [n for part in dependency_graph(schema).components() for n in part]
    if upto:
        need, todo = set(), [upto]
        while todo:
            n = todo.pop()
            if n not in need:
                need.add(n)
                todo += schema[n].refs
        names = [n for n in names if n in need]
    body = ",\n".join(f"valid_{n} AS MATERIALIZED (SELECT entity FROM {entities(
        m, schema[n].entity_class,
    )} WHERE " + (" AND ".join(_holds(m, schema[n], c) for c in schema[n].body) or "TRUE") + ")" for n in names)
    return f"WITH {body}"


def verdicts(m: Mapping, schema: ShapeSchema, only: str | None = None) -> str:
    named = [s.name for s in schema.shapes if s.target and only in (None, s.name)]
    parts = [f"SELECT '{n}' AS shape, CAST(entity AS VARCHAR) AS entity, entity IN (SELECT entity FROM valid_{n}) AS valid FROM {entities(m, schema[n].target)}" for n in named]
    return valid_ctes(m, schema, only) + "\n" + "\nUNION ALL ".join(parts)


def summary(m: Mapping, schema: ShapeSchema) -> str:
    return f"SELECT shape, bool_and(valid) AS all_valid, count(*) FILTER (WHERE valid) AS n_valid, count(*) FILTER (WHERE NOT valid) AS n_invalid FROM ({verdicts(
        m, schema,
    )}) GROUP BY shape"


def _subsets(pairs: str, n: int, stem: str) -> tuple[str, list[str]]:
    """All ``n``-subsets of the values of each entity, and their columns."""
    cols = [f"{stem}{i}" for i in range(1, n + 1)]
    froms = " JOIN ".join(f"{pairs} p{i}" + (f" ON p{i}.entity = p1.entity AND p{i - 1}.value < p{i}.value" if i > 1 else "") for i in range(1, n + 1))
    return f"(SELECT p1.entity, {', '.join(f'p{i}.value AS {c}' for i, c in enumerate(cols, 1))} FROM {froms})", cols


def capped(m: Mapping, schema: ShapeSchema, cap: int) -> str:
    """Verdicts of the naive evaluation where every answer is sorted and ends after ``cap`` rows."""
    ctes = []
    for n in (n for part in dependency_graph(schema).components() for n in part):
        s = schema[n]
        cols, froms, good = [], f"{entities(m, s.target)} t", []
        for k, c in enumerate(s.counts("min"), 1):
            if c.n:
                rows, own = _subsets(witnesses(m, s, c, False), c.n, f"m{k}_")
                froms += f" JOIN {rows} j{k} ON j{k}.entity = t.entity"
                cols += own
                good += [f"{x} IN (SELECT entity FROM seen_{c.ref})" for x in own if c.ref]
        answer = f"(SELECT {', '.join(['t.entity', *cols])} FROM {froms} ORDER BY ALL LIMIT {cap})"
        bad = ""
        for c in s.counts("max"):
            rows, own = _subsets(witnesses(m, s, c, False), c.n + 1, "x")
            broken = " AND ".join(f"{x} IN (SELECT entity FROM seen_{c.ref})" for x in own) if c.ref else "TRUE"
            bad += f" EXCEPT SELECT entity FROM (SELECT * FROM {rows} ORDER BY ALL LIMIT {cap}) WHERE {broken}"
        ctes.append(f"seen_{n} AS MATERIALIZED (SELECT DISTINCT entity FROM {answer} WHERE {' AND '.join(good) or 'TRUE'}{bad})")
    parts = [f"SELECT '{s.name}' AS shape, CAST(entity AS VARCHAR) AS entity, entity IN (SELECT entity FROM seen_{s.name}) AS valid FROM {entities(
        m, s.target,
    )}" for s in schema.shapes]
    return "WITH " + ",\n".join(ctes) + "\n" + "\nUNION ALL ".join(parts)


def misclassified(exact: str, said: str) -> str:
    """By shape, how two sets of verdicts differ."""
    return f"""SELECT shape, count(*) FILTER (WHERE e.valid) AS n_valid, count(*) FILTER (WHERE e.valid AND NOT s.valid) AS n_missed, count(*) FILTER (WHERE NOT e.valid AND s.valid) AS n_wrongly_valid,
    (count(*) FILTER (WHERE e.valid AND NOT s.valid))::DOUBLE / nullif(count(*) FILTER (WHERE e.valid), 0) AS share_missed FROM ({exact}) e JOIN ({said}) s USING (shape, entity) GROUP BY shape"""


def predicates(m: Mapping) -> list[tuple[str, str]]:
    """Name and SQL of the pairs of every predicate of the long form: those given, and inverses that no other one mirrors."""
    direct = {p for c in m.classes.values() for p in (*c.single, *c.multi) if not p.startswith("^")}
    out = []
    for cls, c in m.classes.items():
        for p in (*c.single, *c.multi):
            if not p.startswith("^"):
                out.append((p, f"(SELECT DISTINCT '{cls}/' || entity AS s, CAST(value AS VARCHAR) AS o FROM {_step(m, cls, p)} WHERE entity IS NOT NULL AND value IS NOT NULL)"))
            elif p[1:] not in direct:
                out.append((p[1:], f"(SELECT DISTINCT 'Turn/' || value AS s, CAST(entity AS VARCHAR) AS o FROM {_step(m, cls, p)} WHERE entity IS NOT NULL AND value IS NOT NULL)"))
    return [("type", f"(SELECT '{cls}/' || entity AS s, '{cls}' AS o FROM {entities(m, cls)})") for cls in m.classes] + out


def by_predicate(m: Mapping) -> str:
    """Of the whole graph as triples, by predicate: triples and subjects."""
    return "SELECT p, sum(n)::BIGINT AS n, sum(k)::BIGINT AS n_subjects FROM (" + " UNION ALL ".join(f"SELECT '{p}' AS p, count(*) AS n, count(DISTINCT s) AS k FROM {x}" for p, x in predicates(m)) + ") GROUP BY p"


def counts(m: Mapping, s: Shape) -> str:
    """Witnesses of each top-level constraint, references ignored."""
    cols = [f"(SELECT count(*) FROM {witnesses(m, s, c, False)} w WHERE w.entity = t.entity) AS c{k}" for k, c in enumerate(s.counts(), 1)]
    return f"SELECT t.entity, {', '.join(cols)} FROM {entities(m, s.target)} t"


def rules(m: Mapping, schema: ShapeSchema, planned_order: list[str] | None = None, push: bool = True) -> str:
    """Number of grounded rules in closed form; with an order, witnesses conform to decided shapes, and with ``push`` their lists cut the targets."""
    ctes = [valid_ctes(m, schema)] if planned_order else ["WITH one AS (SELECT 1)"]
    terms, decided = [], set()
    for n in planned_order or schema.names:
        s = schema[n]
        judged = {c for c in s.counts() if c.ref in decided}
        ground = f"SELECT entity FROM {entities(m, s.target)}"
        for c in judged if push else ():
            if c.kind == "min" and c.n >= 1:
                ground = f"SELECT entity FROM ({ground}) WHERE entity IN (SELECT entity FROM {witnesses(m, s, c)})"
        ks = [f"coalesce((SELECT count(*) FROM {witnesses(m, s, c, c in judged)} w WHERE w.entity = t.entity), 0)" for c in s.counts()]
        mins = [f"CAST({_choose(k, c.n)} AS DOUBLE)" for k, c in zip(ks, s.counts()) if c.kind == "min"]
        maxs = [f"CAST({_choose(k, c.n + 1)} AS DOUBLE)" for k, c in zip(ks, s.counts()) if c.kind == "max"]
        body = "1" + (" + " + " * ".join(mins) if mins else "") + "".join(f" + {x}" for x in maxs)
        terms.append(f"SELECT coalesce(sum({body}), 0) AS n FROM ({ground}) t")
        if planned_order:
            decided.add(n)
    return f"{ctes[0]} SELECT CAST(sum(n) AS DOUBLE) AS n_rules FROM (" + " UNION ALL ".join(terms) + ")"


def _choose(k: str, n: int) -> str:
    out = " * ".join(f"greatest({k} - {i}, 0)" for i in range(n)) or "1"
    return f"(({out}) / {_factorial(n)})"


def _factorial(n: int) -> int:
    return 1 if n < 2 else n * _factorial(n - 1)
