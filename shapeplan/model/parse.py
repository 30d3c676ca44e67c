"""Schemas from JSON.

A shape is ``{"name", "target", "constraints"}``; a constraint is either a logical node
(``{"or": [...]}``, ``{"and": [...]}``, ``{"not": ...}``) or ``{"path", "min", "max", "test", "ref"}``,
where both bounds make two constraints.
"""

from __future__ import annotations

import json
from pathlib import Path

from shapeplan.model.ast import And, Constraint, Count, Not, Or, Shape, ShapeSchema, ValueTest

FOLDER = Path(__file__).resolve().parent.parent / "workload" / "schemas"


def _constraint(d: dict) -> list[Constraint]:
    if "or" in d:
        return [Or(tuple(_all(x) for x in d["or"]))]
    if "and" in d:
        return [And(tuple(c for x in d["and"] for c in _constraint(x)))]
    if "not" in d:
        return [Not(_all(d["not"]))]
    test = ValueTest(d["test"]) if d.get("test") else None
    return [Count(d["path"], kind, d[kind], test, d.get("ref")) for kind in ("min", "max") if kind in d]


def _all(d: dict) -> Constraint:
    parts = _constraint(d)
    return parts[0] if len(parts) == 1 else And(tuple(parts))


def schema_from_dict(d: dict) -> ShapeSchema:
    shapes = tuple(Shape(s["name"], s.get("target"), tuple(c for x in s.get("constraints", ()) for c in _constraint(x)), s.get("class")) for s in d["shapes"])
    return ShapeSchema(d["name"], shapes, d.get("options", {}))


def load_schema(name_or_path: str) -> ShapeSchema:
    path = Path(name_or_path)
    if not path.suffix:
        path = FOLDER / f"{name_or_path}.json"
    return schema_from_dict(json.loads(path.read_text()))
