"""Abstract syntax of shape schemas. All of it is small and lives on the driver."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field


class UnsupportedFragment(ValueError):
    """The schema negates through a recursion, for which no polynomial evaluation is known."""


@dataclass(frozen=True)
class ValueTest:
    """A condition on a value, as SQL that Spark and DuckDB both read, over the name ``value``."""

    sql: str

    def on(self, expression: str) -> str:
        return self.sql.replace("value", f"({expression})")


@dataclass(frozen=True)
class Count:
    """At least or at most ``n`` distinct values over ``path`` that pass ``test`` and conform to shape ``ref``."""

    path: str
    kind: str  # "min" or "max"
    n: int
    test: ValueTest | None = None
    ref: str | None = None

    @property
    def label(self) -> str:
        more = f" [{self.test.sql}]" if self.test else ""
        return f"{self.path} {self.kind} {self.n}{more}" + (f" -> {self.ref}" if self.ref else "")

    @property
    def is_inter(self) -> bool:
        return self.ref is not None

    @property
    def steps(self) -> list[str]:
        return self.path.split("/")


@dataclass(frozen=True)
class Not:
    part: Constraint


@dataclass(frozen=True)
class And:
    parts: tuple[Constraint, ...]


@dataclass(frozen=True)
class Or:
    parts: tuple[Constraint, ...]


Constraint = Count | Not | And | Or


def leaves(c: Constraint, positive: bool = True) -> Iterator[tuple[Count, bool]]:
    """The counts in a constraint and whether each stands un-negated.

    A maximum is antitone in the shape that it refers to: more conforming values can break it.
    """
    if isinstance(c, Count):
        yield c, positive
    elif isinstance(c, Not):
        yield from leaves(c.part, not positive)
    else:
        for p in c.parts:
            yield from leaves(p, positive)


def references(c: Constraint) -> Iterator[tuple[str, bool]]:
    """Shapes referred to, with the sign of the dependency."""
    for leaf, positive in leaves(c):
        if leaf.ref:
            yield leaf.ref, positive == (leaf.kind == "min")


@dataclass(frozen=True)
class Shape:
    """A name, the class that it applies to (None: only what refers to it) and a conjunction of constraints."""

    name: str
    target: str | None
    body: tuple[Constraint, ...] = ()
    cls: str | None = None

    @property
    def entity_class(self) -> str | None:
        """The class whose predicates the constraints use."""
        return self.cls or self.target

    @property
    def n_constraints(self) -> int:
        return sum(1 for c in self.body for _ in leaves(c))

    def counts(self, kind: str | None = None) -> list[Count]:
        """Top-level counts."""
        return [c for c in self.body if isinstance(c, Count) and kind in (None, c.kind)]

    @property
    def refs(self) -> list[str]:
        return list(dict.fromkeys(r for c in self.body for r, _ in references(c)))

    @property
    def accepts_bare(self) -> bool:
        """Whether an entity without any value conforms."""

        def bare(c: Constraint) -> bool:
            if isinstance(c, Count):
                return c.kind == "max" or c.n == 0
            if isinstance(c, Not):
                return not bare(c.part)
            return (all if isinstance(c, And) else any)(map(bare, c.parts))

        return all(map(bare, self.body))


@dataclass(frozen=True)
class ShapeSchema:
    name: str
    shapes: tuple[Shape, ...]
    options: dict = field(default_factory=dict, hash=False)

    def __post_init__(self):
        known = {s.name for s in self.shapes}
        if len(known) < len(self.shapes):
            raise ValueError("two shapes with one name")
        for s in self.shapes:
            if missing := set(s.refs) - known:
                raise ValueError(f"{s.name} refers to unknown {sorted(missing)}")

    def __getitem__(self, name: str) -> Shape:
        return next(s for s in self.shapes if s.name == name)

    @property
    def names(self) -> list[str]:
        return [s.name for s in self.shapes]

    @property
    def n_constraints(self) -> int:
        return sum(s.n_constraints for s in self.shapes)
