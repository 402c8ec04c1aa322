"""One-pattern-removed subqueries, their halves and types."""

from __future__ import annotations

from dataclasses import dataclass

from .bgp import Const, GraphQuery, Term, Var, components


@dataclass(frozen=True)
class Half:
    """A connected part of a subquery and the variable by which the missing edge attaches at each of its ends."""

    number: int
    positions: tuple[int, ...]
    out_var: str | None  # it holds the missing edge's subject
    in_var: str | None  # it holds the missing edge's object


@dataclass(frozen=True)
class Subquery:
    query: GraphQuery
    missing: int
    kind: str
    halves: tuple[Half, ...]

    @property
    def sqid(self) -> str:
        return f"{self.query.name}#{self.missing}"

    @property
    def pattern(self):
        return self.query.body[self.missing]

    @property
    def exp_rel(self) -> str:
        return self.pattern.label or "*"

    @property
    def annotated(self) -> tuple[Half, ...]:
        """Halves whose matches are kept at vertices: for type II the larger one alone."""
        if self.kind == "II":
            return (max(self.halves, key=lambda h: (len(h.positions), -h.number)),)
        return self.halves

    def patterns(self, half: Half) -> list:
        return [self.query.body[i] for i in half.positions]


def _occurs(t: Term, names: set[str]) -> bool:
    return isinstance(t, Var) and t.name in names


def generate(query: GraphQuery) -> list[Subquery]:
    """The subquery of each position."""
    out = []
    for i, missing in enumerate(query.body):
        rest = [k for k in range(len(query.body)) if k != i]
        parts = components(query.body, rest)
        if not rest:
            out.append(Subquery(query, i, "empty", ()))
            continue
        halves = []
        for number, part in enumerate(sorted(parts, key=lambda p: (-len(p), p))):
            names = {v for k in part for v in query.body[k].variables}
            halves.append(Half(number, tuple(part), missing.s.name if _occurs(missing.s, names) else None, missing.o.name if _occurs(missing.o, names) else None))
        attached = [h for h in halves if h.out_var or h.in_var or _occurs(missing.p, {v for k in h.positions for v in query.body[k].variables})]
        if len(attached) < len(halves) or len(halves) > 2:
            kind = "free"
        elif len(halves) == 2:
            kind = "II" if min(len(h.positions) for h in halves) == 1 else "III"
        elif halves[0].out_var and halves[0].in_var and halves[0].out_var != halves[0].in_var:
            kind = "IV"
        else:
            kind = "I"
        out.append(Subquery(query, i, kind, tuple(halves)))
    return out


def pick_annotated_half(sub: Subquery, estimate) -> Half:
    """Type II with two single patterns: the half with the lower estimate is annotated."""
    if all(len(h.positions) == 1 for h in sub.halves):
        return min(sub.halves, key=lambda h: (estimate(sub.patterns(h)), h.number))
    return sub.annotated[0]


def expected_other(sub: Subquery, direction: str) -> str | None:
    """The constant at the missing edge's other end, if it is bound."""
    other = sub.pattern.o if direction == "out" else sub.pattern.s
    return other.value if isinstance(other, Const) else None
