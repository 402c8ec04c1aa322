"""Which positions of a query can one edge fill together, and what label properties rule out."""

from __future__ import annotations

from dataclasses import dataclass, field
from itertools import combinations

from .bgp import Const, GraphQuery, Var


@dataclass(frozen=True)
class Constraints:
    """Declared or profiled label properties; `domains` maps (label, end) to the vertex classes seen there."""

    functional: frozenset = frozenset()
    inverse_functional: frozenset = frozenset()
    asymmetric: frozenset = frozenset()
    irreflexive: frozenset = frozenset()
    acyclic: frozenset = frozenset()
    symmetric: frozenset = frozenset()
    domains: dict = field(default_factory=dict)

    def without(self, broken: dict[str, set]) -> Constraints:
        """The constraints that still hold after an update broke some, e.g. {"functional": {"locatedIn"}}; domains grow by the classes seen."""
        kept = {k: getattr(self, k) - broken.get(k, set()) for k in ("functional", "inverse_functional", "asymmetric", "irreflexive", "acyclic")}
        wider = {k: v | frozenset(broken.get("domains", {}).get(k, ())) for k, v in self.domains.items()}
        return Constraints(**kept, symmetric=self.symmetric, domains=wider)


NONE = Constraints()


class _Classes:
    def __init__(self):
        self.up: dict = {}

    def find(self, t):
        while self.up.get(t, t) != t:
            t = self.up[t]
        return t

    def merge(self, a, b) -> bool:
        a, b = self.find(a), self.find(b)
        if a == b:
            return False
        self.up[a] = b
        return True


def label_candidates(q: GraphQuery) -> list[tuple[int, int]]:
    """Pairs with the same label, or of which one has a variable label."""
    return [(i, j) for i, j in combinations(range(len(q.body)), 2) if q.body[i].label is None or q.body[j].label is None or q.body[i].label == q.body[j].label]


def _closed(q: GraphQuery, merges: list, c: Constraints) -> _Classes | None:
    """Closure under functional labels; None if a class holds two constants."""
    k = _Classes()
    for a, b in merges:
        k.merge(a, b)
    changed = True
    while changed:
        changed = False
        for x, y in combinations(q.body, 2):
            if x.label is None or x.label != y.label:
                continue
            if x.label in c.functional and k.find(x.s) == k.find(y.s):
                changed |= k.merge(x.o, y.o)
            if x.label in c.inverse_functional and k.find(x.o) == k.find(y.o):
                changed |= k.merge(x.s, y.s)
    held: dict = {}
    for t in {t for p in q.body for t in p.terms if isinstance(t, Const)}:
        if held.setdefault(k.find(t), t) != t:
            return None
    return k


def _cycle(edges: set, longest: int | None) -> bool:
    """Is there a directed cycle (of at most `longest` edges)?"""
    nodes = {a for a, _ in edges}
    for start in nodes:
        layer, steps = {start}, 0
        seen = set()
        while layer and (longest is None or steps < longest):
            layer = {b for a, b in edges if a in layer}
            steps += 1
            if start in layer:
                return True
            if longest is None:
                layer -= seen
                seen |= layer
    return False


def _allowed(q: GraphQuery, k: _Classes, c: Constraints) -> bool:
    for label in {p.label for p in q.body if p.label}:
        edges = {(k.find(p.s), k.find(p.o)) for p in q.body if p.label == label}
        if label in c.irreflexive and any(a == b for a, b in edges):
            return False
        if label in c.asymmetric and _cycle(edges, 2) or label in c.acyclic and _cycle(edges, None):
            return False
    kinds: dict = {}
    for p in q.body:
        for end, t in (("s", p.s), ("o", p.o)):
            own = {t.value.split(":")[0]} if isinstance(t, Const) else c.domains.get((p.label, end))
            if own is not None:
                r = k.find(t)
                kinds[r] = kinds.get(r, own) & own
                if not kinds[r]:
                    return False
    return True


def foldable_pairs(q: GraphQuery, constraints: Constraints = NONE) -> list[tuple[int, int]]:
    """Pairs of positions that one edge can fill in some graph satisfying the constraints."""
    out = []
    for i, j in label_candidates(q):
        x, y = q.body[i], q.body[j]
        ways = [[(x.s, y.s), (x.o, y.o), (x.p, y.p)]]
        if (x.label or y.label) in constraints.symmetric or x.label is None and y.label is None and constraints.symmetric:
            ways.append([(x.s, y.o), (x.o, y.s), (x.p, y.p)])
        for way in ways:
            k = _closed(q, way, constraints)
            if k is not None and _allowed(q, k, constraints):
                out.append((i, j))
                break
    return out


def klass(q: GraphQuery, constraints: Constraints = NONE) -> str:
    return "folding" if foldable_pairs(q, constraints) else "plain"


def trigger_subqueries(q: GraphQuery, constraints: Constraints = NONE) -> list[int]:
    """Positions whose label is shared by a foldable pair: one subquery of each such label represents the query."""
    first: dict = {}
    for i, _ in foldable_pairs(q, constraints):
        first.setdefault(q.body[i].label, i)
    return sorted(first.values())


__all__ = ["Constraints", "NONE", "Var", "foldable_pairs", "klass", "label_candidates", "trigger_subqueries"]
