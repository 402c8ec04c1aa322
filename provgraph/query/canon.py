"""One key for expressions that are equal up to the names of variables."""

from __future__ import annotations

from dataclasses import dataclass
from itertools import permutations, product

from .bgp import Const, TriplePattern, Var


def _colours(patterns: list[TriplePattern]) -> dict[str, tuple]:
    """Colour refinement: a variable's colour is what its patterns look like from it."""
    names = list(dict.fromkeys(v for t in patterns for v in t.variables))
    colour: dict[str, int] = dict.fromkeys(names, 0)
    while True:
        seen = {v: (colour[v], tuple(sorted(tuple(("=",) if isinstance(x, Var) and x.name == v else ("v", colour[x.name]) if isinstance(x, Var) else ("c", x.value) for x in t.terms) for t in patterns if v in t.variables))) for v in names}
        ranks = {s: i for i, s in enumerate(sorted(set(seen.values()), key=repr))}
        new = {v: ranks[s] for v, s in seen.items()}
        if len(set(new.values())) == len(set(colour.values())):
            return new
        colour = new


def canonical(patterns: list[TriplePattern] | tuple[TriplePattern, ...]) -> tuple[str, list[str]]:
    """(key, variables in canonical order): the least text over renamings that respect the colours."""
    patterns = list(patterns)
    colour = _colours(patterns)
    classes: dict[int, list[str]] = {}
    for v, c in colour.items():
        classes.setdefault(c, []).append(v)
    best = None
    for choice in product(*(permutations(vs) for _, vs in sorted(classes.items()))):
        order = [v for vs in choice for v in vs]
        number = {v: i for i, v in enumerate(order)}
        key = " . ".join(sorted(" ".join(f"?{number[x.name]}" if isinstance(x, Var) else x.value for x in t.terms) for t in patterns))
        if best is None or key < best[0]:
            best = (key, order)
    return best


def renamed(patterns: list[TriplePattern], order: list[str]) -> list[TriplePattern]:
    """The patterns with canonical variable names x0, x1, ..., in the order of the key."""
    number = {v: f"x{i}" for i, v in enumerate(order)}
    swap = lambda x: Var(number[x.name]) if isinstance(x, Var) else Const(x.value)
    return sorted((TriplePattern(*map(swap, t.terms)) for t in patterns), key=repr)


@dataclass(frozen=True)
class Form:
    """A list of patterns up to names: key, variables in canonical order, places of the list in the order of the renamed patterns."""

    key: str
    order: tuple[str, ...]
    places: tuple[int, ...]
    patterns: tuple[TriplePattern, ...]


def form(patterns: list[TriplePattern] | tuple[TriplePattern, ...]) -> Form:
    key, order = canonical(patterns)
    number = {v: f"x{i}" for i, v in enumerate(order)}
    swap = lambda x: Var(number[x.name]) if isinstance(x, Var) else x
    named = [TriplePattern(*map(swap, t.terms)) for t in patterns]
    places = sorted(range(len(named)), key=lambda i: (repr(named[i]), i))
    return Form(key, tuple(order), tuple(places), tuple(named[i] for i in places))
