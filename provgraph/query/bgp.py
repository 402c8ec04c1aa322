"""Conjunctive graph patterns with projection, their shape and a small text form."""

from __future__ import annotations

import re
from dataclasses import dataclass


class UnsupportedPattern(ValueError):
    """The text needs more than a conjunction of triple patterns with projection."""


@dataclass(frozen=True, order=True)
class Var:
    name: str


@dataclass(frozen=True, order=True)
class Const:
    value: str


Term = Var | Const


@dataclass(frozen=True)
class TriplePattern:
    s: Term
    p: Term
    o: Term

    @property
    def terms(self) -> tuple[Term, Term, Term]:
        return self.s, self.p, self.o

    @property
    def variables(self) -> list[str]:
        return list(dict.fromkeys(t.name for t in self.terms if isinstance(t, Var)))

    @property
    def label(self) -> str | None:
        return self.p.value if isinstance(self.p, Const) else None


@dataclass(frozen=True)
class GraphQuery:
    name: str
    head: tuple[str, ...]
    body: tuple[TriplePattern, ...]

    def __post_init__(self):
        missing = set(self.head) - set(self.variables)
        if missing:
            raise ValueError(f"head variables not in the body: {sorted(missing)}")

    @property
    def variables(self) -> list[str]:
        return list(dict.fromkeys(v for t in self.body for v in t.variables))

    @property
    def labels(self) -> set[str]:
        return {t.label or "*" for t in self.body}

    def mentions(self, label: str) -> bool:
        return label in self.labels or "*" in self.labels


def components(patterns: list[TriplePattern] | tuple[TriplePattern, ...], positions: list[int] | None = None) -> list[list[int]]:
    """Positions grouped by shared variables; constants do not connect."""
    left = list(range(len(patterns))) if positions is None else list(positions)
    out = []
    while left:
        group, names = [left.pop(0)], set()
        names |= set(patterns[group[0]].variables)
        grown = True
        while grown:
            grown = False
            for i in list(left):
                if names & set(patterns[i].variables):
                    left.remove(i)
                    group.append(i)
                    names |= set(patterns[i].variables)
                    grown = True
        out.append(sorted(group))
    return out


_TOKEN = re.compile(r'\s+|(?P<var>\?\w+)|(?P<quoted>"[^"]*")|(?P<punct>[{}.;])|(?P<word>[^\s{};"?]+?(?=[.;]?(?:[\s{}]|$)))')
_BEYOND = {"optional", "filter", "union", "order", "group", "limit", "offset", "having", "minus", "service", "bind", "values", "exists", "construct", "ask", "describe", "prefix", "count", "sum", "avg", "min", "max"}


def tokens(text: str) -> list[str]:
    out, at = [], 0
    while at < len(text):
        m = _TOKEN.match(text, at)
        if not m:
            raise UnsupportedPattern(f"unexpected text at {at}: {text[at:at + 20]!r}")
        if m.lastgroup:
            out.append(m.group())
        at = m.end()
    return out


def parse_select(text: str, name: str = "q") -> GraphQuery:
    """SELECT ?a ?b [WHERE] { s p o . s p o ; p o }; `a` stands for the label `type`; SELECT * takes all variables."""
    t = tokens(text)
    if not t or t[0].lower() != "select":
        raise UnsupportedPattern("only SELECT queries")
    if any(x.lower() in _BEYOND or any(c in x for c in "()|/^+!") and not x.startswith(('"', "?")) and ":" not in x for x in t[1:]):
        raise UnsupportedPattern("only conjunctions of triple patterns")
    at = 1
    if at < len(t) and t[at].lower() == "distinct":
        at += 1
    head = []
    while at < len(t) and (t[at].startswith("?") or t[at] == "*"):
        head.append(t[at])
        at += 1
    if at < len(t) and t[at].lower() == "where":
        at += 1
    if at >= len(t) or t[at] != "{" or t[-1] != "}" or t.count("{") != 1:
        raise UnsupportedPattern("one group of patterns is expected")
    body, subject, items = [], None, []
    for x in [*t[at + 1 : -1], "."]:
        if x not in ".;":
            items.append(x)
            continue
        if items:
            if len(items) == 3:
                subject = items.pop(0)
            if len(items) != 2 or subject is None:
                raise UnsupportedPattern(f"a pattern has three terms: {items}")
            body.append(TriplePattern(_term(subject), Const("type") if items[0] == "a" else _term(items[0]), _term(items[1])))
            items = []
        if x == ".":
            subject = None
    if not body:
        raise UnsupportedPattern("empty group")
    names = list(dict.fromkeys(v for p in body for v in p.variables))
    chosen = names if head == ["*"] else [x[1:] for x in head]
    try:
        return GraphQuery(name, tuple(chosen), tuple(body))
    except ValueError as e:
        raise UnsupportedPattern(str(e)) from e


def _term(x: str) -> Term:
    if x.startswith("?"):
        return Var(x[1:])
    return Const(f"lit:{x[1:-1]}" if x.startswith('"') else x)


def star_chain(q: GraphQuery) -> list[tuple[Term, list[int]]]:
    """Stars by subject, each with the positions of its patterns, chained by patterns whose object is another star's centre."""
    stars: dict[Term, list[int]] = {}
    for i, t in enumerate(q.body):
        stars.setdefault(t.s, []).append(i)
    return list(stars.items())


def links(q: GraphQuery) -> list[tuple[Term, Term, int]]:
    """(centre, centre, position) of patterns that lead from one star to another."""
    centres = {t.s for t in q.body}
    return [(t.s, t.o, i) for i, t in enumerate(q.body) if t.o in centres and t.o != t.s]
