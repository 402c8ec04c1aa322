"""AND-OR graphs of an expression's join orders, plan choice, and the plan shared by all expressions."""

from __future__ import annotations

from collections import deque
from dataclasses import dataclass, field
from functools import lru_cache

from ..query.bgp import TriplePattern
from ..query.canon import canonical, form

#: Expressions with more patterns are planned greedily without enumeration.
MOST_PATTERNS = 12


@dataclass(frozen=True)
class AndOr:
    """OR nodes: connected subsets (bit masks); AND nodes: splits of a subset in two that share a variable."""

    patterns: tuple[TriplePattern, ...]
    splits: dict[int, tuple[tuple[int, int], ...]] = field(hash=False)

    @property
    def sizes(self) -> tuple[int, int]:
        return len(self.splits), sum(map(len, self.splits.values()))


def _neighbours(patterns: tuple[TriplePattern, ...]) -> list[int]:
    names = [set(p.variables) for p in patterns]
    return [sum(1 << j for j in range(len(patterns)) if j != i and names[i] & names[j]) for i in range(len(patterns))]


def _connected(mask: int, near: list[int]) -> bool:
    reached = mask & -mask
    grown = True
    while grown:
        grown = False
        for i in range(len(near)):
            if reached >> i & 1:
                new = near[i] & mask & ~reached
                if new:
                    reached |= new
                    grown = True
    return reached == mask


@lru_cache(maxsize=4096)
def build(patterns: tuple[TriplePattern, ...], bushy: bool = True) -> AndOr:
    n, near = len(patterns), _neighbours(patterns)
    if n > MOST_PATTERNS:
        raise ValueError(f"more than {MOST_PATTERNS} patterns: choose greedily instead")
    good = {m for m in range(1, 1 << n) if _connected(m, near)}
    splits: dict[int, tuple] = {}
    for m in sorted(good):
        low, own = m & -m, []
        part = (m - 1) & m
        while part:
            other = m ^ part
            single = not part & (part - 1) or not other & (other - 1)
            if part & low and part in good and other in good and (bushy or single):
                own.append((part, other))
            part = (part - 1) & m
        splits[m] = tuple(own)
    return AndOr(patterns, splits)


@dataclass
class LocalPlan:
    """Chosen split of each subset that is used; steps in evaluation order."""

    patterns: tuple[TriplePattern, ...]
    split: dict[int, tuple[int, int]]
    root: int

    def order(self) -> list[int]:
        """Positions in the order in which they are joined (left-deep plans)."""
        out: list[int] = []

        def visit(m: int) -> None:
            if m in self.split:
                a, b = self.split[m]
                for x in sorted((a, b), key=lambda x: -x.bit_count()):
                    visit(x)
            else:
                out.append(m.bit_length() - 1)

        visit(self.root)
        return out


def _members(patterns, mask: int) -> tuple:
    return tuple(p for i, p in enumerate(patterns) if mask >> i & 1)


def cost(plan: LocalPlan, estimate) -> float:
    """Sum of the estimated sizes of all intermediate results."""
    return sum(estimate(_members(plan.patterns, m)) for m in plan.split)


def choose(patterns: tuple[TriplePattern, ...], estimate, policy: str = "greedy") -> LocalPlan:
    """greedy: level by level the cheapest subset that grows the last one; dp: least total over all splits."""
    n = len(patterns)
    full = (1 << n) - 1
    sized = lru_cache(maxsize=None)(lambda m: estimate(_members(patterns, m)))
    key = lru_cache(maxsize=None)(lambda m: canonical(_members(patterns, m))[0])
    if n == 1:
        return LocalPlan(patterns, {}, full)
    if policy == "dp":
        graph = build(patterns)
        best: dict[int, tuple[float, tuple | None]] = {}
        for m in sorted(graph.splits, key=int.bit_count):
            best[m] = (0.0, None) if not m & (m - 1) else min((sized(m) + best[a][0] + best[b][0], (a, b)) for a, b in graph.splits[m])
        split, todo = {}, [full]
        while todo:
            m = todo.pop()
            if best[m][1]:
                split[m] = best[m][1]
                todo += best[m][1]
        return LocalPlan(patterns, split, full)
    near = _neighbours(patterns)
    pairs = [1 << i | 1 << j for i in range(n) for j in range(i + 1, n) if near[i] >> j & 1]
    now = min(pairs, key=lambda m: (sized(m), key(m), m))
    low = now & -now
    split = {now: (low, now ^ low)}
    while now != full:
        reach = 0
        for i in range(n):
            if now >> i & 1:
                reach |= near[i]
        grown = min((now | 1 << i for i in range(n) if reach & ~now & full & 1 << i), key=lambda m: (sized(m), key(m), m))
        split[grown] = (now, grown ^ now)
        now = grown
    return LocalPlan(patterns, split, full)


@dataclass
class Node:
    """An expression of the shared plan, its variables and patterns in canonical order.

    For each child, `maps` has the places in this node of the child's variables and of its edges.
    """

    key: str
    patterns: tuple[TriplePattern, ...]
    width: int = 0
    children: tuple[str, ...] = ()
    maps: tuple[tuple[tuple[int, ...], tuple[int, ...]], ...] = ()

    @property
    def labels(self) -> set[str]:
        return {p.label or "*" for p in self.patterns}


class GlobalPlan:
    """Local plans merged top-down: where an equivalent expression is present already, its node is shared.

    With shared=False (an ablation) each plan keeps nodes of its own.
    """

    def __init__(self, shared: bool = True):
        self.shared = shared
        self.nodes: dict[str, Node] = {}
        self.roots: dict[str, str] = {}

    def add(self, name: str, plan: LocalPlan) -> str:
        def at(m: int):
            own = [i for i in range(len(plan.patterns)) if m >> i & 1]
            f = form([plan.patterns[i] for i in own])
            return f, tuple(own[i] for i in f.places), f.key if self.shared else f"{f.key} @ {name}"

        self.roots[name] = at(plan.root)[2]
        queue = deque([plan.root])
        while queue:
            m = queue.popleft()
            f, places, key = at(m)
            if key in self.nodes:
                continue
            parts = plan.split.get(m, ())
            below = [at(x) for x in parts]
            maps = tuple((tuple(f.order.index(v) for v in g.order), tuple(places.index(i) for i in own)) for g, own, _ in below)
            self.nodes[key] = Node(key, f.patterns, len(f.order), tuple(k for _, _, k in below), maps)
            queue.extend(parts)
        return self.roots[name]

    def affected(self, labels) -> list[str]:
        """Nodes in which one of the labels occurs, leaves first."""
        wanted = set(labels)
        return [k for k, n in sorted(self.nodes.items(), key=lambda x: len(x[1].patterns)) if n.labels & wanted or "*" in n.labels]

    @property
    def leaves(self) -> int:
        return sum(not n.children for n in self.nodes.values())

    def measures(self) -> dict[str, float]:
        labels = {x for n in self.nodes.values() for x in n.labels}
        inner = len(self.nodes) - self.leaves
        return {
            "nodes": len(self.nodes), "leaves": self.leaves, "inner": inner, "labels": len(labels),
            "coverage": inner / max(1, len(labels)),
            "mean_affected": sum(len(self.affected([x])) for x in labels) / max(1, len(labels)),
        }


def intermediate_expressions(sizes) -> int:
    """Expressions without sharing: size - 1 patterns for each subquery of each query."""
    return sum(n * (n - 1) for n in sizes)
