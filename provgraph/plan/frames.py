"""The shared plan as frames: each expression is evaluated once from its children, and refreshed from their new rows.

A row is a match: (binding, edges), both arrays in the expression's canonical order.  New rows also have `fresh`, which tells the edges
of the batch from those that were there before.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..query.bgp import Const, TriplePattern, Var
from .andor import GlobalPlan, Node

SCHEMA = "binding array<string>, edges array<bigint>"


def leaf(triples: DataFrame, pattern: TriplePattern, width: int) -> DataFrame:
    """Matches of one pattern; constants and repeated variables are filters, which reach the scan."""
    first: dict[str, str] = {}
    for column, t in zip(("p", "s", "o"), (pattern.p, pattern.s, pattern.o)):
        if isinstance(t, Const):
            triples = triples.where(F.col(column) == t.value)
    for column, t in zip(("s", "p", "o"), pattern.terms):
        if isinstance(t, Var) and first.setdefault(t.name, column) != column:
            triples = triples.where(F.col(column) == F.col(first[t.name]))
    binding = f"array({', '.join(first[f'x{i}'] for i in range(width))})" if width else "cast(array() AS array<string>)"
    return triples.selectExpr(f"{binding} AS binding", "array(edge_id) AS edges")


def combine(node: Node, left: DataFrame, right: DataFrame, fresh: bool = False) -> DataFrame:
    """Join of two children's rows on the variables that they share."""
    (lv, le), (rv, re) = node.maps
    shared = [v for v in lv if v in rv]
    more = ["fresh"] if fresh else []
    side = lambda df, own, name: df.selectExpr(*(f"binding[{own.index(v)}] AS _k{v}" for v in shared), *(f"{c} AS {name}_{c}" for c in ("binding", "edges", *more)))
    j = side(left, lv, "l").join(side(right, rv, "r"), [f"_k{v}" for v in shared])
    pick = lambda c, own, other, many: "array(" + ", ".join(f"l_{c}[{own.index(i)}]" if i in own else f"r_{c}[{other.index(i)}]" for i in range(many)) + f") AS {c}"
    binding = pick("binding", lv, rv, node.width) if node.width else "cast(array() AS array<string>) AS binding"
    return j.selectExpr(binding, *(pick(c, le, re, len(node.patterns)) for c in ("edges", *more)))


class Frames:
    """Frames of a plan's nodes over one graph; `stored` gives those that are kept as tables."""

    def __init__(self, plan: GlobalPlan, triples: DataFrame, stored: Callable[[str], DataFrame | None] = lambda key: None):
        self.plan, self.triples, self.stored, self.made = plan, triples, stored, {}

    def frame(self, key: str) -> DataFrame:
        if key not in self.made:
            node = self.plan.nodes[key]
            kept = self.stored(key) if node.children else None
            self.made[key] = kept if kept is not None else leaf(self.triples, node.patterns[0], node.width) if not node.children else combine(node, *(self.frame(k) for k in node.children))
        return self.made[key]


    def size(self, key: str) -> DataFrame:
        """(n): how many rows a node has, by how often its children have each value of what they share; its rows are not made."""
        node = self.plan.nodes[key]
        if not node.children:
            return self.frame(key).agg(F.count("*").alias("n"))
        (lv, _), (rv, _) = node.maps
        keys = [f"_k{v}" for v in lv if v in rv]
        side = lambda k, own, name: self.frame(k).selectExpr(*(f"binding[{own.index(v)}] AS _k{v}" for v in own if f"_k{v}" in keys)).groupBy(*keys).agg(F.count("*").alias(name))
        both = side(node.children[0], lv, "_l").join(side(node.children[1], rv, "_r"), keys)
        return both.agg(F.coalesce(F.sum(F.col("_l") * F.col("_r")), F.lit(0).cast("long")).alias("n"))


class Refresh:
    """New rows of the nodes that a batch touches, bottom-up: new rows of one child with all of the other, old rows of the first with new ones of the other.

    So each new match comes out once.
    """

    def __init__(self, old: Frames, delta: DataFrame, affected: set[str]):
        self.old, self.delta, self.affected, self.made = old, delta, affected, {}

    def before(self, key: str) -> DataFrame:
        n = len(self.old.plan.nodes[key].patterns)
        return self.old.frame(key).selectExpr("binding", "edges", f"array_repeat(false, {n}) AS fresh")

    def rows(self, key: str) -> DataFrame | None:
        if key not in self.affected:
            return None
        if key not in self.made:
            node = self.old.plan.nodes[key]
            if not node.children:
                self.made[key] = leaf(self.delta, node.patterns[0], node.width).selectExpr("*", "array(true) AS fresh")
            else:
                a, b = node.children
                new_a, new_b = self.rows(a), self.rows(b)
                parts = []
                if new_a is not None:
                    parts.append(combine(node, new_a, self.before(b) if new_b is None else self.before(b).unionByName(new_b), True))
                if new_b is not None:
                    parts.append(combine(node, self.before(a), new_b, True))
                self.made[key] = parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])
        return self.made[key]
