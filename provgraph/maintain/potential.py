"""Registration tables: half queries in the shared plan, annotations of connection points, inverted indexes."""

from __future__ import annotations

from dataclasses import dataclass, field
from multiprocessing.pool import ThreadPool

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..match.evaluate import match_counts
from ..plan.andor import MOST_PATTERNS, GlobalPlan, choose
from ..plan.frames import Frames
from ..query.bgp import Const, GraphQuery, Var
from ..query.canon import form
from ..query.subquery import Half, Subquery, generate

EXPR_SCHEMA = "expr_id string, binding array<string>, mono array<bigint>, n bigint"
NODE_SCHEMA = "node int, binding array<string>, edges array<bigint>"
ANNOTATED = ("I", "II", "III", "IV")
#: Ends of halves that are counted at the same time.
AT_ONCE = 4


def by_shape(patterns) -> float:
    """Estimate without statistics: each variable widens a result, each constant at an end narrows it."""
    names = {v for p in patterns for v in p.variables}
    return 10.0 ** len(names) / 100.0 ** sum(isinstance(t, Const) for p in patterns for t in (p.s, p.o))


@dataclass
class Catalog:
    """What the driver knows of the registered queries: subqueries, their halves, and the plan that all halves share.

    `policy` says which nodes are kept as tables: 'roots' (the annotated halves), 'shared' (also nodes with several parents), 'all' inner nodes;
    'none' keeps none.  With share=False each half has a plan of its own.  Halves whose root is `wide` are not kept: new edges look for their matches
    in the graph.
    """

    queries: dict[str, GraphQuery] = field(default_factory=dict)
    subqueries: list[Subquery] = field(default_factory=list)
    order: dict[tuple[str, int], list[str]] = field(default_factory=dict)
    places: dict[tuple[str, int], list[int]] = field(default_factory=dict)
    root: dict[tuple[str, int], str] = field(default_factory=dict)
    plan: GlobalPlan = field(default_factory=GlobalPlan)
    number: dict[str, int] = field(default_factory=dict)
    estimate: object = by_shape
    policy: str = "all"
    choice: str = "greedy"
    wide: set[str] = field(default_factory=set)

    def add(self, q: GraphQuery) -> None:
        self.queries[q.name] = q
        for sub in generate(q):
            self.subqueries.append(sub)
            for half in sub.halves:
                patterns = tuple(sub.patterns(half))
                f = form(patterns)
                at = (sub.sqid, half.number)
                self.order[at], self.places[at] = list(f.order), [half.positions[i] for i in f.places]
                if sub.kind in ANNOTATED and half in sub.annotated:
                    self.root[at] = self.plan.add(f"{sub.sqid}.{half.number}", choose(patterns, self.estimate, self.choice if len(patterns) <= MOST_PATTERNS else "greedy"))
        for key in self.plan.nodes:
            self.number.setdefault(key, len(self.number))

    def remove(self, qid: str) -> None:
        self.queries.pop(qid)
        self.subqueries = [s for s in self.subqueries if s.query.name != qid]
        self.root = {at: k for at, k in self.root.items() if any(s.sqid == at[0] for s in self.subqueries)}

    def index(self, sub: Subquery, half: Half, name: str | None) -> int | None:
        return None if name is None else self.order[sub.sqid, half.number].index(name) + 1

    def kept(self) -> list[str]:
        """Nodes that some annotation needs (the smaller half of type II is looked up in the graph instead)."""
        return sorted(set(self.root.values()))

    def stored(self) -> list[str]:
        """Nodes that are kept as tables, small ones first; single patterns only where an annotation needs them."""
        if self.policy == "none":
            return []
        keep = set(self.root.values()) - self.wide
        live = self._live()
        if self.policy == "all":
            keep |= {k for k in live if self.plan.nodes[k].children}
        elif self.policy == "shared":
            parents: dict[str, int] = {}
            for k in live:
                for c in self.plan.nodes[k].children:
                    parents[c] = parents.get(c, 0) + 1
            keep |= {k for k, n in parents.items() if n > 1 and self.plan.nodes[k].children}
        return sorted(keep, key=lambda k: (len(self.plan.nodes[k].patterns), self.number[k]))

    def _live(self) -> set[str]:
        return self._below(set(self.root.values()) - self.wide)

    def _below(self, roots: set[str]) -> set[str]:
        todo, seen = list(roots), set()
        while todo:
            k = todo.pop()
            if k not in seen:
                seen.add(k)
                todo += self.plan.nodes[k].children
        return seen

    def widen(self, most: float) -> set[str]:
        """Roots of which a node is estimated above `most` rows become wide, and stay so; gives the nodes that are no longer kept."""
        return self.drop({k for k in self._live() if self.estimate(self.plan.nodes[k].patterns) > most})

    def drop(self, large: set[str]) -> set[str]:
        """Roots above one of the nodes become wide; gives the nodes that are no longer kept."""
        before = set(self.stored())
        self.wide |= {r for r in set(self.root.values()) - self.wide if self._below({r}) & large}
        return before - set(self.stored())

    def is_wide(self, s: Subquery) -> bool:
        """A subquery with a wide half, which finds new matches from the new edge outwards."""
        return any(self.root.get((s.sqid, h.number)) in self.wide for h in s.halves)

    def rows(self, probes_only: bool = False) -> list[tuple]:
        """A row for each end of each kept half.

        at: place in the binding of the vertex that is annotated; other_at: place of the missing edge's other end, if the half holds it; p_at: place
        of a variable label that the half holds; before: places among the edges whose position in the query is below the missing one;
        heads: (position in the head, place in the binding) of projected values.  With probes_only an end is left out if the half has another already.
        """
        out = []
        for s in self.subqueries:
            if s.kind not in ANNOTATED:
                continue
            for h in s.annotated:
                p = s.pattern.p.name if isinstance(s.pattern.p, Var) else None
                names = self.order[s.sqid, h.number]
                ends = [("out", h.out_var, h.in_var, s.pattern.o), ("in", h.in_var, h.out_var, s.pattern.s)]
                ends = [e for e in ends if e[1]]
                before = [k for k, i in enumerate(self.places[s.sqid, h.number]) if i < s.missing]
                heads = [(k, names.index(v) + 1) for k, v in enumerate(s.query.head) if v in names]
                for d, own, other, far in ends[:1] if probes_only else ends:
                    exp_other = far.value if isinstance(far, Const) else None
                    out.append((self.number[self.root[s.sqid, h.number]], s.sqid, s.query.name, s.kind, s.missing, h.number, s.exp_rel, d, self.index(s, h, own), self.index(s, h, other), exp_other, self.index(s, h, p) if p in names else None, before, heads))
        return out


ROWS_SCHEMA = "node int, sqid string, qid string, kind string, missing int, half int, exp_rel string, dir string, at int, other_at int, exp_other string, p_at int, before array<int>, heads array<struct<pos:int,at:int>>"


def union_all(frames: list[DataFrame], spark: SparkSession, schema: str) -> DataFrame:
    """Union as a balanced tree, so that the plan stays shallow however many terms there are."""
    if not frames:
        return spark.createDataFrame([], schema)
    while len(frames) > 1:
        frames = [a.unionByName(b) for a, b in zip(frames[::2], frames[1::2])] + ([frames[-1]] if len(frames) % 2 else [])
    return frames[0]


def node_rows(catalog: Catalog, frames: Frames, keys: list[str]) -> DataFrame:
    """(node, binding, edges) of some nodes."""
    return union_all([frames.frame(k).selectExpr(f"{catalog.number[k]} AS node", "binding", "edges") for k in keys], frames.triples.sparkSession, NODE_SCHEMA)


def potential_matches(triples: DataFrame, catalog: Catalog) -> DataFrame:
    """(node, binding, edges): matches of every annotated half, evaluated by the shared plan."""
    return node_rows(catalog, Frames(catalog.plan, triples), catalog.kept())


def as_expressions(rows: DataFrame, catalog: Catalog) -> DataFrame:
    """(expr_id, binding, mono, n) of node rows: halves by their canonical text."""
    keys = {catalog.number[k]: k for k in catalog.kept()}
    names = F.broadcast(rows.sparkSession.createDataFrame(sorted(keys.items()), "node int, expr_id string"))  # a row for each half
    return rows.join(names, "node").groupBy("expr_id", "binding", F.array_sort("edges").alias("mono")).agg(F.count("*").alias("n"))


def annotations(potential: DataFrame, catalog: Catalog, probes_only: bool = False) -> DataFrame:
    """Connection points: a row for each match of a half at each vertex where the missing edge attaches, with the projected values that the half holds."""
    # a few rows for each registered pattern
    rows = F.broadcast(potential.sparkSession.createDataFrame(catalog.rows(probes_only), ROWS_SCHEMA))
    get = lambda c: F.when(F.col(c).isNotNull(), F.element_at("binding", F.coalesce(F.col(c), F.lit(1))))
    result = F.transform("heads", lambda h: F.struct(h["pos"].alias("pos"), F.get(F.col("binding"), h["at"] - 1).alias("val")))
    more = [c for c in ("fresh",) if c in potential.columns]
    return potential.join(rows, "node").select(
        get("at").alias("vertex"), "exp_rel", "dir", "sqid", "qid", "kind", "missing", "half", "exp_other", get("other_at").alias("other"), get("p_at").alias("p_value"), result.alias("result"), "before",
        "binding", "edges", F.array_sort("edges").alias("mono"), F.lit(1).cast("bigint").alias("n"), *more,
    )


def annotation_sizes(triples: DataFrame, catalog: Catalog) -> DataFrame:
    """(sqid, half, dir, n, vertices): annotations and distinct vertices of each end of each half, counted by elimination of variables without making them.

    A half may have far more matches than the graph has edges: all pairs of vertices that share a literal, for one.  Each end is a job of its
    own with one row, as a single plan of all of them takes longer to plan than to run.
    """
    ends = [(s, h, d, v) for s in catalog.subqueries if s.kind in ANNOTATED for h in s.annotated for d, v in (("out", h.out_var), ("in", h.in_var)) if v]

    def counted(end: tuple) -> tuple:
        s, h, direction, var = end
        r = match_counts(triples, s.patterns(h), (var,)).agg(F.sum("n").alias("n"), F.count(f"v_{var}").alias("vertices")).first()
        return s.sqid, h.number, direction, r["n"], r["vertices"]

    with ThreadPool(AT_ONCE) as pool:  # jobs of small tables, which leave cores idle one by one
        rows = [r for r in pool.map(counted, ends) if r[3]]
    return triples.sparkSession.createDataFrame(rows, "sqid string, half bigint, dir string, n bigint, vertices bigint")


def aggregated(ann: DataFrame) -> DataFrame:
    """One row for each connection point, subquery and projected values, with its polynomial."""
    per = ann.groupBy("vertex", "exp_rel", "dir", "sqid", "half", "result", "mono").agg(F.sum("n").alias("coef"))
    return per.groupBy("vertex", "exp_rel", "dir", "sqid", "half", "result").agg(F.array_sort(F.collect_list(F.struct("mono", "coef"))).alias("poly"))


def edge_to_answer(deriv: DataFrame) -> DataFrame:
    return deriv.select(F.explode(F.array_distinct("mono")).alias("edge_id"), "qid", "ans").distinct()


def edge_to_cp(ann: DataFrame) -> DataFrame:
    return ann.select(F.explode(F.array_distinct("mono")).alias("edge_id"), "sqid", "half", "vertex", "dir").distinct()
