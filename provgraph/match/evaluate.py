"""Evaluation of graph patterns as equi-joins over label-pruned scans."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..query.bgp import Const, GraphQuery, TriplePattern, UnsupportedPattern, Var, components

V, E = "v_", "e_"


def scan(triples: DataFrame, pattern: TriplePattern, position: int, keep_edge: bool = True) -> DataFrame:
    """Bindings of one pattern: constants and repeated variables become filters, the edge id column e_<position>."""
    df = triples
    for column, t in zip(("p", "s", "o"), (pattern.p, pattern.s, pattern.o)):
        if isinstance(t, Const):
            df = df.where(F.col(column) == t.value)
    out, first = [], {}
    for column, t in zip(("s", "p", "o"), pattern.terms):
        if isinstance(t, Var):
            if t.name in first:
                df = df.where(F.col(column) == F.col(first[t.name]))
            else:
                first[t.name] = column
                out.append(F.col(column).alias(V + t.name))
    if keep_edge:
        out.append(F.col("edge_id").alias(f"{E}{position}"))
    return df.select(*out)


def join_order(patterns: list[TriplePattern], start: int | None = None) -> list[int]:
    """Positions so that each shares a variable with those before it where that is possible, constants first, then fixed labels before variable ones."""
    left = list(range(len(patterns)))
    bound = lambda i: (-sum(isinstance(t, Const) for t in (patterns[i].s, patterns[i].o)), not isinstance(patterns[i].p, Const))
    order = [start if start is not None else min(left, key=lambda i: (bound(i), i))]
    left.remove(order[0])
    names = set(patterns[order[0]].variables)
    while left:
        near = [i for i in left if names & set(patterns[i].variables)] or left
        i = min(near, key=lambda i: (bound(i), i))
        order.append(i)
        left.remove(i)
        names |= set(patterns[i].variables)
    return order


def evaluate(sources: DataFrame | list[DataFrame], query: GraphQuery, keep_edges: bool = True, allow_cross: bool = False, order: list[int] | None = None) -> DataFrame:
    """One row for each match: a column v_<name> for each variable and e_<i> for each pattern.

    `sources` is the graph, or one edge table for each position.  Several patterns may bind one edge.
    """
    patterns = list(query.body)
    if not allow_cross and len(components(patterns)) > 1:
        raise UnsupportedPattern(f"{query.name} is disconnected; allow_cross=True permits the product")
    tables = sources if isinstance(sources, list) else [sources] * len(patterns)
    scans = [scan(t, p, i, keep_edges) for i, (t, p) in enumerate(zip(tables, patterns))]

    def step(left: DataFrame, i: int) -> DataFrame:
        right = scans[i]
        shared = [c for c in right.columns if c.startswith(V) and c in left.columns]
        return left.join(right, shared) if shared else left.crossJoin(right)

    first, *rest = order or join_order(patterns)
    return reduce(step, rest, scans[first])


def match_counts(triples: DataFrame, patterns: list[TriplePattern] | tuple[TriplePattern, ...], keep: tuple[str, ...] = ()) -> DataFrame:
    """(v_<kept variable>..., n): how many matches of connected patterns there are for each value of `keep`, without making the matches.

    Variables are eliminated one by one: what holds one is joined and summed over it, so what is joined grows with distinct values, not with
    matches.  Those go first that leave few variables; what is an object only may be shared by very many, so it waits for all subjects unless it leaves one variable at most.
    """
    factors = [(set(p.variables), scan(triples, p, i, keep_edge=False).withColumn("n", F.lit(1).cast("long"))) for i, p in enumerate(patterns)]
    subjects = {p.s.name for p in patterns if isinstance(p.s, Var)}

    def joined(a: tuple, b: tuple) -> tuple:
        shared = sorted(V + v for v in a[0] & b[0])
        right = b[1].withColumnRenamed("n", "_m")
        both = a[1].join(right, shared) if shared else a[1].crossJoin(right)
        return a[0] | b[0], both.withColumn("n", F.col("n") * F.col("_m")).drop("_m")

    left = set().union(*(names for names, _ in factors)) - set(keep)
    while left:
        leaves = {v: set().union(*(names for names, _ in factors if v in names)) - {v} for v in left}
        v = min(left, key=lambda v: (v not in subjects and len(leaves[v]) > 1, len(leaves[v]), v not in subjects, v))
        left.remove(v)
        names, df = reduce(joined, sorted((f for f in factors if v in f[0]), key=lambda f: len(f[0])))
        factors = [f for f in factors if v not in f[0]]
        factors.append((names - {v}, df.groupBy(*sorted(V + x for x in names - {v})).agg(F.sum("n").alias("n"))))
    df = reduce(joined, factors)[1]
    return df.groupBy(*(V + v for v in keep)).agg(F.coalesce(F.sum("n"), F.lit(0).cast("long")).alias("n"))


def head_columns(query: GraphQuery) -> list:
    return [F.col(V + v) for v in query.head]


def answers(triples: DataFrame, query: GraphQuery, **kw) -> DataFrame:
    """Distinct projections, under the head's names."""
    return evaluate(triples, query, keep_edges=False, **kw).select(*[F.col(V + v).alias(v) for v in query.head]).distinct()


def derivations(bindings: DataFrame, query: GraphQuery, by_answer: bool = False) -> DataFrame:
    """(qid, ans, mono, n): a row for each answer and monomial, n the number of matches that give it.

    With by_answer the rows are dealt by answer once, for what gathers each answer's monomials afterwards.
    """
    ans = F.array(*[c.cast("string") for c in head_columns(query)]) if query.head else F.array().cast("array<string>")
    mono = F.array_sort(F.array(*[F.col(f"{E}{i}") for i in range(len(query.body))]))
    rows = bindings.select(F.lit(query.name).alias("qid"), ans.alias("ans"), mono.alias("mono"))
    return (rows.repartition("ans") if by_answer else rows).groupBy("qid", "ans", "mono").agg(F.count("*").alias("n"))
