"""Cost and size measures of registered query sets."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plan.andor import GlobalPlan, build, choose, intermediate_expressions
from ..query.bgp import GraphQuery
from ..query.subquery import generate


def global_plan(queries: list[GraphQuery], estimate, policy: str = "greedy") -> GlobalPlan:
    """The shared plan of all halves of all queries."""
    plan = GlobalPlan()
    for q in queries:
        for sub in generate(q):
            for half in sub.halves:
                patterns = tuple(sub.patterns(half))
                plan.add(f"{sub.sqid}.{half.number}", choose(patterns, estimate, policy))
    return plan


def sharing(queries: list[GraphQuery], estimate) -> dict[str, float]:
    """Subqueries, expressions without and with sharing, sharing gain, coverage."""
    sizes = [len(q.body) for q in queries]
    m = global_plan(queries, estimate).measures()
    alone = intermediate_expressions(sizes)
    return {"queries": len(queries), "subqueries": sum(sizes), "intermediate": alone, "gain": 1 - m["nodes"] / alone, **m}


def by_size(queries: list[GraphQuery], estimate) -> list[dict]:
    groups: dict[int, list[GraphQuery]] = {}
    for q in queries:
        groups.setdefault(len(q.body), []).append(q)
    return [{"size": n, **sharing(qs, estimate)} for n, qs in sorted(groups.items())]


def connection_points(ann: DataFrame) -> DataFrame:
    """(vertices, points, annotations): distinct vertices, distinct (vertex, label, direction, subquery), rows."""
    point = F.struct("vertex", "exp_rel", "dir", "sqid")
    return ann.agg(F.count_distinct("vertex").alias("vertices"), F.count_distinct(point).alias("points"), F.count("*").alias("annotations"))


def polynomial_sizes(deriv: DataFrame) -> DataFrame:
    """(answers, monomials, largest): how many monomials answers have."""
    per = deriv.groupBy("qid", "ans").agg(F.count("*").alias("m"))
    return per.agg(F.count("*").alias("answers"), F.sum("m").alias("monomials"), F.max("m").alias("largest"))


def time_split(spans: DataFrame) -> DataFrame:
    """(klass, phase, share) of spans (klass, phase, seconds)."""
    total = spans.groupBy("klass").agg(F.sum("seconds").alias("_t"))
    return spans.groupBy("klass", "phase").agg(F.sum("seconds").alias("s")).join(total, "klass").select("klass", "phase", (F.col("s") / F.col("_t")).alias("share"))


def and_or_sizes(q: GraphQuery, bushy: bool = True) -> tuple[int, int]:
    return build(q.body, bushy).sizes
