"""Characteristic sets and pairs, and cardinality estimates from them."""

from __future__ import annotations

import json
from collections import defaultdict
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..query.bgp import Const, GraphQuery, TriplePattern, Var, links, star_chain

#: Sets and pairs that reach the driver at most; where there are more, all of them stay a table that estimates are summed over.
MOST = 100_000


def charset_of(triples: DataFrame) -> DataFrame:
    """(vertex, preds): the labels that leave each vertex."""
    return triples.select(F.col("s").alias("vertex"), "p").distinct().groupBy("vertex").agg(F.array_sort(F.collect_list("p")).alias("preds"))


def charsets(triples: DataFrame) -> DataFrame:
    """(preds, vertices, edges): how many vertices have the set, and how many edges leave them by each label."""
    per = triples.groupBy("s", "p").agg(F.count("*").alias("k"))
    sets = charset_of(triples)
    by = per.join(sets, per["s"] == sets["vertex"]).groupBy("preds", "p").agg(F.sum("k").alias("k"))
    edges = by.groupBy("preds").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("p", "k")))).alias("edges"))
    return sets.groupBy("preds").agg(F.count("*").alias("vertices")).join(edges, "preds")


def charpairs(triples: DataFrame) -> DataFrame:
    """(s_preds, o_preds, p, cnt): edges between sets, only where the object's set isn't empty."""
    sets = charset_of(triples)
    subject = sets.select(F.col("vertex").alias("s"), F.col("preds").alias("s_preds"))
    target = sets.select(F.col("vertex").alias("o"), F.col("preds").alias("o_preds"))
    return triples.select("s", "p", "o").join(subject, "s").join(target, "o").groupBy("s_preds", "o_preds", "p").agg(F.count("*").alias("cnt"))


def _held(table: DataFrame, row) -> list | DataFrame:
    """Rows of a table in the driver; the table itself, kept by Spark, where there are more than MOST."""
    table = table.persist()
    rows = table.limit(MOST + 1).collect()
    if len(rows) > MOST:
        return table
    table.unpersist()
    return [row(r) for r in rows]


def _has(preds: str, wanted: set[str]) -> Column:
    return F.size(F.array_except(F.array(*map(F.lit, sorted(wanted))).cast("array<string>"), F.col(preds))) == 0


@dataclass
class Estimator:
    """Estimates from all sets and pairs: lists in the driver, or tables (preds, vertices, edges) and (s_preds, o_preds, p, cnt) where there are more than MOST."""

    sets: list | DataFrame = field(default_factory=list)
    pairs: list | DataFrame = field(default_factory=list)
    label_edges: dict = field(default_factory=dict)
    label_subjects: dict = field(default_factory=dict)
    label_objects: dict = field(default_factory=dict)
    formula: str = "pair_sum"

    @classmethod
    def build(cls, triples: DataFrame, formula: str = "pair_sum") -> Estimator:
        sets = _held(charsets(triples), lambda r: (frozenset(r["preds"]), r["vertices"], r["edges"]))
        pairs = _held(charpairs(triples), lambda r: (frozenset(r["s_preds"]), frozenset(r["o_preds"]), r["p"], r["cnt"]))
        rows = triples.groupBy("p").agg(F.count("*").alias("n"), F.approx_count_distinct("s").alias("ns"), F.approx_count_distinct("o").alias("no")).collect()
        return cls(sets, pairs, {r["p"]: r["n"] for r in rows}, {r["p"]: r["ns"] for r in rows}, {r["p"]: r["no"] for r in rows}, formula)

    @classmethod
    def of_labels(cls, triples: DataFrame) -> Estimator:
        """Sizes of the labels only, by one scan; joins are taken to be independent."""
        rows = triples.groupBy("p").agg(F.count("*").alias("n"), F.approx_count_distinct("s").alias("ns"), F.approx_count_distinct("o").alias("no")).collect()
        return cls([], [], {r["p"]: r["n"] for r in rows}, {r["p"]: r["ns"] for r in rows}, {r["p"]: r["no"] for r in rows}, "independence")

    @property
    def edges(self) -> int:
        return sum(self.label_edges.values())

    def estimate(self, patterns: list[TriplePattern] | tuple) -> float:
        return getattr(self, f"_{self.formula}")(GraphQuery("_", (), tuple(patterns)))

    def _bound(self, t: TriplePattern) -> float:
        """Share of a label's edges that a pattern's constants leave."""
        out = 1.0
        if isinstance(t.o, Const):
            out /= max(1, self.label_objects.get(t.label, 1))
        if isinstance(t.s, Const):
            out /= max(1, self.label_subjects.get(t.label, 1))
        return out

    def _star(self, q: GraphQuery) -> float:
        """Vertices of all supersets times the mean multiplicity of each label, star by star."""
        if isinstance(self.sets, DataFrame):
            rows = F.col("vertices").cast("double")
            for t in q.body:
                k = F.element_at("edges", t.label) if t.label else F.aggregate(F.map_values("edges"), F.lit(0).cast("long"), lambda a, x: a + x)
                rows = rows * (k / F.col("vertices") * self._bound(t))
            found = self.sets.where(_has("preds", {t.label for t in q.body if t.label}))
            return float(found.agg(F.sum(rows).alias("n")).first()["n"] or 0)
        total = 0.0
        for preds, vertices, edges in self.sets:
            if all(t.label is None or t.label in preds for t in q.body):
                rows = float(vertices)
                for t in q.body:
                    rows *= (edges.get(t.label, 0) if t.label else sum(edges.values())) / vertices * self._bound(t)
                total += rows
        return total

    def _pair_sum(self, q: GraphQuery) -> float:
        """Sum of pair counts over linked stars; a single star falls back on its sets."""
        stars = {c: {q.body[i].label for i in at} - {None} for c, at in star_chain(q)}
        between = links(q)
        if not between:
            return self._star(q) if len(stars) == 1 else self._independence(q)
        if isinstance(self.pairs, DataFrame):
            found = [F.when((F.col("p") == q.body[i].label) & _has("s_preds", stars[a]) & _has("o_preds", stars[b]), F.col("cnt")).otherwise(0) for a, b, i in between]
            return float(self.pairs.agg(*(F.sum(n).alias(f"n{k}") for k, n in enumerate(found))).select(sum(F.col(f"n{k}") for k in range(len(found))).alias("n")).first()["n"] or 0)
        return float(sum(n for a, b, i in between for s, t, p, n in self.pairs if p == q.body[i].label and stars[a] <= s and stars[b] <= t))

    def _label_count(self, q: GraphQuery) -> float:
        return float(min(self.label_edges.get(t.label, sum(self.label_edges.values())) for t in q.body))

    def _independence(self, q: GraphQuery) -> float:
        """Product of sizes over the larger number of distinct values of each join."""
        rows, seen = 1.0, {}
        for t in q.body:
            rows *= self.label_edges.get(t.label, sum(self.label_edges.values())) * self._bound(t)
            for x, sizes in ((t.s, self.label_subjects), (t.o, self.label_objects)):
                if isinstance(x, Var):
                    n = max(1, sizes.get(t.label, 1) if t.label else max(sizes.values(), default=1))
                    if x.name in seen:
                        rows /= max(n, seen[x.name])
                    seen[x.name] = max(n, seen.get(x.name, 1))
        return rows


def q_error(estimate: float, exact: float) -> float:
    a, b = max(estimate, 1.0), max(exact, 1.0)
    return max(a / b, b / a)


def degree(triples: DataFrame) -> dict:
    """Edges by label, for reports."""
    out: dict = defaultdict(int)
    for r in triples.groupBy("p").count().collect():
        out[r["p"]] = r["count"]
    return json.loads(json.dumps(out))
