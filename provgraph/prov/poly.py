"""Provenance polynomials over derivation rows (qid, ans, mono, n).

A monomial is a sorted array of edge ids, a repeated id being an exponent; n is its coefficient.  Rows are the storage; the
polynomial of an answer is an array<struct<mono, coef>> made on demand.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

KEY = ["qid", "ans"]


def how(deriv: DataFrame, merged: bool = False) -> DataFrame:
    """(qid, ans, poly); merged: each monomial of an answer is one row already."""
    terms = deriv.withColumnRenamed("n", "coef") if merged else deriv.groupBy(*KEY, "mono").agg(F.sum("n").alias("coef"))
    return terms.groupBy(*KEY).agg(F.array_sort(F.collect_list(F.struct("mono", "coef"))).alias("poly"))


def render(poly: Column | str) -> Column:
    """Text: ids by '.', terms by ' + ', a coefficient above one as '2*'."""
    poly = F.col(poly) if isinstance(poly, str) else poly
    one = lambda t: F.concat(F.when(t["coef"] > 1, F.concat(t["coef"].cast("string"), F.lit("*"))).otherwise(F.lit("")), F.array_join(F.transform(t["mono"], lambda e: e.cast("string")), "."))
    return F.array_join(F.array_sort(F.transform(poly, one)), " + ")


def how_text(deriv: DataFrame, merged: bool = False) -> DataFrame:
    """(ans, poly) as text: head values joined by '|'."""
    return how(deriv, merged).select(F.array_join("ans", "|").alias("ans"), render("poly").alias("poly"))


def why(deriv: DataFrame, minimal: bool = False) -> DataFrame:
    """(qid, ans, witnesses): set of edge sets; minimal drops sets that hold another one."""
    sets = deriv.select(*KEY, F.array_distinct("mono").alias("w")).distinct()
    out = sets.groupBy(*KEY).agg(F.array_sort(F.collect_list("w")).alias("witnesses"))
    if minimal:
        holds = lambda w: F.exists("witnesses", lambda x: (x != w) & (F.size(F.array_except(x, w)) == 0))
        out = out.withColumn("witnesses", F.filter("witnesses", lambda w: ~holds(w)))
    return out


def lineage(deriv: DataFrame) -> DataFrame:
    """(qid, ans, edges): all edges that take part in some derivation."""
    return deriv.select(*KEY, F.explode("mono").alias("e")).distinct().groupBy(*KEY).agg(F.array_sort(F.collect_list("e")).alias("edges"))


def zero_out(poly: Column | str, edge: Column | int) -> Column:
    """The polynomial with an edge set to 0 and the others left as they are."""
    return F.filter(poly, lambda t: ~F.array_contains(t["mono"], edge))


def plus(a: Column, b: Column) -> Column:
    """Sum with like monomials merged."""
    both = F.concat(a, b)
    monos = F.array_sort(F.array_distinct(F.transform(both, lambda t: t["mono"])))
    coef = lambda m: F.aggregate(F.filter(both, lambda t: t["mono"] == m), F.lit(0).cast("long"), lambda s, t: s + t["coef"])
    return F.transform(monos, lambda m: F.struct(m.alias("mono"), coef(m).alias("coef")))


def times(a: Column, b: Column) -> Column:
    """Product with like monomials merged."""
    pairs = F.flatten(F.transform(a, lambda x: F.transform(b, lambda y: F.struct(F.array_sort(F.concat(x["mono"], y["mono"])).alias("mono"), (x["coef"] * y["coef"]).alias("coef")))))
    return plus(pairs, F.filter(pairs, lambda t: F.lit(False)))


def total(deriv: DataFrame) -> DataFrame:
    """(qid, ans, n): number of derivations."""
    return deriv.groupBy(*KEY).agg(F.sum("n").alias("n"))
