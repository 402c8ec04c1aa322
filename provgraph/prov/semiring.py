"""Values of polynomials in commutative semirings, over derivation rows and a valuation of edges."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .poly import KEY


@dataclass(frozen=True)
class Semiring:
    """times: folds an array of values; plus: aggregates (value, n) of the monomials."""

    name: str
    times: Callable[[Column], Column]
    plus: Callable[[Column, Column], Column]
    kind: str = "long"


def _fold(start, op, kind):
    return lambda xs: F.aggregate(xs, F.lit(start).cast(kind), op)


BOOL = Semiring("bool", _fold(True, lambda a, x: a & x, "boolean"), lambda v, n: F.bool_or(v), "boolean")
COUNT = Semiring("count", _fold(1, lambda a, x: a * x, "long"), lambda v, n: F.sum(v * n))
TROPICAL = Semiring("tropical", _fold(0, lambda a, x: a + x, "long"), lambda v, n: F.min(v))
#: max of the least value of a monomial: the confidence of the weakest link.
FUZZY = Semiring("fuzzy", _fold(2**62, lambda a, x: F.least(a, x), "long"), lambda v, n: F.max(v))
VITERBI = Semiring("viterbi", _fold(1.0, lambda a, x: a * x, "double"), lambda v, n: F.max(v), "double")
#: Clearance: the least of the highest levels that a derivation needs.
SECURITY = Semiring("security", _fold(0, lambda a, x: F.greatest(a, x), "long"), lambda v, n: F.min(v))
SEMIRINGS = {s.name: s for s in (BOOL, COUNT, TROPICAL, FUZZY, VITERBI, SECURITY)}


def evaluate(deriv: DataFrame, valuation: Callable[[Column], Column], semiring: Semiring) -> DataFrame:
    """(qid, ans, value); `valuation` maps the column of an edge id to its value."""
    v = semiring.times(F.transform("mono", lambda e: valuation(e).cast(semiring.kind)))
    return deriv.withColumn("_v", v).groupBy(*KEY).agg(semiring.plus(F.col("_v"), F.col("n")).alias("value"))


def evaluate_table(deriv: DataFrame, values: DataFrame, semiring: Semiring) -> DataFrame:
    """The same with a valuation table (edge_id, value): exploded ids joined, so it may be of any size."""
    d = deriv.withColumn("_d", F.xxhash64("qid", "ans", "mono"))
    v = d.select(*KEY, "n", "mono", F.posexplode("mono").alias("_k", "edge_id")).join(values, "edge_id")
    monos = v.groupBy(*KEY, "mono", "n").agg(F.collect_list("value").alias("_vs"))
    return monos.withColumn("_v", semiring.times(F.transform("_vs", lambda x: x.cast(semiring.kind)))).groupBy(*KEY).agg(semiring.plus(F.col("_v"), F.col("n")).alias("value"))
