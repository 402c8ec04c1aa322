"""User functions on polynomials where column expressions don't reach: own semirings, probabilities, terms."""

from __future__ import annotations

from collections.abc import Callable
from itertools import combinations

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf

#: Up to so many monomials are handled by inclusion and exclusion, more by sampling.
EXACT = 16


def custom_semiring(value: Callable[[int], float], times: Callable[[float, float], float], plus: Callable[[float, float], float], zero: float, one: float):
    """A pandas UDF that evaluates a polynomial in a semiring of Python functions."""

    @pandas_udf("double")
    def evaluate(poly: pd.Series) -> pd.Series:
        def one_poly(terms) -> float:
            total = zero
            for t in terms:
                v = one
                for e in t["mono"]:
                    v = times(v, value(int(e)))
                for _ in range(int(t["coef"])):
                    total = plus(total, v)
            return float(total)

        return poly.map(one_poly)

    return evaluate


def probability(monos: list[tuple[int, ...]], p: Callable[[int], float], samples: int = 20_000, seed: int = 7) -> float:
    """Probability that some monomial's edges all exist, edges being independent."""
    sets = [frozenset(m) for m in dict.fromkeys(map(tuple, monos))]
    if len(sets) <= EXACT:
        total = 0.0
        for k in range(1, len(sets) + 1):
            for chosen in combinations(sets, k):
                q = 1.0
                for e in frozenset().union(*chosen):
                    q *= p(e)
                total += q if k % 2 else -q
        return total
    import numpy as np

    edges = sorted(set().union(*sets))
    at = {e: i for i, e in enumerate(edges)}
    there = np.random.default_rng(seed).random((samples, len(edges))) < np.array([p(e) for e in edges])
    return float(np.logical_or.reduce([there[:, [at[e] for e in s]].all(1) for s in sets]).mean())


def answer_probabilities(deriv: DataFrame, p: Callable[[int], float]) -> DataFrame:
    """(qid, ans, probability) of each answer."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"qid": [pdf["qid"].iloc[0]], "ans": [list(pdf["ans"].iloc[0])], "probability": [probability([tuple(m) for m in pdf["mono"]], p)]})

    return deriv.groupBy("qid", "ans").applyInPandas(run, "qid string, ans array<string>, probability double")


def smallest(monos) -> list[list[int]]:
    """The sets among `monos` that hold no other one, by size."""
    kept: list[frozenset] = []
    for s in sorted({frozenset(m) for m in monos}, key=len):
        if not any(k <= s for k in kept):
            kept.append(s)
    return [sorted(k) for k in kept]


def minimal_witnesses(deriv: DataFrame) -> DataFrame:
    """(qid, ans, witness): minimal edge sets, by size, for answers with many monomials.

    Answers reach Python in batches, each with its monomials, not as a group of their own; a single set is minimal by itself.
    """

    def run(batches):
        for batch in batches:
            found = [[sorted(set(monos[0]))] if len(monos) == 1 else smallest(monos) for monos in batch.column("monos").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("qid"), batch.column("ans"), pa.array(found, pa.list_(pa.list_(pa.int64())))], names=["qid", "ans", "found"])

    per = deriv.groupBy("qid", "ans").agg(F.collect_list("mono").alias("monos"))
    return per.mapInArrow(run, "qid string, ans array<string>, found array<array<bigint>>").select("qid", "ans", F.explode("found").alias("witness"))


@udtf(returnType="mono array<bigint>, coef bigint")
class PolyTerms:
    """The terms of a polynomial as rows, for lateral joins."""

    def eval(self, poly):
        for t in poly or []:
            yield list(t["mono"]), t["coef"]


def register_sql(spark) -> None:
    spark.udtf.register("poly_terms", PolyTerms)


def explain_rows(how: DataFrame) -> DataFrame:
    return how.select("qid", "ans", F.explode("poly").alias("t")).select("qid", "ans", "t.mono", "t.coef")
