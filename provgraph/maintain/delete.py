"""Deletion by inverted index: candidates, zero valuation, refresh."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

KEY = ["qid", "ans"]


def touches(ids: DataFrame, index: DataFrame) -> bool:
    """Does any of the edges occur in the index?  If not, the deletion changes nothing."""
    return not index.join(ids, "edge_id", "left_semi").isEmpty()


def candidates(ids: DataFrame, index: DataFrame) -> DataFrame:
    """Answers with a derivation by one of the edges."""
    return index.join(ids, "edge_id", "left_semi").select(*KEY).distinct()


def dead(rows: DataFrame, ids: DataFrame, edges: str = "mono") -> DataFrame:
    """Rows that hold one of the edges, each once: the monomials whose value is zero."""
    key = [c for c in rows.columns if c != "n"]
    hit = rows.select(*key, F.explode(F.array_distinct(edges)).alias("edge_id")).join(ids, "edge_id", "left_semi").select(*key).distinct()
    return rows.join(hit, key, "left_semi")


def refine(deriv: DataFrame, ids: DataFrame, index: DataFrame | None = None) -> DataFrame:
    """(qid, ans, left, lost): derivations that the candidates keep and lose.

    With the index only candidates' derivations are valued; without it all monomials are.
    """
    d = deriv.join(candidates(ids, index), KEY, "left_semi") if index is not None else deriv
    gone = dead(d, ids).groupBy(*KEY).agg(F.sum("n").alias("lost"))
    return d.groupBy(*KEY).agg(F.sum("n").alias("_n")).join(gone, KEY).select(*KEY, (F.col("_n") - F.col("lost")).alias("left"), "lost")


def verdicts(refined: DataFrame) -> DataFrame:
    """(qid, ans, change, n): removed where all monomials are zero, else support_lost."""
    return refined.select(*KEY, F.when(F.col("left") == 0, "removed").otherwise("support_lost").alias("change"), F.col("lost").alias("n"))
