"""Provenance as a circuit of hashed gates, computed inside the operators (product at joins, sum at projections)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def token(edge: Column) -> Column:
    return F.sha2(F.concat(F.lit("v:"), edge.cast("string")), 256)


def times_gate(left: Column, right: Column) -> Column:
    """Products commute, so the gate's name doesn't depend on the sides."""
    return F.sha2(F.concat(F.lit("*:"), F.least(left, right), F.lit(","), F.greatest(left, right)), 256)


def plus_gate(children: Column) -> Column:
    return F.sha2(F.concat(F.lit("+:"), F.array_join(children, ",")), 256)


def gates(df: DataFrame, gate: str, kind: str, children: Column) -> DataFrame:
    return df.select(F.col(gate).alias("gate"), F.lit(kind).alias("kind"), children.alias("children")).distinct()
