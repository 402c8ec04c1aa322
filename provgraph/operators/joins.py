"""Joins that Spark has no operator for: as-of, interval, salted."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def asof(left: DataFrame, right: DataFrame, by: str, time: str, value: str) -> DataFrame:
    """Each left row with the last right `value` at or before its time, in the same `by`; one shuffle, no product."""
    both = left.withColumn("_v", F.lit(None).cast(right.schema[value].dataType)).withColumn("_side", F.lit(1)).unionByName(right.select(by, time, F.col(value).alias("_v")).withColumn("_side", F.lit(0)), allowMissingColumns=True)
    w = Window.partitionBy(by).orderBy(time, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(value, F.last("_v", ignorenulls=True).over(w)).where("_side = 1").drop("_v", "_side")


def interval(points: DataFrame, spans: DataFrame, time: str, start: str, end: str, width: int, by: str | None = None) -> DataFrame:
    """Points (seconds in `time`) with the spans that hold them, start <= time < end, by an equi-join on bins of `width`."""
    p = points.withColumn("_bin", F.floor(F.col(time) / width))
    s = spans.withColumn("_bin", F.explode(F.sequence(F.floor(F.col(start) / width), F.floor((F.col(end) - 1) / width))))
    keys = ["_bin", *([by] if by else [])]
    return p.join(s, keys).where((F.col(start) <= F.col(time)) & (F.col(time) < F.col(end))).drop("_bin")


def salted(large: DataFrame, small: DataFrame, key: str, salts: int = 16) -> DataFrame:
    """An inner join whose hot keys are dealt over `salts` tasks; the small side is repeated for each.

    The copies are merged, as Spark's size estimate misses them and would send them all to the driver for a broadcast.
    """
    spread = large.withColumn("_salt", F.pmod(F.xxhash64(*large.columns), F.lit(salts)).cast("int"))
    copies = small.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return spread.join(copies.hint("merge"), [key, "_salt"]).drop("_salt")
