"""Cleaning a query log down to the standing queries: SELECT texts, then plain conjunctions, then distinct ones of two patterns or more."""

from __future__ import annotations

from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..query.bgp import UnsupportedPattern, parse_select
from ..query.canon import canonical


def parsed(log: DataFrame) -> DataFrame:
    """(qid, text, is_select, size, key): size and key are null where the text is no plain conjunction."""

    def read(text):
        try:
            q = parse_select(text or "")
        except UnsupportedPattern:
            return None, None
        key, order = canonical(q.body)
        return len(q.body), f"{key} | {' '.join(sorted(str(order.index(v)) for v in q.head))}"

    def run(batches):
        one = lru_cache(50_000)(read)  # a log repeats its texts
        for batch in batches:
            sizes, keys = [], []
            for size, key in map(one, batch.column("text").to_pylist()):
                sizes.append(size)
                keys.append(key)
            yield pa.RecordBatch.from_arrays([batch.column("qid"), batch.column("text"), batch.column("is_select"), pa.array(sizes, pa.int64()), pa.array(keys, pa.string())], names=["qid", "text", "is_select", "size", "key"])

    marked = log.select(F.col("qid").cast("long"), "text", F.lower(F.ltrim("text")).startswith("select").alias("is_select"))
    return marked.mapInArrow(run, "qid long, text string, is_select boolean, size long, key string")


def clean(log: DataFrame) -> DataFrame:
    """(qid, text, size): the first text of each distinct conjunction of two patterns or more."""
    return parsed(log).where("size > 1").groupBy("key").agg(F.min(F.struct("qid", "text", "size")).alias("q")).select("q.*")


def funnel(log: DataFrame) -> DataFrame:
    """(requests, selects, conjunctions, distinct_queries)."""
    p = parsed(log.groupBy("text").agg(F.count("*").alias("qid")))  # each text is parsed once; qid: how many requests have it
    count = lambda c: F.coalesce(F.sum(F.when(c, F.col("qid"))), F.lit(0))
    return p.agg(count(F.lit(True)).alias("requests"), count(F.col("is_select")).alias("selects"), count(F.col("size") > 1).alias("conjunctions"), F.count_distinct(F.when(F.col("size") > 1, F.col("key"))).alias("distinct_queries"))
