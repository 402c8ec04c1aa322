"""Readers of graphs and updates."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TRIPLES = "edge_id long, s string, p string, o string, inverse boolean"
UPDATES = "seq long, ts timestamp, op string, edge_id long, s string, p string, o string, inverse boolean"


def triples_parquet(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(TRIPLES).parquet(path)


def triples_orc(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(TRIPLES).orc(path)


def triples_csv(spark: SparkSession, path: str, sep: str = "\t", header: bool = False) -> DataFrame:
    """edge_id, s, p, o separated by `sep`."""
    return spark.read.schema("edge_id long, s string, p string, o string").csv(path, sep=sep, header=header).withColumn("inverse", F.lit(False))


def triples_lines(spark: SparkSession, path: str) -> DataFrame:
    """Lines `<s> <p> <o> .` or with a quoted literal object; the id is a hash of the line, so equal lines are one edge."""
    pattern = r'^<([^>]*)>\s+<([^>]*)>\s+(?:<([^>]*)>|"([^"]*)")\s*\.\s*$'
    part = lambda k: F.regexp_extract("value", pattern, k)
    df = spark.read.text(path).where(F.col("value").rlike(pattern)).distinct()
    o = F.when(part(3) != "", part(3)).otherwise(F.concat(F.lit("lit:"), part(4)))
    return df.select(F.xxhash64("value").alias("edge_id"), part(1).alias("s"), part(2).alias("p"), o.alias("o"), F.lit(False).alias("inverse"))


def updates_json(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(UPDATES).json(path)


def updates_stream(spark: SparkSession, path: str, files: int = 10) -> DataFrame:
    return spark.readStream.schema(UPDATES).option("maxFilesPerTrigger", files).parquet(path)


def triples_jdbc(spark: SparkSession, url: str, table: str, lower: int, upper: int, partitions: int, **options) -> DataFrame:
    """A relational edge table, read by ranges of its id."""
    return spark.read.jdbc(url, table, column="edge_id", lowerBound=lower, upperBound=upper, numPartitions=partitions, properties=options)


def vertical(triples: DataFrame, label: str) -> DataFrame:
    """The relation of one label; a partition scan where the table is partitioned by p."""
    return triples.where(F.col("p") == label).select("edge_id", "s", "o")
