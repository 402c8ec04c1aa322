"""Writers: graphs by label, change feeds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def write_graph(triples: DataFrame, path: str, label_buckets: int = 0) -> None:
    """Partitioned by label, sorted by subject within files; many labels go to hashed label buckets instead."""
    by = "p"
    if label_buckets:
        triples, by = triples.withColumn("p_bucket", F.pmod(F.xxhash64("p"), F.lit(label_buckets))), "p_bucket"
    triples.repartition(by).sortWithinPartitions(by, "s").write.partitionBy(by).parquet(path)


def append_changes(changes: DataFrame, path: str, batch: int) -> None:
    """One folder for each batch, so writing a batch again replaces nothing else."""
    changes.write.mode("overwrite").parquet(f"{path}/batch={batch}")
