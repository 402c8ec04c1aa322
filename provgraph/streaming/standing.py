"""Standing queries over an update stream, and reports on its changes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..maintain.maintainer import Maintainer


def run(updates: DataFrame, maintainer: Maintainer, checkpoint: str, changes_path: str | None = None) -> None:
    """Apply a stream of updates by micro-batches; a batch that was applied already is skipped.

    Late rows are applied like others: netting by edge id and seq makes their order irrelevant.
    """
    done = {"batch": -1}

    def step(batch: DataFrame, batch_id: int) -> None:
        if batch_id <= done["batch"]:
            return
        changes = maintainer.apply(batch)
        if changes_path:
            changes.withColumn("batch", F.lit(batch_id)).write.mode("append").parquet(f"{changes_path}/batch={batch_id}")
        done["batch"] = batch_id

    updates.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def deduplicated(updates: DataFrame, late: str = "2 hours") -> DataFrame:
    """Each update once, however often it was delivered within the watermark."""
    return updates.withWatermark("ts", late).dropDuplicatesWithinWatermark(["seq"])


def tumbling(changes: DataFrame, width: str = "1 day", late: str = "2 hours") -> DataFrame:
    return changes.withWatermark("ts", late).groupBy(F.window("ts", width).alias("w"), "op").agg(F.count("*").alias("n"))


def sliding(changes: DataFrame, width: str = "1 day", slide: str = "6 hours", late: str = "2 hours") -> DataFrame:
    return changes.withWatermark("ts", late).groupBy(F.window("ts", width, slide).alias("w"), "op").agg(F.count("*").alias("n"))


def sessions(changes: DataFrame, gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    return changes.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "s").agg(F.count("*").alias("n"))
