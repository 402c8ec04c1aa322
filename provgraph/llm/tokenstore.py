"""Token ids in ORC: run-length encoded integers, row indexes and Bloom filters on document ids.

Documents are dealt by ranges of their id and sorted within each, so each file holds one range in order, a stripe's
statistics bound its ids, and readers prune files, stripes and row groups by id.  `part` numbers
the ranges in order.  Positions (`start`) follow from the ranges' totals and a running sum within each range, so no
step sees all documents at once.

Defined results: null and empty texts hold the end id only; a null id sorts first; repeated rows are written as often
as they occur, in an order fixed by their checksum; an empty table gives an empty result.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .runtime import Stage, ship, shuffle_partitions
from .subwords import END_ID, array_encoder, default_path

OPTIONS = {
    "compression": "zstd",
    "orc.bloom.filter.columns": "doc_id",
    "orc.bloom.filter.fpp": "0.01",
    "orc.create.index": "true",
    "orc.row.index.stride": "1000",
    "orc.stripe.size": str(16 << 20),
}


def _encoded(docs: DataFrame, path: str) -> DataFrame:
    def run(batches):
        encode = array_encoder(path, added=True)
        for batch in batches:
            for i in range(0, batch.num_rows, 2048):
                part = batch.slice(i, 2048)
                flat, sizes = encode(part.column(1))
                offsets = np.concatenate([[0], np.cumsum(sizes + 1)]).astype(np.int32)
                flat = np.insert(flat, np.cumsum(sizes), END_ID).view(np.int32)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array((sizes + 1).astype(np.int32)), pa.ListArray.from_arrays(offsets, pa.array(flat))], names=["doc_id", "n_tokens", "ids"])

    return docs.mapInArrow(run, "doc_id long, n_tokens int, ids array<int>")


def write(docs: DataFrame, path: str, tokenizer: str | None = None, id_col: str = "doc_id", text_col: str = "text", parts: int | None = None) -> None:
    """Encode documents and write them in ascending id order, a file for each range."""
    spark = docs.sparkSession
    ship(spark)
    ranged = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).repartitionByRange(parts or shuffle_partitions(spark), "doc_id").sortWithinPartitions("doc_id")
    _encoded(ranged, tokenizer or default_path()).withColumn("part", F.spark_partition_id()).write.options(**OPTIONS).orc(path)


def read(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("doc_id long, n_tokens int, ids array<int>, part int").orc(path)


def lookup(spark: SparkSession, path: str, ids: list[int]) -> DataFrame:
    """Token ids of some documents; the filter reaches ORC's statistics and Bloom filters."""
    return read(spark, path).where(F.col("doc_id").isin(ids)).select("doc_id", "ids")


def positions(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of each stored document, read back from the files."""
    stored = read(spark, path)

    def run(batches):
        for batch in batches:
            lists = batch.column(3)
            flat, offsets = lists.values.to_numpy(zero_copy_only=False).astype("<u4", copy=False), lists.offsets.to_numpy()
            crc = [zlib.crc32(flat[a:b].tobytes()) for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist())]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), pa.array(crc, pa.int64())], names=["part", "doc_id", "n_tokens", "ids_crc32"])

    sums = stored.select("part", "doc_id", "n_tokens", "ids").mapInArrow(run, "part int, doc_id long, n_tokens int, ids_crc32 long")
    totals = stored.groupBy("part").agg(F.sum("n_tokens").alias("_n"))  # a row for each range; reads two columns only
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    base = F.broadcast(totals.select(F.col("part").alias("_p"), F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_base")))
    within = Window.partitionBy("part").orderBy(F.col("doc_id").asc_nulls_first(), "ids_crc32", "n_tokens").rowsBetween(Window.unboundedPreceding, -1)
    placed = sums.withColumn("_in", F.coalesce(F.sum("n_tokens").over(within), F.lit(0))).join(base, F.col("part") == F.col("_p"))
    return placed.select("doc_id", (F.col("_base") + F.col("_in")).alias("start"), F.col("n_tokens").cast("long").alias("n_tokens"), "ids_crc32")


def store(docs: DataFrame, tokenizer: str | None = None) -> DataFrame:
    """Write all documents to the shared folder and read their positions back."""
    stage = Stage(docs.sparkSession)
    path = stage.path("token_ids")
    write(docs, path, tokenizer)
    return positions(docs.sparkSession, path)
