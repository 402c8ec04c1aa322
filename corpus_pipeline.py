"""The corpus pipeline: quality rules, language, near copies, packing.

Each stage takes (spark, docs, sf_dir) and returns the documents it keeps, the last one the packed pieces.  Rows are told apart by themselves, not
by doc_id, so rows with a null or repeated id are judged like all others and keep their id; columns beyond those of documents pass through.
An empty table gives an empty result in each stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from provgraph.llm import jaccard, langid, packing, quality
from provgraph.llm.runtime import Stage

#: A document stays if this share of its letters is in its main language.
LEAST_SHARE = 0.4


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows that the base rules and the compression bands keep; null and empty texts go, and each repeated row is judged by itself."""
    return quality.keep(docs)


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose text fits a language that was learned from all of the stage's own rows with a language.

    Texts that are null, without letters, in a script or language that was not learned, or mixed below LEAST_SHARE go; if no row has a
    language, nothing could be learned and all rows go.
    """
    return langid.keep(docs, LEAST_SHARE)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each component of linked texts stays: that with the smallest id (null after all others), or the smallest checksum if ids repeat.

    Rows that are equal in id and text are one.  Rows without words link nothing and stay.
    """
    rows = docs.withColumn("_row", F.xxhash64("doc_id", "text"))
    found = jaccard.join(rows.select("_row", "text"), id_col="_row").select(F.col("doc_id").alias("_row"), "component_id").distinct()
    ids = rows.groupBy("_row").agg(F.min("doc_id").alias("_id"))
    first = found.join(ids, "_row").groupBy("component_id").agg(F.min_by("_row", F.struct(F.col("_id").isNull(), "_id", "_row")).alias("_kept"))
    kept = rows.join(first.select(F.col("_kept").alias("_row")), "_row", "left_semi").dropDuplicates(["_row"])
    return kept.select(*docs.columns)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all rows in sequences; a null or empty text is one piece of the end id, a null id stays null, repeated rows are packed each."""
    return packing.pack_documents(docs)


STAGES = [("quality rules", quality_rules), ("language", language), ("near copies", near_copies), ("packing", pack)]

#: Compression, the language model and the tokenizer have no SQL form; tests/llm compares with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    stage = Stage(spark)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, step in STAGES[:-1]:
        docs = stage.table(step(spark, docs, sf_dir), name.replace(" ", "_"))
    return STAGES[-1][1](spark, docs, sf_dir)
