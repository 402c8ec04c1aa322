"""The queries of this subpackage: opN_<name>, over whole tables with production parameters."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import ann, bpe, jaccard, langid, lmscore, packing, quality, tokenstore, toxicity, wordpieces


def _documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _documents(spark, sf_dir)
    return toxicity.score(docs, toxicity.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _documents(spark, sf_dir)
    return langid.label(docs, langid.fit(docs))


def op3_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.join(_documents(spark, sf_dir))


def op4_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.round_trip(_documents(spark, sf_dir))


def op5_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokenstore.store(_documents(spark, sf_dir))


def op6_cross_entropy_difference(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Target: documents whose labels say good quality; background: all others."""
    good = spark.read.parquet(f"{sf_dir}/labels.parquet").where("quality = 1")
    return lmscore.difference(_documents(spark, sf_dir), good)


def op7_adaptive_dimension_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann.search(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))


def op8_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return wordpieces.piece_counts(_documents(spark, sf_dir))


def op9_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(_documents(spark, sf_dir))


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.quality(_documents(spark, sf_dir))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages of corpus_pipeline.py in turn."""
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


OPERATORS = (op1_toxicity, op2_language_id, op3_jaccard_join, op4_byte_bpe, op5_token_store, op6_cross_entropy_difference, op7_adaptive_dimension_scan, op8_token_counts, op9_best_fit_packing, op10_quality_rules, pipeline)


def queries() -> dict:
    return {f.__name__: f for f in OPERATORS}


def oracle_sql() -> dict:
    return {}
