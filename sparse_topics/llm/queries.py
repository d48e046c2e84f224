"""The registered queries of this subpackage: thin, over whole tables, with the operators' production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontaminate, langid, media, mixing, quality, sharding, simhash, substrings, toxicity, urls
from .common import load, remainder

FOLDS, LANG_FOLDS = 5, 4


def bounded_batches(spark: SparkSession) -> None:
    """Few whole texts an Arrow batch. Operators work with any size of batch and change no setting; the registered queries
    and the pipeline, which own their session, always ask for this one."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "500")


def op1_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(load(spark, sf_dir, "documents"))


def op2_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    bounded_batches(spark)
    return simhash.near_duplicates(load(spark, sf_dir, "documents"))


def op3_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urls.filter_urls(load(spark, sf_dir, "pages"), urls.rule_table(spark, urls.RULES))


def learnable(labels: DataFrame) -> DataFrame:
    return labels.where(remainder(F.col("doc_id"), FOLDS) != 0)


def _judged(docs: DataFrame, model, threshold: float) -> DataFrame:
    scored = quality.score_documents(docs, model)
    return scored.select("doc_id", (remainder(F.col("doc_id"), FOLDS) == 0).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    bounded_batches(spark)
    docs = load(spark, sf_dir, "documents")
    learn = remainder(F.col("doc_id"), FOLDS) != 0
    sample = quality.learning_sample(docs, learnable(load(spark, sf_dir, "labels")), "toxic", per_class=toxicity.PER_CLASS, unlabelled=toxicity.UNLABELLED, may_learn=learn)
    return _judged(docs, toxicity.fit(*sample), 0.5)


def quality_model(docs: DataFrame, labels: DataFrame) -> quality.NeighbourModel:
    return quality.fit(*quality.labelled_sample(docs, learnable(labels), "quality", per_class=quality.PER_CLASS))


def op5_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    bounded_batches(spark)
    docs = load(spark, sf_dir, "documents")
    return _judged(docs, quality_model(docs, load(spark, sf_dir, "labels")), 0.3)


def op6_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    bounded_batches(spark)
    out = substrings.remove_repeats(load(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_bytes", "n_removed", F.size("spans").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"))


def op7_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_documents(load(spark, sf_dir, "documents"), shards=8)


def op8_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.find_leaks(load(spark, sf_dir, "documents"), load(spark, sf_dir, "benchmark")).drop("text_hash")


def op9_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    bounded_batches(spark)
    return media.media_columns(load(spark, sf_dir, "documents"))


def op10_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    bounded_batches(spark)
    docs = load(spark, sf_dir, "documents")
    learned = langid.learn_dictionaries(docs.where(remainder(F.col("doc_id"), LANG_FOLDS) != 2))
    out = langid.identify(docs, learned)
    return out.select("doc_id", (remainder(F.col("doc_id"), LANG_FOLDS) == 2).alias("held_out"), "lang_pred", "score", "rejected")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    own = (op1_mixing, op2_simhash, op3_url_filter, op4_toxicity, op5_quality, op6_suffix_dedup, op7_sharding, op8_decontamination, op9_media, op10_language)
    return {f.__name__: f for f in own}


def oracle_sql() -> dict[str, str]:
    return {"op1_mixing": mixing.SQL, "op3_url_filter": urls.SQL, "op6_suffix_dedup": substrings.SQL, "op7_sharding": sharding.SQL, "op8_decontamination": decontaminate.SQL}
