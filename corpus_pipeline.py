"""A training-corpus pipeline of five stages; each takes what the stage before it kept.

``STAGES`` lists (name, function); a function takes (spark, docs, sf_dir) and returns a DataFrame. ``run`` applies them
in order to ``documents``, each result written to the shared folder and read again; a stage's table is removed once the
next one is written.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from sparse_topics.llm import decontaminate, mixing, quality, resemblance, sharding
from sparse_topics.llm.common import load, remove, write_table
from sparse_topics.llm.queries import bounded_batches, quality_model


def good_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents that the quality classifier scores 0.3 or more, with all their columns.

    Labels of four of five folds are learned from; rows with null or contradicting labels are not. Null and empty texts
    have the share of good labels as score; without labels every score is 0.5 and all stay; repeated rows are judged
    alike; an empty table stays empty.
    """
    bounded_batches(spark)
    return quality.keep_good(docs, quality_model(docs, load(spark, sf_dir, "labels")))


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group whose sets of five-word shingles have a Jaccard of 0.8 or more (SimHash's contract of
    three words and two bits is ``op2_simhash`` alone): that of the smallest doc_id.

    A null doc_id comes last; null, empty and wordless texts are copies of each other; of repeated rows one stays; an empty
    table stays empty.
    """
    bounded_batches(spark)
    return resemblance.keep_one(docs)


def without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents that hold less than 0.8 of the shingles of every benchmark item.

    Null and empty texts hold nothing and stay; items that are null or have no words are in no document; repeated rows are
    judged alike; an empty table, of documents or of items, takes nothing away.
    """
    return decontaminate.drop_leaks(docs, load(spark, sf_dir, "benchmark"))


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix of sources takes it: never, once, or up to four times.

    Null and empty texts have no words and are not taken unless their source is repeated whole; a null source is a source
    of its own; rows equal in doc_id and text are taken alike; an empty table stays empty.
    """
    return mixing.mix_rows(docs)


def sharded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents with ``shard`` (0 to 7) and ``slot``; columns of these names are replaced.

    Null texts and null sources are rows and sources like others; repeated rows each get a place and are interchangeable;
    an empty table stays empty.
    """
    return sharding.shard_rows(docs, shards=8)


STAGES = [("quality", good_quality), ("near_duplicates", one_of_each), ("decontamination", without_benchmark), ("mixing", mixed), ("sharding", sharded)]

#: The classifier can't be said in SQL; tests/llm/test_pipeline.py compares run() with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, before = load(spark, sf_dir, "documents"), None
    for name, stage in STAGES:
        docs, path = write_table(stage(spark, docs, sf_dir), f"stage-{name}")
        if before:
            remove(spark, before)
        before = path
    return docs
