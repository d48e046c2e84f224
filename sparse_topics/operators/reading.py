"""Reading a model: strongest terms, members, assignments, fold-in of new documents, search."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import linalg
from .factors import Factor
from .matrix import TermDoc
from .sparsify import Limits, rank_key, truncate


def top_terms(u: Factor, r: int = 5) -> DataFrame:
    """(topic, rank, term, value)."""
    rank = F.row_number().over(Window.partitionBy("topic").orderBy(rank_key().desc(), "row"))
    return u.long().withColumn("rank", rank).where(F.col("rank") <= r).select("topic", "rank", F.col("row").alias("term"), "value")


def topic_table(u: Factor, r: int = 5) -> DataFrame:
    """One row a rank, one column a topic; blanks where a topic has fewer entries."""
    return top_terms(u, r).groupBy("rank").pivot("topic", list(range(u.k))).agg(F.first("term")).toDF("rank", *[f"topic_{t}" for t in range(u.k)])


def members(v: Factor, tau: float = 0.0) -> DataFrame:
    """(topic, doc_id) of the documents with an entry over ``tau``."""
    return v.long().where(F.col("value") > F.lit(tau)).select("topic", F.col("row").alias("doc_id"))


def assign(v: Factor) -> DataFrame:
    """(doc_id, topic, value): each document's strongest topic, the lower one on ties."""
    best = F.max(F.struct("value", (-F.col("topic")).alias("t"))).alias("best")
    return v.long().groupBy(F.col("row").alias("doc_id")).agg(best).select("doc_id", (-F.col("best.t")).alias("topic"), F.col("best.value").alias("value"))


def topic_sizes(f: Factor) -> DataFrame:
    """(topic, nnz), topics without entries included."""
    topics = f.frame.sparkSession.range(f.k).select(F.col("id").cast("int").alias("topic"))
    counts = f.long().groupBy("topic").agg(F.count(F.lit(1)).alias("nnz"))
    return topics.join(counts, "topic", "left").select("topic", F.coalesce("nnz", F.lit(0)).alias("nnz"))


def fold_in(td_new: TermDoc, u: Factor, limits: Limits | None = None) -> DataFrame:
    """(row, topic, value) of unseen documents, U fixed: one document half step."""
    solved = linalg.solve_docs(td_new, u)
    long = solved.select("row", F.posexplode("w").alias("topic", "value")).where("value > 0")
    return truncate(long, limits or Limits(), "v")


def rank_documents(u: Factor, v: Factor, terms: list[str], n: int = 10) -> DataFrame:
    """(doc_id, score): documents ranked for query terms through the topics they share."""
    query = u.long().where(F.col("row").isin(terms)).groupBy("topic").agg(F.sum("value").alias("q"))
    hits = v.long().join(F.broadcast(query), "topic").groupBy(F.col("row").alias("doc_id")).agg(F.sum(F.col("value") * F.col("q")).alias("score"))
    return hits.orderBy(F.rint(F.col("score") * F.lit(1e12)).desc(), "doc_id").limit(n)


def topic_profile_map(u: Factor, r: int = 5) -> DataFrame:
    """(topic, profile): the strongest terms as a map."""
    return top_terms(u, r).groupBy("topic").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("term", "value")))).alias("profile"))


def topic_json(u: Factor, r: int = 5) -> DataFrame:
    return topic_profile_map(u, r).select("topic", F.to_json("profile").alias("json"))


def register_views(u: Factor, v: Factor, prefix: str = "") -> None:
    """Temporary views <prefix>u (row, topic, value) and <prefix>v for SQL users."""
    u.long().createOrReplaceTempView(f"{prefix}u")
    v.long().createOrReplaceTempView(f"{prefix}v")
