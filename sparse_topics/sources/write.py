"""Sinks: matrices bucketed by document, models on disk."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.als import TRACE, FitResult
from ..operators.factors import Factor
from ..operators.matrix import TermDoc


def save_matrix(td: TermDoc, table: str, buckets: int, by: str = "doc_id") -> None:
    """A as a table bucketed by document (or term) and sorted by the other key, so that half steps on that side need no
    exchange and row groups can be skipped by term."""
    other = "term" if by == "doc_id" else "doc_id"
    td.coo.write.mode("overwrite").bucketBy(buckets, by).sortBy(other).saveAsTable(table)


def load_matrix(spark: SparkSession, table: str, weight: str = "df", docs: int | None = None) -> TermDoc:
    return TermDoc(spark.table(table), weight, docs)


def save_fit(fit: FitResult, path: str) -> None:
    """U, V (long form) and the trace under one folder."""
    spark = fit.u.frame.sparkSession
    for name, f in (("u", fit.u), ("v", fit.v)):
        f.long().write.mode("overwrite").parquet(f"{path}/{name}")
    fit.trace(spark).write.mode("overwrite").parquet(f"{path}/trace")
    spark.createDataFrame([(json.dumps({"k": fit.k}),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/meta")


def load_fit(spark: SparkSession, path: str) -> FitResult:
    from ..operators.factors import pack

    k = json.loads(spark.read.text(f"{path}/meta").first()[0])["k"]
    u, v = (Factor(k, pack(spark.read.parquet(f"{path}/{n}"), k)) for n in ("u", "v"))
    names = [f.split()[0] for f in TRACE.split(", ")]
    steps = [tuple(r[n] for n in names) for r in spark.read.parquet(f"{path}/trace").orderBy("iter").collect()]
    return FitResult(u, v, k, steps)


def export_topics(top: DataFrame, path: str, fmt: str = "json") -> None:
    """Topic tables as csv or json."""
    top.coalesce(1).write.mode("overwrite").option("header", True).format(fmt).save(path)


def partitioned(df: DataFrame, path: str, by: list[str]) -> None:
    """Rows under one folder a key, for pruning by corpus or language."""
    df.repartition(*[F.col(c) for c in by]).write.mode("overwrite").partitionBy(*by).parquet(path)
