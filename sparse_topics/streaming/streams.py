"""Event-time matrices, fold-in of arriving documents, incremental counts, refits, drift, deduplication, interval joins."""

from __future__ import annotations

import json
from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.query import StreamingQuery

from ..functions.text import words
from ..operators import linalg
from ..operators.als import FitResult, sparse_als
from ..operators.factors import Factor
from ..operators.matrix import TermDoc, build_term_doc, count_terms
from ..operators.sparsify import Limits
from ..plans.choice import LOCAL_ENTRIES
from ..session import new_path
from ..sources import load_fit, save_fit


def events_stream(spark: SparkSession, sf_dir: str, files_per_trigger: int = 1) -> DataFrame:
    """The events table as a stream; ``ts`` becomes a timestamp, since a watermark needs one."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    path = f"{sf_dir}/events.parquet"
    reader = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger)
    # a single file is read through a glob, since a stream source wants a folder or a pattern
    return reader.parquet(path.replace("events.parquet", "events.parque[t]")).withColumn("ts", F.col("ts").cast("timestamp"))


def docs_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    schema = spark.read.parquet(f"{sf_dir}/documents.parquet").schema
    return spark.readStream.schema(schema).parquet(f"{sf_dir}/documents.parque[t]")


def event_windows(events: DataFrame, size: str, slide: str | None = None, watermark: str | None = "2 hours") -> DataFrame:
    """(start, event_type, n, total) by tumbling or sliding windows; rows later than the watermark are dropped, and counted by
    ``late_rows``."""
    rows = events.withWatermark("ts", watermark) if watermark and events.isStreaming else events
    window = F.window("ts", size, slide) if slide else F.window("ts", size)
    return rows.groupBy(window.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), "event_type", "n", "total")


def session_windows(events: DataFrame, gap: str = "30 minutes", watermark: str | None = "2 hours") -> DataFrame:
    """(user_id, start, n) of sessions that end after a gap."""
    rows = events.withWatermark("ts", watermark) if watermark and events.isStreaming else events
    return rows.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def fold_in_stream(docs: DataFrame, u: Factor, df: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, topic, value) of arriving documents with U fixed. Stateless: a document is one row, and its product with
    U is summed inside the row by looking its terms up in a broadcast map of U's few entries."""
    if u.count() > LOCAL_ENTRIES:
        raise ValueError(f"U has {u.count()} entries; truncate it to {LOCAL_ENTRIES} before it is sent to every task")
    inverse = linalg.invert_gram(linalg.gram(u))
    k = u.k
    table = u.frame.join(df, F.col("row") == F.col("term")).select("row", F.transform("w", lambda x: x / F.col("df")).alias("x"))
    one = table.agg(F.map_from_entries(F.collect_list(F.struct("row", "x"))).alias("u_map"))
    looked = docs.select(F.col(id_col).alias("doc_id"), words(F.col(text_col)).alias("terms")).crossJoin(F.broadcast(one))
    hits = F.filter(F.transform("terms", lambda t: F.try_element_at("u_map", t)), lambda x: x.isNotNull())
    total = F.aggregate(hits, F.array_repeat(F.lit(0.0), k), lambda a, x: F.zip_with(a, x, lambda p, q: p + q))
    b = looked.select("doc_id", total.alias("b"))
    solved = b.select("doc_id", F.transform(linalg.times("b", inverse), linalg.project_nonneg).alias("w"))
    return solved.select("doc_id", F.posexplode("w").alias("topic", "value")).where("value > 0")


def count_stream(docs: DataFrame, table_path: str, checkpoint: str, available_now: bool = True) -> StreamingQuery:
    """Adds each micro-batch's counts, and its share of the terms' totals, under its batch number: a repeated batch replaces
    its own rows. ``merged_totals`` and ``matrix_so_far`` read them."""

    def add(batch: DataFrame, number: int) -> None:
        counts = f"{table_path}/counts/batch={number}"
        count_terms(batch).write.mode("overwrite").parquet(counts)
        per_term = batch.sparkSession.read.parquet(counts).groupBy("term").agg(F.sum("tf").alias("total"), F.count(F.lit(1)).alias("df"))
        per_term.write.mode("overwrite").parquet(f"{table_path}/totals/batch={number}")

    writer = docs.writeStream.foreachBatch(add).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if available_now else writer).start()


def merged_totals(spark: SparkSession, table_path: str) -> DataFrame:
    """(term, total, df) over all batches so far; a document arrives in one batch, so its share adds up."""
    return spark.read.parquet(f"{table_path}/totals").groupBy("term").agg(F.sum("total").alias("total"), F.sum("df").alias("df"))


def matrix_so_far(spark: SparkSession, table_path: str, min_count: int = 2, weight: str = "df") -> TermDoc:
    """A of all batches so far: the terms that are frequent enough by the merged totals."""
    kept = merged_totals(spark, table_path).where(F.col("total") >= min_count).select("term", "df")
    return TermDoc(spark.read.parquet(f"{table_path}/counts").join(kept, "term").select("term", "doc_id", "tf", "df"), weight)


def warm_als(k: int, limits: Limits | None = None, max_iter: int = 5, **options) -> Callable[[DataFrame, FitResult | None], FitResult]:
    """A fit for ``refit_stream``: prepares the documents so far and starts from the last model's U."""

    def fit(docs: DataFrame, last: FitResult | None) -> FitResult:
        return sparse_als(build_term_doc(docs), k, limits, init=last.u if last else None, max_iter=max_iter, **options)

    return fit


def last_model(spark: SparkSession, table_path: str) -> tuple[FitResult | None, int]:
    """The newest whole model of a refit stream and its batch number (None and -1 if there is none)."""
    p = spark._jvm.org.apache.hadoop.fs.Path(f"{table_path}/model")
    fs = p.getFileSystem(spark._jsc.hadoopConfiguration())
    found = [f.getPath().getName() for f in fs.listStatus(p)] if fs.exists(p) else []
    whole = [int(n.removeprefix("batch=")) for n in found if fs.exists(spark._jvm.org.apache.hadoop.fs.Path(f"{table_path}/model/{n}/meta/_SUCCESS"))]
    return (load_fit(spark, f"{table_path}/model/batch={max(whole)}"), max(whole)) if whole else (None, -1)


def refit_stream(docs: DataFrame, every: int, fit: Callable[[DataFrame, FitResult | None], FitResult], table_path: str, checkpoint: str) -> StreamingQuery:
    """Keeps each micro-batch's documents under its number, and after every ``every``-th calls ``fit(all documents so far,
    last model)``. Models are kept under their batch number too, so that the warm start survives a restart, and a repeated
    batch replaces what it wrote."""

    def step(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        batch.write.mode("overwrite").parquet(f"{table_path}/docs/batch={number}")
        if (number + 1) % every == 0:
            model, at = last_model(spark, table_path)
            if at < number:
                save_fit(fit(spark.read.parquet(f"{table_path}/docs").drop("batch"), model), f"{table_path}/model/batch={number}")

    return docs.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


ROCKSDB = ("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")


def topic_drift(assigned: DataFrame, key: str = "user_id", ttl_ms: int | None = None) -> DataFrame:
    """(key, old, new): emitted when a key's topic changes; the last topic is the state. assigned: (key, topic). ttl_ms: a key
    that was silent so long (processing time) is forgotten. The session must have the setting ``ROCKSDB``."""
    from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

    if assigned.sparkSession.conf.get(ROCKSDB[0], None) != ROCKSDB[1]:
        raise ValueError(f"this operator keeps its state in RocksDB: set {ROCKSDB[0]} to {ROCKSDB[1]}")

    class Drift(StatefulProcessor):
        def init(self, handle: StatefulProcessorHandle) -> None:
            self.last = handle.getValueState("last", "topic int", ttl_ms) if ttl_ms else handle.getValueState("last", "topic int")

        def handleInputRows(self, k, rows: Iterator, timer_values) -> Iterator:
            import pandas as pd

            old = self.last.get()[0] if self.last.exists() else None
            out = []
            for frame in rows:
                for topic in frame["topic"]:
                    if old is not None and topic != old:
                        out.append((k[0], int(old), int(topic)))
                    old = topic
            if old is not None:
                self.last.update((int(old),))
            yield pd.DataFrame(out, columns=[key, "old", "new"])

        def close(self) -> None:
            pass

    kind = assigned.schema[key].dataType.simpleString()
    return assigned.groupBy(key).transformWithStateInPandas(Drift(), f"{key} {kind}, old int, new int", "append", "processingTime" if ttl_ms else "none")


def dedup_stream(docs: DataFrame, text_col: str = "text", ts: str | None = None, watermark: str = "1 hour") -> DataFrame:
    """Arriving documents without those whose text hash was seen (within the watermark, if there is a time column)."""
    keyed = docs.withColumn("text_md5", F.md5(F.col(text_col).cast("binary")))
    if ts:
        return keyed.withWatermark(ts, watermark).dropDuplicatesWithinWatermark(["text_md5"])
    return keyed.dropDuplicates(["text_md5"])


def interval_join_stream(clicks: DataFrame, purchases: DataFrame, within: str = "1 hour", watermark: str = "2 hours") -> DataFrame:
    """(user_id, click_ts, purchase_ts): a purchase that follows a click of the same user within the interval."""
    c = clicks.select(F.col("user_id").alias("c_user"), F.col("ts").alias("click_ts"))
    p = purchases.select(F.col("user_id").alias("p_user"), F.col("ts").alias("purchase_ts"))
    if clicks.isStreaming:
        c, p = c.withWatermark("click_ts", watermark), p.withWatermark("purchase_ts", watermark)
    on = (F.col("c_user") == F.col("p_user")) & (F.col("purchase_ts") >= F.col("click_ts")) & (F.col("purchase_ts") <= F.col("click_ts") + F.expr(f"INTERVAL {within}"))
    return c.join(p, on).select(F.col("c_user").alias("user_id"), "click_ts", "purchase_ts")


def late_rows(query: StreamingQuery) -> int:
    """Rows that the watermark dropped as too late, over the query's progress so far."""
    return sum(state.get("numRowsDroppedByWatermark", 0) for p in (json.loads(q.json) for q in query.recentProgress) for state in p.get("stateOperators", []))


def drain_counted(stream: DataFrame, spark: SparkSession, name: str, mode: str = "append") -> tuple[DataFrame, int]:
    """Runs a stream over what is available into a table in the shared folder: (the table, rows dropped as too late)."""
    path = new_path(spark, f"stream-{name}")
    if mode == "append":
        writer = stream.writeStream.format("parquet").option("path", f"{path}/out")
    else:

        def put(batch: DataFrame, number: int) -> None:
            batch.write.mode("overwrite").parquet(f"{path}/out")

        writer = stream.writeStream.foreachBatch(put)
    query = writer.option("checkpointLocation", f"{path}/state").outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/out"), late_rows(query)


def drain(stream: DataFrame, spark: SparkSession, name: str, mode: str = "append") -> DataFrame:
    return drain_counted(stream, spark, name, mode)[0]
