"""Sharding by proportional stratified interleaving.

Rows get a seeded-shuffled rank within their source; a row's place is its fractional rank (rank + 1/2) / n, so every
stretch of the order holds each source in proportion; equal cuts of that order are the shards. Neither rank needs a
group in one task: rows are range-partitioned and sorted by (source, hash), ``monotonically_increasing_id`` numbers
them inside their partition, and the counts of the partitions (one row each) give the offsets. The same is done once
more by fractional rank.

Law: ``rows`` (counts of the shards are at most one apart). Defined results: a null text has size 1; a null source is
a source of its own; rows with equal doc_id are ordered by their text's hash, and rows equal in both are
interchangeable; an empty table gives no rows; columns of ``docs`` stay with ``shard_rows``, where ``shard`` and
``slot`` replace columns of the same name.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import hash60, source_key, written

_LOW = (1 << 33) - 1
SOURCE_BOUND = 100_000  # sources that are broadcast


def _places(ordered: DataFrame) -> DataFrame:
    """Adds ``place``, the row's number in the order of its range partitions; ``ordered`` is sorted inside them."""
    rows = written(ordered.withColumn("mono", F.monotonically_increasing_id()), "shard-order")
    part = F.shiftright("mono", 33)
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = rows.groupBy(part.alias("part")).count().select("part", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("offset"))
    return rows.withColumn("part", part).join(F.broadcast(offsets), "part").withColumn("place", F.col("offset") + F.col("mono").bitwiseAND(_LOW)).drop("part", "offset", "mono")


def interleave(slim: DataFrame, shards: int) -> DataFrame:
    """slim: (…, key, hash, tie). Adds shard and slot."""
    order = ["key", "hash", "tie"]
    first = _places(slim.repartitionByRange(*order).sortWithinPartitions(*order))
    counts = slim.groupBy("key").agg(F.count(F.lit(1)).alias("n"))
    starts = counts.withColumn("start", F.coalesce(F.sum("n").over(Window.orderBy("key").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    listed = F.broadcast(starts) if counts.count() <= SOURCE_BOUND else starts
    ranked = first.join(listed, "key").withColumn("frac", (2 * (F.col("place") - F.col("start")) + 1) / (2 * F.col("n"))).drop("place", "start", "n")
    order = ["frac", *order]
    total = slim.count()
    placed = _places(ranked.repartitionByRange(*order).sortWithinPartitions(*order))
    shard = F.expr(f"CAST(place * {shards} div {max(total, 1)} AS INT)")
    start = F.expr(f"(CAST(shard AS LONG) * {total} + {shards - 1}) div {shards}")
    return placed.withColumn("shard", shard).withColumn("slot", (F.col("place") - start).cast("long"))


def _keys(docs: DataFrame, id_col: str, source_col: str, tied: list[str]) -> list[Column]:
    return [source_key(F.col(source_col)).alias("key"), hash60(F.col(id_col), salt="shard:").alias("hash"), F.xxhash64(*[docs[c] for c in tied]).alias("tie")]


def shard_documents(docs: DataFrame, *, shards: int = 8, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """(doc_id, size, text_crc32, law, shard, slot, grown_shard) for each document; texts are not moved."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    slim = written(docs.select(
        F.col(id_col).alias("doc_id"), (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"),
        *_keys(docs, id_col, source_col, [text_col]),
    ), "shard-rows")
    return interleave(slim, shards).select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def shard_rows(docs: DataFrame, *, shards: int = 8, id_col: str = "doc_id", source_col: str = "source") -> DataFrame:
    """The documents with ``shard`` and ``slot``; rows equal in all columns are interchangeable.

    Ranks are found on slim rows; whole rows move once, for the join that gives each ranked row its columns.
    """
    keys = _keys(docs, id_col, source_col, docs.columns)
    ranked = interleave(written(docs.select(*keys), "shard-rows"), shards).select("hash", "tie", "shard", "slot")
    names = [c for c in docs.columns if c not in ("shard", "slot")]
    rows = docs.select(F.struct(*names).alias("row"), *keys[1:]).dropDuplicates(["hash", "tie"])
    return rows.join(ranked, ["hash", "tie"]).select("row.*", "shard", "slot")


SQL = r"""
WITH crc AS (SELECT list(list_reduce(range(8), lambda x, i: CASE WHEN x & 1 = 1 THEN xor(x >> 1, 3988292384) ELSE x >> 1 END, n) ORDER BY n) AS t FROM range(256) r(n)),
d AS (SELECT doc_id, CAST(strlen(coalesce(text, '')) + 1 AS BIGINT) AS size, hex(encode(coalesce(text, ''))) AS h, CASE WHEN source IS NULL THEN 't' ELSE 's' || source END AS key,
    ('0x' || substr(md5('shard:' || coalesce(CAST(doc_id AS VARCHAR), '')), 1, 15))::BIGINT AS hash FROM documents),
r AS (SELECT *, CAST(2 * (row_number() OVER (PARTITION BY key ORDER BY hash) - 1) + 1 AS DOUBLE) / (2 * count(*) OVER (PARTITION BY key)) AS frac FROM d),
p AS (SELECT *, row_number() OVER (ORDER BY frac, key, hash) - 1 AS place, count(*) OVER () AS n FROM r),
q AS (SELECT *, CAST(place * 8 // n AS INTEGER) AS shard FROM p)
SELECT doc_id, size, xor(list_reduce(list_transform(range(0, length(h) // 2), lambda i: CAST('0x' || substr(h, 2 * i + 1, 2) AS BIGINT)), lambda x, b: xor(x >> 8, t[(xor(x, b) & 255) + 1]), 4294967295), 4294967295) AS text_crc32,
    'rows' AS law, shard, CAST(place - (shard * n + 7) // 8 AS BIGINT) AS slot, CAST(NULL AS INTEGER) AS grown_shard FROM q, crc
"""
