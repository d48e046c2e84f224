"""Benchmark decontamination by size-partitioned MinHash containment search (DataFrame functions only).

Items are partitioned by size (powers of two of their distinct shingles); the partition fixes how many of an item's
smallest shingle hashes make its signature. A document that holds at least a share t of an item's n shingles lacks at
most n - ceil(t n) of them; with one hash more than that, for the largest n of the partition, some signature hash must
occur in the document, however long it is. A document's own sketch is the lower part of its shingle hashes, up to the
largest signature hash of the partition, so that whatever could meet a signature is in it: no pair is lost, and the
rest of a long document is not even exploded. What meets is verified by exact containment of the shingle strings. A
document is compared with an item through the hashes they share and never with all items.

Shingles are five words (A-Z lower-cased); an item of fewer words is one shingle of its own length, an item without
words is never found. Defined results: null and empty texts hold nothing; repeated rows count once for a doc_id and
text; items are told apart by item_id and text, so that repeated or null ids pool nothing and equal rows count once; an
empty table gives no pairs; other columns are ignored by ``find_leaks`` and kept by ``drop_leaks``. The signature table
grows with the benchmark, not with the corpus, and is broadcast under ``BROADCAST_ROWS`` only.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import words_of, write_table

SHINGLE, SHARE = 5, 0.8
BROADCAST_ROWS = 500_000
PAIRS = "doc_id long, text_hash long, item_id long, shingles long, found long, containment double"


def _starts(words: str, length: int) -> Column:
    last = F.size(words) - length + 1
    return F.when(last >= 1, F.sequence(F.lit(1), last)).otherwise(F.array().cast("array<int>"))


def word_hashes(words: str) -> Column:
    return F.transform(words, lambda w: F.xxhash64(w))


def shingle_hashes(hashes: str, length: int) -> Column:
    """One 64-bit hash for each run of ``length`` words of the array column ``hashes``, the words' own hashes."""
    h = F.col(hashes)
    return F.transform(_starts(hashes, length), lambda i: F.xxhash64(F.lit(length), *[F.element_at(h, i + k) for k in range(length)]))


def shingle_texts(words: str, length: int) -> Column:
    w = F.col(words)
    return F.transform(_starts(words, length), lambda i: F.concat_ws(" ", *[F.element_at(w, i + k) for k in range(length)]))


def _checked(df: DataFrame, bound: int = BROADCAST_ROWS) -> DataFrame:
    return F.broadcast(df) if df.count() <= bound else df


def _keyed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(doc_id, text_hash, text)."""
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(F.coalesce(F.col(text_col), F.lit(""))).alias("text_hash"), F.col(text_col).alias("text"))


def item_shingles(benchmark: DataFrame, item_col: str = "item_id", text_col: str = "text", share: float = SHARE) -> DataFrame:
    """(item, item_id, length, shingle, hash, n, size_class, keep): distinct shingles of each item; ``item`` tells items
    apart, ``keep`` marks the shingles of the signature."""
    id_, text = F.col(item_col).cast("long"), F.col(text_col)
    words = benchmark.select(F.xxhash64(id_, text).alias("item"), id_.alias("item_id"), words_of(text).alias("w")).where(F.size("w") > 0)
    words = words.withColumn("h", word_hashes("w"))
    made = None
    for length in range(1, SHINGLE + 1):
        fits = F.size("w") == length if length < SHINGLE else F.size("w") >= length
        both = F.arrays_zip(shingle_texts("w", length).alias("shingle"), shingle_hashes("h", length).alias("hash"))
        part = words.where(fits).select("item", "item_id", F.lit(length).alias("length"), F.inline(both)).toDF("item", "item_id", "length", "shingle", "hash")
        made = part if made is None else made.unionByName(part)
    of_item = Window.partitionBy("item")
    missing = lambda n: F.floor(n * (1 - share) + 1e-9)
    return (
        made.distinct()
        .withColumn("n", F.count(F.lit(1)).over(of_item))
        .withColumn("size_class", F.ceil(F.log2(F.col("n").cast("double"))).cast("int"))
        .withColumn("keep", F.row_number().over(of_item.orderBy("hash", "shingle")) <= missing(F.pow(F.lit(2.0), F.col("size_class"))) + 1)
    )


def sketch(hashes: str, lengths: dict[int, int]) -> Column:
    """A document's shingle hashes that could meet a signature: for each length those up to its bound."""
    def low(top: int):
        return lambda h: h <= F.lit(top)

    parts = [F.filter(shingle_hashes(hashes, n), low(top)) for n, top in sorted(lengths.items())]
    return F.concat(*parts) if len(parts) > 1 else parts[0]


def find_leaks(docs: DataFrame, benchmark: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", share: float = SHARE) -> DataFrame:
    """(doc_id, text_hash, item_id, shingles, found, containment) for each document that holds at least ``share`` of an item."""
    spark = docs.sparkSession
    items, _ = write_table(item_shingles(benchmark, item_col, item_text_col, share), "leak-items")
    # one row a length, five at most: the largest signature hash of its partitions
    lengths = {r["length"]: r["top"] for r in items.where("keep").groupBy("length").agg(F.max("hash").alias("top")).collect()}
    if not lengths:
        return spark.createDataFrame([], PAIRS)
    signature = _checked(items.where("keep").select("hash", "item"))
    texts = _keyed(docs, id_col, text_col)
    hashed = texts.select("doc_id", "text_hash", words_of(F.col("text")).alias("w")).select("doc_id", "text_hash", word_hashes("w").alias("h"))
    met = hashed.select("doc_id", "text_hash", F.explode(sketch("h", lengths)).alias("hash")).join(signature, "hash")
    candidates, _ = write_table(met.select("doc_id", "text_hash", "item").distinct(), "leak-candidates")
    suspects = candidates.select(F.col("doc_id").alias("c_doc"), F.col("text_hash").alias("c_hash")).distinct()
    again = texts.join(_checked(suspects), F.col("doc_id").eqNullSafe(F.col("c_doc")) & (F.col("text_hash") == F.col("c_hash")), "left_semi")
    again = again.select("doc_id", "text_hash", words_of(F.col("text")).alias("w"))
    every = [shingle_texts("w", n) for n in sorted(lengths)]
    # a shingle's length shows in its text, so that the lengths need not be told apart
    spread = again.select("doc_id", "text_hash", F.explode(F.concat(*every) if len(every) > 1 else every[0]).alias("shingle"))
    held = spread.join(_checked(items.select("shingle", "item")), "shingle").groupBy("doc_id", "text_hash", "item").agg(F.count_distinct("shingle").alias("found"))
    pair = [F.col("doc_id").eqNullSafe(F.col("p_doc")), F.col("text_hash") == F.col("p_hash"), F.col("item") == F.col("p_item")]
    kept = held.join(candidates.toDF("p_doc", "p_hash", "p_item"), pair, "left_semi")
    sizes = items.groupBy("item").agg(F.first("item_id").alias("item_id"), F.first("n").alias("shingles"))
    return kept.join(_checked(sizes), "item").where(F.col("found") >= F.lit(share) * F.col("shingles")).select(
        "doc_id", "text_hash", "item_id", "shingles", "found", (F.col("found") / F.col("shingles")).alias("containment")
    )


def drop_leaks(docs: DataFrame, benchmark: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The documents that hold no item, with all their columns."""
    found = find_leaks(docs, benchmark, id_col=id_col, text_col=text_col, **options)
    bad, _ = write_table(found.select(F.col("doc_id").alias("__b_doc"), F.col("text_hash").alias("__b_hash")).distinct(), "leak-documents")
    same = docs[id_col].cast("long").eqNullSafe(bad["__b_doc"]) & (F.xxhash64(F.coalesce(docs[text_col], F.lit(""))) == bad["__b_hash"])
    return docs.join(_checked(bad), same, "left_anti")


SQL = r"""
WITH norm AS (SELECT DISTINCT item_id, text, list_filter(regexp_split_to_array(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM benchmark),
sized AS (SELECT row_number() OVER () AS item, item_id, w, least(len(w), 5) AS k FROM norm WHERE len(w) > 0),
items AS (SELECT DISTINCT item, item_id, k, unnest([array_to_string(w[i:i + k - 1], ' ') FOR i IN range(1, len(w) - k + 2)]) AS shingle FROM sized),
counts AS (SELECT item, count(*) AS shingles FROM items GROUP BY item),
dnorm AS (SELECT DISTINCT doc_id, text, list_filter(regexp_split_to_array(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
dsh AS (SELECT DISTINCT doc_id, text, k, unnest([array_to_string(w[i:i + k - 1], ' ') FOR i IN range(1, len(w) - k + 2)]) AS shingle FROM dnorm, (SELECT DISTINCT k FROM sized)),
hit AS (SELECT doc_id, text, item, item_id, count(*) AS found FROM dsh JOIN items USING (shingle, k) GROUP BY ALL)
SELECT doc_id, item_id, CAST(shingles AS BIGINT) AS shingles, CAST(found AS BIGINT) AS found, CAST(found AS DOUBLE) / shingles AS containment
FROM hit JOIN counts USING (item) WHERE found >= 0.8 * shingles
"""
