"""Near-duplicates by SimHash candidates and the resemblance of word shingles: every pair with a Jaccard of ``SHARE`` or more.

A document is the set of its distinct five-word shingles (A-Z lower-cased, XXH64), fewer words are one shingle of their
own length. Candidates come first from SimHash fingerprints of the sets that the pigeonring search of ``simhash`` finds
within ``BITS`` bits: they join the close copies of a group without its pairs. A Jaccard of 0.8 is about 9 bits, where no
segment of a fingerprint has to be equal, so the exact way for the rest is a join by shingles: under any one order of all
shingles, two sets of a Jaccard of at least t share one of the first n - ceil(t n) + 1 shingles of each, so these are the
join key and no pair is lost. Shingles that are frequent in a sample come last in the order; the sample decides how many
candidates there are and never which pairs are found. In each of ``STARS`` rounds the members of a key that are not in one
component yet are compared with one of them, chosen by hash for each key; only then are the pairs that share a key and are
still apart, and of these only those are made that pass the bound. Sets, not documents, are compared, so copies meet once.

Sketches travel only with rows that can still meet: a set leaves a key that holds no other set whose size and position
admit the share, and of keys with the same members a set keeps its first one, since the first shingle that two
resembling sets have in common is also the first of all keys with that key's members.

A candidate is held against a bound: a set's parity sketch has a bit for each slot of a hash table of about twice
its size, set if an odd number of its shingles falls there, and two sketches differ in at most as many bits as the sets
differ in shingles. What the bound leaves is verified by the exact intersection of the sets, which are made again from
the texts and not kept.

Defined results: null, empty and wordless texts have the empty set and are copies of each other; otherwise as in
``simhash.keep_one``.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import release, remove, sliced, write_table
from .components import components
from .simhash import KEEP_BROADCAST, keep_smallest, majority_bits, nearest

SHINGLE, SHARE, SEED, STARS, BITS = 5, 0.8, 42, 1, 5
ORDER_TEXTS, ORDER_SHINGLES, FREQUENT = 4_000, 200_000, 3  # bounds of the sample that sets the order


def shingle_set(text: str | None, length: int = SHINGLE) -> np.ndarray:
    """The distinct shingle hashes of one text in ascending order, as signed longs."""
    import xxhash

    words = (text or "").encode().lower().split()  # bytes: only A-Z change, and only the six ASCII blanks part words
    if not words:
        return np.empty(0, np.int64)
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    n = max(1, len(words) - length + 1)
    stops = ends[min(length, len(words)) - 1 :]
    digest = xxhash.xxh64_intdigest
    return np.unique(np.fromiter((digest(joined[a:b], SEED) for a, b in zip(starts[:n].tolist(), stops.tolist(), strict=True)), np.uint64, n).view(np.int64))


def prefix_length(n: int, share: float) -> int:
    return n - math.ceil(share * n - 1e-9) + 1


def set_hash(shingles: np.ndarray) -> int:
    import xxhash

    return int(np.uint64(xxhash.xxh64_intdigest(shingles.tobytes(), SEED)).view(np.int64))


def texts_of(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text_hash, text)."""
    text = F.col(text_col).cast("string")
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(F.coalesce(text, F.lit(""))).alias("text_hash"), text.alias("text"))


def shingle_sets(texts: DataFrame, length: int = SHINGLE) -> DataFrame:
    """(fp, shingles) for each text; fp is a hash of the whole set."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches):
            sets = [shingle_set(t.as_py(), length) for t in b.column(0)]
            yield pa.RecordBatch.from_arrays([pa.array(map(set_hash, sets), pa.int64()), pa.array(sets, pa.list_(pa.int64()))], ["fp", "shingles"])

    return texts.select("text").mapInArrow(run, "fp long, shingles array<long>")


def frequent(texts: DataFrame, length: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """(shingles ascending, their texts) of the most frequent shingles in a bounded sample of the texts."""
    part = max(1, texts.count() // ORDER_TEXTS)
    some = texts.where(F.pmod(F.xxhash64("text_hash"), F.lit(part)) == 0)
    seen = shingle_sets(some, length).select(F.explode("shingles").alias("s")).groupBy("s").count()
    top = seen.where(F.col("count") >= FREQUENT).orderBy(F.desc("count"), "s").limit(ORDER_SHINGLES).toPandas().sort_values("s")
    return top["s"].to_numpy(np.int64), top["count"].to_numpy(np.int64)


def sketch_bits(n: int) -> int:
    """Bits of a set's parity sketch: the power of two at or above twice its size, 64 at least."""
    return max(64, 1 << (2 * max(1, n) - 1).bit_length())


def parity_sketch(shingles: np.ndarray) -> np.ndarray:
    """The sketch as signed longs; halves that are XORed give the sketch of half as many bits."""
    m = sketch_bits(len(shingles))
    odd = np.bincount((shingles.view(np.uint64) & np.uint64(m - 1)).astype(np.int64), minlength=m) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").view("<i8")


def marked(texts: DataFrame, length: int = SHINGLE, share: float = SHARE) -> DataFrame:
    """(doc_id, text_hash, fp, n, sim, keys, sketch) for each text: its set's hash, size and SimHash fingerprint, the first
    shingles in the common order, and the parity sketch."""
    common, weight = frequent(texts, length)

    def keys(s: np.ndarray) -> np.ndarray:
        if not len(s):
            return s
        often = np.zeros(len(s), np.int64)
        if len(common):
            at = np.minimum(np.searchsorted(common, s), len(common) - 1)
            often = np.where(common[at] == s, weight[at], 0)
        return s[np.lexsort((s, often))[: prefix_length(len(s), share)]]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches):
            sets = [shingle_set(t.as_py(), length) for t in b.column(2)]
            made = [pa.array(map(set_hash, sets), pa.int64()), pa.array(map(len, sets), pa.int32()), pa.array(np.array([majority_bits(x.view(np.uint64)) for x in sets], np.uint64).view(np.int64))]
            made += [pa.array(map(f, sets), pa.list_(pa.int64())) for f in (keys, parity_sketch)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), *made], ["doc_id", "text_hash", "fp", "n", "sim", "keys", "sketch"])

    return texts.select("doc_id", "text_hash", "text").mapInArrow(run, "doc_id long, text_hash long, fp long, n int, sim long, keys array<long>, sketch array<long>")


def folded(sketch: Column, to: Column) -> Column:
    """A sketch of ``to`` or twice ``to`` longs as one of ``to`` longs."""
    half = F.zip_with(F.slice(sketch, F.lit(1), to), F.slice(sketch, to + 1, to), lambda x, y: x.bitwiseXOR(F.coalesce(y, F.lit(0).cast("long"))))
    return F.when(F.size(sketch) == to, sketch).otherwise(half)


def _bound(share: float, nu: Column, nv: Column, su: Column, sv: Column) -> Column:
    """May sets of these sizes and sketches have a Jaccard of ``share`` or more?"""
    to = F.least(F.size(su), F.size(sv))
    differ = F.aggregate(F.zip_with(folded(su, to), folded(sv, to), lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda x, y: x + y)
    # sets of a Jaccard of t differ in (1 - t) / (1 + t) of their sizes' sum, and their sizes by t, so that sketches are at most one fold apart
    near = differ <= F.lit((1 - share) / (1 + share)) * (nu + nv) + 1e-6
    return (F.least(nu, nv) >= F.lit(share) * F.greatest(nu, nv) - 1e-6) & near


def _verified(pairs: DataFrame, texts: DataFrame, marks: DataFrame, length: int, share: float) -> DataFrame:
    """(u, v) of the pairs whose sets resemble each other by ``share`` or more."""
    spark = texts.sparkSession
    sketches = marks.select("fp", "n", "sketch").dropDuplicates(["fp"])
    bound = pairs.distinct().join(sketches.toDF("u", "nu", "su"), "u").join(sketches.toDF("v", "nv", "sv"), "v")
    bound = bound.where(_bound(share, *map(F.col, ("nu", "nv", "su", "sv"))))
    pairs, path = write_table(bound.select("u", "v"), "resemblance-candidates")
    named = pairs.select(F.col("u").alias("fp")).unionByName(pairs.select(F.col("v").alias("fp"))).distinct()
    # a semi join would be pushed below the sums, and all copies of a set would go to one task
    one = marks.groupBy("fp").agg(F.min(F.struct("text_hash", "doc_id")).alias("t")).join(named, "fp")
    wanted, wanted_path = write_table(one.select(F.col("t.doc_id").alias("w_doc"), F.col("t.text_hash").alias("w_hash")), "resemblance-texts")
    listed = F.broadcast(wanted) if wanted.count() <= KEEP_BROADCAST else wanted
    chosen = texts.join(listed, F.col("doc_id").eqNullSafe(F.col("w_doc")) & (F.col("text_hash") == F.col("w_hash")), "left_semi")
    held, held_path = write_table(shingle_sets(chosen, length), "resemblance-sets")
    release(spark)
    both = pairs.join(held.toDF("v", "b"), "v").join(held.toDF("u", "a"), "u")
    met = both.select("u", "v", (F.size("a") + F.size("b")).alias("n"), F.size(F.array_intersect("a", "b")).alias("met"))
    out, _ = write_table(met.where(F.col("met") / (F.col("n") - F.col("met")) >= F.lit(share)).select("u", "v").distinct(), "resemblance-links")
    remove(spark, path, wanted_path, held_path)
    release(spark)
    return out


def _joined(rows: DataFrame, found: DataFrame) -> DataFrame:
    """``rows`` with the root of their set's component so far."""
    return rows.join(components(found).toDF("fp", "root"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))


def _reach(share: float) -> Column:
    """The largest size of a set that can share this row's key first and resemble its set."""
    return (F.col("n") - F.col("pos")) * F.lit((1 + share) / share) - F.col("n") + 1e-6


def _apart(rows: DataFrame, share: float, star: int) -> DataFrame:
    """``rows`` of keys whose sets are not all in one component yet, without those that fit no size in their key; ``members``
    names the sets of the key, ``center`` one of them."""
    of_key = Window.partitionBy("key")
    # plain columns first: what is made from them needs no place in the exchange
    met = rows.withColumn("lo", F.min("root").over(of_key)).withColumn("hi", F.max("root").over(of_key)).withColumn("least", F.min("n").over(of_key))
    met = met.withColumn("reach", _reach(share)).where("lo < hi and least <= reach").drop("lo", "hi", "least")
    center = F.min(F.struct(F.xxhash64(F.lit(star), F.col("fp"), F.col("key")).alias("h"), "fp", "n", "pos", "root")).over(of_key)
    members = F.struct(*[F.bit_xor(F.xxhash64(F.lit(i), F.col("fp"))).over(of_key).alias(f"h{i}") for i in (1, 2)])
    met = met.select("*", F.max("reach").over(of_key).alias("most"), center.alias("center"), members.alias("members"))
    return met.where("most >= n").drop("most", "reach")


def _first_keys(rows: DataFrame) -> DataFrame:
    """``rows`` with one key for each set and group of keys with the same members: the first in the common order."""
    dealt = rows.repartition("fp")  # that of the join with the sketches
    first = dealt.groupBy("fp", "members").agg(F.min(F.struct("pos", "key")).alias("at"), F.first("n").alias("n"), F.first("root").alias("root"))
    return first.select("fp", "n", "at.pos", "at.key", "root")


def links(texts: DataFrame, marks: DataFrame, length: int = SHINGLE, share: float = SHARE) -> DataFrame:
    """(u, v): edges that connect the sets which resemble each other by ``share`` or more."""
    spark = texts.sparkSession
    # the first common shingle of a pair bounds what is common from it on
    fits = lambda na, pa, nb, pb: F.least(na - pa, nb - pb) >= F.lit(share / (1 + share)) * (na + nb) - 1e-6
    close = nearest(marks.select(F.col("fp").alias("mark"), F.col("sim").alias("fp")).dropDuplicates(["mark"]), BITS)
    found, path = _verified(close, texts, marks, length, share), None
    # roots are joined to the sets and not to their keys, of which there are many times more
    open_ = _joined(marks.select("fp", "n", "keys").dropDuplicates(["fp"]), found).select("fp", "n", F.posexplode("keys").alias("pos", "key"), "root")
    for star in range(STARS + 1):
        rest, rest_path = write_table(_apart(open_, share, star), "resemblance-keys")
        if path:
            remove(spark, path)
        path = rest_path
        release(spark)
        if star < STARS:
            near = fits(F.col("n"), F.col("pos"), F.col("center.n"), F.col("center.pos"))
            pairs = rest.where((F.col("root") != F.col("center.root")) & near).select(F.least("fp", "center.fp").alias("u"), F.greatest("fp", "center.fp").alias("v"))
        else:
            # the bound is part of the join, so that pairs it rules out are never made
            whole = _first_keys(rest).join(marks.select("fp", "sketch").dropDuplicates(["fp"]), "fp")
            # written, so that both sides of the join read one exchange
            whole, path = write_table(whole, "resemblance-last")
            remove(spark, rest_path)
            release(spark)
            a, b = whole.alias("a"), whole.alias("b")
            within = fits(F.col("a.n"), F.col("a.pos"), F.col("b.n"), F.col("b.pos")) & _bound(share, *map(F.col, ("a.n", "b.n", "a.sketch", "b.sketch")))
            pairs = a.join(b, (F.col("a.key") == F.col("b.key")) & (F.col("a.fp") < F.col("b.fp")) & (F.col("a.root") != F.col("b.root")) & within)
            pairs = pairs.select(F.col("a.fp").alias("u"), F.col("b.fp").alias("v"))
        found = found.unionByName(_verified(pairs, texts, marks, length, share))
        if star < STARS:
            open_ = _joined(rest.drop("center", "members", "root"), found)
    remove(spark, path)
    return found


def keep_one(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", length: int = SHINGLE, share: float = SHARE) -> DataFrame:
    """The documents with all their columns, one row for each component: that of the smallest doc_id (null last)."""
    texts = texts_of(docs, id_col=id_col, text_col=text_col)
    marks, _ = write_table(marked(texts, length, share), "shingle-marks")
    roots = components(links(texts, marks, length, share)).withColumnRenamed("node", "fp")
    classes = marks.select("fp").distinct().join(roots, "fp", "left").select("fp", F.coalesce("root", "fp").alias("root"))
    return keep_smallest(docs, marks.select("doc_id", "text_hash", "fp"), classes, id_col=id_col, text_col=text_col)
