"""Quality classifier: nearest-neighbour voting among labelled latent-semantic vectors.

A text's terms are its words (A-Z lower-cased), its word shapes (letters collapsed to one, punctuation kept), pairs of
neighbouring shapes, and bins of a few whole-text ratios (repeated words, capitals, symbols). Hashed tf-idf vectors of a
bounded labelled sample (``PER_CLASS`` rows and ``SAMPLE_BYTES`` bytes a class) are reduced by a truncated SVD; the
sample's vectors (2 x PER_CLASS x RANK numbers) and the projection go to every executor, and each document's cosines
with all of them come from blocked matrix products. The ``NEIGHBOURS`` nearest vote with their similarity; the classes'
sampling rates are corrected by weight.

Defined results: null, empty and wordless texts have the labelled rows' share of label 1 as their score; unlabelled
rows, null labels and rows with conflicting labels are not learned from; without any labelled row every score is 0.5;
ties between neighbours (cosines equal to nine digits) go to the earlier sample row; repeated rows each get a row; empty
tables and other columns are fine.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import hash60, written

PER_CLASS, BUCKETS, RANK, NEIGHBOURS = 1500, 8192, 32, 25
SAMPLE_BYTES = 32 << 20
SLICE = 256  # rows of a batch that are made into Python objects at once
SCHEMA = "doc_id long, score double"

_CLASS = bytes(
    97 if 97 <= c <= 122 or c >= 128 else 65 if 65 <= c <= 90 else 48 if 48 <= c <= 57 else 32 if c in b" \t\n\r\x0b\x0c" else c for c in range(256)
)
_RUNS = re.compile(rb"(a|A|0)\1+")


def terms(text: str | None) -> Counter:
    data = (text or "").encode()
    words = data.split()
    out: Counter = Counter()
    if not words:
        return out
    shapes = _RUNS.sub(rb"\1", data.translate(_CLASS)).split()
    out.update(shapes)
    out.update(zip(shapes, shapes[1:], strict=False))
    n, share = len(words), Counter(words)
    for w, c in share.items():
        out[w.lower().decode()] += c  # as a string, so that no word is taken for a shape
    weight = max(1, n // 8)
    letters = sum(data.count(bytes([c])) for c in b"ABCDEFGHIJKLMNOPQRSTUVWXYZ")
    for name, ratio in (("distinct", len(share) / n ** 0.9), ("most", max(share.values()) / n), ("capitals", letters / len(data)), ("symbols", sum(data.count(c) for c in (b"*", b"#", b"$", b"%", b"&", b"|", b"!")) / len(data))):
        out[f"{name}{min(9, int(ratio * 10))}"] = weight
    return out


def _slot(term) -> int:
    key = b"\x00".join(term) if isinstance(term, tuple) else b"\x01" + term.encode() if isinstance(term, str) else term
    return zlib.crc32(key) % BUCKETS


def sparse(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """(slots, square-root term frequencies)."""
    sums: dict[int, float] = {}
    for t, c in terms(text).items():
        s = _slot(t)
        sums[s] = sums.get(s, 0.0) + c
    slots = np.fromiter(sums, np.int64, len(sums))
    return slots, np.sqrt(np.fromiter(sums.values(), np.float64, len(sums)))


@dataclass
class NeighbourModel:
    projection: np.ndarray  # BUCKETS x RANK, idf included
    vectors: np.ndarray  # labelled rows x RANK, unit length
    labels: np.ndarray
    weights: np.ndarray
    prior: float

    def embed(self, texts: list[str | None]) -> np.ndarray:
        out = np.zeros((len(texts), self.projection.shape[1]))
        for i, t in enumerate(texts):
            slots, tf = sparse(t)
            if len(slots):
                v = tf @ self.projection[slots]
                out[i] = v / (np.linalg.norm(v) or 1.0)
        return out

    def score(self, texts: list[str | None], block: int = 256) -> np.ndarray:
        out = np.full(len(texts), self.prior)
        k = min(NEIGHBOURS, len(self.labels))
        if not k:
            return out
        vectors = self.embed(texts)
        for a in range(0, len(texts), block):
            # equal rows must have equal cosines, whatever block they are multiplied in
            cos = np.round(vectors[a : a + block] @ self.vectors.T, 9)
            least = np.partition(cos, len(self.labels) - k, axis=1)[:, len(self.labels) - k, None]
            above, equal = cos > least, cos == least
            taken = above | (equal & (np.cumsum(equal, 1) <= k - above.sum(1, keepdims=True)))
            w = np.where(taken, np.maximum(cos, 0.0) ** 2 * self.weights, 0.0)
            total = w.sum(1)
            live = total > 0
            out[a : a + block][live] = (w @ self.labels)[live] / total[live]
        return np.clip(out, 0.0, 1.0)


def _chosen(rows: DataFrame, total: int, n: int) -> list:
    """The ids of ``n`` rows of (l_id) by hash; the hash's bound keeps all but about 2 n rows from being compared."""
    h = hash60(F.col("l_id"), salt="label:")
    some = rows.withColumn("h", h).where(F.col("h") < int(min(1.0, (2 * n + 100) / max(1, total)) * (1 << 60)))
    return [r["l_id"] for r in some.orderBy("h", "l_id").limit(n).select("l_id").collect()]


def learning_sample(
    docs: DataFrame, labels: DataFrame, label: str, *, per_class: int, unlabelled: int = 0, may_learn=None, sample_bytes: int = SAMPLE_BYTES, id_col: str = "doc_id", text_col: str = "text"
) -> tuple[list[tuple[str, int]], dict[int, int], list[str]]:
    """(at most ``per_class`` (text, label) rows of each class, rows of each class, at most ``unlabelled`` other texts), all
    by hash of the id and within ``sample_bytes`` a class. may_learn: a condition on ``docs`` that unlabelled rows fulfil.

    The first row of a class is taken whatever its size; a doc_id with several texts gives the smallest.
    """
    spark = docs.sparkSession
    known = labels.where(F.col(label).isin(0, 1) & F.col("doc_id").isNotNull()).groupBy(F.col("doc_id").cast("long").alias("l_id")).agg(
        F.min(F.col(label).cast("int")).alias("y"), F.max(F.col(label).cast("int")).alias("most")
    ).where("y = most").select("l_id", "y")
    counts = {r["y"]: r["n"] for r in known.groupBy("y").agg(F.count(F.lit(1)).alias("n")).collect()}
    ids = [(i, y) for y in sorted(counts) for i in _chosen(known.where(F.col("y") == y), counts[y], per_class)]
    if unlabelled:
        free = docs if may_learn is None else docs.where(may_learn)
        free = free.select(F.col(id_col).cast("long").alias("l_id")).where("l_id is not null")
        free = free.join(labels.select(F.col("doc_id").cast("long").alias("l_id")), "l_id", "left_anti")
        ids += [(i, -1) for i in _chosen(free, free.count(), unlabelled)]
    if not ids:
        return [], counts, []
    wanted = F.broadcast(spark.createDataFrame(sorted(set(ids)), "l_id long, y int"))  # bounded by the parameters
    rows = docs.select(F.col(id_col).cast("long").alias("l_id"), F.col(text_col).cast("string").alias("text")).join(wanted, "l_id")
    rows = written(rows.groupBy("l_id", "y").agg(F.min("text").alias("text")), "learning-sample")
    sizes = {(r["l_id"], r["y"]): r["n"] for r in rows.select("l_id", "y", F.coalesce(F.octet_length("text"), F.lit(0)).alias("n")).collect()}
    held, keep = Counter(), []
    for key in ids:
        if key in sizes and (not held[key[1]] or held[key[1]] + sizes[key] <= sample_bytes):
            held[key[1]] += sizes[key] + 1
            keep.append(key)
    kept = F.broadcast(spark.createDataFrame(sorted(set(keep)), "l_id long, y int"))
    found = sorted(((r["l_id"], r["y"], r["text"]) for r in rows.join(kept, ["l_id", "y"]).collect()), key=lambda r: r[:2])
    return [(t, y) for _, y, t in found if y >= 0], counts, [t for _, y, t in found if y < 0]


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, *, per_class: int, **options) -> tuple[list[tuple[str, int]], dict[int, int]]:
    return learning_sample(docs, labels, label, per_class=per_class, **options)[:2]


Rows = list[tuple[np.ndarray, np.ndarray]]  # (slots, values) of each row


def _blocks(rows: Rows, width: int, size: int = 256) -> Iterator[tuple[slice, np.ndarray]]:
    """Dense rows, few at a time: the whole matrix would be as large as the driver's other memory."""
    for a in range(0, len(rows), size):
        part = rows[a : a + size]
        dense = np.zeros((len(part), width))
        for i, (slots, values) in enumerate(part):
            dense[i, slots] = values
        yield slice(a, a + len(part)), dense


def latent_axes(rows: Rows, width: int, rank: int, tolerance: float = 1e-12, most: int = 120) -> np.ndarray:
    """The ``rank`` leading right singular vectors as columns: subspace iteration on the rows' Gram matrix (the rows are a
    bounded sample) until the subspace stands still."""
    n = len(rows)
    r = min(rank, n)
    gram = np.empty((n, n))
    for i, x in _blocks(rows, width):
        for j, y in _blocks(rows[: i.stop], width):
            gram[i, j] = x @ y.T
            gram[j, i] = gram[i, j].T
    basis, _ = np.linalg.qr(np.random.default_rng(7).standard_normal((n, min(n, r + 24))))
    old = np.zeros(basis.shape[1])
    for _ in range(most):
        basis, up = np.linalg.qr(gram @ basis)
        new = np.abs(np.diag(up))
        if np.abs(new[:r] - old[:r]).max() <= tolerance * max(new.max(), 1e-300):
            break
        old = new
    _, _, vt = np.linalg.svd(sum(basis[i].T @ x for i, x in _blocks(rows, width)), full_matrices=False)
    return vt[:r].T


def fit(sample: list[tuple[str | None, int]], counts: dict[int, int], rank: int = RANK) -> NeighbourModel:
    n = len(sample)
    total = sum(counts.values())
    prior = counts.get(1, 0) / total if total else 0.5
    if not n:
        return NeighbourModel(np.zeros((BUCKETS, 1)), np.zeros((0, 1)), np.zeros(0), np.zeros(0), prior)
    rows = [sparse(text) for text, _ in sample]
    held = np.zeros(BUCKETS)
    for slots, _ in rows:
        held[slots] += 1
    idf = np.log((1 + n) / (1 + held)) + 1
    for i, (slots, tf) in enumerate(rows):
        weighted = tf * idf[slots]
        rows[i] = slots, weighted / max(np.linalg.norm(weighted), 1e-12)
    axes = latent_axes(rows, BUCKETS, rank)
    model = NeighbourModel(idf[:, None] * axes, np.zeros((0, axes.shape[1])), np.array([y for _, y in sample], np.float64), np.zeros(0), prior)
    model.vectors = model.embed([t for t, _ in sample])
    taken = Counter(y for _, y in sample)
    model.weights = np.array([counts[y] / taken[y] for _, y in sample]) / total
    return model


def _scores(model, texts: pa.Array) -> np.ndarray:
    """``model.score`` over slices, so that few texts are Python objects at once."""
    parts = [model.score(texts.slice(a, SLICE).to_pylist()) for a in range(0, len(texts), SLICE)]
    return np.concatenate(parts) if parts else np.zeros(0)


def score_documents(docs: DataFrame, model, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, score) for each document; ``model`` has ``score(texts)``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(_scores(model, b.column(1)), pa.float64())], ["doc_id", "score"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, SCHEMA)


def keep_good(docs: DataFrame, model: NeighbourModel, *, threshold: float = 0.3, text_col: str = "text") -> DataFrame:
    """The documents whose score reaches the threshold, with all their columns."""

    @F.arrow_udf("double")
    def good(texts: pa.Array) -> pa.Array:
        return pa.array(_scores(model, texts), pa.float64())

    return docs.where(good(F.col(text_col).cast("string")) >= threshold)
