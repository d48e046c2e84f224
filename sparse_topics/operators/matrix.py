"""The term-document matrix as rows (term, doc_id, tf, df); an entry's value is tf / df, or another weighting."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import text as T
from ..plans import choice
from ..session import remove, write_table, written


#: Documents that are counted at once.
SLICE = 500


@dataclass
class TermDoc:
    """A: rows are terms, columns are documents. ``coo`` has term, doc_id, tf, df."""

    coo: DataFrame
    weight: str = "df"
    docs: int | None = None  # all documents, those without a term included
    _facts: dict = field(default_factory=dict)
    _blocks: object = None  # block tables, see lockstep.py
    _terms: DataFrame | None = None  # (term, df) of all terms, if the preparation has written them

    def value(self) -> Column:
        if self.weight == "none":
            return F.col("tf").cast("double")
        if self.weight == "tfidf":
            return F.col("tf") * F.log(F.lit(float(self.n_docs)) / F.col("df"))
        return F.col("tf") / F.col("df")

    def unit(self) -> Column:
        """The value of one occurrence."""
        if self.weight == "none":
            return F.lit(1.0)
        return F.log(F.lit(float(self.n_docs)) / F.col("df")) if self.weight == "tfidf" else 1 / F.col("df")

    def entries(self) -> DataFrame:
        """(term, doc_id, x)."""
        return self.coo.select("term", "doc_id", self.value().alias("x"))

    @property
    def n_docs(self) -> int:
        if self.docs is None:
            self.docs = self.coo.select("doc_id").distinct().count()
        return self.docs

    def facts(self) -> dict:
        """n_terms, nnz and the squared norm, in one pass."""
        if not self._facts:
            x = self.value()
            r = self.coo.agg(F.count_distinct("term").alias("n_terms"), F.count(F.lit(1)).alias("nnz"), F.sum(x * x).alias("norm_sq")).first()
            self._facts = {"n_terms": r["n_terms"], "nnz": r["nnz"], "norm_sq": r["norm_sq"] or 0.0}
        return self._facts

    @property
    def n_terms(self) -> int:
        return self.facts()["n_terms"]

    @property
    def norm_sq(self) -> float:
        return self.facts()["norm_sq"]


def count_terms(docs: DataFrame, how: str = "shuffle", *, id_col: str = "doc_id", text_col: str = "text", stop: tuple[str, ...] = ()) -> DataFrame:
    """(term, doc_id, tf). 'shuffle': SQL aggregation; 'in_row': a document is one row, so its counts need no exchange."""
    if how == "shuffle":
        tokens = T.drop_stop_words(T.tokenize(docs, id_col=id_col, text_col=text_col), stop)
        return tokens.groupBy("term", "doc_id").agg(F.count(F.lit(1)).alias("tf"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for start in range(0, b.num_rows, SLICE):
                ids, w = (b.column(c).slice(start, SLICE) for c in (0, 1))
                lengths = np.diff(w.offsets.to_numpy()) if not w.null_count else np.array([len(x.as_py() or ()) for x in w])
                coded = w.flatten().dictionary_encode()
                n = max(len(coded.dictionary), 1)
                pairs, tf = np.unique(np.repeat(np.arange(len(w)), lengths) * n + coded.indices.to_numpy(), return_counts=True)
                yield pa.RecordBatch.from_arrays([coded.dictionary.take(pa.array(pairs % n)).cast(pa.string()), ids.take(pa.array(pairs // n)), pa.array(tf, pa.int64())], ["term", "doc_id", "tf"])

    kind = docs.schema[id_col].dataType.simpleString()
    out = docs.select(F.col(id_col).alias("doc_id"), T.words(F.col(text_col)).alias("w")).mapInArrow(run, f"term string, doc_id {kind}, tf long")
    return T.drop_stop_words(out, stop)


def kept_terms(counts: DataFrame, by: str = "total", min_count: int = 2, max_df_share: float | None = None, n_docs: int | None = None) -> DataFrame:
    """(term, df, sq) of the terms whose total count (or number of documents) is at least ``min_count``; sq: the sum of squared counts."""
    per_term = counts.groupBy("term").agg(F.sum("tf").alias("total"), F.count(F.lit(1)).alias("df"), F.sum(F.col("tf").cast("double") * F.col("tf")).alias("sq"))
    kept = per_term.where(F.col("total" if by == "total" else "df") >= min_count)
    if max_df_share is not None:
        kept = kept.where(F.col("df") <= max_df_share * n_docs)
    return kept.select("term", "df", "sq")


def prune_rare(counts: DataFrame, by: str = "total", min_count: int = 2, max_df_share: float | None = None, n_docs: int | None = None) -> DataFrame:
    """(term, doc_id, tf, df) of the ``kept_terms``."""
    return _of_terms(counts, kept_terms(counts, by, min_count, max_df_share, n_docs))


def _of_terms(counts: DataFrame, kept: DataFrame) -> DataFrame:
    return counts.join(kept.select("term", "df"), "term").select("term", "doc_id", "tf", "df")


def weight_rows(coo: DataFrame, how: str = "df", docs: int | None = None) -> TermDoc:
    """'df': each row divided by its number of entries; 'none': raw counts; 'tfidf'. Kept as an expression over tf, df."""
    return TermDoc(coo, how, docs)


def build_term_doc(
    docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", stop: tuple[str, ...] = T.LANGUAGES, how: str | None = None, prune: str | None = "total",
    min_count: int = 2, max_df_share: float | None = None, weight: str = "df", store: bool = True,
) -> TermDoc:
    """The whole preparation, written once; documents without a term still count as documents. Without ``how``, counts are made
    in the rows if no two rows have one id, and then lie by document without an exchange."""
    if how is None:
        n_docs, ids = docs.agg(F.count(F.lit(1)), F.count_distinct(id_col)).first()
        how = "in_row" if ids == n_docs else "shuffle"
    else:
        n_docs = docs.count()
    counts = count_terms(docs, how, id_col=id_col, text_col=text_col, stop=stop)
    pruning = prune or "total", min_count if prune else 1, max_df_share, n_docs
    if not store:
        return weight_rows(prune_rare(counts, *pruning), weight, n_docs)
    counts, path = write_table(counts, "counts")
    kept = written(kept_terms(counts, *pruning), "terms")
    n_terms, nnz = kept.agg(F.count(F.lit(1)), F.sum("df")).first()
    coo = _of_terms(counts, F.broadcast(kept) if n_terms < choice.BROADCAST_ENTRIES else kept)
    if how != "in_row" or n_terms >= choice.BROADCAST_ENTRIES:
        coo = coo.repartition("doc_id").sortWithinPartitions("term")
    td = weight_rows(written(coo, "matrix"), weight, n_docs)
    remove(docs.sparkSession, path)
    td._terms = kept
    td._facts = {"n_terms": n_terms, "nnz": nnz or 0, "norm_sq": kept.agg(F.sum(F.col("sq") * td.unit() * td.unit())).first()[0] or 0.0}
    return td


def matrix_from_counts(df: DataFrame, row: str | Column, col: str | Column, value: str | Column | None = None, weight: str = "none") -> TermDoc:
    """A from a relation: rows and columns by key, entries by count or by the sum of a non-negative value."""
    as_col = lambda c: F.col(c) if isinstance(c, str) else c
    amount = F.count(F.lit(1)) if value is None else F.sum(as_col(value))
    counts = df.groupBy(as_col(row).cast("string").alias("term"), as_col(col).alias("doc_id")).agg(amount.alias("tf")).where("tf > 0")
    per_row = counts.groupBy("term").agg(F.count(F.lit(1)).alias("df"))
    return TermDoc(counts.join(per_row, "term").select("term", "doc_id", "tf", "df"), weight)


def matrix_from_arrays(df: DataFrame, id_col: str, array_col: str, clip: str = "zero") -> TermDoc:
    """A from arrays of reals: one term for each dimension; negatives are cut, shifted by the least, or split off."""
    long = df.select(F.col(id_col).alias("doc_id"), F.posexplode(F.col(array_col).cast("array<double>")).alias("dim", "x"))
    if clip == "shift":
        least = long.agg(F.least(F.min("x"), F.lit(0.0))).first()[0] or 0.0
        long = long.withColumn("x", F.col("x") - F.lit(least))
    elif clip == "split":
        long = long.withColumn("dim", F.when(F.col("x") < 0, F.concat(F.lit("-"), F.col("dim"))).otherwise(F.col("dim").cast("string"))).withColumn("x", F.abs("x"))
    entries = long.where("x > 0").select(F.col("dim").cast("string").alias("term"), "doc_id", F.col("x").alias("tf"))
    per_row = entries.groupBy("term").agg(F.count(F.lit(1)).alias("df"))
    return TermDoc(entries.join(per_row, "term"), "none")


def corpus_stats(td: TermDoc) -> DataFrame:
    """One row: n_docs, n_terms, nnz, sparsity (share of zeros)."""
    out = td.coo.agg(F.count_distinct("term").alias("n_terms"), F.count(F.lit(1)).alias("nnz")).withColumn("n_docs", F.lit(td.n_docs).cast("long"))
    return out.select("n_docs", "n_terms", "nnz", (1 - F.col("nnz") / (F.col("n_docs") * F.col("n_terms"))).alias("sparsity"))
