"""Products with A, Gram matrices and the clipped least-squares half steps."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.choice import choose_layout, hinted
from .factors import Factor, from_local, key_kind
from .matrix import TermDoc


def _product(td: TermDoc, f: Factor, on: str, to: str, extra: DataFrame | None = None) -> DataFrame:
    """(row, b): for each ``to`` key, the sums of x * w over A's entries. extra: more (row, c) rows to add to the sums."""
    joined = td.entries().join(hinted(f.frame, f.nnz), F.col(on) == F.col("row")).select(F.col(to).alias("row"), F.col("x"), F.col("w"))
    k = f.k
    if choose_layout(k) == "packed":
        parts = joined.select("row", *[(F.col("x") * F.col("w")[t]).alias(f"c{t}") for t in range(k)])
        if extra is not None:
            parts = parts.unionByName(extra.select("row", *[F.col("c")[t].alias(f"c{t}") for t in range(k)]))
        return parts.groupBy("row").agg(*[F.sum(f"c{t}").alias(f"c{t}") for t in range(k)]).select("row", F.array(*[f"c{t}" for t in range(k)]).alias("b"))
    long = joined.select("row", F.posexplode(F.transform("w", lambda v: v * F.col("x"))).alias("topic", "v"))
    if extra is not None:
        long = long.unionByName(extra.select("row", F.posexplode("c").alias("topic", "v")))
    sums = long.groupBy("row", "topic").agg(F.sum("v").alias("v"))
    filled = F.map_from_entries(F.collect_list(F.struct("topic", "v")))
    return sums.groupBy("row").agg(filled.alias("m")).select("row", F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda t: F.coalesce(F.try_element_at("m", t), F.lit(0.0))).alias("b"))


def doc_product(td: TermDoc, u: Factor, extra: DataFrame | None = None) -> DataFrame:
    """A'U as (row = doc_id, b). The join with a truncated U leaves only entries in its support."""
    return _product(td, u, "term", "doc_id", extra)


def term_product(td: TermDoc, v: Factor, extra: DataFrame | None = None) -> DataFrame:
    """AV as (row = term, b)."""
    return _product(td, v, "doc_id", "term", extra)


def gram_columns(w: str, k: int) -> list[Column]:
    return [F.sum(F.col(w)[i] * F.col(w)[j]).alias(f"g{i}_{j}") for i in range(k) for j in range(i, k)]


def gram_of(row, k: int) -> np.ndarray:
    g = np.zeros((k, k))
    for i in range(k):
        for j in range(i, k):
            g[i, j] = g[j, i] = row[f"g{i}_{j}"] or 0.0
    return g


def gram(f: Factor) -> np.ndarray:
    """F'F (k x k): by the driver for a factor it holds, else one aggregate row."""
    if f.local:
        return f.w.T @ f.w
    if choose_layout(f.k) == "packed":
        return gram_of(f.frame.agg(*gram_columns("w", f.k)).first(), f.k)
    return _gram_blocks(f)


def _gram_blocks(f: Factor) -> np.ndarray:
    """For many topics: one partial product a partition, summed."""
    import pyarrow as pa

    k = f.k

    def run(batches):
        total = np.zeros((k, k))
        for b in batches:
            w = np.asarray(b.column(0).flatten()).reshape(b.num_rows, k)
            total += w.T @ w
        yield pa.RecordBatch.from_arrays([pa.array(np.repeat(np.arange(k), k)), pa.array(np.tile(np.arange(k), k)), pa.array(total.ravel())], ["i", "j", "g"])

    rows = f.frame.select("w").mapInArrow(run, "i long, j long, g double").groupBy("i", "j").agg(F.sum("g").alias("g")).collect()
    g = np.zeros((k, k))
    for r in rows:
        g[r["i"], r["j"]] = r["g"]
    return g


def cross_gram(a: Factor, b: Factor) -> np.ndarray:
    """A'B of two factors over the same row keys."""
    if a.local and b.local:
        place = {r: i for i, r in enumerate(a.rows)}
        out = np.zeros((a.k, b.k))
        for r, w in zip(b.rows, b.w, strict=True):
            if r in place:
                out += np.outer(a.w[place[r]], w)
        return out
    both = hinted(a.frame, a.nnz).alias("a").join(hinted(b.frame, b.nnz).alias("b"), "row")
    row = both.agg(*[F.sum(F.col("a.w")[i] * F.col("b.w")[j]).alias(f"g{i}_{j}") for i in range(a.k) for j in range(b.k)]).first()
    return np.array([[row[f"g{i}_{j}"] or 0.0 for j in range(b.k)] for i in range(a.k)])


def invert_gram(g: np.ndarray, method: str = "pinv", rcond: float = 1e-10, ridge: float = 0.0) -> np.ndarray:
    """'pinv' (a topic without entries stays without), 'cholesky', or 'ridge'. The matrix is scaled to a unit diagonal first."""
    if method == "ridge" or ridge:
        return np.linalg.inv(g + (ridge or 1e-8) * np.eye(len(g)))
    d = np.sqrt(np.diag(g))
    s = np.where(d > 0, 1 / np.where(d > 0, d, 1), 0)
    scaled = g * np.outer(s, s)
    if method == "cholesky":
        l = np.linalg.inv(np.linalg.cholesky(scaled))  # noqa: E741
        return (l.T @ l) * np.outer(s, s)
    return np.linalg.pinv(scaled, rcond=rcond, hermitian=True) * np.outer(s, s)


def project_nonneg(c: Column) -> Column:
    return F.greatest(c, F.lit(0.0))


def cells(column: str, m: np.ndarray, shift: float = 0.0) -> list[Column]:
    """The packed row, less ``shift`` in every entry, times a k x j matrix of literals: one expression a column."""
    x = [F.col(column)[i] - F.lit(shift) if shift else F.col(column)[i] for i in range(m.shape[0])]
    out = []
    for j in range(m.shape[1]):
        terms = [x[i] * F.lit(float(m[i, j])) for i in range(m.shape[0]) if m[i, j]]
        total = terms[0] if terms else F.lit(0.0)
        for t in terms[1:]:
            total = total + t
        out.append(total)
    return out


def times(column: str, m: np.ndarray) -> Column:
    return F.array(*cells(column, m))


def apply_gram(b: DataFrame, inverse: np.ndarray, shift: float = 0.0) -> DataFrame:
    """(row, w, b): clipped solution of every row; rows of zeros are dropped. shift: taken from b first (soft threshold)."""
    solved = cells("b", inverse, shift)
    live = solved[0] > 0
    for c in solved[1:]:
        live = live | (c > 0)
    return b.where(live).select("row", F.array(*[project_nonneg(c) for c in solved]).alias("w"), "b")


def correction(done: Factor, c: np.ndarray) -> DataFrame:
    """(row, c): minus the finished block's rows times a cross Gram matrix."""
    return done.frame.select("row", times("w", -c).alias("c"))


def solve_scaled(td: TermDoc, f: Factor, side: str, g: np.ndarray, *, done: tuple[Factor, Factor] | None = None, method: str = "pinv", ridge: float = 0.0) -> DataFrame:
    """A half step from a factor that the driver holds: (row, w, s), w the clipped solution and s the plain one.

    The inverse Gram matrix is multiplied into the factor's few rows before they are sent, so that the sums are the
    solution already. The plan of every iteration is the same text: its generated code is compiled once.
    """
    spark, inverse = f.frame.sparkSession, invert_gram(g, method, ridge=ridge)
    scaled = Factor(f.k, from_local(spark, f.rows, f.w @ inverse, f.k, key_kind(f.frame)).frame, f.nnz)
    extra = None
    if done:
        finished, other = done if side == "v" else done[::-1]
        c = cross_gram(finished, f) @ inverse
        if other.local:
            extra = from_local(spark, other.rows, -other.w @ c, f.k, key_kind(other.frame)).frame.select("row", F.col("w").alias("c"))
        else:
            extra = correction(other, c)
    s = (doc_product if side == "v" else term_product)(td, scaled, extra).select("row", F.col("b").alias("s"))
    return s.where(F.exists("s", lambda x: x > 0)).select("row", F.transform("s", project_nonneg).alias("w"), "s")


def _solved(product, f: Factor, g: np.ndarray | None, method: str, shift: float, ridge: float) -> DataFrame:
    g = gram(f) if g is None else g
    return apply_gram(product(f), invert_gram(g, method, ridge=ridge), shift)


def solve_docs(
    td: TermDoc, u: Factor, *, done: tuple[Factor, Factor] | None = None, method: str = "pinv", shift: float = 0.0, ridge: float = 0.0, gram_u: np.ndarray | None = None
) -> DataFrame:
    """Document half step for fixed U: (row, w, b) before truncation. done: finished (U1, V1) to be taken off; gram_u: U's
    Gram matrix, if it is known."""
    extra = correction(done[1], cross_gram(done[0], u)) if done else None
    return _solved(lambda f: doc_product(td, f, extra), u, gram_u, method, shift, ridge)


def solve_terms(
    td: TermDoc, v: Factor, *, done: tuple[Factor, Factor] | None = None, method: str = "pinv", shift: float = 0.0, ridge: float = 0.0, gram_v: np.ndarray | None = None
) -> DataFrame:
    """Term half step for fixed V."""
    extra = correction(done[0], cross_gram(done[1], v)) if done else None
    return _solved(lambda f: term_product(td, f, extra), v, gram_v, method, shift, ridge)
