"""Alternating least squares with projection, and with the number of entries enforced at every half step.

The driver submits the half steps. A factor that a limit keeps small is one action a half step: product, solution,
clipping and the t largest come back as at most t rows, from which the driver has Gram matrix, residual and error
terms. A factor without such a limit is written to the shared folder, and its sums are observed while it is written.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from ..plans.choice import heap_fits
from ..session import remove, write_table
from . import linalg
from .factors import Factor, discard, from_local, initial_guess, key_kind, pack, stored
from .matrix import TermDoc
from .sparsify import Limits, truncate

TRACE = "iter int, residual double, error double, nnz_u long, nnz_v long, nnz_peak long, nnz_candidate long, live_topics int, seconds double"


@dataclass
class FitResult:
    u: Factor
    v: Factor
    k: int
    steps: list[tuple] = field(default_factory=list)

    def trace(self, spark: SparkSession) -> DataFrame:
        """One row for each iteration: residual, error, entries, time."""
        return spark.createDataFrame(self.steps, TRACE)


@dataclass
class HalfStep:
    factor: Factor
    gram: np.ndarray
    cross: float  # sum of product times solution: the middle term of the error
    candidates: int  # positive entries before truncation, -1 if not counted


def _local_step(solved: DataFrame, k: int, limits: Limits, side: str, gram: np.ndarray | None = None) -> HalfStep:
    """Truncated to few entries: they come to the driver with their products, or with their plain solutions, which the Gram
    matrix they were solved with turns into products."""
    spark = solved.sparkSession
    kind = key_kind(solved)
    seen = Observation()
    if gram is None:
        long = solved.select("row", F.posexplode(F.arrays_zip("w", "b")).alias("topic", "e")).select("row", "topic", F.col("e.w").alias("value"), F.col("e.b").alias("b"))
    else:
        long = solved.select("row", F.posexplode("w").alias("topic", "value"), "s")
    long = long.where("value > 0")
    got = truncate(long.observe(seen, F.count(F.lit(1)).alias("n")), limits, side).collect()
    place: dict = {}
    for r in got:
        place.setdefault(r["row"], len(place))
    w, cross = np.zeros((len(place), k)), 0.0
    for r in got:
        w[place[r["row"]], r["topic"]] = r["value"]
        cross += r["value"] * (r["b"] if gram is None else float(np.dot(r["s"], gram[:, r["topic"]])))
    f = from_local(spark, list(place), w, k, kind)
    return HalfStep(f, w.T @ w, cross, seen.get.get("n", -1) if got else 0)


def _written_step(solved: DataFrame, k: int, limits: Limits, side: str) -> HalfStep:
    """Kept on executors: packed rows are written, their Gram sums, cross term and entries observed on the way."""
    t, tau = limits.side(side)
    out, base_path = solved, None
    if t is not None or tau is not None:
        base, base_path = write_table(solved, f"candidates-{side}")
        long = base.select("row", F.posexplode(F.arrays_zip("w", "b")).alias("topic", "e")).select("row", "topic", F.col("e.w").alias("value"), F.col("e.b").alias("b")).where("value > 0")
        cells = lambda c: F.array(*[F.sum(F.when(F.col("topic") == i, F.col(c)).otherwise(0.0)) for i in range(k)]).alias(c if c == "b" else "w")
        out = truncate(long, limits, side).groupBy("row").agg(cells("value"), cells("b"))
    seen = Observation()
    dot = F.sum(F.aggregate(F.zip_with("w", "b", lambda x, y: x * y), F.lit(0.0), lambda a, x: a + x))
    entries = F.sum(F.size(F.filter("w", lambda x: x > 0)))
    packed = linalg.choose_layout(k) == "packed"
    f = stored(out.observe(seen, dot.alias("cross"), entries.alias("n"), *(linalg.gram_columns("w", k) if packed else [])).select("row", "w"), k, f"factor-{side}")
    remove(solved.sparkSession, base_path)
    got = seen.get
    f.nnz = int(got["n"] or 0)
    return HalfStep(f, linalg.gram_of(got, k) if packed else linalg.gram(f), got["cross"] or 0.0, int(got["n"] or 0))


def half_step(td: TermDoc, f: Factor, limits: Limits, side: str, g: np.ndarray, done, method: str, shift: float, ridge: float) -> HalfStep:
    """The factor of ``side`` for the fixed other one, whose Gram matrix is ``g``."""
    spark, k = f.frame.sparkSession, f.k
    t, _ = limits.side(side)
    few = t is not None and limits.ties == "exact" and heap_fits(spark, t * (k if limits.scope == "topic" else 1))
    if few and f.local and f.rows and not shift and linalg.choose_layout(k) == "packed":
        return _local_step(linalg.solve_scaled(td, f, side, g, done=done, method=method, ridge=ridge), k, limits, side, g)
    options = {"done": done, "method": method, "shift": shift, "ridge": ridge}
    solved = linalg.solve_docs(td, f, gram_u=g, **options) if side == "v" else linalg.solve_terms(td, f, gram_v=g, **options)
    return (_local_step if few else _written_step)(solved, k, limits, side)


def change(new: Factor, old: Factor) -> float:
    """Norm of the difference over the norm of the new factor."""
    if new.local and old.local:
        place = {r: i for i, r in enumerate(old.rows)}
        both = 0.0
        for r, w in zip(new.rows, new.w, strict=True):
            if r in place:
                both += float(w @ old.w[place[r]])
        a, b = float((new.w**2).sum()), float((old.w**2).sum())
        diff = 0.0
        left = set(old.rows)
        for r, w in zip(new.rows, new.w, strict=True):
            left.discard(r)
            diff += float(((w - old.w[place[r]]) ** 2).sum()) if r in place else float((w**2).sum())
        diff += sum(float((old.w[place[r]] ** 2).sum()) for r in left)
        return float(np.sqrt(diff / a)) if a else float("inf") if b else 0.0
    signed = new.long().withColumn("new", F.col("value")).unionByName(old.long().select("row", "topic", (-F.col("value")).alias("value"), F.lit(0.0).alias("new")))
    r = signed.groupBy("row", "topic").agg(F.sum("value").alias("d"), F.sum("new").alias("n")).agg(F.sum(F.col("d") * F.col("d")).alias("d"), F.sum(F.col("n") * F.col("n")).alias("n")).first()
    return float(np.sqrt(r["d"] / r["n"])) if r["n"] else float("inf") if r["d"] else 0.0


def error_from(norm_sq: float, cross: float, gram_u: np.ndarray, gram_v: np.ndarray, rest_sq: float | None = None) -> float:
    """Relative error from sums only: the product of the factors is never formed. rest_sq: the squared norm of what finished
    blocks leave of A, whose product with the factors is ``cross``; A's own if there are none."""
    rest = norm_sq if rest_sq is None else rest_sq
    return float(np.sqrt(max(0.0, rest - 2 * cross + float((gram_u * gram_v).sum())) / norm_sq)) if norm_sq else 0.0


def sparse_als(
    td: TermDoc, k: int, limits: Limits | None = None, *, init: Factor | None = None, init_nnz: int | None = None, max_iter: int = 20, tol: float = 0.0, seed: int = 0,
    method: str = "pinv", shift: tuple[float, float] = (0.0, 0.0), ridge: float = 0.0, done: tuple[Factor, Factor] | None = None, rest_sq: float | None = None,
    measure: bool = True, revive: str = "none",
) -> FitResult:
    """Solve V, clip, truncate; solve U from the truncated V, clip, truncate; repeat.

    Limits(None, None) is projected ALS. The first guess is not truncated. tol: stop when the relative change of U is at
    most this. done: finished blocks, taken off by algebra; rest_sq: the squared norm of what they leave of A. A topic that
    lost all entries stays empty, or with revive='reseed' gets its column of the guess (another seed) added to U. Tables of
    factors are removed as soon as the next ones are there; only the last two stay.
    """
    limits = limits or Limits()
    u = init
    if u is None:
        u = initial_guess(td, k, nnz=init_nnz, seed=seed)
        u = u if u.local or u.path else stored(u.frame, k, "guess", u.nnz)
    first_nnz = u.count() if measure else 0
    peak, steps = first_nnz, []
    v = None
    gram_u = linalg.gram(u)
    for i in range(1, max_iter + 1):
        began = time.perf_counter()
        v_step = half_step(td, u, limits, "v", gram_u, done, method, shift[1], ridge)
        discard(v)
        v = v_step.factor
        peak = max(peak, u.nnz + v.nnz) if u.nnz is not None else peak
        u_step = half_step(td, v, limits, "u", v_step.gram, done, method, shift[0], ridge)
        new, gram_u = u_step.factor, u_step.gram
        revived = revive == "reseed" and (np.diag(gram_u) == 0).any()
        if revived:
            new, dead = _revived(td, new, np.flatnonzero(np.diag(gram_u) == 0).tolist(), seed + i), new
            discard(dead)
            gram_u = linalg.gram(new)
            new.count()
        residual = change(new, u) if measure or tol else float("nan")
        if u is not init:
            discard(u)
        u = new
        peak = max(peak, u.nnz + v.nnz)
        known = measure and (done is None or rest_sq is not None) and not revived
        error = error_from(td.norm_sq, u_step.cross, gram_u, v_step.gram, rest_sq) if known else float("nan")
        steps.append((i, residual, error, u.nnz, v.nnz, peak, max(u_step.candidates, v_step.candidates), int((np.diag(gram_u) > 0).sum()), time.perf_counter() - began))
        if tol and residual <= tol:
            break
    return FitResult(u, v, k, steps)


def _revived(td: TermDoc, u: Factor, dead: list[int], seed: int) -> Factor:
    guess = initial_guess(td, u.k, nnz=max(1, (u.count() or u.k) // u.k) * u.k, seed=seed).long().where(F.col("topic").isin(dead))
    return stored(pack(u.long().unionByName(guess), u.k), u.k, "revived")


def projected_als(td: TermDoc, k: int, *, init: Factor | None = None, max_iter: int = 20, tol: float = 0.0, seed: int = 0, **options) -> FitResult:
    """Dense projected ALS: the same loop without limits."""
    return sparse_als(td, k, Limits(), init=init, max_iter=max_iter, tol=tol, seed=seed, **options)


def truncate_after(fit: FitResult, limits: Limits) -> FitResult:
    """One truncation of a finished model, each side if it has a limit."""
    sides = {}
    for name, f in (("u", fit.u), ("v", fit.v)):
        if limits.side(name) == (None, None):
            sides[name] = f
            continue
        sides[name] = stored(pack(truncate(f.long(), limits, name), fit.k), fit.k, f"truncated-{name}")
    return FitResult(sides["u"], sides["v"], fit.k, fit.steps)
