"""Factorisation block by block: finished topics are frozen and taken off by algebra, A itself never changes."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .als import FitResult, sparse_als
from .factors import Factor, discard, from_local, key_kind, stored
from .matrix import TermDoc
from .sparsify import Limits


def append_block(done: Factor | None, new: Factor) -> Factor:
    """The finished topics with the new ones after them."""
    if done is None:
        return new
    k = done.k + new.k
    if done.local and new.local:
        place = {r: i for i, r in enumerate(done.rows)}
        rows = list(done.rows) + [r for r in new.rows if r not in place]
        w = np.zeros((len(rows), k))
        w[: len(done.rows), : done.k] = done.w
        at = {r: i for i, r in enumerate(rows)}
        for r, x in zip(new.rows, new.w, strict=True):
            w[at[r], done.k :] = x
        return from_local(done.frame.sparkSession, rows, w, k, key_kind(done.frame))
    zeros = lambda n: F.array_repeat(F.lit(0.0), n)
    both = done.frame.select("row", F.concat("w", zeros(new.k)).alias("w")).unionByName(new.frame.select("row", F.concat(zeros(done.k), "w").alias("w")))
    summed = both.groupBy("row").agg(F.array(*[F.sum(F.col("w")[i]) for i in range(k)]).alias("w"))
    out = stored(summed, k, "blocks", done.count() + new.count())
    discard(done), discard(new)
    return out


def sequential_als(
    td: TermDoc, n_blocks: int, *, block: int = 1, limits: Limits | None = None, iters_per_block: int = 20, tol: float = 0.0, seed: int = 0,
    init_per_block: str = "same", init_nnz: int | None = None, measure: bool = True,
) -> FitResult:
    """n_blocks blocks of ``block`` topics; limits hold in each block. Every block starts from the same guess, or a fresh one.
    The trace has each block's own residual, and the error of all topics so far."""
    done_u = done_v = rest_sq = None
    steps: list[tuple] = []
    for b in range(n_blocks):
        done = (done_u, done_v) if done_u is not None else None
        fit = sparse_als(
            td, block, limits, init_nnz=init_nnz, seed=seed if init_per_block == "same" else seed + b, max_iter=iters_per_block, tol=tol, done=done, rest_sq=rest_sq, measure=measure
        )
        held = (done_u.nnz + done_v.nnz) if done_u is not None else 0
        rest_sq = fit.steps[-1][2] ** 2 * td.norm_sq if measure else None
        steps += [(b * iters_per_block + s[0], s[1], s[2], s[3], s[4], s[5] + held, s[6], s[7], s[8]) for s in fit.steps]
        done_u, done_v = append_block(done_u, fit.u), append_block(done_v, fit.v)
    return FitResult(done_u, done_v, n_blocks * block, steps)


def block_of(steps: DataFrame, iters_per_block: int) -> DataFrame:
    """The trace with the block each iteration belongs to."""
    return steps.withColumn("block", F.floor((F.col("iter") - 1) / iters_per_block).cast("int"))
