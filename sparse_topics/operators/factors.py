"""Factors: n x k matrices of non-negative reals, zeros not stored.

A factor is held as packed rows (row, w: array of k) on executors, or by the driver if it has few entries; the long
form (row, topic, value) is derived. The driver's form is what truncation to t entries makes possible.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.choice import LOCAL_ENTRIES
from ..session import remove, write_table
from .matrix import TermDoc

_ARROW = {"string": pa.string(), "bigint": pa.int64(), "long": pa.int64(), "int": pa.int32()}
DRAWS = float(1 << 32)
RANK_SCALE = 1e12  # ranks compare values rounded to twelve digits, so that the order of additions can't turn them


@dataclass
class Factor:
    k: int
    frame: DataFrame  # (row, w), entries of w not negative
    nnz: int | None = None
    rows: list | None = None  # with w: the driver's copy
    w: np.ndarray | None = None
    path: str | None = None  # of the table that a fit wrote for it and may remove

    @property
    def local(self) -> bool:
        return self.rows is not None

    def long(self) -> DataFrame:
        return self.frame.select("row", F.posexplode("w").alias("topic", "value")).where("value > 0")

    def count(self) -> int:
        if self.nnz is None:
            self.nnz = self.long().count()
        return self.nnz


def from_local(spark: SparkSession, rows: list, w: np.ndarray, k: int, kind: str) -> Factor:
    """A driver-held factor; ``kind`` is the SQL type of its row key."""
    if kind in _ARROW:  # an Arrow table becomes a local relation: broadcasting it needs no job
        ends = pa.array(np.arange(0, len(rows) * k + 1, k), pa.int32())
        cells = pa.ListArray.from_arrays(ends, pa.array(np.ascontiguousarray(w, np.float64).ravel()))
        frame = spark.createDataFrame(pa.table({"row": pa.array(list(rows), _ARROW[kind]), "w": cells}))
    else:
        frame = spark.createDataFrame([(r, x) for r, x in zip(rows, w.tolist(), strict=True)], f"row {kind}, w array<double>")
    return Factor(k, frame, int((w > 0).sum()), list(rows), w)


def from_entries(spark: SparkSession, entries: list[tuple], k: int, kind: str) -> Factor:
    """From (row, topic, value) tuples held by the driver."""
    place: dict = {}
    for r, _, _ in entries:
        place.setdefault(r, len(place))
    w = np.zeros((len(place), k))
    for r, t, v in entries:
        w[place[r], t] = v
    return from_local(spark, list(place), w, k, kind)


def key_kind(frame: DataFrame) -> str:
    return frame.schema["row"].dataType.simpleString()


def stored(frame: DataFrame, k: int, name: str, nnz: int | None = None) -> Factor:
    """A factor written to the shared folder."""
    frame, path = write_table(frame, name)
    return Factor(k, frame, nnz, path=path)


def discard(f: Factor | None) -> None:
    """Removes the table of a factor that no later plan reads."""
    if f is not None and f.path:
        remove(f.frame.sparkSession, f.path)


def pack(long: DataFrame, k: int) -> DataFrame:
    """(row, w) from (row, topic, value)."""
    return long.groupBy("row").agg(F.array(*[F.sum(F.when(F.col("topic") == t, F.col("value")).otherwise(0.0)) for t in range(k)]).alias("w"))


def localized(f: Factor, limit: int = LOCAL_ENTRIES) -> Factor:
    """The driver's form, if the factor is known to be small."""
    if f.local or f.count() > limit:
        return f
    got = f.frame.collect()
    return from_local(f.frame.sparkSession, [r["row"] for r in got], np.array([r["w"] for r in got]).reshape(len(got), f.k), f.k, key_kind(f.frame))


def hash_draw(*parts: Column | str) -> Column:
    """The first 32 bits of the MD5 of the parts joined by bars."""
    cols = [F.lit(p) if isinstance(p, str) else p.cast("string") for p in parts]
    return F.conv(F.substring(F.md5(F.concat_ws("|", *cols).cast("binary")), 1, 8), 16, 10).cast("long")


def hash_unit(*parts: Column | str) -> Column:
    """A number in [0, 1) from ``hash_draw``."""
    return hash_draw(*parts) / F.lit(DRAWS)


def initial_guess(td: TermDoc, k: int, *, nnz: int | None = None, seed: int = 0) -> Factor:
    """Uniform by hash of (term, topic, seed); with ``nnz``, only that many entries, those of least second hash."""
    terms = td.coo.select(F.col("term").alias("row")).distinct()
    if nnz is None:
        w = F.array(*[hash_unit(F.col("row"), str(t), str(seed)) for t in range(k)])
        return Factor(k, terms.select("row", w.alias("w")))
    topics = F.explode(F.sequence(F.lit(0), F.lit(k - 1)))
    long = terms.select("row", topics.alias("topic")).withColumn("value", hash_unit(F.col("row"), F.col("topic"), str(seed))).where("value > 0")
    placed = long.withColumn("place", hash_unit(F.col("row"), F.col("topic"), str(seed), "place"))
    # the hash's bound keeps all but about twice the entries wanted from being compared
    bound = (2 * nnz + 1000) / max(1, td.n_terms * k)
    some = placed.where(F.col("place") < bound) if bound < 1 else placed
    chosen = some.orderBy("place", "row", "topic").limit(nnz).select("row", "topic", "value")
    if nnz <= LOCAL_ENTRIES:
        return from_entries(terms.sparkSession, [tuple(r) for r in chosen.collect()], k, "string")
    return stored(pack(chosen, k), k, "guess")


def nnz(f: Factor) -> int:
    return f.count()


def sparsity(f: Factor, n_rows: int) -> float:
    """Share of zeros among n_rows x k."""
    return 1.0 - f.count() / (n_rows * f.k)
