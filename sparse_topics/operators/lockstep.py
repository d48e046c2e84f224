"""Many fits of one matrix side by side, for factors that the driver can hold.

A is written twice to the shared folder, in blocks of documents and in blocks of terms. A half step of all fits together
is one pass over the blocks without an exchange: a block has its rows whole, so their solutions, and the t largest of the
task's blocks, are made where the block is read. The driver holds the factors as arrays and sends them along. Beyond
``HELD_ENTRIES`` the fits go through DataFrames (als.py), which this path doesn't replace.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Generator, Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans import choice
from ..session import new_path
from . import linalg
from .als import FitResult, error_from, sparse_als
from .factors import DRAWS, RANK_SCALE, Factor, from_local, hash_draw, initial_guess
from .matrix import TermDoc
from .sequential import sequential_als
from .sparsify import Limits

#: Entries of factors that go through one pass (8 bytes each), beyond them a half step takes several.
PASS_ENTRIES = 8_000_000
#: So many times as many may the fits that go along hold, beyond them they are done in turns.
TURN = 4
#: Entries of a block, and what a row counts besides its entries (it needs a cell for each topic of each fit).
BLOCK, ROW = (20_000, 1_000_000), 20
#: Numbers that a slice of a block's products may have, so that it stays in a core's cache.
CACHED = 131_072
_BLOCK = "rows binary, ends binary, cols binary, x binary, unit binary"
_OUT = "ask int, rows binary, topics binary, w binary, b binary, cross double, n long"


@dataclass
class Blocks:
    docs: DataFrame
    terms: DataFrame
    doc_ids: pa.Array  # sorted, as the terms are: places compare like keys
    names: pa.Array
    unit: np.ndarray  # what an occurrence of a term counts
    sizes: dict[str, np.ndarray]  # entries of each document (v) and term (u)


def held_by_driver(td: TermDoc, k: int) -> bool:
    """Its keys are broadcast, its factors are the driver's arrays."""
    rows = max(td.n_terms, td.n_docs)
    return rows < choice.BROADCAST_ENTRIES and rows * k <= choice.HELD_ENTRIES


def _packed(unit) -> object:
    def pack(t: pa.Table) -> pa.Table:
        r, c, x = (t.column(n).to_numpy() for n in ("r", "c", "x"))
        order = np.argsort((r.astype(np.int64) << 32) | c)
        r, c, x = r[order], c[order], x[order]
        rows, starts = np.unique(r, return_index=True)
        for kind in (np.uint8, np.uint16):  # counts are small
            if (x.astype(kind) == x).all():
                x = x.astype(kind)
                break
        weights = np.empty(0) if unit is None else unit.value[rows]
        parts = (rows.astype(np.int32), np.append(starts[1:], len(r)).astype(np.int32), c.astype(np.int32), x, weights)
        return pa.table([pa.array([p.tobytes()], pa.binary()) for p in parts], ["rows", "ends", "cols", "x", "unit"])

    return pack


def _placed(t: pa.Table, key: str, per: int) -> pa.Table:
    """Sorted by key, with each key's place and block."""
    t = t.take(pc.sort_indices(t.column(key)))
    block = (np.cumsum(t.column("n").to_numpy() + ROW) - 1) // per
    return t.append_column("at", pa.array(np.arange(t.num_rows, dtype=np.int32))).append_column("block", pa.array(block.astype(np.int32)))


def blocks(td: TermDoc) -> Blocks:
    """Both block tables of a matrix, written once."""
    if td._blocks is None:
        spark = td.coo.sparkSession
        if td._terms is None:
            terms = td.coo.groupBy("term").agg(F.count(F.lit(1)).alias("n"), F.max(td.unit()).alias("unit")).toArrow()
        else:
            terms = td._terms.select("term", F.col("df").alias("n"), td.unit().alias("unit")).toArrow()
        docs = td.coo.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).toArrow()
        entries = pc.sum(docs.column("n")).as_py() or 0
        per = min(max(entries // (4 * spark.sparkContext.defaultParallelism), BLOCK[0]), BLOCK[1])
        terms, docs = _placed(terms, "term", per), _placed(docs, "doc_id", per)
        unit = terms.column("unit").to_numpy()
        frames = [F.broadcast(spark.createDataFrame(t.select([key, "at", "block"]).rename_columns([key, at, block]))) for t, key, at, block in ((terms, "term", "t", "tb"), (docs, "doc_id", "d", "db"))]
        coded = td.coo.join(frames[0], "term").join(frames[1], "doc_id")
        shared = spark.sparkContext.broadcast(unit)
        tables = []
        for r, c, b, weights in (("d", "t", "db", None), ("t", "d", "tb", shared)):
            part = coded.select(F.col(r).alias("r"), F.col(c).alias("c"), F.col("tf").cast("double").alias("x"), F.col(b).alias("b"))
            made = part.groupBy("b").applyInArrow(_packed(weights), _BLOCK)
            tables.append(_one_a_file(made, f"blocks-{r}"))
        shared.destroy()
        td._blocks = Blocks(*tables, docs.column("doc_id").combine_chunks(), terms.column("term").combine_chunks(), unit, {"v": docs.column("n").to_numpy(), "u": terms.column("n").to_numpy()})
    return td._blocks


def _one_a_file(df: DataFrame, name: str) -> DataFrame:
    path = new_path(df.sparkSession, name)
    df.write.option("maxRecordsPerFile", 1).parquet(path)  # so that the reader can deal them to tasks
    return df.sparkSession.read.schema(df.schema).parquet(path)


class Held(Factor):
    """A factor as arrays of the driver: places of its rows, and their entries. The keys and the DataFrame are made on demand."""

    local = True

    def __init__(self, spark: SparkSession, keys: pa.Array, at: np.ndarray, w: np.ndarray):
        self.k, self.keys, self.at, self.w, self.path, self._spark = w.shape[1], keys, at, w, None, spark
        self.nnz = int((w > 0).sum())

    @cached_property
    def rows(self) -> list:
        return self.keys.take(pa.array(self.at)).to_pylist()

    @cached_property
    def frame(self) -> DataFrame:
        kind = {pa.string(): "string", pa.int64(): "bigint", pa.int32(): "int"}.get(self.keys.type, "string")
        return from_local(self._spark, self.rows, self.w, self.k, kind).frame

    @cached_property
    def gram(self) -> np.ndarray:
        return self.w.T @ self.w

    @cached_property
    def inverse(self) -> np.ndarray:
        return linalg.invert_gram(self.gram)

    @property
    def solving(self) -> np.ndarray:
        """The rows times the inverse Gram matrix: sums with them are solutions."""
        return self.w @ self.inverse


class Guess(Held):
    """A first guess of all terms, kept as the whole numbers that were drawn."""

    def __init__(self, spark: SparkSession, keys: pa.Array, drawn: np.ndarray):
        self.k, self.keys, self.at, self.drawn, self.path, self._spark = drawn.shape[1], keys, np.arange(len(drawn)), drawn, None, spark
        self.nnz = int((drawn > 0).sum())

    @property
    def w(self) -> np.ndarray:
        return self.drawn / DRAWS


def _common(a: Held, b: Held) -> tuple[np.ndarray, np.ndarray]:
    _, i, j = np.intersect1d(a.at, b.at, assume_unique=True, return_indices=True)
    return i, j


def _change(new: Held, old: Held) -> float:
    i, j = _common(new, old)
    a, b = float((new.w**2).sum()), float((old.w**2).sum())
    apart = a - float((new.w[i] ** 2).sum()) + b - float((old.w[j] ** 2).sum())
    diff = float(((new.w[i] - old.w[j]) ** 2).sum()) + (max(0.0, apart) if len(i) < max(len(new.at), len(old.at)) else 0.0)
    return float(np.sqrt(diff / a)) if a else float("inf") if b else 0.0


@dataclass
class Ask:
    """A half step wanted by a fit."""

    side: str
    f: Held
    limit: int | None
    scope: str
    extra: tuple[np.ndarray, np.ndarray] | None  # places and sums to add, of finished topics
    raw: bool = False  # the products with A themselves, for all rows
    each: Callable[[np.ndarray, np.ndarray], np.ndarray] | None = None  # with raw: what a task makes of rows of products and the Gram matrix


@dataclass
class Answer:
    factor: Held
    cross: float
    candidates: int


def _cut(key: np.ndarray, row: np.ndarray, topic: np.ndarray, t: int) -> np.ndarray:
    """Places of the t largest; ties by row and topic."""
    if t <= 0:
        return np.empty(0, np.int64)
    if len(key) <= t:
        return np.arange(len(key))
    least = np.partition(key, len(key) - t)[len(key) - t]
    above, equal = np.flatnonzero(key > least), np.flatnonzero(key == least)
    return np.concatenate([above, equal[np.lexsort((topic[equal], row[equal]))][: t - len(above)]])


class _Largest:
    """The t largest entries seen so far, of the matrix or of one topic."""

    def __init__(self, t: int):
        self.t, self.floor, self.n = t, 0.0, 0
        self.kept = [np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0), np.empty(0)]

    def add(self, rows: np.ndarray, s: np.ndarray, gram: np.ndarray, topics: np.ndarray) -> None:
        """s: plain solutions of the rows, of which the columns ``topics`` are meant."""
        x = s[:, topics]
        self.n += int((x > 0).sum())
        i, j = np.nonzero(x > self.floor)
        if not len(i):
            return
        topic, value = topics[j], x[i, j]
        new = [rows[i].astype(np.int64), topic, value, np.einsum("ij,ji->i", s[i], gram[:, topic])] if len(i) <= 4 * self.t else self._best(rows, s, gram, topics, i, j, x)
        self.merge(*new)

    def _best(self, rows, s, gram, topics, i, j, x):
        best = _cut(np.rint(x[i, j] * RANK_SCALE), rows[i], topics[j], self.t)
        i, j = i[best], j[best]
        return [rows[i].astype(np.int64), topics[j], x[i, j], np.einsum("ij,ji->i", s[i], gram[:, topics[j]])]

    def merge(self, rows, topics, values, b) -> None:
        both = [np.concatenate(p) for p in zip(self.kept, (rows, topics, values, b), strict=True)]
        key = np.rint(both[2] * RANK_SCALE)
        best = _cut(key, both[0], both[1], self.t)
        self.kept = [p[best] for p in both]
        if len(best) and len(best) == self.t:
            self.floor = max(0.0, (key[best].min() - 1) / RANK_SCALE)


def _laid(sources: list, n: int) -> tuple[np.ndarray, dict, dict, np.ndarray]:
    """Factors over ``n`` rows: those with few rows by place among all their rows, those with many side by side."""
    whole, few, width = {}, {}, 0
    small = [at for at, _ in sources if len(at) * 8 <= n]
    union = np.unique(np.concatenate([np.empty(0, np.int64), *small]))
    near_at = np.full(n, -1, np.int32)  # one look-up finds the entries that any of the few need
    near_at[union] = np.arange(len(union))
    for i, (at, f) in enumerate(sources):
        if len(at) * 8 > n:
            whole[i] = slice(width, width + f.shape[1])
            width += f.shape[1]
        else:
            place = np.full(len(union), -1, np.int32)
            place[near_at[at]] = np.arange(len(at))
            few[i] = place, np.ascontiguousarray(f.T)
    beside = np.zeros((n, width))  # one look-up of a row serves all fits
    for i, part in whole.items():
        beside[sources[i][0], part] = sources[i][1]
    return near_at, few, whole, beside


def _reader(shared, n: int):
    """Runs over blocks of rows that have ``n`` columns: solutions for all asks, unlimited ones block by block, the largest at the end."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sent = shared.value
        if "sources" in sent:  # laid out once a worker and pass, not once a task
            sent["laid"] = _laid(sent.pop("sources"), n)
        asks, (near_at, few, whole, beside) = sent["asks"], sent["laid"]
        width = beside.shape[1]
        largest = {}
        for a, (_, _, gram, limit, scope, *_) in enumerate(asks):
            if limit is not None:
                sets = [np.array([t]) for t in range(len(gram))] if scope == "topic" else [np.arange(len(gram))]
                largest[a] = [(_Largest(limit), topics) for topics in sets]

        def summed(of, f, cols, x, m) -> np.ndarray:
            return np.stack([np.bincount(of, f[t][cols] * x, m) for t in range(len(f))], 1).astype(np.float64, copy=False)  # of no entries it counts whole numbers

        room = np.empty((max(CACHED // max(width, 1), 256), width))

        def summed_beside(ends, cols, x) -> np.ndarray:
            out = np.zeros((len(ends), width))
            for start in range(0, len(cols), len(room)):
                part = room[: min(len(room), len(cols) - start)]
                stop = start + len(part)
                np.take(beside, cols[start:stop], axis=0, out=part, mode="clip")
                part *= x[start:stop].astype(np.float64)[:, None]
                first, last = np.searchsorted(ends, (start, stop - 1), "right")
                out[first : last + 1] += np.add.reduceat(part, np.append(0, ends[first:last] - start), axis=0)
            return out

        def product(rows, ends, cols, x, unit) -> dict[int, np.ndarray]:
            out = {}
            if whole:
                sums = summed_beside(ends, cols, x)
                out = {i: np.ascontiguousarray(sums[:, part]) for i, part in whole.items()}
            if few:
                q = near_at[cols]
                near = np.flatnonzero(q >= 0)
                of, q, x = np.searchsorted(ends, near, "right"), q[near], x[near].astype(np.float64)
                for i, (place, f) in few.items():
                    p = place[q]
                    hit = np.flatnonzero(p >= 0)
                    p, o, y = p[hit], of[hit], x[hit]
                    out[i] = summed(o, f, p, y, len(rows))
            if len(unit):
                for s in out.values():
                    s *= unit[:, None]
            return out

        def record(a, cross, n_, *parts):
            return pa.RecordBatch.from_arrays([pa.array([a], pa.int32()), *[pa.array([p.tobytes()], pa.binary()) for p in parts], pa.array([cross], pa.float64()), pa.array([n_], pa.int64())], ["ask", "rows", "topics", "w", "b", "cross", "n"])

        none = np.empty(0)
        for batch in batches:
            for i in range(batch.num_rows):
                rows, ends, cols, x, unit = (batch.column(c)[i].as_buffer() for c in range(5))
                rows, ends, cols = np.frombuffer(rows, np.int32), np.frombuffer(ends, np.int32), np.frombuffer(cols, np.int32)
                x = np.frombuffer(x, {1: np.uint8, 2: np.uint16, 8: np.float64}[x.size // len(cols)])
                sums = product(rows, ends, cols, x, np.frombuffer(unit, np.float64))
                for a, (source, extra, gram, limit, _, raw, each) in enumerate(asks):
                    s = sums[source]
                    if extra is not None and len(extra[0]):
                        at = np.minimum(np.searchsorted(extra[0], rows), len(extra[0]) - 1)
                        hit = np.flatnonzero(extra[0][at] == rows)
                        s = s.copy()
                        s[hit] += extra[1][at[hit]]
                    if limit is not None:
                        for top, topics in largest[a]:
                            top.add(rows, s, gram, topics)
                        continue
                    if raw:
                        w, live = (s, slice(None)) if each is None else ((w := each(s, gram)), np.flatnonzero((w > 0).any(1)))
                        yield record(a, 0.0 if each is None else float((w * s).sum()), int((w > 0).sum()), rows[live], none, w[live], none)
                        continue
                    live = np.flatnonzero((s > 0).any(1))
                    s = s[live]
                    w = np.maximum(s, 0.0)
                    yield record(a, float((w * (s @ gram)).sum()), int((w > 0).sum()), rows[live], none, w, none)
        for a, tops in largest.items():
            for top, _ in tops:
                if top.n:
                    yield record(a, 0.0, top.n, *top.kept)

    return run


def half_steps(td: TermDoc, side: str, asks: list[Ask]) -> list[Answer]:
    """All asks of a side: one pass over the blocks, or as many as the factors that go out and come back need."""
    sizes = blocks(td).sizes
    rows, other = (sizes["v"], sizes["u"]) if side == "v" else (sizes["u"], sizes["v"])
    out: dict[int, Answer] = {}
    turn, sent, going, coming = [], set(), 0, 0
    for a in sorted(range(len(asks)), key=lambda a: (id(asks[a].f), asks[a].raw)):  # those that share their sums beside each other
        ask, key = asks[a], (id(asks[a].f), asks[a].raw)
        size = ask.f.k * len(ask.f.at)
        back = 0 if ask.limit is not None else ask.f.k * (len(rows) if ask.raw or ask.extra else min(len(rows), int(other[ask.f.at].sum())))
        if turn and (going + (0 if key in sent else size) > PASS_ENTRIES or coming + back > TURN * PASS_ENTRIES):
            out.update(zip(turn, _pass(td, side, [asks[i] for i in turn]), strict=True))
            turn, sent, going, coming = [], set(), 0, 0
        going += 0 if key in sent else size
        coming += back
        turn.append(a)
        sent.add(key)
    out.update(zip(turn, _pass(td, side, [asks[i] for i in turn]), strict=True))
    return [out[a] for a in range(len(asks))]


def _pass(td: TermDoc, side: str, asks: list[Ask]) -> list[Answer]:
    """One pass over the blocks."""
    kept = blocks(td)
    spark = td.coo.sparkSession
    table, keys, n = (kept.docs, kept.doc_ids, len(kept.names)) if side == "v" else (kept.terms, kept.names, len(kept.doc_ids))
    places, sources, plain = {}, [], []
    for ask in asks:
        key = id(ask.f), ask.raw
        if key not in places:  # fits from one guess share its sums
            places[key] = len(sources)
            f = ask.f.w if ask.raw else ask.f.solving
            sources.append((ask.f.at, f * kept.unit[ask.f.at, None] if side == "v" else f))
        plain.append((places[key], ask.extra, ask.f.gram, ask.limit, ask.scope, ask.raw, ask.each))
    shared = spark.sparkContext.broadcast({"sources": sources, "asks": plain})
    got = table.mapInArrow(_reader(shared, n), _OUT).toArrow()
    shared.destroy()
    parts: dict[int, list[dict]] = {}
    for r in got.to_pylist():
        parts.setdefault(r["ask"], []).append(r)
    out = []
    for a, ask in enumerate(asks):
        k, found = ask.f.k, parts.get(a, [])
        candidates = sum(r["n"] for r in found)
        if ask.limit is None:
            at = np.concatenate([np.frombuffer(r["rows"], np.int32) for r in found] or [np.empty(0, np.int32)]).astype(np.int64)
            w = np.concatenate([np.frombuffer(r["w"]) for r in found] or [np.empty(0)]).reshape(-1, k)
            order = np.argsort(at)
            out.append(Answer(Held(spark, keys, at[order], w[order]), sum(r["cross"] for r in found), candidates))
            continue
        tops = {t: _Largest(ask.limit) for t in (range(k) if ask.scope == "topic" else [-1])}
        for r in found:
            entries = [np.frombuffer(r["rows"], np.int64), np.frombuffer(r["topics"], np.int64), np.frombuffer(r["w"]), np.frombuffer(r["b"])]
            if len(entries[0]):
                tops[int(entries[1][0]) if ask.scope == "topic" else -1].merge(*entries)
        rows, topics, values, b = (np.concatenate(p) for p in zip(*[t.kept for t in tops.values()], strict=True))
        at, place = np.unique(rows, return_inverse=True)
        w = np.zeros((len(at), k))
        w[place, topics] = values
        out.append(Answer(Held(spark, keys, at, w), float((values * b).sum()), candidates))
    return out


def _asked(f: Held, side: str, limits: Limits, done: tuple[Held, Held] | None) -> Ask:
    extra = None
    if done:
        finished, other = done if side == "v" else done[::-1]
        i, j = _common(finished, f)
        extra = other.at, -other.w @ (finished.w[i].T @ f.w[j] @ f.inverse)
    return Ask(side, f, limits.side(side)[0], limits.scope, extra)


Fit = Generator[Ask, Answer, FitResult]


def als_fit(td: TermDoc, k: int, limits: Limits, guess: Held, max_iter: int, measure: bool, done: tuple[Held, Held] | None = None, rest_sq: float | None = None) -> Fit:
    """The loop of ``sparse_als``; its half steps are asked for."""
    u, steps = guess, []
    peak = u.nnz if measure else 0
    for i in range(1, max_iter + 1):
        began = time.perf_counter()
        v_step = yield _asked(u, "v", limits, done)
        v = v_step.factor
        peak = max(peak, u.nnz + v.nnz)
        u_step = yield _asked(v, "u", limits, done)
        old, u = u, u_step.factor
        residual = _change(u, old) if measure else float("nan")
        peak = max(peak, u.nnz + v.nnz)
        known = measure and (done is None or rest_sq is not None)
        error = error_from(td.norm_sq, u_step.cross, u.gram, v.gram, rest_sq) if known else float("nan")
        steps.append((i, residual, error, u.nnz, v.nnz, peak, max(u_step.candidates, v_step.candidates), int((np.diag(u.gram) > 0).sum()), time.perf_counter() - began))
    return FitResult(u, v, k, steps)


def _after(done: Held | None, new: Held) -> Held:
    if done is None:
        return new
    at = np.union1d(done.at, new.at)
    w = np.zeros((len(at), done.k + new.k))
    w[np.searchsorted(at, done.at), : done.k] = done.w
    w[np.searchsorted(at, new.at), done.k :] = new.w
    return Held(new._spark, new.keys, at, w)


def sequential_fit(td: TermDoc, n_blocks: int, limits: Limits, guess: Held, iters_per_block: int, measure: bool) -> Fit:
    """The loop of ``sequential_als`` with one topic a block and the same guess for each."""
    done, rest_sq, steps = None, None, []
    for b in range(n_blocks):
        fit = yield from als_fit(td, 1, limits, guess, iters_per_block, measure, done, rest_sq)
        before = done[0].nnz + done[1].nnz if done else 0
        rest_sq = fit.steps[-1][2] ** 2 * td.norm_sq if measure else None
        steps += [(b * iters_per_block + s[0], *s[1:5], s[5] + before, *s[6:]) for s in fit.steps]
        done = (_after(done[0], fit.u), _after(done[1], fit.v)) if done else (fit.u, fit.v)
    return FitResult(*done, n_blocks, steps)


@dataclass(frozen=True)
class Plan:
    """A fit of k topics: together, or one after the other with max_iter / k iterations each; limits as in ``Limits``."""

    k: int
    limits: Limits = Limits()
    max_iter: int = 20
    seed: int = 0
    init_nnz: int | None = None
    measure: bool = True
    sequential: bool = False

    @property
    def per_block(self) -> int:
        return max(1, self.max_iter // self.k)


def hold(td: TermDoc, f: Factor, side: str = "u") -> Held:
    """A guess over terms (documents) as the driver's arrays."""
    kept, t = blocks(td), f.frame.select("row", "w").toArrow()
    keys = kept.names if side == "u" else kept.doc_ids
    at = pc.index_in(t.column("row"), value_set=keys).to_numpy().astype(np.int64)
    w = np.asarray(t.column("w").combine_chunks().flatten(), np.float64).reshape(-1, f.k)
    order = np.argsort(at)
    return Held(td.coo.sparkSession, keys, at[order], w[order])


def listed(td: TermDoc) -> TermDoc:
    """The terms only, which a guess needs."""
    return TermDoc(td.coo.sparkSession.createDataFrame(pa.table({"term": blocks(td).names})), docs=td.docs, _facts=td.facts())


def cut(f: Held, t: int) -> Held:
    """The t largest entries; ties by row and topic."""
    i, j = np.nonzero(f.w > 0)
    best = _cut(np.rint(f.w[i, j] * RANK_SCALE), i, j, t)
    live, place = np.unique(i[best], return_inverse=True)
    w = np.zeros((len(live), f.k))
    w[place, j[best]] = f.w[i[best], j[best]]
    return Held(f._spark, f.keys, f.at[live], w)


def guessed(td: TermDoc, k: int, seed: int) -> Guess:
    """The first guess of all terms, as ``initial_guess`` draws it."""
    names, spark = blocks(td).names, td.coo.sparkSession
    terms = spark.createDataFrame(pa.table({"at": np.arange(len(names), dtype=np.int32), "term": names}))
    terms = terms.repartition(spark.sparkContext.defaultParallelism, "at")  # a local table's columns would be made by the planner
    t = terms.select("at", *[hash_draw(F.col("term"), str(i), str(seed)).alias(f"c{i}") for i in range(k)]).toArrow()
    drawn = np.empty((len(names), k), np.uint32)
    at = t.column("at").to_numpy()
    for i in range(k):
        drawn[at, i] = t.column(f"c{i}").to_numpy()
    return Guess(spark, names, drawn)


def _weight(td: TermDoc, p: Plan) -> int:
    """Most entries that the factors of a plan can have: a limited one leaves the other one no more rows than its own have entries."""
    sizes, most = blocks(td).sizes, {}
    for side, other in (("u", "v"), ("v", "u")):
        t, from_ = (None if x is None else x * (p.k if p.limits.scope == "topic" else 1) for x in (p.limits.side(side)[0], p.limits.side(other)[0]))
        rows = len(sizes[side])
        if t is not None:
            rows = min(rows, t)
        elif from_ is not None and not p.sequential and from_ < len(sizes[other]):
            rows = min(rows, int(np.sort(sizes[other])[len(sizes[other]) - from_ :].sum()))
        most[side] = rows
    return p.k * sum(most.values())


def fit_many(td: TermDoc, plans: list[Plan], read: Callable[[FitResult], object] = lambda fit: fit) -> list:
    """``read`` of the fit of each plan; the fit itself is let go. Equal plans are fitted once. The seconds of a step are
    those of all fits that went along."""
    different = list(dict.fromkeys(plans))

    def many(f: Callable, items: list) -> list:
        with ThreadPoolExecutor(5) as pool:
            return list(pool.map(f, items))

    if not all(held_by_driver(td, p.k) for p in different) or blocks(td).doc_ids.null_count:
        found = dict(zip(different, many(lambda p: read(_through_frames(td, p)), different), strict=True))
        return [found[p] for p in plans]
    guesses: dict[tuple, Held] = {}
    found, turn, room = {}, [], 0
    for p in [*different, None]:
        if turn and (p is None or room + _weight(td, p) > TURN * PASS_ENTRIES):
            found.update(zip(turn, many(read, _together(td, turn, guesses)), strict=True))
            turn, room = [], 0
        if p is not None:
            turn.append(p)
            room += _weight(td, p)
    return [found[p] for p in plans]


def _through_frames(td: TermDoc, p: Plan) -> FitResult:
    options = {"init_nnz": p.init_nnz, "seed": p.seed, "measure": p.measure}
    if p.sequential:
        return sequential_als(td, p.k, limits=p.limits, iters_per_block=p.per_block, **options)
    return sparse_als(td, p.k, p.limits, max_iter=p.max_iter, **options)


def _together(td: TermDoc, plans: list[Plan], guesses: dict) -> list[FitResult]:
    fits: list[Fit] = []
    terms = listed(td)
    for p in plans:
        key = (1 if p.sequential else p.k, p.init_nnz, p.seed)
        if key not in guesses and p.init_nnz is None:
            most = max(1 if q.sequential else q.k for q in plans if (q.init_nnz, q.seed) == key[1:]), *key[1:]
            if most not in guesses:
                guesses[most] = guessed(td, most[0], p.seed)
            if key != most:  # fewer topics are the first ones of more
                guesses[key] = Guess(guesses[most]._spark, guesses[most].keys, guesses[most].drawn[:, : key[0]])
        elif key not in guesses:
            guesses[key] = hold(td, initial_guess(terms, key[0], nnz=p.init_nnz, seed=p.seed))
        made = sequential_fit(td, p.k, p.limits, guesses[key], p.per_block, p.measure) if p.sequential else als_fit(td, p.k, p.limits, guesses[key], p.max_iter, p.measure)
        fits.append(made)
    return advance(td, fits)


def advance(td: TermDoc, fits: list[Generator]) -> list:
    """What the fits return; the half steps of a side that they ask for are made in one pass."""
    results: list = [None] * len(fits)
    asked = {i: next(f) for i, f in enumerate(fits)}
    while asked:
        for side in ("v", "u"):
            going = [i for i in asked if asked[i].side == side]
            for i, answer in zip(going, half_steps(td, side, [asked[i] for i in going]) if going else [], strict=True):
                try:
                    asked[i] = fits[i].send(answer)
                except StopIteration as end:
                    results[i] = end.value
                    del asked[i]
    return results
