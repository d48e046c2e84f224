"""Related methods to compare with: other updates, penalties, and other topic models."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructField, StructType

from ..session import new_path, remove
from . import linalg
from .als import FitResult, change, error_from, sparse_als
from .factors import Factor, discard, hash_unit, initial_guess, pack, stored
from .matrix import TermDoc
from .sparsify import Limits

TINY = 1e-12


def doc_guess(td: TermDoc, k: int, seed: int = 0) -> Factor:
    """A positive first V by hash of (doc_id, topic, seed)."""
    w = F.array(*[hash_unit(F.col("row"), str(t), f"v{seed}") for t in range(k)])
    return stored(td.coo.select(F.col("doc_id").alias("row")).distinct().select("row", w.alias("w")), k, "guess-v")


def _guess(td: TermDoc, k: int, seed: int) -> Factor:
    return stored(initial_guess(td, k, seed=seed).frame, k, "guess")


def _steps(td: TermDoc, fit: list, i: int, u: Factor, old: Factor, v: Factor) -> None:
    b = linalg.term_product(td, v)
    dot = F.aggregate(F.zip_with("b", "w", lambda x, y: x * y), F.lit(0.0), lambda a, x: a + x)
    cross = b.join(u.frame, "row").agg(F.sum(dot)).first()[0] or 0.0
    gu, gv = linalg.gram(u), linalg.gram(v)
    fit.append((i, change(u, old), error_from(td.norm_sq, cross, gu, gv), u.count(), v.count(), u.count() + v.count(), 0, int((np.diag(gu) > 0).sum()), 0.0))


def _multiplied(own: Factor, product: DataFrame, gram: np.ndarray, k: int, name: str) -> Factor:
    rows = own.frame.join(product, "row").withColumn("d", linalg.times("w", gram))
    new = F.transform(F.arrays_zip("w", "b", "d"), lambda e: e["w"] * e["b"] / F.greatest(e["d"], F.lit(TINY)))
    return stored(rows.select("row", new.alias("w")), k, name)


def multiplicative_nmf(td: TermDoc, k: int, *, max_iter: int = 20, seed: int = 0, measure: bool = True) -> FitResult:
    """Element-wise multiplicative updates of V, then U; the objective never rises."""
    u, v, steps = _guess(td, k, seed), doc_guess(td, k, seed), []
    for i in range(1, max_iter + 1):
        before, v = v, _multiplied(v, linalg.doc_product(td, u), linalg.gram(u), k, "mu-v")
        discard(before)
        old, u = u, _multiplied(u, linalg.term_product(td, v), linalg.gram(v), k, "mu-u")
        if measure:
            _steps(td, steps, i, u, old, v)
        discard(old)
    return FitResult(u, v, k, steps)


def _descended(own: Factor, product: DataFrame, gram: np.ndarray, k: int, step: float, name: str) -> Factor:
    rate = step / (2 * max(np.linalg.eigvalsh(gram).max(), TINY))
    rows = own.frame.join(product, "row").withColumn("d", linalg.times("w", gram))
    new = F.transform(F.arrays_zip("w", "b", "d"), lambda e: F.greatest(e["w"] - F.lit(2 * rate) * (e["d"] - e["b"]), F.lit(0.0)))
    return stored(rows.select("row", new.alias("w")), k, name)


def gradient_nmf(td: TermDoc, k: int, *, step: float = 1.0, max_iter: int = 20, seed: int = 0, measure: bool = True) -> FitResult:
    """Projected gradient steps of length step / L, L from the largest eigenvalue of the other side's Gram matrix."""
    u, v, steps = _guess(td, k, seed), doc_guess(td, k, seed), []
    for i in range(1, max_iter + 1):
        before, v = v, _descended(v, linalg.doc_product(td, u), linalg.gram(u), k, step, "pg-v")
        discard(before)
        old, u = u, _descended(u, linalg.term_product(td, v), linalg.gram(v), k, step, "pg-u")
        if measure:
            _steps(td, steps, i, u, old, v)
        discard(old)
    return FitResult(u, v, k, steps)


def nnls_rows(b: np.ndarray, g: np.ndarray) -> np.ndarray:
    """For each row of b the x >= 0 that minimises x g x' - 2 b x': active sets, all rows with one set solved together."""
    n, k = b.shape
    x = np.zeros((n, k))
    free = np.zeros((n, k), bool)
    tol = 1e-12 * max(1.0, np.abs(g).max())
    for _ in range(5 * k + 10):
        grad = b - x @ g
        grad[free] = -np.inf
        enter = grad.argmax(1)
        todo = np.flatnonzero(grad[np.arange(n), enter] > tol * (1 + np.abs(b).max(1)))
        if not len(todo):
            break
        free[todo, enter[todo]] = True
        pending = todo
        while len(pending):
            z = np.zeros((len(pending), k))
            sets, inverse = np.unique(free[pending], axis=0, return_inverse=True)
            for s, mask in enumerate(sets):
                rows = np.flatnonzero(inverse.ravel() == s)
                if mask.any():
                    z[np.ix_(rows, mask)] = b[pending[rows]][:, mask] @ np.linalg.pinv(g[np.ix_(mask, mask)], hermitian=True)
            bad = (z < 0) & free[pending]
            ok = ~bad.any(1)
            x[pending[ok]] = z[ok]
            back = np.flatnonzero(~ok)
            for i in back:
                row = pending[i]
                down = bad[i]
                alpha = (x[row, down] / np.maximum(x[row, down] - z[i, down], TINY)).min()
                x[row] += alpha * (z[i] - x[row])
                drop = free[row] & (x[row] <= TINY)
                if not drop.any():
                    drop = down
                x[row, drop] = 0.0
                free[row, drop] = False
            pending = pending[back]
    return x


def _exact_rows(product: DataFrame, gram: np.ndarray, k: int) -> DataFrame:
    kind = product.schema["row"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            b = np.asarray(batch.column(1).flatten()).reshape(batch.num_rows, k)
            x = nnls_rows(b, gram)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(pa.array(np.arange(0, len(x) * k + 1, k), pa.int32()), pa.array(x.ravel()))], ["row", "w"])

    return product.mapInArrow(run, f"row {kind}, w array<double>").where(F.exists("w", lambda v: v > 0))


def anls_nmf(td: TermDoc, k: int, *, max_iter: int = 20, seed: int = 0, measure: bool = True) -> FitResult:
    """Alternating non-negative least squares, each row solved exactly."""
    u, steps, v = _guess(td, k, seed), [], None
    for i in range(1, max_iter + 1):
        before, v = v, stored(_exact_rows(linalg.doc_product(td, u), linalg.gram(u), k), k, "nnls-v")
        discard(before)
        old, u = u, stored(_exact_rows(linalg.term_product(td, v), linalg.gram(v), k), k, "nnls-u")
        if measure:
            _steps(td, steps, i, u, old, v)
        discard(old)
    return FitResult(u, v, k, steps)


def l1_nmf(td: TermDoc, k: int, lambda_u: float, lambda_v: float, **options) -> FitResult:
    """Projected ALS with an L1 penalty on the factors: products are lowered by lambda / 2 before the solution."""
    return sparse_als(td, k, Limits(), shift=(lambda_u / 2, lambda_v / 2), **options)


def norm_ratio_maps(long: DataFrame, k: int, n: int, sparseness: float, most: int = 60) -> list[tuple[float, float, float]]:
    """The maps of ``norm_ratio_lines`` for entries (row, topic, value) on executors."""
    spark = long.sparkSession

    def sums(low: list[float]) -> list[tuple[float, float, float]]:
        bounds = spark.createDataFrame(list(enumerate(map(float, low))), "topic int, low double")  # one row a topic
        x = F.col("value")
        free = long.join(F.broadcast(bounds), "topic").where(x >= F.col("low")).groupBy("topic").agg(F.count(F.lit(1)).alias("n"), F.sum(x).alias("s"), F.sum(x * x).alias("ss"))
        got = {r["topic"]: (r["n"], r["s"], r["ss"]) for r in free.collect()}
        return [got.get(t, (0, 0.0, 0.0)) for t in range(k)]

    return norm_ratio_lines(sums, k, n, sparseness, most)


def norm_ratio_lines(sums: Callable[[list[float]], list[tuple[float, float, float]]], k: int, n: int, sparseness: float, most: int = 60) -> list[tuple[float, float, float]]:
    """For each topic (p, q, low): its closest non-negative column of the given ratio of sum to norm, and of the norm it has,
    is p x + q where x >= low and 0 elsewhere.

    Every step of the projection maps all entries that are still free by one line, and the entries it fixes at zero are
    those below a bound. So a step needs count, sum and squares of the free entries only, which ``sums`` has for the positive
    entries from each topic's bound on: one aggregate row a topic, for all topics at once. Zeros are not stored; they are
    free as long as the bound is not above 0.
    """
    root = float(np.sqrt(n))
    low = [-np.inf] * k
    now = whole = sums([0.0] * k)
    free = [float(n)] * k
    l2 = [float(np.sqrt(x[2])) for x in whole]
    l1 = [x * (root - sparseness * (root - 1)) for x in l2]
    line = [(1.0, (l1[t] - whole[t][1]) / n) for t in range(k)]
    todo = [t for t in range(k) if l2[t] > 0]
    for _ in range(most):
        moved = []
        for t in todo:
            (p, q), (_, s, ss), m = line[t], now[t], l1[t] / free[t]
            e = q - m
            a, b, c = p * p * ss + 2 * p * e * s + free[t] * e * e, 2 * m * (p * s + free[t] * e), free[t] * m * m - l2[t] ** 2
            alpha = (-b + np.sqrt(max(0.0, b * b - 4 * a * c))) / (2 * a) if a > TINY else 0.0
            line[t] = p, q = alpha * p, m + alpha * e
            if p > 0 and -q / p > max(low[t], 0.0) + TINY:
                moved.append((t, -q / p))
        if not moved:
            break
        for t, bound in moved:
            low[t] = bound
        new = sums([max(x, 0.0) for x in low])
        todo = []
        for t, _ in moved:
            if new[t][0] == 0 or new[t][0] == free[t]:
                continue  # nothing is left free, or nothing was fixed
            now[t], free[t] = new[t], float(new[t][0])
            p, q = line[t]
            line[t] = p, q - (p * now[t][1] + free[t] * q - l1[t]) / free[t]
            todo.append(t)
    return [(*line[t], low[t]) if l2[t] else (1.0, 0.0, -np.inf) for t in range(k)]


def project_norm_ratio(terms: DataFrame, solved: DataFrame, k: int, n: int, sparseness: float) -> DataFrame:
    """(row, w): each column of ``solved`` (row, w) brought to the given sparseness. terms: all rows (row)."""
    long = solved.select("row", F.posexplode("w").alias("topic", "value")).where("value > 0")
    maps = norm_ratio_maps(long, k, n, sparseness)
    zeros = any(q > 0 and low <= 0 for _, q, low in maps)  # a column that gives stored entries to all rows
    rows = terms.join(solved.select("row", "w"), "row", "left") if zeros else solved.select("row", "w")
    x = lambda t: F.coalesce(F.col("w")[t], F.lit(0.0))
    new = [F.greatest(F.lit(0.0), F.when(x(t) >= F.lit(float(low)), x(t) * F.lit(float(p)) + F.lit(float(q))).otherwise(0.0)) for t, (p, q, low) in enumerate(maps)]
    return rows.select("row", F.array(*new).alias("w")).where(F.exists("w", lambda v: v > 0))


def norm_ratio_nmf(td: TermDoc, k: int, sparseness_u: float, *, max_iter: int = 10, seed: int = 0, measure: bool = False) -> FitResult:
    """Projected ALS whose U columns are projected to a given ratio of sum to norm."""
    u, steps, v = _guess(td, k, seed), [], None
    terms = td.coo.select(F.col("term").alias("row")).distinct()
    for i in range(1, max_iter + 1):
        before, v = v, stored(linalg.solve_docs(td, u).select("row", "w"), k, "ratio-v")
        discard(before)
        solved = stored(linalg.solve_terms(td, v).select("row", "w"), k, "ratio-solved")
        old, u = u, stored(project_norm_ratio(terms, solved.frame, k, td.n_terms, sparseness_u), k, "ratio-u")
        discard(solved)
        if measure:
            _steps(td, steps, i, u, old, v)
        discard(old)
    return FitResult(u, v, k, steps)


def plsa_baseline(td: TermDoc, k: int, *, max_iter: int = 10, seed: int = 0) -> FitResult:
    """Probabilistic latent semantic analysis by expectation-maximisation over the counts: U holds P(term | topic), V
    P(topic | document). Both sides are updated from the same posterior."""
    n = td.coo.select("term", "doc_id", F.col("tf").cast("double").alias("x"))

    def normalised(f: DataFrame) -> DataFrame:
        total = f.agg(F.array(*[F.sum(F.col("w")[t]) for t in range(k)]).alias("s")).first()["s"]
        return f.select("row", F.array(*[F.col("w")[t] / F.lit(float(total[t] or 1.0)) for t in range(k)]).alias("w"))

    u = stored(normalised(initial_guess(td, k, seed=seed).frame), k, "plsa-u")
    guess = doc_guess(td, k, seed)
    share = F.aggregate("w", F.lit(0.0), lambda a, x: a + x)
    v = stored(guess.frame.select("row", F.transform("w", lambda x: x / share).alias("w")), k, "plsa-v")
    discard(guess)
    steps = []
    sums = [F.sum(f"c{t}").alias(f"c{t}") for t in range(k)]
    w = F.array(*[f"c{t}" for t in range(k)])
    for i in range(1, max_iter + 1):
        at = n.join(u.frame.toDF("term", "p"), "term").join(v.frame.toDF("doc_id", "q"), "doc_id")
        at = at.withColumn("z", F.zip_with("p", "q", lambda a, b: a * b)).withColumn("all", F.aggregate("z", F.lit(0.0), lambda a, x: a + x)).where("all > 0")
        # the posterior has an entry for each of A's: it is summed where it is made, once for each side, and never kept
        post = at.select("term", "doc_id", *[(F.col("x") * F.col("z")[t] / F.col("all")).alias(f"c{t}") for t in range(k)], (F.col("x") * F.log("all")).alias("ll"))
        seen = Observation()
        raw = stored(post.observe(seen, F.sum("ll").alias("ll")).groupBy(F.col("term").alias("row")).agg(*sums).select("row", w.alias("w")), k, "plsa-sums")
        new_v = post.groupBy(F.col("doc_id").alias("row")).agg(*sums).select("row", w.alias("w"))
        v_next = stored(new_v.select("row", F.transform("w", lambda x: x / share).alias("w")), k, "plsa-v")
        u_next = stored(normalised(raw.frame), k, "plsa-u")
        for f in (raw, u, v):
            discard(f)
        u, v = u_next, v_next
        steps.append((i, 0.0, -float(seen.get["ll"] or 0.0), u.count(), v.count(), u.count() + v.count(), 0, k, 0.0))
    return FitResult(u, v, k, steps)


def lsa_baseline(td: TermDoc, k: int, *, power: int = 6, seed: int = 0) -> tuple[Factor, Factor, np.ndarray]:
    """Truncated SVD by orthogonal iteration on the same two products, without clipping: (U, V, singular values)."""
    u = stored(initial_guess(td, k, seed=seed).frame.select("row", F.transform("w", lambda x: x - F.lit(0.5)).alias("w")), k, "lsa-u")

    def orthonormal(product: DataFrame, name: str) -> tuple[Factor, np.ndarray]:
        f = stored(product.select("row", F.col("b").alias("w")), k, f"{name}-raw")
        s, q = np.linalg.eigh(linalg.gram(f))
        order = np.argsort(-s)
        s, q = np.sqrt(np.maximum(s[order], TINY)), q[:, order]
        out = stored(f.frame.select("row", linalg.times("w", q / s).alias("w")), k, name)
        discard(f)
        return out, s

    s, v = np.zeros(k), None
    for _ in range(power):
        before, (v, _) = v, orthonormal(linalg.doc_product(td, u), "lsa-v")
        discard(before)
        before, (u, s) = u, orthonormal(linalg.term_product(td, v), "lsa-u")
        discard(before)
    return u, v, s


def lda_baseline(td: TermDoc, k: int, *, max_iter: int = 10, seed: int = 0, r: int = 5) -> DataFrame:
    """(topic, rank, term, value) of Spark's online LDA over the counts of all terms; its driver holds the vocabulary."""
    model, vocabulary, _, path = _lda(td, k, max_iter, seed)
    remove(td.coo.sparkSession, path)
    tops = model.describeTopics(r).select("topic", F.posexplode(F.arrays_zip("termIndices", "termWeights")).alias("rank", "e"))
    tops = tops.select("topic", (F.col("rank") + 1).alias("rank"), F.col("e.termIndices").alias("i"), F.col("e.termWeights").alias("value"))
    return tops.join(vocabulary, "i").select("topic", "rank", "term", "value")


def lda_topics(td: TermDoc, k: int, *, max_iter: int = 10, seed: int = 0) -> Factor:
    """Each document's distribution over the topics of the same model, as V."""
    from pyspark.ml.functions import vector_to_array

    model, _, counted, path = _lda(td, k, max_iter, seed)
    v = stored(model.transform(counted).select(F.col("doc_id").alias("row"), vector_to_array("topicDistribution").alias("w")), k, "lda-v")
    remove(td.coo.sparkSession, path)
    return v


def _lda(td: TermDoc, k: int, max_iter: int, seed: int) -> tuple:
    """(model, vocabulary (i, term) from the most frequent term on, counts as vectors, their path). The vectors are written
    once: the model reads all of them in each iteration."""
    from pyspark.ml.clustering import LDA
    from pyspark.ml.linalg import VectorUDT

    spark = td.coo.sparkSession
    n = td.coo.select("doc_id", "term", F.col("tf").cast("int").alias("n"))
    terms = n.groupBy("term").agg(F.sum("n").alias("all")).where("all > 0").orderBy(F.desc("all"), "term").select("term").toArrow()
    vocabulary = spark.createDataFrame(terms.append_column("i", pa.array(np.arange(terms.num_rows, dtype=np.int32))))
    entry = F.struct("i", F.col("n").cast("double").alias("x"))
    docs = n.join(F.broadcast(vocabulary), "term").groupBy("doc_id").agg(F.filter(F.sort_array(F.collect_list(entry)), lambda e: e["x"] > 0).alias("e"))
    parts = [F.lit(0).cast("tinyint").alias("type"), F.lit(terms.num_rows).alias("size"), F.col("e.i").alias("indices"), F.col("e.x").alias("values")]  # a sparse vector
    path = new_path(spark, "lda-counts")
    docs.select("doc_id", F.struct(*parts).alias("features")).sortWithinPartitions("doc_id").write.parquet(path)
    counted = spark.read.schema(StructType([StructField("doc_id", td.coo.schema["doc_id"].dataType), StructField("features", VectorUDT())])).parquet(path)
    return LDA(k=k, maxIter=max_iter, seed=seed, optimizer="online").fit(counted), vocabulary, counted, path


def tfidf_terms(td: TermDoc, r: int = 5) -> DataFrame:
    """(doc_id, rank, term, value): each document's terms of largest tf log(N / df)."""
    scored = td.coo.select("doc_id", "term", (F.col("tf") * F.log(F.lit(float(td.n_docs)) / F.col("df"))).alias("value"))
    rank = F.row_number().over(Window.partitionBy("doc_id").orderBy(F.rint(F.col("value") * F.lit(1e9)).desc(), "term"))
    return scored.withColumn("rank", rank).where(F.col("rank") <= r).select("doc_id", "rank", "term", "value")
