"""Accuracy, error, sparsity and cost of a factorisation."""

from __future__ import annotations

from collections.abc import Callable
from time import perf_counter

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import linalg
from .als import FitResult, change, error_from
from .factors import Factor, from_local, key_kind, localized
from .matrix import TermDoc
from .reading import topic_sizes, top_terms

BYTES_PER_ENTRY = 16
SUM_TOPICS, SET_PAIRS, DENSE_CELLS, MEMBER_PAIRS = 16, 100_000_000, 100_000_000, 100_000_000


def residual(new: Factor, old: Factor) -> float:
    return change(new, old)


def relative_error(td: TermDoc, fit: FitResult, how: str = "trace") -> float:
    """Norm of A - UV' over the norm of A.

    'trace': sums and k x k matrices (cancels below about 1e-8); 'entries': differences at A's entries plus the rest by
    Gram matrices; 'dense': every cell, for tables of at most ``DENSE_CELLS`` of them.
    """
    u, v = fit.u, fit.v
    if how == "trace":
        b = linalg.doc_product(td, u)
        dot = F.aggregate(F.zip_with("b", "w", lambda x, y: x * y), F.lit(0.0), lambda a, x: a + x)
        cross = b.join(v.frame, "row").agg(F.sum(dot)).first()[0] or 0.0
        return error_from(td.norm_sq, cross, linalg.gram(u), linalg.gram(v))
    dot = F.coalesce(F.aggregate(F.zip_with("wu", "wv", lambda x, y: x * y), F.lit(0.0), lambda a, x: a + x), F.lit(0.0))
    uu, vv = u.frame.select(F.col("row").alias("term"), F.col("w").alias("wu")), v.frame.select(F.col("row").alias("doc_id"), F.col("w").alias("wv"))
    if how == "entries":
        at = td.entries().join(uu, "term", "left").join(vv, "doc_id", "left").withColumn("p", dot)
        inside = at.agg(F.sum((F.col("x") - F.col("p")) ** 2 - F.col("p") ** 2)).first()[0] or 0.0
        return float(np.sqrt(max(0.0, inside + float((linalg.gram(u) * linalg.gram(v)).sum())) / td.norm_sq))
    if td.n_terms * td.n_docs > DENSE_CELLS:
        raise ValueError("too many cells for how='dense'")
    terms, docs = td.coo.select("term").distinct(), td.coo.select("doc_id").distinct()
    cells = terms.crossJoin(docs).join(td.entries(), ["term", "doc_id"], "left").join(uu, "term", "left").join(vv, "doc_id", "left")
    diff = F.coalesce("x", F.lit(0.0)) - dot
    return float(np.sqrt(cells.agg(F.sum(diff * diff)).first()[0] / td.norm_sq))


def topic_mask(w: str = "w") -> Column:
    """The topics of a packed row as bits of a long (up to 62 topics)."""
    return F.aggregate(F.transform(w, lambda x, i: F.when(x > 0, F.expr("1L")).otherwise(F.expr("0L")) * F.pow(F.lit(2.0), i).cast("long")), F.lit(0).cast("long"), lambda a, x: a + x)


def _pairs_allowed(a: DataFrame, b: DataFrame) -> None:
    pairs = a.count() * b.count()
    if pairs > SET_PAIRS:
        raise ValueError(f"{pairs} pairs of topic sets; truncate the factors first")


def product_nonzeros(u: Factor, v: Factor) -> DataFrame:
    """One row: cells of UV' that are not zero. A cell is non-zero if its term and document share a topic, so rows are
    counted by their set of topics and only the sets are paired: up to ``SUM_TOPICS`` topics by subset sums over all
    possible sets, beyond it set by set, which is refused for more than ``SET_PAIRS`` pairs."""
    if u.k <= SUM_TOPICS:
        counts = []
        for f in (u, v):
            n = np.zeros(1 << u.k, object)
            for r in f.frame.groupBy(topic_mask().alias("m")).agg(F.count(F.lit(1)).alias("n")).collect():  # at most 2^k rows
                n[r["m"]] = r["n"]
            counts.append(n)
        within = counts[1].copy()  # rows of V whose topics are a subset of the mask
        for t in range(u.k):
            blocks = within.reshape(-1, 2, 1 << t)
            blocks[:, 1] += blocks[:, 0]
        apart = int((counts[0] * within[::-1]).sum())  # the complement of a mask stands at the mirrored place
        total = int(counts[0].sum()) * int(counts[1].sum())
        return u.frame.sparkSession.createDataFrame([(total - apart,)], "nonzeros long")
    if u.k <= 62:
        a = u.frame.groupBy(topic_mask().alias("a")).agg(F.count(F.lit(1)).alias("na"))
        b = v.frame.groupBy(topic_mask().alias("b")).agg(F.count(F.lit(1)).alias("nb"))
        _pairs_allowed(a, b)
        pairs = a.crossJoin(F.broadcast(b)).where(F.col("a").bitwiseAND(F.col("b")) != 0)
    else:
        topics = F.filter(F.transform("w", lambda x, i: F.when(x > 0, i)), lambda x: x.isNotNull())
        a = u.frame.groupBy(topics.alias("a")).agg(F.count(F.lit(1)).alias("na"))
        b = v.frame.groupBy(topics.alias("b")).agg(F.count(F.lit(1)).alias("nb"))
        _pairs_allowed(a, b)
        pairs = a.crossJoin(F.broadcast(b)).where(F.arrays_overlap("a", "b"))
    return pairs.agg(F.coalesce(F.sum(F.col("na") * F.col("nb")), F.lit(0)).cast("long").alias("nonzeros"))


def product_sparsity(u: Factor, v: Factor, n_terms: int, n_docs: int) -> float:
    return 1.0 - product_nonzeros(u, v).first()[0] / (n_terms * n_docs)


def accuracy_terms(counts: DataFrame, n_groups: int) -> DataFrame:
    """(topic, n_docs, same_pairs, floor_pairs, all_pairs, acc) from (topic, c): members of one group in one topic."""
    sums = counts.groupBy("topic").agg(F.sum("c").alias("n_docs"), F.sum(F.expr("c * (c - 1) div 2")).alias("same_pairs"))
    q, r = f"(n_docs div {n_groups})", f"(n_docs % {n_groups})"
    floor = F.expr(f"CAST({r} * ({q} + 1) * {q} div 2 + ({n_groups} - {r}) * {q} * ({q} - 1) div 2 AS LONG)")
    pairs = F.expr("n_docs * (n_docs - 1) div 2")
    acc = F.when((F.col("n_docs") < 2) | F.lit(n_groups < 2), F.lit(1.0)).otherwise((F.col("same_pairs") - F.col("floor_pairs")) / F.nullif(F.col("all_pairs") - F.col("floor_pairs"), F.lit(0)))
    return sums.withColumn("floor_pairs", floor).withColumn("all_pairs", pairs).withColumn("acc", F.coalesce(acc, F.lit(1.0)))


def topic_accuracy(v: Factor, groups: DataFrame, n_groups: int, how: str = "closed") -> DataFrame:
    """Share of same-group pairs among a topic's members, shifted and scaled so that even mixing is 0 and one group 1.

    groups: (doc_id, group). 'closed' counts members by group; 'pairs' compares members pair by pair, for at most
    ``MEMBER_PAIRS`` of them. Members without a group are not counted. Topics with fewer than two members have accuracy 1.
    """
    topics = v.frame.sparkSession.range(v.k).select(F.col("id").cast("int").alias("topic"))
    rows = v.long().select("topic", F.col("row").alias("doc_id")).join(groups, "doc_id")
    if how == "closed":
        out = accuracy_terms(rows.groupBy("topic", "group").agg(F.count(F.lit(1)).alias("c")), n_groups)
    else:
        largest = rows.groupBy("topic").count().agg(F.max("count")).first()[0] or 0
        if largest * largest * v.k > MEMBER_PAIRS:
            raise ValueError("too many members for how='pairs'")
        a, b = rows.alias("a"), rows.alias("b")
        same = a.join(b, (F.col("a.topic") == F.col("b.topic")) & (F.col("a.doc_id") < F.col("b.doc_id"))).groupBy(F.col("a.topic").alias("topic")).agg(
            F.count_if(F.col("a.group") == F.col("b.group")).alias("pairs"))
        out = accuracy_terms(rows.groupBy("topic", "group").agg(F.count(F.lit(1)).alias("c")), n_groups).join(same, "topic", "left").withColumn("same_pairs", F.coalesce("pairs", F.lit(0))).drop("pairs")
    zero = {c: 0 for c in ("n_docs", "same_pairs", "floor_pairs", "all_pairs")}
    return topics.join(out, "topic", "left").fillna(zero | {"acc": 1.0})


def mean_accuracy(v: Factor, groups: DataFrame, n_groups: int) -> DataFrame:
    """One row: mean_acc over all topics, mean_live over those with two members or more, n_live."""
    t = topic_accuracy(v, groups, n_groups)
    return t.agg(F.avg("acc").alias("mean_acc"), F.avg(F.when(F.col("n_docs") > 1, F.col("acc"))).alias("mean_live"), F.count_if(F.col("n_docs") > 1).alias("n_live"))


def mean_accuracies(vs: list[Factor], groups: DataFrame, n_groups: int) -> list[float]:
    """``mean_acc`` of many models with few members and as many topics each, by one query."""
    k, vs = vs[0].k, [localized(v) for v in vs]
    w = np.zeros((sum(len(v.rows) for v in vs), k * len(vs)))
    first = 0
    for i, v in enumerate(vs):  # each model's topics after those of the one before
        w[first : first + len(v.rows), i * k : (i + 1) * k] = v.w
        first += len(v.rows)
    both = from_local(groups.sparkSession, [r for v in vs for r in v.rows], w, w.shape[1], key_kind(vs[0].frame))
    acc = {r["topic"]: r["acc"] for r in topic_accuracy(both, groups, n_groups).collect()}
    return [sum(acc[i * k + t] for t in range(k)) / k for i in range(len(vs))]


def skew(f: Factor) -> DataFrame:
    """One row: the largest topic's share of the entries, Gini coefficient of the topic sizes, live topics."""
    sizes = topic_sizes(f)
    ranked = sizes.withColumn("r", F.row_number().over(Window.orderBy("nnz", "topic")))  # k rows
    return ranked.agg(
        F.coalesce(F.max("nnz") / F.nullif(F.sum("nnz"), F.lit(0)), F.lit(0.0)).alias("max_share"),
        F.coalesce(F.sum((2 * F.col("r") - f.k - 1) * F.col("nnz")) / F.nullif(f.k * F.sum("nnz"), F.lit(0)), F.lit(0.0)).alias("gini"), F.count_if(F.col("nnz") > 0).alias("live_topics"),
    )


def iterations_to(trace: DataFrame, tol: float) -> DataFrame:
    """One row: the first iteration whose residual is at most ``tol``."""
    return trace.agg(F.min(F.when(F.col("residual") <= tol, F.col("iter"))).alias("iterations"))


def topic_overlap(a: Factor, b: Factor, r: int = 5) -> DataFrame:
    """(topic_a, topic_b, shared, jaccard) of the strongest r terms."""
    x, y = top_terms(a, r).select(F.col("topic").alias("topic_a"), "term"), top_terms(b, r).select(F.col("topic").alias("topic_b"), "term")
    shared = x.join(y, "term").groupBy("topic_a", "topic_b").agg(F.count(F.lit(1)).alias("shared"))
    sizes = lambda d, c: d.groupBy(c).agg(F.count(F.lit(1)).alias(f"n_{c}"))
    return shared.join(sizes(x, "topic_a"), "topic_a").join(sizes(y, "topic_b"), "topic_b").select(
        "topic_a", "topic_b", "shared", (F.col("shared") / (F.col("n_topic_a") + F.col("n_topic_b") - F.col("shared"))).alias("jaccard"))


def npmi(u: Factor, td: TermDoc, r: int = 5) -> DataFrame:
    """(topic, pairs, npmi): mean normalised pointwise mutual information of a topic's strongest r terms, by documents."""
    tops = F.broadcast(top_terms(u, r).select("topic", "term", "rank"))
    posts = td.coo.select("term", "doc_id", "df").join(tops, "term")
    a, b = posts.alias("a"), posts.alias("b")
    both = a.join(b, (F.col("a.topic") == F.col("b.topic")) & (F.col("a.doc_id") == F.col("b.doc_id")) & (F.col("a.rank") < F.col("b.rank")))
    joint = both.groupBy(F.col("a.topic").alias("topic"), F.col("a.rank").alias("ra"), F.col("b.rank").alias("rb")).agg(F.count(F.lit(1)).alias("n"))
    df = posts.groupBy("topic", "rank").agg(F.max("df").alias("df"))
    pairs = df.alias("x").join(df.alias("y"), (F.col("x.topic") == F.col("y.topic")) & (F.col("x.rank") < F.col("y.rank"))).select(
        F.col("x.topic").alias("topic"), F.col("x.rank").alias("ra"), F.col("y.rank").alias("rb"), F.col("x.df").alias("da"), F.col("y.df").alias("db"))
    m = float(td.n_docs)
    value = F.when(F.col("n") >= m, F.lit(1.0)).otherwise(F.log(F.col("n") * m / (F.col("da") * F.col("db"))) / -F.log(F.col("n") / m))
    scored = pairs.join(joint, ["topic", "ra", "rb"], "left").withColumn("v", F.when(F.col("n").isNull(), F.lit(-1.0)).otherwise(value))
    return scored.groupBy("topic").agg(F.count(F.lit(1)).alias("pairs"), F.avg("v").alias("npmi"))


def memory_ratio(dense: FitResult, sparse: FitResult) -> tuple[float, int, int]:
    """(ratio, bytes dense, bytes sparse) of the peak stored entries."""
    a, b = (max(s[5] for s in f.steps) * BYTES_PER_ENTRY for f in (dense, sparse))
    return a / b, a, b


def norm_ratio(f: Factor, n_rows: int) -> DataFrame:
    """(topic, ratio): sparseness of each column from the ratio of its sum to its norm, 0 flat and 1 for one entry."""
    s = f.long().groupBy("topic").agg(F.sum("value").alias("l1"), F.sqrt(F.sum(F.col("value") * F.col("value"))).alias("l2"))
    root = float(np.sqrt(n_rows))
    return s.select("topic", ((F.lit(root) - F.col("l1") / F.col("l2")) / F.lit(root - 1)).alias("ratio"))


def time_iterations(run: Callable[[], FitResult]) -> tuple[float, int]:
    """(seconds, iterations) of a fit."""
    began = perf_counter()
    fit = run()
    return perf_counter() - began, len(fit.steps)
