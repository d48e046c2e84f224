
from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import baselines as B
from .operators import measures as M
from .operators import related
from .operators.als import FitResult, projected_als, sparse_als, truncate_after
from .operators.factors import Factor, discard, initial_guess, localized
from .operators.lockstep import PASS_ENTRIES, Plan, advance, als_fit, blocks, cut, fit_many, held_by_driver
from .operators.matrix import TermDoc, build_term_doc, matrix_from_arrays, matrix_from_counts
from .operators.reading import top_terms, topic_sizes
from .operators.relational import user_hours
from .operators.sequential import sequential_als
from .operators.sparsify import Limits
from .sources import load_table

SWEEP = "workload string, mode string, side string, t_u long, t_v long, seed int, measure string, value double"
GRID = (10, 25, 50, 100, 250, 1000, 10_000, None)


def corpus(spark: SparkSession, sf_dir: str, lang: str | None = None) -> TermDoc:
    docs = load_table(spark, sf_dir, "documents")
    if lang:
        return build_term_doc(docs.where(F.col("lang") == lang), stop=("english",))
    return build_term_doc(docs)


def groups(spark: SparkSession, sf_dir: str, column: str = "lang") -> DataFrame:
    if column in ("quality", "toxic"):
        return load_table(spark, sf_dir, "labels").select("doc_id", F.col(column).cast("string").alias("group"))
    return load_table(spark, sf_dir, "documents").select("doc_id", F.col(column).alias("group"))


def side_limits(side: str, t: int | None, scope: str = "matrix") -> Limits:
    return Limits(t if side in ("u", "both") else None, t if side in ("v", "both") else None, scope)


def _rows(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, SWEEP)


def _many(jobs: list, workers: int = 5) -> list:
    """Independent fits share one matrix and are submitted together, so that their small jobs fill the cluster."""
    with ThreadPoolExecutor(workers) as pool:
        return list(pool.map(lambda f: f(), jobs))


def run_density_table(spark: SparkSession, td: TermDoc, k: int = 5, iters: int = 10, name: str = "D") -> DataFrame:
    """Zeros of A, U, V and UV' after dense ALS."""
    fit = projected_als(td, k, max_iter=iters, measure=False)
    f = td.facts()
    n, m = f["n_terms"], td.n_docs
    zeros = [("A", 1 - f["nnz"] / (n * m)), ("U", 1 - fit.u.count() / (n * k)), ("V", 1 - fit.v.count() / (m * k)), ("UV'", M.product_sparsity(fit.u, fit.v, n, m))]
    return _rows(spark, [(f"density {name}", "dense", "none", None, None, 0, f"zeros of {what}", float(x)) for what, x in zeros])


def run_convergence_trace(spark: SparkSession, td: TermDoc, k: int = 5, t_u: int = 55, iters: int = 75) -> DataFrame:
    """(run, iter, residual, error, …) of sparse U and of dense, which go along together; seconds are those of both."""
    fits = fit_many(td, [Plan(k, Limits(t_u=t_u), iters), Plan(k, max_iter=iters)])
    out = [fit.trace(spark).withColumn("run", F.lit(name)) for name, fit in zip((f"t_u={t_u}", "dense"), fits, strict=True)]
    return out[0].unionByName(out[1])


def run_topic_tables(spark: SparkSession, td: TermDoc, k: int = 5, t_u: int = 55, iters: int = 20, r: int = 5) -> tuple[DataFrame, DataFrame]:
    """Strongest terms of sparse and dense models, and how far their topics share terms."""
    init = initial_guess(td, k)
    sparse, dense = sparse_als(td, k, Limits(t_u=t_u), init=init, max_iter=iters, measure=False), projected_als(td, k, init=init, max_iter=iters, measure=False)
    both = top_terms(sparse.u, r).withColumn("run", F.lit("sparse")).unionByName(top_terms(dense.u, r).withColumn("run", F.lit("dense")))
    return both, M.topic_overlap(sparse.u, dense.u, r)


def run_nnz_sweep(spark: SparkSession, td: TermDoc, k: int, *, measure: str = "convergence", labels: DataFrame | None = None, n_groups: int = 4, grid: tuple = GRID, sides: tuple = ("u", "v", "both"), iters: int = 75, seeds: tuple = (0,)) -> DataFrame:
    """Error and residual, or mean accuracy, against the entries allowed in U, V or both; all modes start from one guess a seed."""
    cases = [(seed, side, t) for seed in seeds for side in sides for t in grid]
    plans = [Plan(k, side_limits(side, t), iters, seed, measure=measure == "convergence") for seed, side, t in cases]

    def read(fit: FitResult) -> list[tuple[str, float]]:
        if measure == "convergence":
            return [("residual", float(fit.steps[-1][1])), ("error", float(fit.steps[-1][2]))]
        a = M.mean_accuracy(fit.v, labels, n_groups).first()
        return [("mean accuracy", float(a["mean_acc"])), ("live topics", float(a["n_live"]))]

    rows = []
    for (seed, side, _), p, found in zip(cases, plans, fit_many(td, plans, read), strict=True):
        rows += [(f"sweep {measure}", "whole", side, p.limits.t_u, p.limits.t_v, seed, *x) for x in found]
    return _rows(spark, rows)


def run_skew(spark: SparkSession, td: TermDoc, k: int = 5, t_u: int = 50, iters: int = 20) -> DataFrame:
    """Entries of each topic under one limit for the whole matrix, and under very small limits on both sides."""
    rows = []
    for name, lim in (("whole", Limits(t_u=t_u)), ("tiny", Limits(t_u=10, t_v=20)), ("topic", Limits(t_u=t_u // k, scope="topic"))):
        fit = sparse_als(td, k, lim, max_iter=iters, measure=False)
        rows += [("skew", name, "u", lim.t_u, lim.t_v, 0, f"entries of topic {r.topic}", float(r.nnz)) for r in topic_sizes(fit.u).orderBy("topic").collect()]
        s = M.skew(fit.u).first()
        rows += [("skew", name, "u", lim.t_u, lim.t_v, 0, "gini", float(s["gini"])), ("skew", name, "u", lim.t_u, lim.t_v, 0, "largest share", float(s["max_share"]))]
    return _rows(spark, rows)


def run_during_vs_after(spark: SparkSession, td: TermDoc, labels: DataFrame, n_groups: int, k: int = 4, grid: tuple = (200, 400, 800, 1600), iters: int = 50, seeds: tuple = (0,)) -> DataFrame:
    """Mean accuracy when V is truncated in every iteration, and once at the end."""
    def read(fit: FitResult) -> float:
        return float(M.mean_accuracy(fit.v, labels, n_groups).first()["mean_acc"])

    rows = []
    for seed in seeds:
        limits = [Limits(), *[Limits(t_v=t) for t in grid]]
        dense, *during = fit_many(td, [Plan(k, x, iters, seed, measure=False) for x in limits])
        after = [truncate_after(dense, Limits(t_v=t)) for t in grid]
        for t, *both in zip(grid, _many([lambda fit=fit: read(fit) for fit in during]), _many([lambda fit=fit: read(fit) for fit in after]), strict=True):
            rows += [("during or after", mode, "v", None, t, seed, "mean accuracy", x) for mode, x in zip(("during", "after"), both, strict=True)]
    return _rows(spark, rows)


def run_peak_nnz(spark: SparkSession, td: TermDoc, k: int = 4, limits: tuple = (50, 500, 5000), guesses: tuple = (400, 4000, 40_000, None), iters: int = 10) -> DataFrame:
    """Most entries stored at once, by limit and by entries of the first guess; and the ratio to dense."""
    cases = [(g, t) for g in guesses for t in limits]
    plans = [Plan(k, max_iter=max(2, iters // 3)), *[Plan(k, Limits(t, t), iters, init_nnz=g) for g, t in cases]]
    top, *peaks = fit_many(td, plans, lambda fit: max(s[5] for s in fit.steps))
    rows = [("peak", "dense", "both", None, None, 0, "peak entries", float(top))]
    for (g, t), peak in zip(cases, peaks, strict=True):
        rows += [("peak", f"guess {g or 'dense'}", "both", t, t, 0, "peak entries", float(peak)), ("peak", f"guess {g or 'dense'}", "both", t, t, 0, "dense over sparse", top / max(1, peak))]
    return _rows(spark, rows)


MODES = ("whole", "topic", "sequential")


def mode_plans(k: int, t_u: int | None, t_v: int | None, iters: int, seed: int = 0, measure: bool = False, names: tuple = MODES) -> dict[str, Plan]:
    """Whole-matrix, column-wise and sequential fits with the same number of entries and of half steps a topic; those in ``names``."""
    part = lambda t: None if t is None else max(1, t // k)
    plans = {
        "whole": Plan(k, Limits(t_u, t_v), iters, seed, measure=measure),
        "topic": Plan(k, Limits(part(t_u), part(t_v), scope="topic"), iters, seed, measure=measure),
        "sequential": Plan(k, Limits(part(t_u), part(t_v)), iters, seed, measure=measure, sequential=True),
    }
    return {name: plans[name] for name in names}


def modes(td: TermDoc, k: int, t_u: int | None, t_v: int | None, iters: int, seed: int = 0, measure: bool = False, names: tuple = MODES) -> dict[str, FitResult]:
    """The fits of ``mode_plans``."""
    plans = mode_plans(k, t_u, t_v, iters, seed, measure, names)
    return dict(zip(plans, fit_many(td, list(plans.values())), strict=True))


def run_even_topics(spark: SparkSession, td: TermDoc, k: int = 5, per_topic: int = 10, iters: int = 20, r: int = 5) -> DataFrame:
    """Strongest terms of the column-wise and the sequential model, ``per_topic`` entries each."""
    fits = modes(td, k, per_topic * k, None, iters, names=("topic", "sequential"))
    return top_terms(fits["topic"].u, r).withColumn("mode", F.lit("topic")).unionByName(top_terms(fits["sequential"].u, r).withColumn("mode", F.lit("sequential")))


def run_even_accuracy(spark: SparkSession, td: TermDoc, labels: DataFrame, n_groups: int, k: int = 4, t_u: int = 40, t_v: int = 400, iters: int = 20, seeds: tuple = (0, 1, 2, 3, 4)) -> DataFrame:
    """Mean accuracy of the three modes from the same guesses."""
    cases = [(seed, mode, p) for seed in seeds for mode, p in mode_plans(k, t_u, t_v, iters, seed).items()]
    rows = []
    for (seed, mode, _), a in zip(cases, fit_many(td, [p for *_, p in cases], lambda fit: M.mean_accuracy(fit.v, labels, n_groups).first()), strict=True):
        rows += [("even accuracy", mode, "both", t_u, t_v, seed, "mean accuracy", float(a["mean_acc"])), ("even accuracy", mode, "both", t_u, t_v, seed, "live topics", float(a["n_live"]))]
    return _rows(spark, rows)


def run_timing(spark: SparkSession, td: TermDoc, k: int = 4, t_u: int = 55, t_v: int = 400, iters: int = 100) -> DataFrame:
    """Seconds of ``iters`` iterations in each mode, one after the other; sequential has k blocks of iters / k."""
    rows = []
    if held_by_driver(td, k):
        blocks(td)  # belong to the matrix and not to the first mode
    for mode, p in mode_plans(k, t_u, t_v, iters).items():
        s, n = M.time_iterations(lambda p=p: fit_many(td, [p])[0])
        rows += [("timing", mode, "both", t_u, t_v, 0, "seconds", s), ("timing", mode, "both", t_u, t_v, 0, "iterations", float(n))]
    return _rows(spark, rows)


def run_seed_spread(spark: SparkSession, td: TermDoc, labels: DataFrame, n_groups: int, k: int = 4, per_topic: int = 10, iters: int = 5, seeds: tuple = (0, 1, 2)) -> DataFrame:
    """Accuracy and coherence of each topic of sequential fits from several guesses: is one topic weak?"""
    rows = []
    for seed in seeds:
        fit = sequential_als(td, k, limits=Limits(per_topic, per_topic * 10), iters_per_block=iters, seed=seed, measure=False)
        base = ("seed spread", "sequential", "both", per_topic, per_topic * 10, seed)
        rows += [(*base, f"accuracy of topic {r.topic}", float(r.acc)) for r in M.topic_accuracy(fit.v, labels, n_groups).orderBy("topic").collect()]
        rows += [(*base, f"npmi of topic {r.topic}", float(r.npmi)) for r in M.npmi(fit.u, td).orderBy("topic").collect()]
    return _rows(spark, rows)


def relational_matrices(spark: SparkSession, sf_dir: str) -> dict[str, TermDoc]:
    t = lambda n: load_table(spark, sf_dir, n)
    bought = t("orders").select("o_orderkey", "o_custkey").join(t("lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "l_partkey"), "o_orderkey")
    part_words = t("part").select(F.col("p_partkey").alias("doc_id"), F.col("p_name").alias("text"))
    return {
        "customer x part": matrix_from_counts(bought, "l_partkey", "o_custkey"),
        "user x event hour": matrix_from_counts(user_hours(t("events")), "item", "user_id"),
        "embeddings": matrix_from_arrays(t("embeddings"), "vec_id", "embedding"),
        "part words": build_term_doc(part_words, stop=()),
    }


def run_relational_matrices(spark: SparkSession, sf_dir: str, k: int = 3, t_u: int = 60, t_v: int = 300, iters: int = 3) -> DataFrame:
    """Error and entries of sparse fits of matrices that are not text."""
    rows = []
    for name, td in relational_matrices(spark, sf_dir).items():
        fit = sparse_als(td, k, Limits(t_u, t_v), max_iter=iters)
        last = fit.steps[-1]
        rows += [(name, "whole", "both", t_u, t_v, 0, "error", float(last[2])), (name, "whole", "both", t_u, t_v, 0, "entries", float(last[3] + last[4]))]
    return _rows(spark, rows)


def run_related_methods(spark: SparkSession, td: TermDoc, labels: DataFrame, n_groups: int, k: int = 4, iters: int = 5) -> DataFrame:
    """Error and mean accuracy of the related methods, V cut to its largest entries for membership (for LSA by magnitude).
    Ranked terms by tf-idf have no topics and so neither measure."""
    held = held_by_driver(td, k) and not blocks(td).doc_ids.null_count
    found = (_related_held if held else _related_frames)(td, k, iters)
    accuracies = M.mean_accuracies([found[name][1] for name in RELATED], labels, n_groups)
    rows = []
    for name, accuracy in zip(RELATED, accuracies, strict=True):
        if name not in ("plsa", "lda"):
            rows.append(("related", name, "none", None, 400, 0, "error", float(found[name][0])))
        rows.append(("related", name, "none", None, 400, 0, "mean accuracy", accuracy))
    return _rows(spark, rows)


RELATED = ("projected als", "enforced", "threshold", "multiplicative", "gradient", "exact rows", "l1", "norm ratio", "plsa", "lsa", "lda")
MEMBERS = Limits(t_v=400)


def _left(td: TermDoc, singular) -> float:
    """The error of a truncated SVD."""
    return (max(0.0, td.norm_sq - float((singular**2).sum())) / td.norm_sq) ** 0.5 if td.norm_sq else 0.0


def _members(fit: FitResult) -> Factor:
    """V cut to its largest entries, held by the driver; the tables of the fit are removed."""
    few = truncate_after(fit, MEMBERS).v
    kept = localized(few)
    for f in (few, fit.u, fit.v):
        discard(f)
    return kept


def _related_frames(td: TermDoc, k: int, iters: int) -> dict[str, tuple[float | None, Factor]]:
    """Error and V cut to its largest entries, by name."""
    def read(fit: FitResult) -> tuple[float | None, Factor]:
        return fit.steps[-1][2] if fit.steps else None, _members(fit)

    def lsa() -> FitResult:
        u, v, singular = B.lsa_baseline(td, k, power=iters)
        return FitResult(u, Factor(k, v.frame.select("row", F.transform("w", lambda x: F.abs(x)).alias("w"))), k, [(iters, 0.0, _left(td, singular))])

    def lda() -> FitResult:
        v = B.lda_topics(td, k, max_iter=iters)
        return FitResult(v, v, k)

    fits = {
        "projected als": lambda: projected_als(td, k, max_iter=iters), "enforced": lambda: sparse_als(td, k, Limits(55, 400), max_iter=iters),
        "threshold": lambda: sparse_als(td, k, Limits(tau_u=1e-3, tau_v=1e-3), max_iter=iters), "multiplicative": lambda: B.multiplicative_nmf(td, k, max_iter=iters),
        "gradient": lambda: B.gradient_nmf(td, k, max_iter=iters), "exact rows": lambda: B.anls_nmf(td, k, max_iter=iters), "l1": lambda: B.l1_nmf(td, k, 0.01, 0.01, max_iter=iters),
        "norm ratio": lambda: B.norm_ratio_nmf(td, k, 0.9, max_iter=iters, measure=True), "plsa": lambda: B.plsa_baseline(td, k, max_iter=iters), "lsa": lsa, "lda": lda,
    }
    return dict(zip(fits, _many([lambda f=f: read(f()) for f in fits.values()], 3), strict=True))


def _related_held(td: TermDoc, k: int, iters: int) -> dict[str, tuple[float | None, Factor]]:
    """The same from the driver's arrays: the fits go along together, as many as a pass may hold."""
    u, v = related.first_terms(td, k), related.first_docs(td, k)
    fits = {
        "enforced": als_fit(td, k, Limits(55, 400), u, iters, True), "projected als": als_fit(td, k, Limits(), u, iters, True),
        "threshold": related.updated_fit(td, u, None, related.threshold(1e-3, 1e-3), iters), "multiplicative": related.updated_fit(td, u, v, related.multiplicative, iters),
        "gradient": related.updated_fit(td, u, v, related.gradient(), iters), "exact rows": related.updated_fit(td, u, None, None, iters),
        "l1": related.updated_fit(td, u, None, related.l1(0.01, 0.01), iters), "norm ratio": related.updated_fit(td, u, None, related.norm_ratio(td.n_terms, 0.9), iters),
        "lsa": related.lsa_fit(u, iters),
    }
    names = list(fits)
    size = max(1, PASS_ENTRIES // max(1, k * (td.n_terms + td.n_docs)))
    turns = [names[:1], *[names[i : i + size] for i in range(1, len(names), size)]]
    turns[:2] = [turns[0] + turns[1]]  # the limited fit takes no room

    def read(name: str, fit) -> tuple[float, Factor]:
        if name == "lsa":
            _, v, singular = fit
            return _left(td, singular), cut(related.magnitudes(v), MEMBERS.t_v)
        return fit.steps[-1][2], cut(fit.v, MEMBERS.t_v)

    def turn(names: list[str]) -> dict:
        return {name: read(name, fit) for name, fit in zip(names, advance(td, [fits.pop(name) for name in names]), strict=True)}

    def lda() -> dict:
        v = B.lda_topics(td, k, max_iter=iters)
        return {"lda": (None, _members(FitResult(v, v, k)))}

    jobs = [lda, *[lambda names=names: turn(names) for names in turns], lambda: {"plsa": (None, cut(related.plsa(td, u, v, iters).v, MEMBERS.t_v))}]
    found: dict = {}
    for got in _many(jobs, 3):
        found |= got
    return found
