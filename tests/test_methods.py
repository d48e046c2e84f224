"""The methods against dense NumPy on small planted matrices, and the worked cases."""

import numpy as np
import pytest
import reference_dense as D
from pyspark.sql import functions as F

from sparse_topics.operators import baselines as B
from sparse_topics.operators import linalg
from sparse_topics.operators import lockstep as L
from sparse_topics.operators import measures as M
from sparse_topics.operators import reading as R
from sparse_topics.operators.als import projected_als, sparse_als, truncate_after
from sparse_topics.operators.factors import Factor, from_local, hash_unit, initial_guess, localized
from sparse_topics.operators.matrix import TermDoc, build_term_doc, matrix_from_arrays, matrix_from_counts, prune_rare
from sparse_topics.operators.sequential import block_of, sequential_als
from sparse_topics.operators import sparsify
from sparse_topics.operators.sparsify import Limits, keep_above, keep_largest, keep_largest_per_topic, kth_largest, kth_largest_of
from sparse_topics.plans.choice import choose_join, choose_layout, plan_text

N, DOCS, K = 14, 11, 3


def term_doc(spark, a):
    rows = [(f"t{i:02d}", j, float(a[i, j]), 1) for i in range(a.shape[0]) for j in range(a.shape[1]) if a[i, j]]
    return TermDoc(spark.createDataFrame(rows, "term string, doc_id long, tf double, df long").cache(), "none", a.shape[1])


@pytest.fixture(scope="module")
def planted(spark):
    rng = np.random.default_rng(4)
    a = np.round(rng.random((N, DOCS)) * (rng.random((N, DOCS)) < 0.5) * 6, 3)
    a[:4, :4] += 5
    a[5:9, 4:8] += 4
    a[a.sum(1) == 0, 0] = 1
    a[0, a.sum(0) == 0] = 1
    return a, term_doc(spark, a)


def dense(f, rows, prefix=True):
    out = np.zeros((rows, f.k))
    for r in f.long().collect():
        out[int(r.row[1:]) if prefix else r.row, r.topic] = r.value
    return out


def start(td, k=K, **o):
    f = initial_guess(td, k, **o)
    return f, dense(f, N)


LIMITS = [Limits(), Limits(4, 3, scope="topic", ties="keep"), Limits(9), Limits(None, 7), Limits(9, 7), Limits(9, 7, ties="keep"), Limits(4, 3, scope="topic"), Limits(tau_u=0.3, tau_v=0.1), Limits(0, 5)]


@pytest.mark.parametrize("limits", LIMITS, ids=str)
def test_als_equals_dense(planted, limits):
    a, td = planted
    init, u0 = start(td)
    fit = sparse_als(td, K, limits, init=init, max_iter=3)
    u, v, trace = D.als(a, u0, 3, limits.t_u, limits.t_v, limits.scope, limits.ties, (limits.tau_u, limits.tau_v))
    assert np.allclose(dense(fit.u, N), u, atol=1e-8) and np.allclose(dense(fit.v, DOCS, False), v, atol=1e-8)
    if u.any():
        assert np.allclose([s[1] for s in fit.steps], [t[0] for t in trace]) and np.allclose([s[2] for s in fit.steps], [t[1] for t in trace])
    assert fit.steps[-1][3] == (u > 0).sum() and fit.steps[-1][4] == (v > 0).sum()
    if limits.t_u is not None and limits.scope == "matrix" and limits.ties == "exact":
        assert all(s[3] <= limits.t_u for s in fit.steps)


def test_limits_without_effect_are_dense(planted):
    _, td = planted
    init, _ = start(td)
    plain = projected_als(td, K, init=init, max_iter=2)
    wide = sparse_als(td, K, Limits(N * K, DOCS * K), init=init, max_iter=2)
    flat = sparse_als(td, K, Limits(tau_u=0.0, tau_v=0.0), init=init, max_iter=2)
    for other in (wide, flat):
        assert np.allclose(dense(plain.u, N), dense(other.u, N)) and np.allclose(dense(plain.v, DOCS, False), dense(other.v, DOCS, False))


def test_truncate_after(planted):
    a, td = planted
    init, u0 = start(td)
    fit = truncate_after(projected_als(td, K, init=init, max_iter=2), Limits(8, None))
    u, v, _ = D.als(a, u0, 2)
    assert np.allclose(dense(fit.u, N), D.largest(u, 8)) and np.allclose(dense(fit.v, DOCS, False), v)


def test_sequential(planted):
    a, td = planted
    init, u0 = start(td, 1)
    fit = sequential_als(td, 3, limits=Limits(5, 4), iters_per_block=2)
    u, v = D.sequential(a, u0, 3, 2, 5, 4)
    assert np.allclose(dense(fit.u, N), u) and np.allclose(dense(fit.v, DOCS, False), v) and len(fit.steps) == 6
    loose = sequential_als(td, 2, iters_per_block=2)
    u, v = D.sequential(a, u0, 2, 2)
    assert np.allclose(dense(loose.u, N), u) and np.allclose(dense(loose.v, DOCS, False), v)
    one = sequential_als(td, 1, block=2, limits=Limits(9, 7), iters_per_block=2)
    whole = sparse_als(td, 2, Limits(9, 7), max_iter=2)
    assert np.allclose(dense(one.u, N), dense(whole.u, N))


@pytest.mark.parametrize("limits", [Limits(9, 7), Limits()], ids=str)
def test_blocks_of_two_topics(planted, limits):
    a, td = planted
    _, u0 = start(td, 2)
    fit = sequential_als(td, 2, block=2, limits=limits, iters_per_block=3)
    u, v = D.sequential(a, u0, 2, 3, limits.t_u, limits.t_v)
    assert np.allclose(dense(fit.u, N), u, atol=1e-8) and np.allclose(dense(fit.v, DOCS, False), v, atol=1e-8)
    # the error of all topics so far, iteration by iteration
    first = D.als(a, u0, 3, limits.t_u, limits.t_v)
    want = [t[1] for t in first[2]]
    for i in (1, 2, 3):
        u2, v2, _ = D.als(a, u0, i, limits.t_u, limits.t_v, done=first[:2])
        want.append(np.linalg.norm(a - first[0] @ first[1].T - u2 @ v2.T) / np.linalg.norm(a))
    assert np.allclose([s[2] for s in fit.steps], want)
    assert [r.block for r in block_of(fit.trace(td.coo.sparkSession), 3).orderBy("iter").collect()] == [0, 0, 0, 1, 1, 1]


def test_fresh_guesses_for_blocks(planted):
    a, td = planted
    fit = sequential_als(td, 2, limits=Limits(5, 4), iters_per_block=2, seed=3, init_per_block="fresh")
    u1, v1, _ = D.als(a, start(td, 1, seed=3)[1], 2, 5, 4)
    u2, _, _ = D.als(a, start(td, 1, seed=4)[1], 2, 5, 4, done=(u1, v1))
    assert np.allclose(dense(fit.u, N), np.hstack([u1, u2]))


def test_stops_when_u_stands_still(planted):
    a, td = planted
    init, u0 = start(td)
    fit = sparse_als(td, K, Limits(9, 7), init=init, max_iter=40, tol=1e-6, measure=False)
    residuals = [t[0] for t in D.als(a, u0, 40, 9, 7)[2]]
    first = next(i for i, r in enumerate(residuals, 1) if r <= 1e-6)
    assert len(fit.steps) == first < 40


@pytest.mark.parametrize("method, ridge", [("pinv", 0.0), ("cholesky", 0.0), ("ridge", 0.5)])
def test_inverses(planted, method, ridge):
    a, td = planted
    init, u0 = start(td)
    g = u0.T @ u0 + ridge * np.eye(K)
    got = Factor(K, linalg.solve_docs(td, init, method=method, ridge=ridge).select("row", "w"))
    assert np.allclose(dense(got, DOCS, False), np.maximum(a.T @ u0 @ np.linalg.inv(g), 0))
    assert np.allclose(linalg.invert_gram(u0.T @ u0, method, ridge=ridge), np.linalg.inv(g))


def test_a_small_factor_moves_to_the_driver(planted):
    _, td = planted
    f = initial_guess(td, K)
    near = localized(f)
    assert near.local and np.allclose(dense(near, N), dense(f, N)) and localized(near) is near and not localized(f, 3).local


def test_block_step_is_least_squares_on_the_rest(planted, spark):
    a, td = planted
    rng = np.random.default_rng(0)
    u1, v1, u2 = rng.random((N, 2)), rng.random((DOCS, 2)), rng.random((N, 1))
    terms = [f"t{i:02d}" for i in range(N)]
    f1, g1, f2 = (from_local(spark, r, x, x.shape[1], k) for r, x, k in ((terms, u1, "string"), (list(range(DOCS)), v1, "long"), (terms, u2, "string")))
    got = Factor(1, linalg.solve_docs(td, f2, done=(f1, g1)).select("row", "w"))
    want = np.maximum((a - u1 @ v1.T).T @ u2 @ np.linalg.inv(u2.T @ u2), 0)
    assert np.allclose(dense(got, DOCS, False), want)


def test_rank_one_is_recovered(spark):
    u, v = np.array([1.0, 2, 3, 4]), np.array([2.0, 1, 5])
    td = term_doc(spark, np.outer(u, v))
    fit = projected_als(td, 1, max_iter=2)
    assert M.relative_error(td, fit, "dense") < 1e-12 and fit.steps[1][1] < 1e-12


def test_blocks_become_topics(spark):
    a = np.zeros((8, 8))
    a[:4, :4], a[4:, 4:] = 2.0, 3.0
    td = term_doc(spark, a)
    init = from_local(spark, [f"t{i:02d}" for i in range(8)], np.vstack([np.tile([1, 0.1], (4, 1)), np.tile([0.1, 1], (4, 1))]), 2, "string")
    fit = sparse_als(td, 2, Limits(8, 8), init=init, max_iter=4)
    groups = spark.createDataFrame([(j, "a" if j < 4 else "b") for j in range(8)], "doc_id long, group string")
    assert M.topic_accuracy(fit.v, groups, 2).agg(F.min("acc")).first()[0] == 1.0
    assert M.mean_accuracy(fit.v, groups, 2).first()["n_live"] == 2


def test_ties(spark):
    long = spark.createDataFrame([(i, 0, float(v)) for i, v in enumerate([5, 3, 3, 3, 1])], "row long, topic int, value double")
    assert sorted(r.row for r in keep_largest(long, 2).collect()) == [0, 1]
    assert keep_largest(long, 2, "keep").count() == 4 and keep_largest(long, 9).count() == 5 and keep_largest(long, 0).count() == 0
    assert sorted(r.row for r in keep_largest(long, 3, local=1).collect()) == [0, 1, 2]
    assert kth_largest(long, 2) == (3e12, 1, 3) and kth_largest(long, 6)[0] == 0.0
    assert keep_above(long, 3.0).count() == 4 and keep_largest_per_topic(long, 2).count() == 2


def test_kth_largest_narrows(spark):
    rng = np.random.default_rng(1)
    values = np.round(rng.exponential(1.0, 5000), 3) + 0.001
    long = spark.createDataFrame([(i, 0, float(v)) for i, v in enumerate(values)], "row long, topic int, value double")
    for t in (1, 17, 2500, 5000):
        key, above, equal = kth_largest(long, t, collect=20)
        want = np.sort(values)[::-1][t - 1]
        assert key == np.rint(want * 1e12) and above == (values > want).sum() and equal == (values == want).sum()


def test_dead_topic(planted, spark):
    _, td = planted
    w = np.zeros((N, 2))
    w[:, 0] = 1
    init = from_local(spark, [f"t{i:02d}" for i in range(N)], w, 2, "string")
    fit = sparse_als(td, 2, Limits(9, 7), init=init, max_iter=2)
    assert np.isfinite(dense(fit.u, N)).all() and fit.steps[-1][7] == 1
    assert [r.nnz for r in R.topic_sizes(fit.u).orderBy("topic").collect()][1] == 0
    again = sparse_als(td, 2, Limits(9, 7), init=init, max_iter=2, revive="reseed")
    assert again.steps[0][7] == 2


def test_scaling_moves_thresholds_only(planted, spark):
    a, td = planted
    big = term_doc(spark, a * 10)
    support = lambda f: {(r.row, r.topic) for r in f.long().collect()}
    init, _ = start(td)
    assert support(sparse_als(td, K, Limits(9, 7), init=init, max_iter=2).u) == support(sparse_als(big, K, Limits(9, 7), init=init, max_iter=2).u)
    lim = Limits(tau_v=1.0)
    assert sparse_als(td, K, lim, init=init, max_iter=1).v.count() != sparse_als(big, K, lim, init=init, max_iter=1).v.count()


@pytest.mark.parametrize("limits", [Limits(), Limits(9, 7)], ids=str)
def test_errors_agree(planted, limits):
    a, td = planted
    fit = sparse_als(td, K, limits, max_iter=2)
    want = np.linalg.norm(a - dense(fit.u, N) @ dense(fit.v, DOCS, False).T) / np.linalg.norm(a)
    for how in ("trace", "entries", "dense"):
        assert M.relative_error(td, fit, how) == pytest.approx(want, abs=1e-9)
    product = dense(fit.u, N) @ dense(fit.v, DOCS, False).T
    assert M.product_nonzeros(fit.u, fit.v).first()[0] == (product > 0).sum()
    assert M.product_sparsity(fit.u, fit.v, N, DOCS) == pytest.approx((product == 0).mean())


def test_many_topics_use_the_long_layout(planted, monkeypatch):
    _, td = planted
    f, _ = start(td)
    packed = {r.row: r.b for r in linalg.doc_product(td, f).collect()}
    g = linalg.gram(f)
    monkeypatch.setattr(linalg, "choose_layout", lambda k: "long")
    long = {r.row: r.b for r in linalg.doc_product(td, f).collect()}
    assert packed.keys() == long.keys() and all(np.allclose(packed[r], long[r]) for r in packed)
    assert np.allclose(linalg.gram(f), g)
    assert choose_layout(10) == "packed" and choose_layout(500) == "long"


def test_wide_masks(spark):
    k = 70
    rng = np.random.default_rng(2)
    u, v = ((rng.random((9, k)) < 0.05) * 1.0 for _ in range(2))
    fu, fv = (from_local(spark, list(range(9)), x, k, "long") for x in (u, v))
    assert M.product_nonzeros(fu, fv).first()[0] == ((u @ v.T) > 0).sum()


@pytest.mark.parametrize("groups, j", [("aabbccddee", 5), ("aaaaaaaaaa", 5), ("aaabbcc", 3), ("", 5), ("a", 5), ("ab", 5), ("aabb", 1), ("aaaaab", 4)])
def test_accuracy_cases(spark, groups, j):
    v = from_local(spark, list(range(len(groups))), np.ones((len(groups), 1)), 1, "long")
    g = spark.createDataFrame([(i, c) for i, c in enumerate(groups)], "doc_id long, group string")
    for how in ("closed", "pairs"):
        assert M.topic_accuracy(v, g, j, how).first()["acc"] == pytest.approx(D.accuracy(groups, j))


def test_accuracy_as_an_aggregate(spark):
    from sparse_topics.functions.sql import register, topic_accuracy_udaf

    df = spark.createDataFrame([(c, 3) for c in "aabbbc"], "g string, j int")
    assert df.agg(topic_accuracy_udaf()(F.col("g"), F.col("j"))).first()[0] == pytest.approx(D.accuracy("aabbbc", 3))
    register(spark)
    assert spark.sql("SELECT accuracy_floor(10, 5), accuracy_floor(7, 3), topic_bit(3)").first()[:] == (5, 5, 8)
    assert {tuple(r) for r in spark.sql("SELECT * FROM tokens('a b A')").collect()} == {("a", 2), ("b", 1)}


def test_updates_equal_dense(planted):
    a, td = planted
    _, u0 = start(td)
    v0 = dense(B.doc_guess(td, K), DOCS, False)
    for fit, want in ((B.multiplicative_nmf(td, K, max_iter=3), D.multiplicative(a, u0, v0, 3)), (B.gradient_nmf(td, K, max_iter=3), D.gradient(a, u0, v0, 3))):
        assert np.allclose(dense(fit.u, N), want[0]) and np.allclose(dense(fit.v, DOCS, False), want[1])
        errors = [s[2] for s in fit.steps]
        assert all(y <= x + 1e-9 for x, y in zip(errors, errors[1:]))


def test_exact_rows_are_optimal():
    rng = np.random.default_rng(3)
    m = rng.random((20, 4))
    g, b = m.T @ m, rng.standard_normal((300, 4)) * 3
    x = B.nnls_rows(b, g)
    grad = x @ g - b
    assert (x >= 0).all() and (grad >= -1e-7).all() and np.abs(x * grad).max() < 1e-6


def test_other_baselines(planted):
    a, td = planted
    _, u0 = start(td)
    fit = B.anls_nmf(td, K, max_iter=3)
    assert all(y[2] <= x[2] + 1e-9 for x, y in zip(fit.steps, fit.steps[1:]))
    u, v, _ = D.als(a, u0, 2, shift=0.2)
    assert np.allclose(dense(B.l1_nmf(td, K, 0.4, 0.4, max_iter=2).u, N), u)
    assert B.norm_ratio_nmf(td, K, 0.3, max_iter=1).u.count() > 0
    ratio = M.norm_ratio(B.norm_ratio_nmf(td, K, 0.6, max_iter=2).u, N).collect()
    assert all(r.ratio == pytest.approx(0.6, abs=1e-6) for r in ratio)
    p = B.plsa_baseline(td, K, max_iter=4)
    assert np.allclose(dense(p.u, N).sum(0), 1) and np.allclose(dense(p.v, DOCS, False).sum(1), 1)
    assert all(y[2] <= x[2] + 1e-9 for x, y in zip(p.steps, p.steps[1:]))
    s = B.lsa_baseline(td, K, power=25)[2]
    assert np.allclose(s, np.linalg.svd(a)[1][:K], rtol=1e-3)
    lda = B.lda_baseline(TermDoc(td.coo.withColumn("tf", F.ceil("tf")), "none", DOCS), 2, max_iter=2)
    assert lda.count() == 10
    assert B.tfidf_terms(td, 2).groupBy("doc_id").count().agg(F.max("count")).first()[0] == 2


def test_guess(planted, spark):
    _, td = planted
    assert spark.range(1).select(hash_unit("abc", "0", "7")).first()[0] == pytest.approx(0.9160499402787536)
    f = initial_guess(td, 2, nnz=5)
    whole = {(r.row, r.topic): r.value for r in initial_guess(td, 2).long().collect()}
    assert f.count() == 5 and all(whole[r.row, r.topic] == r.value for r in f.long().collect())


def test_reading(planted, spark):
    _, td = planted
    fit = sparse_als(td, K, Limits(9, 7), max_iter=2)
    u = dense(fit.u, N)
    for r in R.top_terms(fit.u, 2).collect():
        assert r.value == pytest.approx(np.sort(u[:, r.topic])[::-1][r.rank - 1])
    assert R.topic_table(fit.u, 3).columns == ["rank", "topic_0", "topic_1", "topic_2"]
    v = dense(fit.v, DOCS, False)
    assert {(r.topic, r.doc_id) for r in R.members(fit.v).collect()} == {(t, d) for d, t in zip(*np.nonzero(v))}
    assert {r.doc_id: r.topic for r in R.assign(fit.v).collect()} == {d: v[d].argmax() for d in range(DOCS) if v[d].any()}
    folded = R.fold_in(td, fit.u, Limits(None, 7))
    assert folded.count() <= 7
    assert R.topic_json(fit.u).count() <= K
    M.iterations_to(fit.trace(spark), 1e-30).first()
    assert M.topic_overlap(fit.u, fit.u).where("topic_a = topic_b").agg(F.min("jaccard")).first()[0] == 1.0
    R.register_views(fit.u, fit.v, "m_")
    assert spark.sql("SELECT count(*) FROM m_u").first()[0] == fit.u.count()


def test_published_tables_overlap(spark):
    """Topic sizes shown in a skewed table: 5, 1, 5, 3, 5."""
    sizes = [5, 1, 5, 3, 5]
    w = np.zeros((19, 5))
    w[np.arange(19), np.repeat(np.arange(5), sizes)] = 1
    f = from_local(spark, list(range(19)), w, 5, "long")
    assert [r.nnz for r in R.topic_sizes(f).orderBy("topic").collect()] == sizes
    s = M.skew(f).first()
    assert s["max_share"] == pytest.approx(5 / 19) and s["live_topics"] == 5 and s["gini"] > 0


def test_arrays(spark):
    df = spark.createDataFrame([(1, [1.0, -2.0, 0.0]), (2, [0.5, 3.0, -1.0])], "id long, x array<double>")
    got = lambda td: {(r.term, r.doc_id, r.tf) for r in td.coo.collect()}
    assert got(matrix_from_arrays(df, "id", "x")) == {("0", 1, 1.0), ("0", 2, 0.5), ("1", 2, 3.0)}
    assert ("-1", 1, 2.0) in got(matrix_from_arrays(df, "id", "x", "split")) and ("0", 1, 3.0) in got(matrix_from_arrays(df, "id", "x", "shift"))


def test_weighting(spark):
    counts = spark.createDataFrame([("a", 1, 2), ("a", 2, 1), ("b", 1, 1), ("c", 1, 3)], "term string, doc_id long, tf long")
    coo = prune_rare(counts)
    td = TermDoc(coo, "df", 2)
    assert {(r.term, r.doc_id): r.x for r in td.entries().collect()} == {("a", 1): 1.0, ("a", 2): 0.5, ("c", 1): 3.0}
    assert {r.term for r in prune_rare(counts, by="docs").collect()} == {"a"}
    assert td.facts()["n_terms"] == 2 and td.norm_sq == pytest.approx(10.25)


def test_other_weights_and_prunings(spark):
    docs = spark.createDataFrame([(1, "a a b c"), (2, "a d d"), (3, "a b")], "doc_id long, text string")
    x = {(r.term, r.doc_id): r.x for r in build_term_doc(docs, stop=(), weight="tfidf", prune=None).entries().collect()}
    assert x == pytest.approx({("a", 1): 0.0, ("b", 1): np.log(1.5), ("c", 1): np.log(3), ("a", 2): 0.0, ("d", 2): 2 * np.log(3), ("a", 3): 0.0, ("b", 3): np.log(1.5)})
    assert {r.term for r in build_term_doc(docs, stop=(), max_df_share=0.7).coo.collect()} == {"b", "d"}


@pytest.mark.parametrize("sparseness", [0.2, 0.6, 0.9])
def test_norm_ratio_projection_equals_dense(spark, sparseness):
    rng = np.random.default_rng(int(sparseness * 10))
    x = np.maximum(rng.standard_normal((40, 3)), 0) * [1.0, 10.0, 0.1]
    x[:, 2] += 0.05  # a column without zeros
    rows = [(f"t{i:02d}", x[i].tolist()) for i in range(40) if x[i].any()]
    solved = spark.createDataFrame(rows, "row string, w array<double>")
    terms = spark.createDataFrame([(f"t{i:02d}",) for i in range(40)], "row string")
    got = dense(Factor(3, B.project_norm_ratio(terms, solved, 3, 40, sparseness)), 40)
    for j in range(3):
        l2 = np.linalg.norm(x[:, j])
        want = D.norm_ratio(x[:, j], l2 * (np.sqrt(40) - sparseness * (np.sqrt(40) - 1)), l2)
        assert np.allclose(got[:, j], want, atol=1e-9) and np.linalg.norm(want) == pytest.approx(l2)


def test_thresholds_of_all_topics(spark, monkeypatch):
    rng = np.random.default_rng(6)
    values = np.round(rng.random((400, 3)) ** 3, 2)  # many ties
    values[:, 2] = np.where(np.arange(400) < 5, 0.5, 0.0)
    long = spark.createDataFrame([(i, t, float(values[i, t])) for i in range(400) for t in range(3) if values[i, t] > 0], "row long, topic int, value double").repartition(5)
    found = kth_largest_of(long, 30, F.col("topic"), collect=10)
    for t in range(2):
        x = np.sort(values[:, t])[::-1]
        assert found[t] == (round(x[29] * 1e12), (x > x[29]).sum(), (x == x[29]).sum())
    assert found[2] == (0.0, 5, 0)
    for ties in ("exact", "keep"):
        rows = lambda df: sorted((r.topic, r.row, r.value) for r in df.collect())
        by_window, by_threshold = keep_largest_per_topic(long, 30, ties), keep_largest_per_topic(long, 30, ties, local=0)
        assert rows(by_window) == rows(by_threshold) and by_window.columns == by_threshold.columns
    monkeypatch.setattr(sparsify, "heap_fits", lambda spark, t: False)
    assert sorted(map(tuple, keep_largest(long, 100).collect())) == sorted(map(tuple, long.orderBy(F.desc("value"), "row", "topic").limit(100).collect()))


def test_single_task_merges_are_bounded(spark, monkeypatch):
    from sparse_topics.plans import choice

    assert choice.heap_fits(spark, 200_000) and not choice.heap_fits(spark, 300_000)
    monkeypatch.setattr(choice, "HEAP_ROWS", 100)
    assert choice.heap_fits(spark, 25) and not choice.heap_fits(spark, 26)


def jobs_of(spark, f):
    spark.sparkContext.setJobGroup("counted", "counted")
    f()
    n = len(spark.sparkContext.statusTracker().getJobIdsForGroup("counted"))
    spark.sparkContext.setJobGroup("rest", "rest")
    return n


def test_iterations_cost_few_jobs_and_no_disk(planted, spark):
    import glob

    _, td = planted
    td.facts()
    folder = spark.conf.get("spark.checkpoint.dir").removeprefix("file://")
    init = initial_guess(td, K, nnz=6)
    few, more = (jobs_of(spark, lambda n=n: sparse_als(td, K, Limits(9, 7), init=init, max_iter=n, measure=False)) for n in (2, 6))
    assert (more - few) / 4 <= 10  # adaptive execution counts every stage as a job
    for make in (lambda n: projected_als(td, K, max_iter=n), lambda n: sparse_als(td, K, Limits(t_u=9), max_iter=n), lambda n: B.multiplicative_nmf(td, K, max_iter=n), lambda n: B.plsa_baseline(td, K, max_iter=n)):
        before = len(glob.glob(f"{folder}/*"))
        make(5)
        assert len(glob.glob(f"{folder}/*")) - before <= 2  # the last U and V
    before = len(glob.glob(f"{folder}/*"))
    sequential_als(td, 3, iters_per_block=3)
    assert len(glob.glob(f"{folder}/*")) - before <= 2


def test_guards_refuse_what_grows(planted, monkeypatch):
    _, td = planted
    fit = projected_als(td, K, max_iter=1)
    whole = M.product_nonzeros(fit.u, fit.v).first()[0]
    monkeypatch.setattr(M, "SUM_TOPICS", 0)
    assert M.product_nonzeros(fit.u, fit.v).first()[0] == whole
    for name in ("SET_PAIRS", "DENSE_CELLS", "MEMBER_PAIRS"):
        monkeypatch.setattr(M, name, 0)
    with pytest.raises(ValueError):
        M.product_nonzeros(fit.u, fit.v)
    with pytest.raises(ValueError):
        M.relative_error(td, fit, "dense")
    with pytest.raises(ValueError):
        M.topic_accuracy(fit.v, td.coo.select("doc_id", F.lit("g").alias("group")).distinct(), 2, "pairs")


def test_memory_ratio_and_peak(planted):
    _, td = planted
    dense_fit, sparse_fit = projected_als(td, K, max_iter=2), sparse_als(td, K, Limits(3, 3), init_nnz=3, max_iter=2)
    assert all(s[5] <= max(3, 3) + 3 for s in sparse_fit.steps)
    assert M.memory_ratio(dense_fit, sparse_fit)[0] > 5


def test_plans(planted, spark):
    _, td = planted
    small = sparse_als(td, K, Limits(9, 7), max_iter=1).u
    plan = plan_text(linalg.solve_docs(td, small))
    assert "BroadcastHashJoin" in plan and "CartesianProduct" not in plan and "BroadcastNestedLoop" not in plan
    assert choose_join(100) == "local" and choose_join(1_000_000) == "broadcast" and choose_join(None) == "shuffle"
    long = small.long()
    assert "TakeOrderedAndProject" in plan_text(keep_largest(long, 5)) and "WindowGroupLimit" in plan_text(keep_largest_per_topic(long, 5))


def test_bucketed_matrix_needs_no_exchange(planted, spark):
    from sparse_topics.sources import load_matrix, save_matrix

    _, td = planted
    save_matrix(td, "bucketed_matrix", 4)
    again = load_matrix(spark, "bucketed_matrix", "none", DOCS)
    small = sparse_als(td, K, Limits(9, 7), max_iter=1).u
    plan = plan_text(linalg.doc_product(again, small))
    assert "hashpartitioning" not in plan.replace("BroadcastExchange", "")
    assert np.allclose(sorted(r.b[0] for r in linalg.doc_product(again, small).collect()), sorted(r.b[0] for r in linalg.doc_product(td, small).collect()))
    spark.sql("DROP TABLE bucketed_matrix")


def test_lda_holds_every_term(spark):
    n = 50_100
    td = matrix_from_counts(spark.range(2 * n).select((F.col("id") % n).cast("string").alias("term"), (F.col("id") % 7).alias("doc_id")), "term", "doc_id")
    assert B.lda_baseline(td, 2, max_iter=1, r=n).select("term").distinct().count() == td.n_terms == n


def test_even_topics_makes_only_the_fits_it_returns(spark, tiny, monkeypatch):
    from sparse_topics import experiments as X

    scopes, fit = [], X.sparse_als
    monkeypatch.setattr(X, "sparse_als", lambda td, k, limits, **more: scopes.append(limits.scope) or fit(td, k, limits, **more))
    rows = X.run_even_topics(spark, X.corpus(spark, tiny), 2, 10, 2).collect()
    assert scopes == ["topic"] and {r["mode"] for r in rows} == {"topic", "sequential"}


TOGETHER = [L.Plan(K, x, 2) for x in (Limits(), Limits(9, 7), Limits(None, 7), Limits(4, 3, scope="topic"))] + [L.Plan(K, Limits(9, 7), 2, init_nnz=6)] + [L.Plan(2, x, 4, sequential=True) for x in (Limits(4, 3), Limits(4, None))]


def test_fits_side_by_side_are_the_single_fits(planted, spark, monkeypatch):
    """In blocks of few rows, with slices shorter than a row, in one turn and in several."""
    _, td = planted
    td = TermDoc(td.coo, "none", DOCS)
    monkeypatch.setattr(L, "BLOCK", (30, 1000))
    monkeypatch.setattr(L, "CACHED", 1)
    alone = [L._through_frames(td, p) for p in TOGETHER]
    for entries in (8_000_000, 60):
        monkeypatch.setattr(L, "PASS_ENTRIES", entries)
        for p, a, b in zip(TOGETHER, alone, L.fit_many(td, TOGETHER), strict=True):
            assert np.allclose(dense(a.u, N), dense(b.u, N), atol=1e-8) and np.allclose(dense(a.v, DOCS, False), dense(b.v, DOCS, False), atol=1e-8), p
            assert np.allclose([s[1:3] for s in a.steps], [s[1:3] for s in b.steps], equal_nan=True, atol=1e-7) and [s[3:6] for s in a.steps] == [s[3:6] for s in b.steps], p


def test_guesses_are_those_of_single_fits_and_passes_are_bounded(planted, spark, monkeypatch):
    """Beyond the entries that are broadcast the fits still go along, in several passes a half step where factors are large."""
    _, td = planted
    td = TermDoc(td.coo, "none", DOCS)
    a, b = L.guessed(td, K, 3), initial_guess(td, K, seed=3)
    assert np.array_equal(dense(a, N), dense(b, N)) and a.nnz == b.count()
    plans = [L.Plan(K, Limits(9, 7), 2, seed) for seed in (0, 1)] + [L.Plan(2, Limits(4, 3), 4, sequential=True), L.Plan(K, max_iter=2)]
    alone, passes, one = [L._through_frames(td, p) for p in plans], [], L._pass
    monkeypatch.setattr(L.choice, "BROADCAST_ENTRIES", N * K - 1)
    monkeypatch.setattr(L, "PASS_ENTRIES", N * K)
    monkeypatch.setattr(L, "TURN", 99)
    monkeypatch.setattr(L, "_pass", lambda td, side, asks: passes.append(sum({id(a.f): a.f.k * len(a.f.at) for a in asks}.values())) or one(td, side, asks))
    assert L.held_by_driver(td, K)
    for p, x, y in zip(plans, alone, L.fit_many(td, plans), strict=True):
        assert np.allclose(dense(x.u, N), dense(y.u, N), atol=1e-8) and np.allclose(dense(x.v, DOCS, False), dense(y.v, DOCS, False), atol=1e-8), p
    assert len(passes) > 8 and max(passes) <= N * K


def test_fits_together_take_the_jobs_of_one(planted, spark):
    _, td = planted
    td = TermDoc(td.coo, "none", DOCS)
    L.fit_many(td, [L.Plan(K, max_iter=1)])
    before, one, many = (jobs_of(spark, lambda p=p: L.fit_many(td, p)) for p in ([], [L.Plan(K, Limits(9), 4)], [L.Plan(K, Limits(t), 4) for t in range(3, 9)]))
    assert many - one == one - before <= 4 * 2 + 2  # two passes an iteration, and the guess


def test_weights_in_blocks_and_factors_beyond_the_driver(spark, monkeypatch):
    docs = spark.createDataFrame([(i, " ".join(w for j, w in enumerate(("red", "blue", "sun", "moon", "tree")) for _ in range((i * (j + 3)) % 4))) for i in range(9)], "doc_id long, text string")
    for weight in ("df", "tfidf"):
        td = build_term_doc(docs, stop=(), weight=weight)
        plans = [L.Plan(2, Limits(6, 9), 3), L.Plan(2, max_iter=3)]
        held = L.fit_many(td, plans, lambda fit: fit.steps[-1][1:3])
        with monkeypatch.context() as m:
            m.setattr(L.choice, "BROADCAST_ENTRIES", 9)
            assert not L.held_by_driver(td, 2)
            assert np.allclose(held, L.fit_many(td, plans, lambda fit: fit.steps[-1][1:3]), atol=1e-6)


@pytest.fixture(scope="module")
def grouped(spark):
    return spark.createDataFrame([(j, "ab"[j % 2]) for j in range(DOCS)], "doc_id long, group string")


def test_related_methods_side_by_side_are_the_single_ones(planted, grouped, spark, monkeypatch):
    """In one pass a half step, and at most four fits without a limit in a pass."""
    import glob

    from sparse_topics import experiments as X

    _, td = planted
    td = TermDoc(td.coo, "none", DOCS)
    asked, half_steps = [], L.half_steps
    monkeypatch.setattr(L, "BLOCK", (30, 1000))
    monkeypatch.setattr(L, "half_steps", lambda td, side, asks: asked.append(len(asks)) or half_steps(td, side, asks))
    alone, together = X._related_frames(td, K, 2), X._related_held(td, K, 2)
    assert asked == [9] * 4 and set(alone) == set(together) == set(X.RELATED)
    monkeypatch.setattr(X, "PASS_ENTRIES", 4 * K * (N + DOCS))
    in_turns = X._related_held(td, K, 2)
    assert sorted(asked[4:]) == [4] * 4 + [5] * 4
    for name in X.RELATED:
        for error, v in (together[name], in_turns[name]):
            assert name in ("plsa", "lda") or error == pytest.approx(alone[name][0], abs=1e-8), name
            assert np.allclose(dense(alone[name][1], DOCS, False), dense(v, DOCS, False), atol=1e-7), name
    want = [M.mean_accuracy(alone[name][1], grouped, 2).first()["mean_acc"] for name in X.RELATED]
    assert M.mean_accuracies([together[name][1] for name in X.RELATED], grouped, 2) == pytest.approx(want)
    assert not glob.glob(spark.conf.get("spark.checkpoint.dir").removeprefix("file://") + "/lda-*")


def test_related_updates_are_those_of_the_single_fits(planted):
    """A ratio that gives entries to rows without one, and all likelihoods of the expectation-maximisation."""
    from sparse_topics.operators import related as S

    _, td = planted
    td = TermDoc(td.coo, "none", DOCS)
    u, v = S.first_terms(td, K), S.first_docs(td, K)
    for sparseness in (0.1, 0.6):
        a, (b,) = B.norm_ratio_nmf(td, K, sparseness, max_iter=2, measure=True), L.advance(td, [S.updated_fit(td, u, None, S.norm_ratio(N, sparseness), 2)])
        assert np.allclose(dense(a.u, N), dense(b.u, N), atol=1e-7) and np.allclose([s[1:6] for s in a.steps], [s[1:6] for s in b.steps], atol=1e-6)
    a, b = B.plsa_baseline(td, K, max_iter=3), S.plsa(td, u, v, 3)
    assert np.allclose(dense(a.u, N), dense(b.u, N), atol=1e-9) and np.allclose([s[2] for s in a.steps], [s[2] for s in b.steps])
