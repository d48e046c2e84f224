"""The registered queries of the methods and what surrounds them, each with its statement for DuckDB where SQL can say it.

Iterated methods run a few iterations on the whole ``documents`` table, so that a statement can unroll them. The workloads
w* run with the defaults of their functions; those with ``_k2`` run the same code with two topics and two iterations,
each with its statement.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import experiments as X
from . import oracles as O
from .functions import text as T
from .operators import baselines as B
from .operators import linalg
from .operators import measures as M
from .operators import reading as R
from .operators import relational as L
from .operators.als import projected_als, sparse_als, truncate_after
from .operators.factors import Factor, initial_guess
from .operators.matrix import TermDoc, build_term_doc, corpus_stats, count_terms, prune_rare
from .operators.sequential import sequential_als
from .operators.sparsify import Limits, keep_above, keep_largest, keep_largest_per_topic, kth_largest
from .sources import load_table
from .streaming import streams as S

_prepared: dict = {}
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def matrix(spark: SparkSession, sf_dir: str) -> TermDoc:
    """The matrix of ``documents``, prepared once a session and folder."""
    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in _prepared:
        _prepared[key] = build_term_doc(load_table(spark, sf_dir, "documents"))
    return _prepared[key]


def query(sql: str | None = None, name: str | None = None):
    """Registers a function of (spark, sf_dir) under its name."""

    def add(f):
        key = name or f.__name__
        QUERIES[key] = f
        if sql:
            SQL[key] = sql
        return f

    return add


def fit_query(name: str, sql: str | None, make: Callable[[SparkSession, str, TermDoc], DataFrame]) -> None:
    query(sql, name)(lambda spark, sf_dir: make(spark, sf_dir, matrix(spark, sf_dir)))


def rounded(f: Factor) -> DataFrame:
    return f.long().select("row", "topic", F.round("value", 6).alias("value"))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Strongest terms of a model with both factors kept sparse at every step."""
    td = build_term_doc(load_table(spark, sf_dir, "documents"))
    return R.top_terms(sparse_als(td, 4, Limits(55, 400), max_iter=3).u)


# ---- preparation ----------------------------------------------------------------------------------------------------

DOCS = "documents"
TOK = r"WITH tok AS (SELECT doc_id, lang, unnest(regexp_extract_all(lower(text), '\p{L}+')) AS term FROM documents) "


@query(TOK + "SELECT lang, count(*) AS tokens, count(DISTINCT term) AS terms FROM tok GROUP BY lang")
def tokens_per_lang(spark, sf_dir):
    docs = load_table(spark, sf_dir, DOCS)
    toks = T.tokenize(docs).join(docs.select("doc_id", "lang"), "doc_id")
    return toks.groupBy("lang").agg(F.count(F.lit(1)).alias("tokens"), F.count_distinct("term").alias("terms"))


@query(TOK + f"SELECT lang, count(*) AS tokens FROM tok ANTI JOIN (VALUES {O.stop_values()}) s(term) USING (term) GROUP BY lang")
def stop_word_removal(spark, sf_dir):
    docs = load_table(spark, sf_dir, DOCS)
    return T.drop_stop_words(T.tokenize(docs)).join(docs.select("doc_id", "lang"), "doc_id").groupBy("lang").agg(F.count(F.lit(1)).alias("tokens"))


COUNTS = TOK + "SELECT term, doc_id, count(*) AS tf FROM tok GROUP BY term, doc_id"


@query(COUNTS)
def term_counts(spark, sf_dir):
    return count_terms(load_table(spark, sf_dir, DOCS))


@query(COUNTS)
def term_counts_in_row(spark, sf_dir):
    return count_terms(load_table(spark, sf_dir, DOCS), "in_row")


@query("WITH " + O.base() + " SELECT term, total, df FROM per")
def rare_term_pruning(spark, sf_dir):
    return matrix(spark, sf_dir).coo.groupBy("term").agg(F.sum("tf").alias("total"), F.max("df").alias("df"))


@query("WITH " + O.base() + ", d AS (SELECT term, count(*) AS df FROM cnt GROUP BY term HAVING count(*) >= 2) SELECT count(*) AS terms, CAST(sum(df) AS BIGINT) AS entries FROM d")
def rare_term_pruning_by_docs(spark, sf_dir):
    kept = prune_rare(count_terms(load_table(spark, sf_dir, DOCS), stop=T.LANGUAGES), by="docs")
    return kept.agg(F.count_distinct("term").alias("terms"), F.count(F.lit(1)).alias("entries"))


@query("WITH " + O.base() + " SELECT term, doc_id, tf, df, round(x, 9) AS x FROM a")
def row_weighted_matrix(spark, sf_dir):
    td = matrix(spark, sf_dir)
    return td.coo.select("term", "doc_id", "tf", "df", F.round(td.value(), 9).alias("x"))


@query("WITH " + O.base() + " SELECT (SELECT count(*) FROM documents) AS n_docs, count(DISTINCT term) AS n_terms, count(*) AS nnz, round(1 - CAST(count(*) AS DOUBLE) / ((SELECT count(*) FROM documents) * count(DISTINCT term)), 9) AS sparsity FROM a", "corpus_stats")
def _corpus_stats(spark, sf_dir):
    return corpus_stats(matrix(spark, sf_dir)).withColumn("sparsity", F.round("sparsity", 9))


@query("SELECT doc_id, lang FROM documents QUALIFY row_number() OVER (PARTITION BY text ORDER BY doc_id) = 1")
def dedup_documents(spark, sf_dir):
    return T.drop_duplicate_docs(load_table(spark, sf_dir, DOCS)).select("doc_id", "lang")


@query("WITH " + O.base() + ", s AS (SELECT doc_id, term, tf * ln((SELECT count(*) FROM documents)::DOUBLE / df) AS value FROM a) SELECT doc_id, CAST(r AS INTEGER) AS rank, term, round(value, 6) AS value FROM (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY round_even(value * 1e9, 0) DESC, term) AS r FROM s) WHERE r <= 5")
def tfidf_top_terms(spark, sf_dir):
    return B.tfidf_terms(matrix(spark, sf_dir)).withColumn("value", F.round("value", 6))


HTML = r"""replace(replace(replace(replace(replace(regexp_replace(regexp_replace(regexp_replace(html, '<(script|style)\b[^>]*>.*?</(script|style)\s*>', ' ', 'gsi'), '<!--.*?-->', ' ', 'gs'), '<[^>]*>', ' ', 'gs'), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#39;', ''''), '&amp;', '&')"""


@query(r"SELECT term, count(*) AS n FROM (SELECT unnest(regexp_extract_all(lower(" + HTML + r"), '\p{L}+')) AS term FROM pages) GROUP BY term")
def html_page_terms(spark, sf_dir):
    pages = load_table(spark, sf_dir, "pages").select(F.col("page_id").alias("doc_id"), T.html_to_text(F.col("html")).alias("text"))
    return T.tokenize(pages).groupBy("term").agg(F.count(F.lit(1)).alias("n"))


@query(r"SELECT role, term, count(*) AS n FROM (SELECT role, unnest(regexp_extract_all(lower(text), '\p{L}+')) AS term FROM conversations) GROUP BY ALL")
def conversation_terms(spark, sf_dir):
    c = load_table(spark, sf_dir, "conversations")
    return c.select("role", F.explode(T.words(F.col("text"))).alias("term")).groupBy("role", "term").agg(F.count(F.lit(1)).alias("n"))


@query(r"SELECT item_id AS doc_id, term, count(*) AS tf FROM (SELECT item_id, unnest(regexp_extract_all(lower(text), '\p{L}+')) AS term FROM benchmark) GROUP BY ALL")
def benchmark_terms(spark, sf_dir):
    return count_terms(load_table(spark, sf_dir, "benchmark"), id_col="item_id").select("doc_id", "term", "tf")


# ---- linear algebra -------------------------------------------------------------------------------------------------

fit_query("initial_guess", "WITH " + O.base() + ", " + O.guess(2) + " SELECT row, topic, round(value, 9) AS value FROM u0 WHERE value > 0", lambda s, d, td: initial_guess(td, 2).long().withColumn("value", F.round("value", 9)))
fit_query("initial_guess_sparse", "WITH " + O.base() + ", " + O.guess(2, nnz=100) + O.entries("u0"), lambda s, d, td: rounded(initial_guess(td, 2, nnz=100)))


def _product(td, f, fn):
    return fn(td, f).select("row", F.posexplode("b").alias("topic", "value")).select("row", "topic", F.round("value", 6).alias("value"))


_U0 = "WITH " + O.base() + ", " + O.guess(2)
fit_query("doc_product", _U0 + " SELECT a.doc_id AS row, topic, round(sum(x * value), 6) AS value FROM a JOIN u0 ON a.term = u0.row GROUP BY ALL", lambda s, d, td: _product(td, initial_guess(td, 2), linalg.doc_product))
_V0 = "WITH " + ", ".join(O.starts()[0])
fit_query("term_product", _V0 + " SELECT a.term AS row, topic, round(sum(x * value), 6) AS value FROM a JOIN v0 ON a.doc_id = v0.row GROUP BY ALL", lambda s, d, td: _product(td, B.doc_guess(td, 2), linalg.term_product))


def _gram_rows(spark, g):
    return spark.createDataFrame([(i, j, round(float(g[i, j]), 4)) for i in range(len(g)) for j in range(len(g))], "i int, j int, g double")


fit_query("gram_matrix", _U0 + " SELECT p.topic AS i, q.topic AS j, round(sum(p.value * q.value), 4) AS g FROM u0 p JOIN u0 q USING (row) GROUP BY ALL", lambda s, d, td: _gram_rows(s, linalg.gram(initial_guess(td, 2))))
fit_query("doc_half_step_k2", _U0 + ", " + O.half("v1", "u0", "v", 2) + O.entries("v1"), lambda s, d, td: rounded(Factor(2, linalg.solve_docs(td, initial_guess(td, 2)).select("row", "w"))))
fit_query("term_half_step_k2", _V0 + ", " + O.half("u1", "v0", "u", 2) + O.entries("u1"), lambda s, d, td: rounded(Factor(2, linalg.solve_terms(td, B.doc_guess(td, 2)).select("row", "w"))))
fit_query("matrix_norm", "WITH " + O.base() + " SELECT round(sum(x * x), 6) AS norm_sq FROM a", lambda s, d, td: td.entries().agg(F.round(F.sum(F.col("x") * F.col("x")), 6).alias("norm_sq")))

# ---- factorisations -------------------------------------------------------------------------------------------------


def add_fit(name: str, side: str, sql: str, make: Callable[[TermDoc], object]) -> None:
    """A query of the entries of one factor of a fit of two iterations."""
    fit_query(name, sql + O.entries(side), lambda s, d, td: rounded(getattr(make(td), side[0] if side[0] in "uv" else side[4])))


def add_trace(name: str, sql: str, make: Callable[[TermDoc], object]) -> None:
    def steps(spark, sf_dir, td):
        return make(td).trace(spark).select("iter", F.round("residual", 6).alias("residual"), F.round("error", 6).alias("error"), "nnz_u", "nnz_v")

    fit_query(name, sql + O.trace(2), steps)


def _als(limits: Limits | None = None, k: int = 2, **options):
    return lambda td: sparse_als(td, k, limits, max_iter=2, **{"measure": False, **options})


BOTH = {"t_u": 55, "t_v": 400}
add_fit("projected_als_k2_u", "u2", O.als(), lambda td: projected_als(td, 2, max_iter=2, measure=False))
add_fit("projected_als_k2_v", "v2", O.als(), lambda td: projected_als(td, 2, max_iter=2, measure=False))
add_fit("projected_als_k1", "u2", O.als(k=1), lambda td: projected_als(td, 1, max_iter=2, measure=False))
add_trace("projected_als_trace", O.als(), lambda td: projected_als(td, 2, max_iter=2))
add_fit("sparse_als_u_only", "u2", O.als(t_u=55), _als(Limits(t_u=55)))
add_fit("sparse_als_v_only", "v2", O.als(t_v=400), _als(Limits(t_v=400)))
add_fit("sparse_als_both", "u2", O.als(**BOTH), _als(Limits(**BOTH)))
add_fit("sparse_als_both_v", "v2", O.als(**BOTH), _als(Limits(**BOTH)))
add_fit("sparse_als_sparse_guess", "u2", O.als(**BOTH, nnz=500), _als(Limits(**BOTH), init_nnz=500))
add_fit("sparse_als_keep_ties", "u2", O.als(**BOTH, ties="keep"), _als(Limits(**BOTH, ties="keep")))
add_fit("sparse_als_threshold", "u2", O.als(tau_u=10.0, tau_v=1e-5), _als(Limits(tau_u=10.0, tau_v=1e-5)))
add_fit("sparse_als_per_topic", "u2", O.als(t_u=10, t_v=100, scope="topic"), _als(Limits(10, 100, scope="topic")))
add_fit("l1_als_k2", "u2", O.als(shift=0.01), lambda td: B.l1_nmf(td, 2, 0.02, 0.02, max_iter=2, measure=False))
add_trace("sparse_als_trace", O.als(**BOTH), _als(Limits(**BOTH), measure=True))
add_trace("convergence_u_only_trace", O.als(t_u=55), _als(Limits(t_u=55), measure=True))
AFTER = O.als() + ", " + O.cut("ta", "(SELECT row, topic, value, b FROM u2)", 55) + ", " + O.cut("tb", "(SELECT row, topic, value, b FROM v2)", 400)
fit_query("truncate_after_als", AFTER + O.entries("ta"), lambda s, d, td: rounded(truncate_after(projected_als(td, 2, max_iter=2, measure=False), Limits(55, None)).u))
fit_query("truncate_after_als_v", AFTER + O.entries("tb"), lambda s, d, td: rounded(truncate_after(projected_als(td, 2, max_iter=2, measure=False), Limits(None, 400)).v))
AFTER_TOPIC = O.als() + ", " + O.cut("ta", "(SELECT row, topic, value, b FROM u2)", 10, "topic")
fit_query("truncate_after_per_topic", AFTER_TOPIC + O.entries("ta"), lambda s, d, td: rounded(truncate_after(projected_als(td, 2, max_iter=2, measure=False), Limits(10, None, scope="topic")).u))

HALF = _U0 + ", " + O.half("v1", "u0", "v", 2)


def _half(td: TermDoc) -> DataFrame:
    return Factor(2, linalg.solve_docs(td, initial_guess(td, 2)).select("row", "w")).long()


def _round_entries(df: DataFrame) -> DataFrame:
    return df.select("row", "topic", F.round("value", 6).alias("value"))


for _name, _cut, _make in (
    ("truncate_exact", O.cut("c", "v1", 300), lambda long: keep_largest(long, 300)),
    ("truncate_exact_large", O.cut("c", "v1", 900), lambda long: keep_largest(long, 900, local=10)),
    ("truncate_keep_ties", O.cut("c", "v1", 300, ties="keep"), lambda long: keep_largest(long, 300, "keep")),
    ("truncate_threshold", O.cut("c", "v1", tau=0.01), lambda long: keep_above(long, 0.01)),
    ("truncate_per_topic", O.cut("c", "v1", 120, "topic"), lambda long: keep_largest_per_topic(long, 120)),
):
    fit_query(_name, HALF + ", " + _cut + O.entries("c"), lambda s, d, td, make=_make: _round_entries(make(_half(td))))


def _kth(spark, td):
    key, above, equal = kth_largest(_half(td), 300, collect=50)
    return spark.createDataFrame([(round(key / 1e12, 6), above, equal)], "kth double, above long, equal long")


_K = f"(SELECT {O.rank_of()} AS r FROM v1 ORDER BY r DESC LIMIT 1 OFFSET 299)"
fit_query("kth_largest", HALF + f" SELECT round((SELECT r FROM {_K}) / 1e12, 6) AS kth, count(*) FILTER (WHERE {O.rank_of()} > (SELECT r FROM {_K})) AS above, count(*) FILTER (WHERE {O.rank_of()} = (SELECT r FROM {_K})) AS equal FROM v1", lambda s, d, td: _kth(s, td))

SEQ = {"t_u": 10, "t_v": 100}
fit_query("sequential_u", O.sequential(**SEQ) + O.entries("doneu2"), lambda s, d, td: rounded(sequential_als(td, 2, limits=Limits(**SEQ), iters_per_block=2, measure=False).u))
fit_query("sequential_v", O.sequential(**SEQ) + O.entries("donev2"), lambda s, d, td: rounded(sequential_als(td, 2, limits=Limits(**SEQ), iters_per_block=2, measure=False).v))
fit_query("sequential_three_blocks", O.sequential(blocks=3, iters=1, **SEQ) + O.entries("doneu3"), lambda s, d, td: rounded(sequential_als(td, 3, limits=Limits(**SEQ), iters_per_block=1, measure=False).u))
fit_query("sequential_dense", O.sequential() + O.entries("doneu2"), lambda s, d, td: rounded(sequential_als(td, 2, iters_per_block=2, measure=False).u))
fit_query("sequential_trace", O.sequential(**SEQ) + O.sequential_trace(), lambda s, d, td: sequential_als(td, 2, limits=Limits(**SEQ), iters_per_block=2).trace(s).select("iter", F.round("residual", 6).alias("residual"), F.round("error", 6).alias("error"), "nnz_u", "nnz_v"))
PAIRED = {"t_u": 40, "t_v": 400}
fit_query("sequential_block2", O.sequential(block=2, **PAIRED) + O.entries("doneu2"), lambda s, d, td: rounded(sequential_als(td, 2, block=2, limits=Limits(**PAIRED), iters_per_block=2, measure=False).u))
fit_query("sequential_block2_v", O.sequential(block=2, **PAIRED) + O.entries("donev2"), lambda s, d, td: rounded(sequential_als(td, 2, block=2, limits=Limits(**PAIRED), iters_per_block=2, measure=False).v))

# ---- reading a model ------------------------------------------------------------------------------------------------

FIT = O.als(**BOTH)
_fit = _als(Limits(**BOTH))
RANKED = f"(SELECT topic, row, value, CAST(row_number() OVER (PARTITION BY topic ORDER BY {O.rank_of()} DESC, row) AS INTEGER) AS rank FROM u2)"
fit_query("top_terms", FIT + f" SELECT topic, rank, row AS term, round(value, 6) AS value FROM {RANKED} WHERE rank <= 5", lambda s, d, td: R.top_terms(_fit(td).u).withColumn("value", F.round("value", 6)))
fit_query("topic_table", FIT + f" SELECT rank, max(row) FILTER (topic = 0) AS topic_0, max(row) FILTER (topic = 1) AS topic_1 FROM {RANKED} WHERE rank <= 5 GROUP BY rank", lambda s, d, td: R.topic_table(_fit(td).u))
fit_query("topic_members", FIT + " SELECT topic, row AS doc_id FROM v2", lambda s, d, td: R.members(_fit(td).v))
fit_query("topic_members_threshold", O.als() + " SELECT topic, row AS doc_id FROM v2 WHERE value > 0.05", lambda s, d, td: R.members(projected_als(td, 2, max_iter=2, measure=False).v, 0.05))
fit_query("topic_sizes", FIT + " SELECT CAST(t.t AS INTEGER) AS topic, count(u2.row) AS nnz FROM range(2) t(t) LEFT JOIN u2 ON u2.topic = t.t GROUP BY 1", lambda s, d, td: R.topic_sizes(_fit(td).u))
fit_query("doc_assignment", FIT + " SELECT row AS doc_id, topic, round(value, 6) AS value FROM v2 QUALIFY row_number() OVER (PARTITION BY row ORDER BY value DESC, topic) = 1", lambda s, d, td: R.assign(_fit(td).v).withColumn("value", F.round("value", 6)))


def _folded(s, d, td):
    new = count_terms(load_table(s, d, "benchmark"), id_col="item_id").join(td.coo.select("term", "df").distinct(), "term")
    return _round_entries(R.fold_in(TermDoc(new.select("term", "doc_id", "tf", "df")), _fit(td).u))


_BENCH = r", bt AS (SELECT term, doc_id, count(*) AS tf FROM (SELECT item_id AS doc_id, unnest(regexp_extract_all(lower(text), '\p{L}+')) AS term FROM benchmark) GROUP BY ALL), ba AS (SELECT term, doc_id, CAST(tf AS DOUBLE) / df AS x FROM bt JOIN per USING (term))"
fit_query("fold_in_docs", FIT + _BENCH + ", " + O.half("f", "u2", "v", 2).replace("FROM a JOIN u2 f", "FROM ba a JOIN u2 f") + O.entries("f"), _folded)
_RANK = FIT + ", q AS (SELECT topic, sum(value) AS q FROM u2 WHERE row IN ('re', 'th', 'tion', 'la', 'ch') GROUP BY topic), h AS (SELECT row AS doc_id, sum(value * q) AS score FROM v2 JOIN q USING (topic) GROUP BY row) SELECT doc_id, round(score, 6) AS score FROM h ORDER BY round_even(h.score * 1e12, 0) DESC, doc_id LIMIT 10"
fit_query("rank_documents", _RANK, lambda s, d, td: (lambda f: R.rank_documents(f.u, f.v, ["re", "th", "tion", "la", "ch"]).withColumn("score", F.round("score", 6)))(_fit(td)))
fit_query("topic_profiles", None, lambda s, d, td: R.topic_json(_fit(td).u))

# ---- measures -------------------------------------------------------------------------------------------------------


def _one(spark, name, value, digits=6):
    return spark.createDataFrame([(round(float(value), digits),)], f"{name} double")


_init = lambda td: initial_guess(td, 2)
fit_query("residual", FIT + f" SELECT round({O.change('u2', 'u1')}, 6) AS residual", lambda s, d, td: _one(s, "residual", _als(Limits(**BOTH), measure=True)(td).steps[-1][1]))
_ERR = f"(SELECT sum(x * x) FROM a)"
_ERR_SQL = f" SELECT round(sqrt(({_ERR} - 2 * (SELECT sum(u2.value * v2.value * a.x) FROM a JOIN u2 ON a.term = u2.row JOIN v2 ON a.doc_id = v2.row AND u2.topic = v2.topic) + {O.gram_dot('u2', 'v2')}) / {_ERR}), 6) AS error"
fit_query("error_trace", FIT + _ERR_SQL, lambda s, d, td: _one(s, "error", M.relative_error(td, _fit(td), "trace")))
fit_query("error_entries", FIT + _ERR_SQL, lambda s, d, td: _one(s, "error", M.relative_error(td, _fit(td), "entries")))
_MASKS = ", um AS (SELECT row, bit_or(1 << topic) AS m FROM u2 GROUP BY row), vm AS (SELECT row, bit_or(1 << topic) AS m FROM v2 GROUP BY row)"
fit_query("product_sparsity", FIT + _MASKS + " SELECT count(*) AS nonzeros FROM um JOIN vm ON (um.m & vm.m) <> 0", lambda s, d, td: (lambda f: M.product_nonzeros(f.u, f.v))(_fit(td)))
fit_query("factor_sparsity", FIT + " SELECT round(1 - CAST((SELECT count(*) FROM u2) AS DOUBLE) / (2 * count(DISTINCT term)), 9) AS sparsity FROM a", lambda s, d, td: _one(s, "sparsity", 1 - _fit(td).u.count() / (2 * td.n_terms), 9))
fit_query("peak_nnz", O.als(**BOTH, nnz=500) + " SELECT greatest((SELECT count(*) FROM u0) + (SELECT count(*) FROM v1), (SELECT count(*) FROM u1) + (SELECT count(*) FROM v1), (SELECT count(*) FROM u1) + (SELECT count(*) FROM v2), (SELECT count(*) FROM u2) + (SELECT count(*) FROM v2), 500) AS peak",
          lambda s, d, td: s.createDataFrame([(max(x[5] for x in _als(Limits(**BOTH), init_nnz=500, measure=True)(td).steps),)], "peak long"))


def _accuracy(column, j, how="closed"):
    return lambda s, d, td: M.topic_accuracy(_fit(td).v, X.groups(s, d, column), j, how).withColumn("acc", F.round("acc", 6))


def _groups_sql(column):
    return f"SELECT doc_id, CAST({column} AS VARCHAR) AS grp FROM {'labels' if column == 'quality' else 'documents'}"


fit_query("topic_accuracy_lang", FIT + O.accuracy("v2", _groups_sql("lang"), 4, 2), _accuracy("lang", 4))
fit_query("topic_accuracy_source", FIT + O.accuracy("v2", _groups_sql("source"), 20, 2), _accuracy("source", 20))
fit_query("topic_accuracy_quality", FIT + O.accuracy("v2", _groups_sql("quality"), 2, 2), _accuracy("quality", 2))
fit_query("topic_accuracy_pairs", FIT + O.accuracy("v2", _groups_sql("lang"), 4, 2), _accuracy("lang", 4, "pairs"))
_MEAN = O.mean_accuracy(FIT, "v2", _groups_sql("lang"), 4) + " SELECT round(avg(acc), 6) AS mean_acc, round(avg(acc) FILTER (n_docs > 1), 6) AS mean_live, count(*) FILTER (n_docs > 1) AS n_live FROM acc"
fit_query("mean_accuracy", _MEAN, lambda s, d, td: M.mean_accuracy(_fit(td).v, X.groups(s, d), 4).select(F.round("mean_acc", 6).alias("mean_acc"), F.round("mean_live", 6).alias("mean_live"), "n_live"))
_OVER = FIT + f", p AS (SELECT topic, row FROM {RANKED} WHERE rank <= 5), q AS (SELECT topic, row FROM (SELECT topic, row, row_number() OVER (PARTITION BY topic ORDER BY {O.rank_of()} DESC, row) AS r FROM u1) WHERE r <= 5) SELECT p.topic AS topic_a, q.topic AS topic_b, count(*) AS shared, round(count(*) / ((SELECT count(*) FROM p x WHERE x.topic = p.topic) + (SELECT count(*) FROM q y WHERE y.topic = q.topic) - count(*))::DOUBLE, 6) AS jaccard FROM p JOIN q USING (row) GROUP BY p.topic, q.topic"
fit_query("topic_overlap", _OVER, lambda s, d, td: M.topic_overlap(_fit(td).u, sparse_als(td, 2, Limits(**BOTH), max_iter=1, measure=False).u).withColumn("jaccard", F.round("jaccard", 6)))
_NPMI = FIT + f""", p AS (SELECT topic, rank, row AS term FROM {RANKED} WHERE rank <= 5), post AS (SELECT p.topic, p.rank, a.doc_id, a.df FROM p JOIN a USING (term)),
df AS (SELECT topic, rank, max(df) AS df FROM post GROUP BY ALL), j AS (SELECT x.topic, x.rank AS ra, y.rank AS rb, count(*) AS n FROM post x JOIN post y ON x.topic = y.topic AND x.doc_id = y.doc_id AND x.rank < y.rank GROUP BY ALL),
m AS (SELECT CAST(count(*) AS DOUBLE) AS m FROM documents)
SELECT x.topic, count(*) AS pairs, round(avg(CASE WHEN n IS NULL THEN -1 WHEN n >= m THEN 1 ELSE ln(n * m / (x.df * y.df)) / -ln(n / m) END), 6) AS npmi FROM df x JOIN df y ON x.topic = y.topic AND x.rank < y.rank LEFT JOIN j ON j.topic = x.topic AND ra = x.rank AND rb = y.rank, m GROUP BY x.topic"""
fit_query("npmi", _NPMI, lambda s, d, td: M.npmi(_fit(td).u, td).withColumn("npmi", F.round("npmi", 6)))
_SKEW = FIT + ", z AS (SELECT t.t AS topic, count(u2.row) AS nnz FROM range(2) t(t) LEFT JOIN u2 ON u2.topic = t.t GROUP BY 1), r AS (SELECT *, row_number() OVER (ORDER BY nnz, topic) AS r FROM z) SELECT round(CAST(max(nnz) AS DOUBLE) / sum(nnz), 6) AS max_share, round(CAST(sum((2 * r - 3) * nnz) AS DOUBLE) / (2 * sum(nnz)), 6) AS gini, count(*) FILTER (nnz > 0) AS live_topics FROM r"
fit_query("skew", _SKEW, lambda s, d, td: M.skew(_fit(td).u).select(F.round("max_share", 6).alias("max_share"), F.round("gini", 6).alias("gini"), "live_topics"))
fit_query("norm_ratio", FIT + " SELECT topic, round((sqrt(n) - sum(value) / sqrt(sum(value * value))) / (sqrt(n) - 1), 6) AS ratio FROM u2, (SELECT CAST(count(DISTINCT term) AS DOUBLE) AS n FROM a) GROUP BY topic, n", lambda s, d, td: M.norm_ratio(_fit(td).u, td.n_terms).withColumn("ratio", F.round("ratio", 6)))
fit_query("iterations_to", FIT + f" SELECT min(i) AS iterations FROM (SELECT 1 AS i, {O.change('u1', 'u0')} AS r UNION ALL SELECT 2, {O.change('u2', 'u1')}) WHERE r <= 2.0", lambda s, d, td: M.iterations_to(_als(Limits(**BOTH), measure=True)(td).trace(s), 2.0))

# ---- baselines ------------------------------------------------------------------------------------------------------

fit_query("multiplicative_k2", O.updates("multiplicative") + O.entries("u2") + " WHERE value > 0", lambda s, d, td: rounded(B.multiplicative_nmf(td, 2, max_iter=2, measure=False).u))
fit_query("gradient_k2", O.updates("gradient") + O.entries("u2") + " WHERE value > 0", lambda s, d, td: rounded(B.gradient_nmf(td, 2, max_iter=2, measure=False).u))
fit_query("plsa_k2", O.plsa() + " SELECT row, topic, round(value, 9) AS value FROM pu2 WHERE value > 0", lambda s, d, td: B.plsa_baseline(td, 2, max_iter=2).u.long().withColumn("value", F.round("value", 9)))
fit_query("anls", None, lambda s, d, td: rounded(B.anls_nmf(td, 3, max_iter=2, measure=False).u))
fit_query("norm_ratio_nmf", None, lambda s, d, td: rounded(B.norm_ratio_nmf(td, 2, 0.9, max_iter=1).u))
fit_query("lda", None, lambda s, d, td: B.lda_baseline(td, 4, max_iter=3))
fit_query("lsa", None, lambda s, d, td: s.createDataFrame([(i, float(x)) for i, x in enumerate(B.lsa_baseline(td, 3, power=3)[2])], "i int, singular_value double"))

# ---- workloads in whole form -----------------------------------------------------------------------------------------

fit_query("w1_density", None, lambda s, d, td: X.run_density_table(s, td))
query(None, "w1_density_en")(lambda s, d: X.run_density_table(s, X.corpus(s, d, "en"), name="D-en"))
query(None, "w2_convergence")(lambda s, d: X.run_convergence_trace(s, X.corpus(s, d, "en")))
query(None, "w3_topic_tables")(lambda s, d: X.run_topic_tables(s, X.corpus(s, d, "en"))[0])
query(None, "w3_topic_overlap")(lambda s, d: X.run_topic_tables(s, X.corpus(s, d, "en"))[1])
query(None, "w4_nnz_sweep")(lambda s, d: X.run_nnz_sweep(s, X.corpus(s, d, "en"), 5))
fit_query("w5_skew", None, lambda s, d, td: X.run_skew(s, td))
fit_query("w6_accuracy_sweep", None, lambda s, d, td: X.run_nnz_sweep(s, td, 4, measure="accuracy", labels=X.groups(s, d), iters=50))
fit_query("w7_during_after", None, lambda s, d, td: X.run_during_vs_after(s, td, X.groups(s, d), 4))
fit_query("w8_peak_nnz", None, lambda s, d, td: X.run_peak_nnz(s, td))
fit_query("w9_even_topics", None, lambda s, d, td: X.run_even_topics(s, td))
fit_query("w10_even_accuracy", None, lambda s, d, td: X.run_even_accuracy(s, td, X.groups(s, d), 4))
fit_query("w11_timing", None, lambda s, d, td: X.run_timing(s, td))
fit_query("w12_seed_spread", None, lambda s, d, td: X.run_seed_spread(s, td, X.groups(s, d), 4))
fit_query("w14_related_methods", None, lambda s, d, td: X.run_related_methods(s, td, X.groups(s, d), 4))

#: Workloads in whole form: many fits of many iterations.
WHOLE = {name for name in QUERIES if name.startswith("w") and name.split("_")[0][1:].isdigit()}

# ---- workloads with two topics and two iterations, which a statement can unroll ---------------------------------------

LANG = _groups_sql("lang")


def _measured(df: DataFrame) -> DataFrame:
    return df.select("mode", "measure", F.round("value", 6).alias("value"))


_DENSE = O.als()
_CELLS = "CAST((SELECT count(DISTINCT term) FROM a) * (SELECT count(*) FROM documents) AS DOUBLE)"
_ZEROS = _DENSE + _MASKS + f""" SELECT 'dense' AS mode, 'zeros of A' AS measure, round(1 - (SELECT count(*) FROM a) / {_CELLS}, 6) AS value
UNION ALL SELECT 'dense', 'zeros of U', round(1 - (SELECT count(*) FROM u2) / CAST(2 * (SELECT count(DISTINCT term) FROM a) AS DOUBLE), 6)
UNION ALL SELECT 'dense', 'zeros of V', round(1 - (SELECT count(*) FROM v2) / CAST(2 * (SELECT count(*) FROM documents) AS DOUBLE), 6)
UNION ALL SELECT 'dense', 'zeros of UV\'\'', round(1 - (SELECT count(*) FROM um JOIN vm ON (um.m & vm.m) <> 0) / {_CELLS}, 6)""".replace("\\'\\'", "''")
fit_query("w1_density_k2", _ZEROS, lambda s, d, td: _measured(X.run_density_table(s, td, 2, 2)))


def _skew_sql(mode: str, **limits) -> str:
    sizes = "SELECT CAST(t.t AS INTEGER) AS topic, count(u2.row) AS nnz FROM range(2) t(t) LEFT JOIN u2 ON u2.topic = t.t GROUP BY 1"
    return O.als(**limits) + f""", z AS ({sizes}), r AS (SELECT *, row_number() OVER (ORDER BY nnz, topic) AS r FROM z)
SELECT '{mode}' AS mode, 'entries of topic ' || topic AS measure, CAST(nnz AS DOUBLE) AS value FROM z
UNION ALL SELECT '{mode}', 'gini', round(CAST(sum((2 * r - 3) * nnz) AS DOUBLE) / (2 * sum(nnz)), 6) FROM r
UNION ALL SELECT '{mode}', 'largest share', round(CAST(max(nnz) AS DOUBLE) / sum(nnz), 6) FROM r"""


fit_query("w5_skew_k2", O.either(_skew_sql("whole", t_u=20), _skew_sql("tiny", t_u=10, t_v=20), _skew_sql("topic", t_u=10, scope="topic")), lambda s, d, td: _measured(X.run_skew(s, td, 2, 20, 2)))


def _mean_row(fit: str, v: str, mode: str, live: bool = False) -> str:
    more = f" UNION ALL SELECT '{mode}', 'live topics', CAST(count(*) FILTER (n_docs > 1) AS DOUBLE) FROM acc" if live else ""
    return O.mean_accuracy(fit, v, LANG, 4) + f" SELECT '{mode}' AS mode, 'mean accuracy' AS measure, round(avg(acc), 6) AS value FROM acc{more}"


_LATER = _DENSE + ", " + O.cut("tb", "(SELECT row, topic, value, b FROM v2)", 200)
fit_query("w7_during_after_k2", O.either(_mean_row(O.als(t_v=200), "v2", "during"), _mean_row(_LATER, "tb", "after")), lambda s, d, td: _measured(X.run_during_vs_after(s, td, X.groups(s, d), 4, 2, (200,), 2)))
_PEAKS = O.either(
    _DENSE + f" SELECT 'dense' AS mode, 'peak entries' AS measure, CAST({O.peak(2)} AS DOUBLE) AS value",
    O.als(t_u=50, t_v=50, nnz=400) + f" SELECT 'guess 400' AS mode, 'peak entries' AS measure, CAST({O.peak(2)} AS DOUBLE) AS value",
)
fit_query("w8_peak_nnz_k2", f"WITH p AS ({_PEAKS}) SELECT * FROM p UNION ALL SELECT 'guess 400', 'dense over sparse', round(max(value) FILTER (mode = 'dense') / max(value) FILTER (mode <> 'dense'), 6) FROM p", lambda s, d, td: _measured(X.run_peak_nnz(s, td, 2, (50,), (400,), 2)))


def _tops(fit: str, u: str, mode: str) -> str:
    rank = f"CAST(row_number() OVER (PARTITION BY topic ORDER BY {O.rank_of()} DESC, row) AS INTEGER)"
    return fit + f" SELECT '{mode}' AS mode, topic, rank, row AS term, round(value, 6) AS value FROM (SELECT topic, row, value, {rank} AS rank FROM {u}) WHERE rank <= 5"


fit_query("w9_even_topics_k2", O.either(_tops(O.als(t_u=10, scope="topic"), "u2", "topic"), _tops(O.sequential(iters=1, t_u=10), "doneu2", "sequential")),
          lambda s, d, td: X.run_even_topics(s, td, 2, 10, 2).select("mode", "topic", "rank", "term", F.round("value", 6).alias("value")))
fit_query("w10_even_accuracy_k2", O.either(_mean_row(O.als(t_u=20, t_v=200), "v2", "whole", True), _mean_row(O.als(t_u=10, t_v=100, scope="topic"), "v2", "topic", True), _mean_row(O.sequential(iters=1, t_u=10, t_v=100), "donev2", "sequential", True)),
          lambda s, d, td: _measured(X.run_even_accuracy(s, td, X.groups(s, d), 4, 2, 20, 200, 2, (0,))))

_HOURS = "event_type || '|' || CAST(hour(ts) AS VARCHAR)"
for _n, _key, _src in (
    ("w13_customer_part", "customer x part", "SELECT CAST(l_partkey AS VARCHAR) AS term, o_custkey AS doc_id, count(*) AS tf FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL"),
    ("w13_user_events", "user x event hour", f"SELECT {_HOURS} AS term, user_id AS doc_id, count(*) AS tf FROM events GROUP BY ALL"),
):
    query(f"WITH c AS ({_src}) SELECT term, doc_id, tf, count(*) OVER (PARTITION BY term) AS df FROM c", _n)(lambda s, d, key=_key: X.relational_matrices(s, d)[key].coo)
query("WITH c AS (SELECT vec_id AS doc_id, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) - 1 AS dim FROM embeddings), p AS (SELECT * FROM c WHERE x > 0) SELECT CAST(dim AS VARCHAR) AS term, doc_id, round(x, 6) AS tf, count(*) OVER (PARTITION BY dim) AS df FROM p", "w13_embeddings")(
    lambda s, d: X.relational_matrices(s, d)["embeddings"].coo.select("term", "doc_id", F.round("tf", 6).alias("tf"), "df"))
query("WITH " + O.base("SELECT p_partkey AS doc_id, p_name AS text FROM part", stop=False) + " SELECT term, doc_id, tf, df FROM a", "w13_part_names")(lambda s, d: X.relational_matrices(s, d)["part words"].coo)
query(None, "w13_fits")(lambda s, d: X.run_relational_matrices(s, d))

# ---- relational operators -------------------------------------------------------------------------------------------


@query("SELECT lang, count(*) AS n FROM documents SEMI JOIN labels USING (doc_id) GROUP BY lang")
def semi_join_labeled(spark, sf_dir):
    return L.labelled(load_table(spark, sf_dir, DOCS), load_table(spark, sf_dir, "labels")).groupBy("lang").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT lang, count(*) AS n FROM documents ANTI JOIN labels USING (doc_id) GROUP BY lang")
def anti_join_unlabeled(spark, sf_dir):
    return L.unlabelled(load_table(spark, sf_dir, DOCS), load_table(spark, sf_dir, "labels")).groupBy("lang").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT doc_id, lang, quality, toxic FROM documents FULL JOIN labels USING (doc_id)")
def outer_join_labels(spark, sf_dir):
    return load_table(spark, sf_dir, DOCS).join(load_table(spark, sf_dir, "labels"), "doc_id", "full").select("doc_id", "lang", "quality", "toxic")


@query("SELECT event_id, p_partkey FROM events, part WHERE value BETWEEN p_retailprice - 1 AND p_retailprice + 1")
def range_join_events_parts(spark, sf_dir):
    part = load_table(spark, sf_dir, "part").select("p_partkey", (F.col("p_retailprice") - 1).alias("lo"), (F.col("p_retailprice") + 1).alias("hi"))
    return L.range_join(load_table(spark, sf_dir, "events").select("event_id", "value"), part, "value", "lo", "hi", 4.0).select("event_id", "p_partkey")


@query("WITH o AS (SELECT o_custkey, o_orderdate, max(o_totalprice) AS price FROM orders GROUP BY ALL) SELECT event_id, price FROM events ASOF LEFT JOIN o ON user_id = o_custkey AND ts >= o_orderdate")
def asof_join_events(spark, sf_dir):
    orders = load_table(spark, sf_dir, "orders").groupBy(F.col("o_custkey").alias("user_id"), "o_orderdate").agg(F.max("o_totalprice").alias("price"))
    return L.asof_join(load_table(spark, sf_dir, "events").select("event_id", "user_id", "ts"), orders, "user_id", "ts", "o_orderdate", "price").select("event_id", "price")


def _sums() -> list:
    return [F.count(F.lit(1)).alias("n"), F.sum("n_chars").cast("long").alias("chars")]


@query("SELECT lang, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY ROLLUP (lang, source)")
def rollup_lang_source(spark, sf_dir):
    return L.summarise(load_table(spark, sf_dir, DOCS), ["lang", "source"], _sums(), "rollup")


@query("SELECT quality, toxic, count(*) AS n FROM labels GROUP BY CUBE (quality, toxic)")
def cube_labels(spark, sf_dir):
    return L.summarise(load_table(spark, sf_dir, "labels"), ["quality", "toxic"], _sums()[:1], "cube")


@query("SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def grouping_sets_docs(spark, sf_dir):
    return L.summarise(load_table(spark, sf_dir, DOCS), ["lang", "source"], _sums()[:1], "sets", [["lang"], ["source"], []])


@query("SELECT event_id, max(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS top FROM events")
def window_running_max(spark, sf_dir):
    return load_table(spark, sf_dir, "events").select("event_id", L.running(DOCS, ["user_id"], ["ts", "event_id"], "value").alias("top"))


@query("SELECT event_id, round(value - lag(value) OVER w, 6) AS delta, lead(event_type) OVER w AS next_type FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def window_lag_delta(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load_table(spark, sf_dir, "events").select("event_id", F.round(F.col("value") - F.lag("value").over(w), 6).alias("delta"), F.lead("event_type").over(w).alias("next_type"))


def _lang_terms(spark, sf_dir, lang):
    return T.tokenize(load_table(spark, sf_dir, DOCS).where(F.col("lang") == lang)).select("term").distinct()


for _how in ("intersect", "except", "union"):
    query(TOK + f"SELECT term FROM tok WHERE lang = 'en' {_how.upper()} SELECT term FROM tok WHERE lang = 'fr'", f"set_{_how}_terms")(
        lambda s, d, how=_how: L.term_overlap(_lang_terms(s, d, "en"), _lang_terms(s, d, "fr"), how))


@query("SELECT kind, count(*) AS n, CAST(sum(length(text)) AS BIGINT) AS chars FROM (SELECT 'doc' AS kind, text FROM documents UNION ALL SELECT 'item', text FROM benchmark UNION ALL SELECT 'turn', text FROM conversations) GROUP BY kind")
def union_corpora(spark, sf_dir):
    parts = [load_table(spark, sf_dir, t).select(F.lit(k).alias("kind"), "text") for k, t in (("doc", DOCS), ("item", "benchmark"), ("turn", "conversations"))]
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).groupBy("kind").agg(F.count(F.lit(1)).alias("n"), F.sum(F.length("text")).alias("chars"))


@query("SELECT source, count(*) FILTER (lang = 'de') AS de, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'es') AS es, count(*) FILTER (lang = 'fr') AS fr FROM documents GROUP BY source")
def pivot_langs(spark, sf_dir):
    return load_table(spark, sf_dir, DOCS).groupBy("source").pivot("lang", ["de", "en", "es", "fr"]).count().fillna(0)


@query("SELECT event_type, CAST(props->>'$.k' AS INTEGER) AS k, count(*) AS n FROM events GROUP BY ALL")
def json_props(spark, sf_dir):
    return L.event_props(load_table(spark, sf_dir, "events")).groupBy("event_type", "k").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT event_type, date_trunc('day', ts) AS day, hour(ts) AS hour, count(*) AS n FROM events GROUP BY ALL")
def date_buckets(spark, sf_dir):
    e = load_table(spark, sf_dir, "events")
    return e.groupBy("event_type", F.date_trunc("day", "ts").cast("timestamp_ntz").alias("day"), F.hour("ts").cast("long").alias("hour")).agg(F.count(F.lit(1)).alias("n"))


@query("SELECT * FROM (SELECT source, doc_id, n_chars, row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) AS r FROM documents) WHERE r <= 3")
def top_documents_per_source(spark, sf_dir):
    top = L.top_n(load_table(spark, sf_dir, DOCS).select("source", "doc_id", "n_chars"), [F.desc("n_chars"), F.asc("doc_id")], 3, ["source"])
    return top.withColumn("r", F.row_number().over(Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")).cast("long"))


@query("SELECT doc_id, CAST(rank() OVER w AS INTEGER) AS r, CAST(dense_rank() OVER w AS INTEGER) AS d, CAST(ntile(4) OVER (PARTITION BY source ORDER BY n_chars, doc_id) AS INTEGER) AS quarter, round(percent_rank() OVER w, 6) AS share FROM documents WINDOW w AS (PARTITION BY source ORDER BY n_chars)")
def window_ranks(spark, sf_dir):
    w = Window.partitionBy("source").orderBy("n_chars")
    quarter = F.ntile(4).over(Window.partitionBy("source").orderBy("n_chars", "doc_id"))
    return load_table(spark, sf_dir, DOCS).select("doc_id", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"), quarter.alias("quarter"), F.round(F.percent_rank().over(w), 6).alias("share"))


@query("SELECT doc_id, lang FROM documents d WHERE n_chars > (SELECT avg(n_chars) FROM documents e WHERE e.lang = d.lang) AND EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id AND quality = 1)")
def correlated_subqueries(spark, sf_dir):
    docs, labels = load_table(spark, sf_dir, DOCS), load_table(spark, sf_dir, "labels")
    return spark.sql(
        "SELECT doc_id, lang FROM {docs} d WHERE n_chars > (SELECT avg(n_chars) FROM {docs} e WHERE e.lang = d.lang) AND EXISTS (SELECT 1 FROM {labels} l WHERE l.doc_id = d.doc_id AND quality = 1)",
        docs=docs, labels=labels)


@query("SELECT s.source, d.doc_id FROM (SELECT DISTINCT source FROM documents) s, LATERAL (SELECT doc_id FROM documents d WHERE d.source = s.source ORDER BY n_chars DESC, doc_id LIMIT 2) d")
def lateral_longest(spark, sf_dir):
    # an ORDER BY with LIMIT inside LATERAL becomes a row number without an order, so that the order is left to the shuffle
    ranked = "(SELECT doc_id, source, row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id NULLS LAST) AS r FROM {docs})"
    return spark.sql(f"SELECT s.source, d.doc_id FROM (SELECT DISTINCT source FROM {{docs}}) s, LATERAL (SELECT doc_id FROM {ranked} d WHERE d.source = s.source AND r <= 2) d", docs=load_table(spark, sf_dir, DOCS))


fit_query("array_pack", "WITH " + O.base() + " SELECT doc_id, count(*) AS entries, CAST(sum(tf) AS BIGINT) AS tokens, min(term) AS first_term FROM a GROUP BY doc_id",
          lambda s, d, td: td.coo.groupBy("doc_id").agg(F.array_sort(F.collect_list(F.struct("term", "tf"))).alias("e")).select("doc_id", F.size("e").cast("long").alias("entries"), F.aggregate("e", F.lit(0).cast("long"), lambda a, x: a + x["tf"]).alias("tokens"), F.element_at("e", 1)["term"].alias("first_term")))
fit_query("map_profile", FIT + f" SELECT topic, row AS term, round(value, 6) AS value FROM {RANKED} WHERE rank <= 5", lambda s, d, td: R.topic_profile_map(_fit(td).u).select("topic", F.explode("profile").alias("term", "value")).withColumn("value", F.round("value", 6)))


@query(None)
def approx_distinct_terms(spark, sf_dir):
    return T.tokenize(load_table(spark, sf_dir, DOCS)).agg(F.approx_count_distinct("term", 0.01).alias("terms"))


@query(None)
def sample_stratified(spark, sf_dir):
    return L.sample_docs(load_table(spark, sf_dir, DOCS), {"en": 0.1, "fr": 0.5, "de": 0.5, "es": 0.5}, 1, "lang").select("doc_id", "lang")


@query("SELECT a.p_name AS a, b.p_name AS b, levenshtein(a.p_name, b.p_name) AS distance FROM (SELECT DISTINCT p_name FROM part) a JOIN (SELECT DISTINCT p_name FROM part) b ON a.p_name < b.p_name AND levenshtein(a.p_name, b.p_name) <= 3")
def near_terms(spark, sf_dir):
    return L.near_terms(load_table(spark, sf_dir, "part").select(F.col("p_name").alias("term")), 3)


# ---- streaming: what a stream gives over all that is there, against the batch statement ------------------------------

_WINDOW = "SELECT time_bucket(INTERVAL '1 day', ts, TIMESTAMP '1970-01-01') AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL"


def _windows(stream, spark, name):
    out = S.drain(stream, spark, name, "complete")
    return out.withColumn("total", F.round("total", 4)).withColumn("start", F.col("start").cast("timestamp_ntz"))


@query(_WINDOW)
def stream_tumbling(spark, sf_dir):
    return _windows(S.event_windows(S.events_stream(spark, sf_dir), "1 day", watermark=None), spark, "tumbling")


@query("SELECT start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM (SELECT event_type, value, unnest([time_bucket(INTERVAL '6 hours', ts, TIMESTAMP '1970-01-01') - INTERVAL 6 HOUR * i FOR i IN range(4)]) AS start FROM events) GROUP BY ALL")
def stream_sliding(spark, sf_dir):
    return _windows(S.event_windows(S.events_stream(spark, sf_dir), "1 day", "6 hours", watermark=None), spark, "sliding")


@query("WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, k")
def stream_session(spark, sf_dir):
    out = S.drain(S.session_windows(S.events_stream(spark, sf_dir), "30 minutes", watermark=None), spark, "session", "complete")
    return out.withColumn("start", F.col("start").cast("timestamp_ntz"))


@query(None)
def stream_fold_in(spark, sf_dir):
    td = matrix(spark, sf_dir)
    u = _fit(td).u
    return _round_entries(S.drain(S.fold_in_stream(S.docs_stream(spark, sf_dir), u, td.coo.select("term", "df").distinct()), spark, "fold-in").withColumnRenamed("doc_id", "row"))


@query("SELECT count(*) AS documents, count(DISTINCT text) AS texts FROM documents")
def stream_dedup(spark, sf_dir):
    out = S.drain(S.dedup_stream(S.docs_stream(spark, sf_dir)).select("doc_id"), spark, "dedup")
    return load_table(spark, sf_dir, DOCS).agg(F.count(F.lit(1)).alias("documents")).crossJoin(out.agg(F.count(F.lit(1)).alias("texts")))


@query("SELECT c.user_id, c.ts AS click_ts, p.ts AS purchase_ts FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts BETWEEN c.ts AND c.ts + INTERVAL 1 HOUR")
def stream_interval_join(spark, sf_dir):
    e = S.events_stream(spark, sf_dir)
    out = S.drain(S.interval_join_stream(e.where("event_type = 'click'"), S.events_stream(spark, sf_dir).where("event_type = 'purchase'")), spark, "interval")
    return out.select("user_id", F.col("click_ts").cast("timestamp_ntz").alias("click_ts"), F.col("purchase_ts").cast("timestamp_ntz").alias("purchase_ts"))
