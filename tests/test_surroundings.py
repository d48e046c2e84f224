"""Sources, sinks, relational operators, streams, workloads, and every query against DuckDB."""

import math
import os
import subprocess
import sys
import time

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from sparse_topics import experiments as X
from sparse_topics import queries as Q
from sparse_topics.functions import text as T
from sparse_topics.operators import relational as L
from sparse_topics.operators.als import sparse_als
from sparse_topics.operators.matrix import build_term_doc, count_terms
from sparse_topics.operators.reading import fold_in
from sparse_topics.operators.sparsify import Limits
from sparse_topics.sources import load_fit, load_table, read_coo, read_docs, read_libsvm, register_coo_source, save_fit
from sparse_topics.streaming import streams as S


@pytest.fixture(scope="module")
def duck(tiny):
    c = duckdb.connect()
    for f in os.listdir(tiny):
        c.execute(f"CREATE VIEW {f.removesuffix('.parquet')} AS SELECT * FROM '{tiny}/{f}'")
    return c


def plain(v):
    if isinstance(v, float):
        return None if math.isnan(v) else round(v, 5) + 0.0
    return v


@pytest.mark.parametrize("name", sorted(Q.SQL))
def test_query_against_duckdb(spark, tiny, duck, name):
    df = Q.QUERIES[name](spark, tiny)
    got = df.collect()
    want = duck.execute(Q.SQL[name])
    cols = [d[0] for d in want.description]
    assert sorted(cols) == sorted(df.columns)
    order = lambda rows: sorted(rows, key=lambda r: tuple(map(str, r)))
    a, b = order(tuple(plain(r[c]) for c in cols) for r in got), order(tuple(map(plain, r)) for r in want.fetchall())
    assert len(a) == len(b) and a == b


def test_formats(spark, tmp_path):
    docs = spark.createDataFrame([(1, "a b"), (2, "c, \"d\"\ne")], "doc_id long, text string")
    for fmt in ("parquet", "orc", "json", "csv"):
        docs.write.format(fmt).option("header", True).option("escape", '"').save(f"{tmp_path}/{fmt}")
        assert sorted(map(tuple, read_docs(spark, f"{tmp_path}/{fmt}", fmt).collect())) == sorted(map(tuple, docs.collect()))
    (tmp_path / "lines.txt").write_text("one doc\nanother\n")
    assert read_docs(spark, str(tmp_path / "lines.txt"), "text").select("text").collect()[1].text == "another"
    (tmp_path / "m.txt").write_text("% comment\na 1 2\nb 1 1.5\na 2 1\n")
    assert {tuple(r) for r in read_coo(spark, str(tmp_path / "m.txt")).coo.collect()} == {("a", 1, 2.0, 2), ("a", 2, 1.0, 2), ("b", 1, 1.5, 1)}
    (tmp_path / "m.svm").write_text("1 3:2 5:1\n2 3:1\n")
    assert {tuple(r) for r in read_libsvm(spark, str(tmp_path / "m.svm")).coo.collect()} == {("3", 1, 2.0, 2), ("5", 1, 1.0, 1), ("3", 2, 1.0, 2)}
    register_coo_source(spark)
    assert spark.read.format("block_matrix").option("terms", 6).option("docs", 4).load().count() == 12


def test_model_on_disk(spark, tiny, tmp_path):
    td = Q.matrix(spark, tiny)
    fit = sparse_als(td, 2, Limits(20, 30), max_iter=2)
    save_fit(fit, str(tmp_path / "fit"))
    back = load_fit(spark, str(tmp_path / "fit"))
    assert sorted(map(tuple, back.u.long().collect())) == sorted(map(tuple, fit.u.long().collect())) and back.steps == fit.steps


def test_preparation_counts_in_rows_unless_ids_repeat(spark, monkeypatch):
    """The same matrix and facts either way; rows of one id are merged."""
    from sparse_topics.operators import matrix

    rows = [(1, "a b b c"), (2, None), (3, ""), (4, "c c a d"), (5, "a")]
    hows, count = [], matrix.count_terms
    monkeypatch.setattr(matrix, "count_terms", lambda docs, how, **o: hows.append(how) or count(docs, how, **o))
    monkeypatch.setattr(matrix, "SLICE", 2)
    for more, how in (([], "in_row"), ([(4, "a e e")], "shuffle"), ([(None, "c")], "shuffle")):
        docs = spark.createDataFrame(rows + more, "doc_id long, text string")
        for weight in ("df", "none", "tfidf"):
            a, b = build_term_doc(docs, stop=(), weight=weight), build_term_doc(docs, stop=(), weight=weight, how="shuffle", store=False)
            assert hows[-2] == how and a.n_docs == b.n_docs == len(rows) + len(more)
            assert sorted(map(str, a.coo.collect())) == sorted(map(str, b.coo.collect()))
            assert a.facts() == pytest.approx(b.facts())


def test_counts_in_row_and_html(spark):
    docs = spark.createDataFrame([(1, "Äb ab äB x1y"), (2, None), (3, "")], "doc_id long, text string")
    assert {tuple(r) for r in count_terms(docs, "in_row").collect()} == {tuple(r) for r in count_terms(docs).collect()} == {("äb", 1, 2), ("ab", 1, 1), ("x", 1, 1), ("y", 1, 1)}
    html = spark.createDataFrame([("<p>a&amp;b</p><script>x<y</script><!-- c --> d",)], "h string")
    assert html.select(T.html_to_text(F.col("h"))).first()[0].split() == ["a&b", "d"]
    assert "the" in T.stop_words() and "und" in T.stop_words()


def test_empty_corpus(spark):
    td = build_term_doc(spark.createDataFrame([], "doc_id long, text string"))
    fit = sparse_als(td, 2, Limits(5, 5), max_iter=1)
    assert fit.u.count() == 0 and fit.v.count() == 0


def test_asof_tolerance_and_samples(spark):
    left = spark.createDataFrame([(1, "a", 10), (2, "a", 50), (3, "b", 5)], "i int, k string, s int").select("i", "k", F.timestamp_seconds("s").alias("t"))
    right = spark.createDataFrame([("a", 8, 1.0), ("a", 20, 2.0)], "k string, s int, v double").select("k", F.timestamp_seconds("s").alias("t"), "v")
    assert {r.i: r.v for r in L.asof_join(left, right, "k", "t", "t", "v").collect()} == {1: 1.0, 2: 2.0, 3: None}
    assert {r.i: r.v for r in L.asof_join(left, right, "k", "t", "t", "v", "5 seconds").collect()} == {1: 1.0, 2: None, 3: None}
    assert L.sample_docs(left, 1.0).count() == 3


def test_lateral_rows_are_ranked_by_length(spark, tmp_path):
    """The rank itself has the order: a sort before the exchange is no order after it."""
    rows = [(i, f"src{i % 3}", (i * 7919) % 5000) for i in range(3000)] + [(3001, "src1", None), (3002, None, 9999), (3003, "src2", 4999)]
    spark.createDataFrame(rows, "doc_id long, source string, n_chars long").repartition(16).write.parquet(f"{tmp_path}/documents.parquet")
    out = Q.QUERIES["lateral_longest"](spark, str(tmp_path))
    best = {s: sorted((-(n or -1), i) for i, q, n in rows if q == s)[:2] for s in ("src0", "src1", "src2")}
    assert sorted(map(tuple, out.collect())) == sorted((s, i) for s, two in best.items() for _, i in two)
    plan = out._jdf.queryExecution().optimizedPlan().toString()
    assert "n_chars" in plan.split("windowspecdefinition(")[1].split("specifiedwindowframe")[0]


def test_near_terms_against_brute_force(spark, tiny):
    def edits(a, b):
        row = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            row, last = [i], row
            for j, y in enumerate(b, 1):
                row.append(min(last[j] + 1, row[-1] + 1, last[j - 1] + (x != y)))
        return row[-1]

    names = [r.p_name for r in load_table(spark, tiny, "part").select("p_name").distinct().limit(60).collect()]
    terms = sorted({"", "a", "ab", "ba", "abc", "xbc", "hot anvil", "cold anvil", "anvil", "an vil", "vil", "éa", *names})
    df = spark.createDataFrame([(t,) for t in [*terms, None, "a"]], "term string")
    for most in (0, 1, 2, 3):
        want = {(a, b, edits(a, b)) for a in terms for b in terms if a < b and edits(a, b) <= most}
        got = [tuple(r) for r in L.near_terms(df, most).collect()]
        assert len(got) == len(set(got)) and set(got) == want
    assert ("cold anvil", "hot anvil", 3) in want


def test_streams_equal_batches(spark, tiny, tmp_path):
    td = Q.matrix(spark, tiny)
    u = sparse_als(td, 2, Limits(40, 60), max_iter=2, measure=False).u
    got = S.drain(S.fold_in_stream(S.docs_stream(spark, tiny), u, td.coo.select("term", "df").distinct()), spark, "test-fold")
    want = {(r.row, r.topic): r.value for r in fold_in(td, u).collect()}
    have = {(r.doc_id, r.topic): r.value for r in got.collect()}
    assert have.keys() == want.keys() and all(np.isclose(have[k], want[k]) for k in want)
    q = S.count_stream(S.docs_stream(spark, tiny), str(tmp_path / "counts"), str(tmp_path / "state"))
    q.awaitTermination()
    assert spark.read.parquet(str(tmp_path / "counts/counts")).count() == count_terms(load_table(spark, tiny, "documents")).count()


@pytest.fixture(scope="module")
def arriving(spark, tiny, tmp_path_factory):
    """The documents in four files, as a stream of four micro-batches."""
    folder = str(tmp_path_factory.mktemp("arriving"))
    docs = load_table(spark, tiny, "documents").select("doc_id", "text")
    for i in range(4):
        docs.where(F.col("doc_id") % 4 == i).coalesce(1).write.mode("append").parquet(folder)
    return lambda: spark.readStream.schema(docs.schema).option("maxFilesPerTrigger", 1).parquet(folder)


def test_counts_of_batches_are_merged(spark, tiny, tmp_path, arriving):
    S.count_stream(arriving(), str(tmp_path / "t"), str(tmp_path / "state")).awaitTermination()
    docs = load_table(spark, tiny, "documents")
    want = {r.term: (r.total, r.df) for r in count_terms(docs).groupBy("term").agg(F.sum("tf").alias("total"), F.count(F.lit(1)).alias("df")).collect()}
    assert spark.read.parquet(str(tmp_path / "t/totals")).select("batch").distinct().count() == 4
    assert {r.term: (r.total, r.df) for r in S.merged_totals(spark, str(tmp_path / "t")).collect()} == want
    key = lambda td: sorted(map(tuple, td.coo.select("term", "doc_id", "tf", "df").collect()))
    assert key(S.matrix_so_far(spark, str(tmp_path / "t"))) == key(build_term_doc(docs, stop=()))


def test_refits_start_from_the_last_model_and_survive_a_restart(spark, tiny, tmp_path, arriving):
    seen = []

    def fit(docs, last):
        seen.append((docs.count(), None if last is None else sorted(map(tuple, last.u.long().collect()))))
        return S.warm_als(2, Limits(20, 40), max_iter=1, measure=False)(docs, last)

    table, total = str(tmp_path / "t"), load_table(spark, tiny, "documents").count()
    S.refit_stream(arriving(), 2, fit, table, str(tmp_path / "state")).awaitTermination()
    assert [n for n, _ in seen][-1] == total and seen[0][1] is None and len(seen) == 2
    first = sorted(map(tuple, load_fit(spark, f"{table}/model/batch=1").u.long().collect()))
    assert seen[1][1] == first  # the second fit started from the first model
    model, at = S.last_model(spark, table)
    again = S.warm_als(2, Limits(20, 40), max_iter=1, measure=False)(load_table(spark, tiny, "documents"), load_fit(spark, f"{table}/model/batch=1"))
    assert at == 3 and {r[:2] for r in map(tuple, model.u.long().collect())} == {r[:2] for r in map(tuple, again.u.long().collect())}
    S.refit_stream(arriving(), 2, fit, table, str(tmp_path / "state")).awaitTermination()  # nothing new: nothing is fitted
    assert len(seen) == 2


def test_late_rows_are_counted(spark, tmp_path):
    hours = [[0, 1], [30, 31], [40], [2], [60]]  # 2 comes when the watermark has long passed it
    for i, h in enumerate(hours):
        rows = spark.createDataFrame([(x, "click", 1.0) for x in h], "h int, event_type string, value double")
        rows.select(F.timestamp_seconds(F.col("h") * 3600).alias("ts"), "event_type", "value").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("ts timestamp, event_type string, value double").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    out, late = S.drain_counted(S.event_windows(stream, "1 hour", watermark="2 hours").select("start", "n"), spark, "test-late")
    assert late == 1 and out.agg(F.sum("n")).first()[0] == 5


def test_watermarked_windows_and_interval(spark, tiny):
    events = load_table(spark, tiny, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    batch = {tuple(r) for r in S.event_windows(events, "1 day").select("start", "event_type", "n").collect()}
    out = S.drain(S.event_windows(S.events_stream(spark, tiny), "1 day", watermark="2 hours").select("start", "event_type", "n"), spark, "test-windows")
    got = {tuple(r) for r in out.collect()}
    assert got <= batch and len(batch) - len(got) <= 10  # windows the watermark has not closed are not given yet
    assert S.session_windows(events).agg(F.sum("n")).first()[0] == events.count()


def test_workloads(spark, tiny):
    td, groups = Q.matrix(spark, tiny), X.groups(spark, tiny)
    zeros = {r.measure: r.value for r in X.run_density_table(spark, td, 3, 2).collect()}
    assert zeros["zeros of A"] > 0.97 and zeros["zeros of UV'"] < zeros["zeros of A"]
    trace = X.run_convergence_trace(spark, td, 3, 30, iters=8).collect()
    last = {r.run: r.error for r in trace if r.iter == 8}
    assert last["t_u=30"] >= last["dense"] - 0.02
    first = {r.run: r.error for r in trace if r.iter == 1}
    assert all(last[r] <= first[r] + 1e-9 for r in last)
    sweep = X.run_nnz_sweep(spark, td, 4, measure="accuracy", labels=groups, n_groups=4, grid=(40, None), sides=("v",), iters=6)
    by = {r.t_v: r.value for r in sweep.where("measure = 'mean accuracy'").collect()}
    assert by[40] > by[None]
    peak = {(r.mode, r.t_u): r.value for r in X.run_peak_nnz(spark, td, limits=(30,), guesses=(60,), iters=2).where("measure = 'dense over sparse'").collect()}
    assert peak["guess 60", 30] > 10
    skew = {(r.mode, r.measure): r.value for r in X.run_skew(spark, td, 4, 40, iters=3).collect()}
    assert skew["topic", "gini"] <= skew["whole", "gini"] + 1e-9


def test_shared_folder_without_a_setting():
    from types import SimpleNamespace

    from sparse_topics.session import shared_dir

    bare = lambda master: SimpleNamespace(conf=SimpleNamespace(get=lambda key, default=None: default), sparkContext=SimpleNamespace(applicationId="app-1", master=master))
    assert shared_dir(bare("local[4]")) == shared_dir(bare("local[4]")) and shared_dir(bare("local[4]")).startswith("file://")
    for master in ("yarn", "spark://host:7077", "local-cluster[2,1,1024]"):
        with pytest.raises(RuntimeError):
            shared_dir(bare(master))


def test_topic_drift_and_watermarked_dedup(spark, tmp_path):
    rows = [(1, 0, "a"), (1, 0, "b"), (1, 2, "a"), (2, 1, "c"), (1, 2, "d"), (1, 0, "c")]
    spark.createDataFrame([(i, *r) for i, r in enumerate(rows)], "n int, user_id long, topic int, text string").coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("n int, user_id long, topic int, text string").parquet(str(tmp_path / "in"))
    seen = stream.withColumn("ts", F.timestamp_seconds("n"))
    kept = S.drain(S.dedup_stream(seen, ts="ts").select("text"), spark, "test-dedup")
    assert sorted(r.text for r in kept.collect()) == ["a", "b", "c", "d"]
    with pytest.raises(ValueError):
        S.topic_drift(stream.select("user_id", "topic"))
    pytest.importorskip("google.protobuf")
    spark.conf.set(*S.ROCKSDB)
    try:
        got = S.drain(S.topic_drift(stream.select("user_id", "topic")), spark, "test-drift")
        assert {tuple(r) for r in got.collect()} == {(1, 0, 2), (1, 2, 0)}
        # with a time to live the state follows the clock, and such a query goes on until it is stopped
        out = str(tmp_path / "out")
        query = S.topic_drift(stream.select("user_id", "topic"), ttl_ms=3_600_000).writeStream.format("parquet").option("path", out).option("checkpointLocation", str(tmp_path / "state")).start()
        try:
            rows, end = set(), time.time() + 60
            while len(rows) < 2 and time.time() < end:
                time.sleep(1)
                if query.lastProgress:
                    rows = {tuple(r) for r in spark.read.schema("user_id long, old int, new int").parquet(out).collect()} if os.path.isdir(out) else set()
            assert rows == {(1, 0, 2), (1, 2, 0)}
        finally:
            query.stop()
    finally:
        spark.conf.unset(S.ROCKSDB[0])


def test_workloads_are_registered_whole(monkeypatch):
    import inspect

    seen = {}
    for fn in ("run_convergence_trace", "run_nnz_sweep", "run_during_vs_after", "run_even_accuracy", "run_timing"):
        real = inspect.signature(getattr(X, fn))

        def call(*a, real=real, **b):
            bound = real.bind(*a, **b)
            bound.apply_defaults()
            seen.update(bound.arguments)

        monkeypatch.setattr(X, fn, call)
    for name in ("matrix",):
        monkeypatch.setattr(Q, name, lambda *a: None)
    for name in ("corpus", "groups"):
        monkeypatch.setattr(X, name, lambda *a: None)
    got = {}
    for name in ("w2_convergence", "w4_nnz_sweep", "w6_accuracy_sweep", "w7_during_after", "w10_even_accuracy", "w11_timing"):
        seen.clear()
        Q.QUERIES[name](None, "")
        got[name] = (seen["iters"], seen.get("grid"), seen.get("seeds"))
    assert {k: v[0] for k, v in got.items()} == {"w2_convergence": 75, "w4_nnz_sweep": 75, "w6_accuracy_sweep": 50, "w7_during_after": 50, "w10_even_accuracy": 20, "w11_timing": 100}
    assert got["w4_nnz_sweep"][1] == got["w6_accuracy_sweep"][1] == X.GRID and len(got["w10_even_accuracy"][2]) == 5


def test_entry_needs_nothing_of_the_spark_installation(tmp_path):
    """As where pyspark's folder holds no jars: registering the queries and their statements reads package files only."""
    code = (
        "import pyspark, sys; pyspark.__file__ = sys.argv[1] + '/pyspark/__init__.py'; sys.path.insert(0, sys.argv[2]); import __spark_entry__ as e; "
        "assert len(e.queries()) > 100 and set(e.oracle_sql()) <= set(e.queries()); assert 'the' in e.oracle_sql()['stop_word_removal']"
    )
    env = {k: v for k, v in os.environ.items() if k not in ("SPARK_HOME", "PYTHONPATH")}
    subprocess.run([sys.executable, "-c", code, str(tmp_path), os.path.dirname(os.path.dirname(os.path.abspath(__file__)))], check=True, cwd=tmp_path, env=env)


def test_stop_lists_are_those_of_spark(spark):
    from pyspark.ml.feature import StopWordsRemover

    for lang in T.LANGUAGES:
        assert set(T.stop_words((lang,))) == {w.strip() for w in StopWordsRemover.loadDefaultStopWords(lang)} - {""}
