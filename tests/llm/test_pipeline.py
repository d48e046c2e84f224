"""The pipeline against brute force: plain Python for three stages, the operators' statements in DuckDB for two."""

from collections import Counter

import duckdb
import pytest

import corpus_pipeline
from sparse_topics.llm import mixing, sharding
from sparse_topics.llm.common import load, write_table
from sparse_topics.llm.queries import quality_model


def grams(text, length=5):
    w = (text or "").encode().lower().split()
    k = min(length, len(w))
    return frozenset(tuple(w[i : i + k]) for i in range(len(w) - k + 1)) if w else frozenset()


def one_of_each(rows):
    """Rows (doc_id, text, …): the smallest id of each component of resembling texts."""
    sets = [grams(r["text"]) for r in rows]
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, a in enumerate(sets):
        for j, b in enumerate(sets[:i]):
            if a == b or (a and b and len(a & b) >= 0.8 * len(a | b)):
                root[find(i)] = find(j)
    best = {}
    for i, r in enumerate(rows):
        key = (r["doc_id"] is None, r["doc_id"] or 0)
        if find(i) not in best or key < best[find(i)][0]:
            best[find(i)] = (key, r)
    return [r for _, r in best.values()]


def without_leaks(rows, items):
    wanted = []
    for t in items:
        w = (t or "").encode().lower().split()
        if w:
            wanted.append((min(5, len(w)), grams(t)))
    return [r for r in rows if not any(len(g & (grams(r["text"], n) if n == 5 else short(r["text"], n))) >= 0.8 * len(g) for n, g in wanted)]


def short(text, n):
    w = (text or "").encode().lower().split()
    return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)}


def by_statement(sql, docs):
    duck = duckdb.connect()
    duck.register("documents", docs.toArrow())
    return duck.execute(sql)


def slow_run(spark, sf_dir):
    """Counter of (doc_id, text, shard, slot)."""
    docs, labels, bench = (load(spark, sf_dir, t) for t in ("documents", "labels", "benchmark"))
    model = quality_model(docs, labels)
    rows = [r.asDict() for r in docs.collect()]
    good = [r for r, s in zip(rows, model.score([r["text"] for r in rows]), strict=True) if s >= 0.3]
    left = without_leaks(one_of_each(good), [r.text for r in bench.collect()])
    frame = lambda x: spark.createDataFrame([tuple(r[c] for c in docs.columns) for r in x], docs.schema)
    if not left:
        return Counter()
    texts = {r["doc_id"]: r for r in left}
    copies = dict(by_statement(f"SELECT doc_id, copies FROM ({mixing.SQL})", frame(left)).fetchall())
    mixed = [texts[i] for i, n in copies.items() for _ in range(n)]
    if not mixed:
        return Counter()
    placed = by_statement(f"SELECT doc_id, shard, slot FROM ({sharding.SQL})", frame(mixed)).fetchall()
    return Counter((i, texts[i]["text"], shard, slot) for i, shard, slot in placed)


def awkward_tables(spark, folder):
    """Null, empty, long and repeated texts, clashing columns, labels that contradict each other."""
    plain = [(i, f"Some plain words of text number {i} that say this and that about thing {i % 7} and {i * 31 % 97}.", "en", f"s{i % 3}") for i in range(10, 40)]
    bad = [(i, "### $$$ %%% &&& ***" * 8 + str(i), "en", "s1") for i in range(50, 62)]
    odd = [(1, None, None, None), (2, "", "en", "b"), (3, "one", "en", None), (60, "two words", None, "s1"), (5, " ".join(f"w{i % 977}" for i in range(20_000)), "en", "s0"), (6, " ".join(f"w{i % 977}" for i in range(20_000)), "fr", "s0"), (8, "a b c the item that must not leak into any text d e", "en", "s2")]
    odd += [(70, plain[0][1], "en", "s1")]
    docs = [(*r, len(r[1] or ""), i, "k") for i, r in enumerate(plain + bad + odd)]
    spark.createDataFrame(docs, "doc_id long, text string, lang string, source string, n_chars int, size int, key string").write.parquet(f"{folder}/documents.parquet")
    labels = [(r[0], 1, 0) for r in plain[:25]] + [(r[0], 0, 0) for r in bad] + [(30, 0, 0), (1, None, None)]
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")
    spark.createDataFrame([(1, "the item that must not leak into any text"), (None, None), (2, " ")], "item_id long, text string").write.parquet(f"{folder}/benchmark.parquet")
    return str(folder)


def fast_run(spark, sf_dir):
    return Counter((r.doc_id, r.text, r.shard, r.slot) for r in corpus_pipeline.run(spark, sf_dir).collect())


def test_run_equals_brute_force(spark, tiny):
    got = fast_run(spark, tiny)
    assert got == slow_run(spark, tiny) and len(got) > 50


def test_run_on_awkward_tables(spark, tmp_path):
    folder = awkward_tables(spark, tmp_path / "t")
    got = fast_run(spark, folder)
    assert got == slow_run(spark, folder)
    ids = {i for i, *_ in got}
    assert 8 not in ids and not ids & set(range(50, 60)) and 70 not in ids and not {5, 6} <= ids


def test_run_on_empty_tables(spark, tiny, tmp_path):
    for t in ("documents", "labels", "benchmark"):
        load(spark, tiny, t).where("1 = 0").write.parquet(f"{tmp_path}/{t}.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0


def test_repeated_rows_are_counted_out(spark, tiny, tmp_path):
    docs = load(spark, tiny, "documents").limit(20)
    docs.unionByName(docs).write.parquet(f"{tmp_path}/documents.parquet")
    for t in ("labels", "benchmark"):
        load(spark, tiny, t).write.parquet(f"{tmp_path}/{t}.parquet")
    rows = corpus_pipeline.run(spark, str(tmp_path)).collect()
    assert max(Counter(r.doc_id for r in rows).values()) <= 4  # the mix alone repeats


def test_columns_of_the_stages(spark, tiny):
    docs = load(spark, tiny, "documents")
    columns = docs.columns
    for name, stage in corpus_pipeline.STAGES:
        docs, _ = write_table(stage(spark, docs, tiny), name)
        assert docs.columns == columns + (["shard", "slot"] if name == "sharding" else [])
    counts = Counter(r.shard for r in docs.select("shard").collect())
    assert max(counts.values()) - min(counts.values()) <= 1


@pytest.mark.parametrize("stage", [s for _, s in corpus_pipeline.STAGES])
def test_stages_state_their_results(stage):
    assert stage.__doc__ and "null" in stage.__doc__
