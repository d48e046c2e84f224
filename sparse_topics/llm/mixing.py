"""Mixing sources to target weights by hash-threshold histograms (DataFrame functions only).

Each source gets a word budget. Whole repeats are given to every document; the rest of the budget is filled by
hash order: words are summed by source and hash bucket, the bucket in which the running sum passes the budget is
found, and only that bucket is divided further (nine hash bits a level, four levels). A document is in the mix if
its hash lies under its source's threshold: no sort, no rank, no row gathered anywhere. Further, nested rounds fill
what the threshold before left over with later documents that still fit, and the last unit is taken if that brings the
sum nearer to the budget.

Defined results: a null text has size 0; a null source is a source of its own, ordered last; rows equal in doc_id and
text share a hash and stand or fall together; an empty table gives an empty mix; other columns of the input are
ignored by ``plan_mix`` and kept by ``mix_rows``. The number of sources is that of a mixture specification: one row
each is aggregated and joined, and the join is a broadcast only under ``SOURCE_BOUND`` rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import hash60, remove, source_key, word_count, write_table, written

BITS, LEVELS, PREFIX = 9, 4, 24  # 60 hash bits; the finest unit is the hash without its last PREFIX bits
SOURCE_BOUND = 100_000
ROUNDS = 3


def _unit(id_col: str, text_col: str) -> Column:
    return F.shiftright(hash60(F.col(id_col), F.col(text_col), salt="mix:"), PREFIX)


def sized(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """(doc_id, key, size, unit): what the histograms need of each document."""
    return docs.select(
        F.col(id_col).alias("doc_id"), source_key(F.col(source_col)).alias("key"), word_count(F.col(text_col)).alias("size"),
        _unit(id_col, text_col).alias("unit"),
    )


def targets(slim: DataFrame, cap: float = 3.0, cycle: int = 3) -> DataFrame:
    """(key, source_size, target): weights 1..cycle by order of the key; no target over ``cap`` times its source.

    Sources are filled in the order of the level at which they reach their cap; the excess of the full ones is shared
    by weight among the rest, so the level follows from running sums.
    """
    sums = slim.groupBy("key").agg(F.sum("size").alias("source_size"))
    everything = Window.partitionBy()
    up = Window.orderBy("fill", "key").rowsBetween(Window.unboundedPreceding, -1)
    t = (
        sums.withColumn("weight", ((F.row_number().over(Window.orderBy("key")) - 1) % cycle + 1).cast("long"))
        .withColumn("fill", F.col("source_size") / F.col("weight"))
        .withColumn("total", F.sum("source_size").over(everything))
        .withColumn("all_weight", F.sum("weight").over(everything))
        .withColumn("full_size", F.coalesce(F.sum("source_size").over(up), F.lit(0)))
        .withColumn("full_weight", F.coalesce(F.sum("weight").over(up), F.lit(0)))
        .withColumn("level", (F.col("total") - F.lit(cap) * F.col("full_size")) / (F.col("all_weight") - F.col("full_weight")))
        .withColumn("open", F.col("level") * F.col("weight") <= F.lit(cap) * F.col("source_size"))
        .withColumn("final", F.min(F.when(F.col("open"), F.struct("fill", "key", "level"))).over(everything)["level"])
    )
    share = F.least(F.lit(cap) * F.col("source_size"), F.col("weight") * F.col("final"))
    return t.select("key", "source_size", F.coalesce(share, F.lit(0.0)).alias("target"))


def _bounded(df: DataFrame) -> DataFrame:
    return F.broadcast(df) if df.count() <= SOURCE_BOUND else df


def _round(slim: DataFrame, state: DataFrame, first: bool) -> DataFrame:
    """One threshold for each source: (…, cut, left): the boundary unit and what of the budget lies before it."""
    fits = (F.col("unit") > F.col("after")) & (F.col("size") > 0)
    if not first:
        fits = fits & (F.col("size") <= F.col("left"))
    rows = slim.join(state.select("key", "after", "left"), "key").where(fits)
    found = None
    for level in range(1, LEVELS + 1):
        shift = BITS * (LEVELS - level)
        bucket = F.shiftright("unit", shift).alias("bucket")
        if found is not None:
            rows_in = rows.drop("left").join(found, "key").where(F.shiftright("unit", shift + BITS) == F.col("bound"))
        else:
            rows_in = rows
        sums = rows_in.groupBy("key", "left", bucket).agg(F.sum("size").alias("held"))
        run = Window.partitionBy("key").orderBy("bucket").rowsBetween(Window.unboundedPreceding, 0)
        passed = sums.withColumn("run", F.sum("held").over(run)).where(F.col("run") > F.col("left"))
        found = passed.groupBy("key").agg(F.min(F.struct("bucket", F.col("run"), "held", "left")).alias("b")).select(
            "key", F.col("b.bucket").alias("bound"), (F.col("b.left") - (F.col("b.run") - F.col("b.held"))).alias("left"), F.col("b.held").alias("held")
        )
    cut = found.select("key", F.col("bound").alias("cut"), F.col("left").alias("new_left"), "held")
    return state.join(cut, "key", "left")


def plan_mix(slim: DataFrame, cap: float = 3.0, cycle: int = 3) -> DataFrame:
    """One row for each source: key, source_size, target, repeats, and the thresholds of each round."""
    budget = targets(slim, cap, cycle)
    repeats = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("int")
    state = written(
        budget.withColumn("repeats", repeats).withColumn("left", F.col("target") - F.col("repeats") * F.col("source_size"))
        .withColumn("after", F.lit(-1).cast("long")),
        "mix-budget",
    )
    for i in range(1, ROUNDS + 1):
        nearest = F.col("held") - F.col("new_left") < F.col("new_left")
        state = written(
            _round(slim, state, i == 1)
            .withColumn(f"from{i}", F.col("after")).withColumn(f"fit{i}", F.lit(None).cast("double") if i == 1 else F.col("left"))
            .withColumn(f"to{i}", F.col("cut")).withColumn(f"last{i}", F.coalesce(nearest, F.lit(False)) & F.lit(i == ROUNDS))
            # no cut: everything after fits, and nothing is left to do
            .withColumn("after", F.coalesce("cut", F.lit((1 << 62) - 1))).withColumn("left", F.coalesce("new_left", F.lit(0.0)))
            .drop("cut", "new_left", "held"),
            "mix-round",
        )
    return state.drop("after", "left")


def copies() -> Column:
    """How often the mix takes a row, from its size and unit and its source's thresholds."""
    chosen = F.lit(False)
    for i in range(1, ROUNDS + 1):
        fits = F.col(f"fit{i}").isNull() | (F.col("size") <= F.col(f"fit{i}"))
        under = F.col(f"to{i}").isNull() | (F.col("unit") < F.col(f"to{i}")) | (F.col(f"last{i}") & (F.col("unit") == F.col(f"to{i}")))
        chosen = chosen | ((F.col("unit") > F.col(f"from{i}")) & fits & under & (F.col("size") > 0))
    return (F.col("repeats") + chosen.cast("int")).cast("int")


def mix(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", cap: float = 3.0, cycle: int = 3) -> DataFrame:
    """(doc_id, size, source_size, target, taken, copies) for each document."""
    slim = written(sized(docs, id_col, text_col, source_col), "mix-sizes")
    plan = _bounded(plan_mix(slim, cap, cycle))
    return slim.join(plan, "key").withColumn("copies", copies()).select(
        "doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).cast("long").alias("taken"), "copies"
    )


def mix_rows(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", cap: float = 3.0, cycle: int = 3) -> DataFrame:
    """The documents themselves, each as often as the mix takes it, with their own columns."""
    spark = docs.sparkSession
    slim, path = write_table(sized(docs, id_col, text_col, source_col), "mix-sizes")
    plan = _bounded(plan_mix(slim, cap, cycle))
    remove(spark, path)
    row = docs.select(
        F.struct("*").alias("row"), source_key(F.col(source_col)).alias("key"), word_count(F.col(text_col)).alias("size"),
        _unit(id_col, text_col).alias("unit"),
    )
    taken = row.join(plan, "key").withColumn("copies", copies()).where(F.col("copies") > 0)
    return taken.select("row", F.explode(F.sequence(F.lit(1), F.col("copies"))).alias("copy")).select("row.*")


def _sql_round(i: int) -> str:
    """One round over sorted hashes: running sums where the operator has histograms."""
    j, fits = i - 1, "true" if i == 1 else f"size <= left{i - 1}"
    last = f" OR (unit = cut{i} AND held{i} - left{i} < left{i})" if i == ROUNDS else ""
    return f"""a{i} AS (SELECT *, CASE WHEN size > 0 AND unit > cut{j} AND {fits} THEN size ELSE 0 END AS size{i} FROM g{j}),
b{i} AS (SELECT *, sum(size{i}) OVER (PARTITION BY key ORDER BY unit) AS run{i} FROM a{i}),
c{i} AS (SELECT key, min(unit) AS cut{i} FROM b{i} WHERE size{i} > 0 AND run{i} > left{j} GROUP BY key),
e{i} AS (SELECT b{i}.*, cut{i}, left{j} - coalesce(sum(size{i}) FILTER (WHERE unit < cut{i}) OVER (PARTITION BY key), 0) AS left{i},
    sum(size{i}) FILTER (WHERE unit = cut{i}) OVER (PARTITION BY key) AS held{i} FROM b{i} LEFT JOIN c{i} USING (key)),
g{i} AS (SELECT *, chosen{j} OR (size{i} > 0 AND (cut{i} IS NULL OR unit < cut{i}{last})) AS chosen{i} FROM e{i})"""


SQL = r"""
WITH d AS (SELECT doc_id, CASE WHEN source IS NULL THEN 't' ELSE 's' || source END AS key,
    CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size,
    ('0x' || substr(md5('mix:' || coalesce(CAST(doc_id AS VARCHAR), '') || coalesce(text, '')), 1, 15))::BIGINT >> 24 AS unit FROM documents),
s AS (SELECT key, CAST(sum(size) AS BIGINT) AS source_size, (row_number() OVER (ORDER BY key) - 1) % 3 + 1 AS weight FROM d GROUP BY key),
w AS (SELECT *, CAST(source_size AS DOUBLE) / weight AS fill, CAST(sum(source_size) OVER () AS BIGINT) AS total, CAST(sum(weight) OVER () AS BIGINT) AS allw FROM s),
l AS (SELECT *, CAST(coalesce(sum(source_size) OVER u, 0) AS BIGINT) AS fs, CAST(coalesce(sum(weight) OVER u, 0) AS BIGINT) AS fw FROM w
    WINDOW u AS (ORDER BY fill, key ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
v AS (SELECT *, (CAST(total AS DOUBLE) - 3.0::DOUBLE * fs) / (allw - fw) AS level FROM l),
t AS (SELECT key, source_size, least(3.0::DOUBLE * source_size, weight * (SELECT level FROM v WHERE level * weight <= 3.0::DOUBLE * source_size ORDER BY fill, key LIMIT 1)) AS target FROM v),
b AS (SELECT *, CASE WHEN source_size > 0 THEN CAST(floor(target / source_size) AS BIGINT) ELSE 0 END AS repeats FROM t),
g0 AS (SELECT d.*, source_size, target, repeats, target - repeats * source_size AS left0, -1 AS cut0, false AS chosen0 FROM d JOIN b USING (key)),
""" + ",\n".join(_sql_round(i) for i in range(1, ROUNDS + 1)) + f"""
SELECT doc_id, size, source_size, target, CAST(size * (repeats + CASE WHEN chosen{ROUNDS} THEN 1 ELSE 0 END) AS BIGINT) AS taken,
    CAST(repeats + CASE WHEN chosen{ROUNDS} THEN 1 ELSE 0 END AS INTEGER) AS copies FROM g{ROUNDS}
"""
