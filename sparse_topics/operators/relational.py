"""Relational operators around the methods: as-of and range joins, summaries, windows, set operations, samples."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def labelled(docs: DataFrame, labels: DataFrame, on: str = "doc_id") -> DataFrame:
    return docs.join(labels.select(on), on, "left_semi")


def unlabelled(docs: DataFrame, labels: DataFrame, on: str = "doc_id") -> DataFrame:
    return docs.join(labels.select(on), on, "left_anti")


def asof_join(left: DataFrame, right: DataFrame, on: str, left_ts: str, right_ts: str, value: str, tolerance: str | None = None) -> DataFrame:
    """Each left row with the ``value`` of the latest right row of the same key not after it (null if none).

    Both inputs are laid in one column of time and the last right value is carried forward: one exchange by key, no
    pairs. tolerance: an interval string; older matches count as none.
    """
    lhs = left.select(F.col(on).alias("__k"), F.col(left_ts).alias("__t"), F.lit(1).alias("__side"), F.struct("*").alias("__row"), F.lit(None).cast(right.schema[value].dataType).alias("__v"), F.lit(None).cast(right.schema[right_ts].dataType).alias("__rt"))
    rhs = right.select(F.col(on).alias("__k"), F.col(right_ts).alias("__t"), F.lit(0).alias("__side"), F.lit(None).cast(lhs.schema["__row"].dataType).alias("__row"), F.col(value).alias("__v"), F.col(right_ts).alias("__rt"))
    w = Window.partitionBy("__k").orderBy("__t", "__side").rowsBetween(Window.unboundedPreceding, 0)
    seen = F.struct(F.col("__rt").alias("t"), F.col("__v").alias("v"))
    out = lhs.unionByName(rhs).withColumn("__last", F.last(F.when(F.col("__side") == 0, seen), ignorenulls=True).over(w)).where("__side = 1")
    found = F.col("__last.v") if tolerance is None else F.when(F.col("__last.t") >= F.col("__t") - F.expr(f"INTERVAL {tolerance}"), F.col("__last.v"))
    return out.select("__row.*", found.alias(value))


def range_join(left: DataFrame, right: DataFrame, value: str, lo: str, hi: str, bin_width: float) -> DataFrame:
    """left.value between right.lo and right.hi, by bins: each interval is listed under the bins it touches, so that the
    join is an equi-join on the bin with the exact condition after it."""
    number = lambda c: F.floor(F.col(c).cast("double") / F.lit(bin_width)).cast("long")
    spread = right.withColumn("__bin", F.explode(F.sequence(number(lo), number(hi))))
    return left.withColumn("__bin", number(value)).join(spread, "__bin").where(F.col(value).between(F.col(lo), F.col(hi))).drop("__bin")


def near_terms(terms: DataFrame, max_distance: int, prefix: int = 0) -> DataFrame:
    """(a, b, distance) of all terms at most ``max_distance`` edits apart; with ``prefix``, of those only that begin alike.

    A term is cut into max_distance + 1 pieces at places that its length fixes. Each edit touches one piece at most, so
    one piece of the longer term occurs unchanged in the other one, moved by max_distance characters at most: an
    equi-join on length, piece and its text, with the exact distance after it. Terms no longer than max_distance have
    empty pieces, which all terms of near lengths share.
    """
    pieces = max_distance + 1
    t = terms.select("term").where("term is not null").distinct().withColumn("n", F.length("term"))
    start = lambda n, i: F.floor(n * i / F.lit(pieces)).cast("int")
    part = lambda n, i, at: F.substring(F.col("term"), at + 1, start(n, i + 1) - start(n, i))
    every = F.sequence(F.lit(0), F.lit(max_distance))
    longer = t.withColumn("i", F.explode(every)).select(F.col("term").alias("long"), "n", "i", part(F.col("n"), F.col("i"), start(F.col("n"), F.col("i"))).alias("piece"))
    shifts = t.withColumnRenamed("n", "m").withColumn("i", F.explode(every)).withColumn("n", F.explode(F.sequence(F.col("m"), F.col("m") + max_distance)))
    at = start(F.col("n"), F.col("i"))
    shifts = shifts.withColumn("at", F.explode(F.sequence(F.greatest(F.lit(0), at - max_distance), F.greatest(F.lit(0), F.least(F.col("m"), at + max_distance)))))
    shorter = shifts.select(F.col("term").alias("short"), "n", "i", part(F.col("n"), F.col("i"), F.col("at")).alias("piece")).distinct()
    order = (F.col("long") != F.col("short")) & ((F.length("short") < F.col("n")) | (F.col("short") < F.col("long")))
    pairs = longer.join(shorter, ["n", "i", "piece"]).where(order).select(F.least("long", "short").alias("a"), F.greatest("long", "short").alias("b")).distinct()
    if prefix:
        pairs = pairs.where(F.substring("a", 1, prefix) == F.substring("b", 1, prefix))
    return pairs.select("a", "b", F.levenshtein("a", "b", max_distance).cast("long").alias("distance")).where("distance >= 0")


def summarise(df: DataFrame, dims: list[str], aggs: list[Column], mode: str = "group", sets: list[list[str]] | None = None) -> DataFrame:
    """'group', 'rollup', 'cube' or 'sets' (grouping sets)."""
    if mode == "sets":
        return df.groupingSets([[F.col(c) for c in s] for s in sets or [dims]], *dims).agg(*aggs)
    grouped = {"group": df.groupBy, "rollup": df.rollup, "cube": df.cube}[mode]
    return grouped(*dims).agg(*aggs)


def running(df: DataFrame, part: list[str], order: list[str], value: str, fn: str = "max", frame: tuple[int, int] = (Window.unboundedPreceding, 0), mode: str = "rows") -> Column:
    """A windowed aggregate as a column: frame by rows or by range."""
    w = Window.partitionBy(*part).orderBy(*order)
    return getattr(F, fn)(value).over(w.rowsBetween(*frame) if mode == "rows" else w.rangeBetween(*frame))


def top_n(df: DataFrame, order: list[Column], n: int, per: list[str] | None = None) -> DataFrame:
    if not per:
        return df.orderBy(*order).limit(n)
    return df.withColumn("__r", F.row_number().over(Window.partitionBy(*per).orderBy(*order))).where(F.col("__r") <= n).drop("__r")


def term_overlap(a: DataFrame, b: DataFrame, how: str = "intersect") -> DataFrame:
    """Set operations on (term): intersect, except, union and their multiset forms."""
    ops = {"intersect": a.intersect, "except": a.subtract, "union": lambda x: a.union(x).distinct(), "intersect_all": a.intersectAll, "except_all": a.exceptAll, "union_all": a.unionAll}
    return ops[how](b)


def sample_docs(df: DataFrame, fraction: float | dict, seed: int = 0, by: str | None = None) -> DataFrame:
    """A simple sample, or one stratified by ``by`` with a fraction for each stratum."""
    return df.sampleBy(by, fraction, seed) if by else df.sample(fraction=fraction, seed=seed)


def event_props(events: DataFrame) -> DataFrame:
    """Events with the ``k`` of their JSON properties."""
    return events.withColumn("k", F.get_json_object("props", "$.k").cast("int"))


def user_hours(events: DataFrame) -> DataFrame:
    """(item, user_id): event type and hour of day as the row key of a matrix."""
    return events.select(F.concat_ws("|", "event_type", F.hour("ts").cast("string")).alias("item"), "user_id")
