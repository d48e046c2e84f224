"""Truncation: the t largest entries of a matrix or of each topic, entries above a constant, limits as a whole."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.choice import LOCAL_ENTRIES, heap_fits
from .factors import RANK_SCALE


GROUP_LIMIT = 1000  # Spark's own bound for limiting groups before an exchange


@dataclass(frozen=True)
class Limits:
    """At most t_u (t_v) entries in U (V): in the whole matrix or in each topic; None: no limit. A threshold instead of a
    number cuts at a constant."""

    t_u: int | None = None
    t_v: int | None = None
    scope: str = "matrix"
    ties: str = "exact"
    tau_u: float | None = None
    tau_v: float | None = None

    def side(self, name: str) -> tuple[int | None, float | None]:
        return (self.t_u, self.tau_u) if name == "u" else (self.t_v, self.tau_v)


def rank_key() -> Column:
    return F.rint(F.col("value") * F.lit(RANK_SCALE))


def _order() -> list[Column]:
    return [rank_key().desc(), F.col("row"), F.col("topic")]


def kth_largest_of(long: DataFrame, t: int, group: Column | None = None, collect: int = 100_000) -> dict[int, tuple[float, int, int]]:
    """For each value of ``group`` (few; one for all if None): (rank key of the t-th largest entry, entries above it, entries
    equal to it), by narrowing histograms and no sort.

    Each pass counts, for all groups at once, the entries of 1,024 equal bins of the group's bracket and keeps the bin that
    holds the t-th; what is left (at most ``collect`` keys) is sorted by the driver. With fewer than t entries the key is 0.
    """
    keys = long.select((F.lit(0) if group is None else group).cast("int").alias("g"), rank_key().alias("key"))
    out: dict[int, tuple[float, int, int]] = {}
    open_: dict[int, list] = {}  # low, high, above, inside
    for r in keys.groupBy("g").agg(F.min("key").alias("low"), F.max("key").alias("high"), F.count(F.lit(1)).alias("n")).collect():
        if r["n"] < t:
            out[r["g"]] = (0.0, r["n"], 0)
        else:
            open_[r["g"]] = [r["low"], r["high"], 0, r["n"]]

    def settled(g: int) -> bool:
        if g in open_ and open_[g][0] == open_[g][1]:
            low, _, above, inside = open_.pop(g)
            out[g] = (low, above, inside)
        return g in out

    def bracket() -> DataFrame:
        rows = [(g, x[0], x[1]) for g, x in open_.items()]
        listed = long.sparkSession.createDataFrame(rows, "g int, low double, high double")  # one row a group
        return keys.join(F.broadcast(listed), "g").where(F.col("key").between(F.col("low"), F.col("high")))

    for g in list(open_):
        settled(g)
    while open_ and sum(x[3] for x in open_.values()) > collect:
        width = (F.col("high") - F.col("low")) / 1024
        bin_ = F.least(F.floor((F.col("key") - F.col("low")) / width), F.lit(1023)).alias("bin")
        counted = bracket().groupBy("g", bin_).agg(F.count(F.lit(1)).alias("n"), F.min("key").alias("least"), F.max("key").alias("most")).collect()
        for r in sorted(counted, key=lambda r: (r["g"], -r["bin"])):
            x = open_.get(r["g"])
            if x is None or len(x) > 4:
                continue
            if x[2] + r["n"] >= t:
                open_[r["g"]] = [r["least"], r["most"], x[2], r["n"], "found"]
            else:
                x[2] += r["n"]
        for g in list(open_):
            open_[g] = open_[g][:4]
            settled(g)
    if open_:
        left: dict[int, list[float]] = {g: [] for g in open_}
        for r in bracket().select("g", "key").collect():
            left[r["g"]].append(r["key"])
        for g, (_, _, above, _) in open_.items():
            found = sorted(left[g], reverse=True)
            key = found[t - above - 1]
            out[g] = (key, above + sum(x > key for x in found), sum(x == key for x in found))
    return out


def kth_largest(long: DataFrame, t: int, collect: int = 100_000) -> tuple[float, int, int]:
    """(rank key of the t-th largest entry, entries above it, entries equal to it) of the whole matrix."""
    return kth_largest_of(long, t, collect=collect).get(0, (0.0, 0, 0))


def keep_largest(long: DataFrame, t: int, ties: str = "exact", local: int = LOCAL_ENTRIES) -> DataFrame:
    """At most t entries ('exact', ties by row and topic), or all entries not below the t-th ('keep').

    By a heap in each partition and a merge, if what all of them send to the merging task is bounded; beyond that, and
    beyond ``local`` entries, by threshold and filter.
    """
    if t <= 0:
        return long.where("1 = 0")
    if ties == "exact" and t <= local and heap_fits(long.sparkSession, t):
        return long.orderBy(*_order()).limit(t)
    key, above, equal = kth_largest(long, t)
    if ties == "keep" or above + equal <= t:
        return long.where(rank_key() >= F.lit(key))
    some = long.where(rank_key() == F.lit(key)).orderBy("row", "topic").limit(t - above)
    return long.where(rank_key() > F.lit(key)).unionByName(some)


def keep_largest_per_topic(long: DataFrame, t: int, ties: str = "exact", local: int = GROUP_LIMIT) -> DataFrame:
    """The t largest entries of each topic. Spark limits the groups before the exchange up to ``local`` entries a topic;
    beyond that, or where the partitions would send too many, thresholds of all topics are narrowed at once."""
    if t <= 0:
        return long.where("1 = 0")
    if t <= local and heap_fits(long.sparkSession, t):
        w = Window.partitionBy("topic")
        rank = F.row_number().over(w.orderBy(*_order()[:2])) if ties == "exact" else F.rank().over(w.orderBy(rank_key().desc()))
        return long.withColumn("__rank", rank).where(F.col("__rank") <= t).drop("__rank")
    found = kth_largest_of(long, t, F.col("topic"))
    if not found:
        return long
    listed = long.sparkSession.createDataFrame([(g, key, t - above) for g, (key, above, _) in found.items()], "topic int, __key double, __more long")  # one row a topic
    near = long.join(F.broadcast(listed), "topic").where(rank_key() >= F.col("__key"))
    if ties == "exact" and any(above + equal > t for _, above, equal in found.values()):
        # only entries equal to a topic's threshold are ranked
        over = near.where(rank_key() == F.col("__key")).withColumn("__rank", F.row_number().over(Window.partitionBy("topic").orderBy("row")))
        near = near.where(rank_key() > F.col("__key")).unionByName(over.where(F.col("__rank") <= F.col("__more")).drop("__rank"))
    return near.select(*long.columns)


def keep_above(long: DataFrame, tau: float) -> DataFrame:
    """Entries of at least ``tau``."""
    return long.where(F.col("value") >= F.lit(tau))


def truncate(long: DataFrame, limits: Limits, side: str) -> DataFrame:
    t, tau = limits.side(side)
    if tau is not None:
        long = keep_above(long, tau)
    if t is None:
        return long
    return keep_largest_per_topic(long, t, limits.ties) if limits.scope == "topic" else keep_largest(long, t, limits.ties)
