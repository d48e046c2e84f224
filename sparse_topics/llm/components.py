"""Connected components of an edge table by alternating star contraction; nothing is gathered in the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import remove, write_table


def _state(edges: DataFrame) -> tuple[int, int]:
    r = edges.agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("u", "v") % (1 << 40)).alias("s")).first()
    return r["n"], r["s"] or 0


def components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """edges: (u, v) longs, any direction. Gives (node, root) for every node that is not the smallest of its component.

    Each round points the larger neighbours of a node, then the smaller ones, to the smallest it knows; every join can
    be split where one node has a great many edges. The rounds end when the edge table stays the same.
    """
    spark = edges.sparkSession
    now, path = write_table(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
    state = _state(now)
    for _ in range(most_rounds):
        if not state[0]:
            break
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select("u", F.col("m").alias("v"))).distinct()
        new, new_path = write_table(small, "edges")
        remove(spark, path)
        new_state = _state(new)
        now, path, done, state = new, new_path, new_state == state, new_state
        if done:
            return now.toDF("node", "root")
    if state[0]:
        raise RuntimeError(f"components did not settle in {most_rounds} rounds")
    return now.toDF("node", "root")
