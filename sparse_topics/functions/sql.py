"""Functions for SQL users: temporary SQL functions, a table function for tokens, an aggregate as a second form."""

import re

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

_WORD = re.compile(r"[^\W\d_]+")


def register(spark: SparkSession) -> list[str]:
    """Registers accuracy_floor(d, j), topic_bit(t), tokens(text) for this session; returns their names."""
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION accuracy_floor(d BIGINT, j BIGINT) RETURNS BIGINT RETURN "
        "(d % j) * ((d div j + 1) * (d div j) div 2) + (j - d % j) * ((d div j) * (d div j - 1) div 2)"
    )
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION topic_bit(t INT) RETURNS BIGINT RETURN shiftleft(CAST(1 AS BIGINT), t)")

    @F.udtf(returnType="term: string, n: int")
    class Tokens:
        def eval(self, text: str):
            seen: dict[str, int] = {}
            for w in _WORD.findall((text or "").lower()):
                seen[w] = seen.get(w, 0) + 1
            yield from seen.items()

    spark.udtf.register("tokens", Tokens)
    return ["accuracy_floor", "topic_bit", "tokens"]


def topic_accuracy_udaf():
    """The accuracy of one topic from its members' groups, as a grouped pandas aggregate (for comparison in tests)."""
    import pandas as pd

    @F.pandas_udf("double")
    def accuracy(groups: pd.Series, j: pd.Series) -> float:
        d, j0 = len(groups), int(j.iloc[0])
        if d < 2 or j0 < 2:
            return 1.0
        same = sum(c * (c - 1) // 2 for c in groups.value_counts())
        q, r = divmod(d, j0)
        floor = r * (q + 1) * q // 2 + (j0 - r) * q * (q - 1) // 2
        return (same - floor) / (d * (d - 1) // 2 - floor)

    return accuracy
