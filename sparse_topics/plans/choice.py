"""Which join, layout and selection to use, from exact entry counts."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Factors of at most so many entries are held by the driver and broadcast (24 bytes an entry, below 5 MB).
LOCAL_ENTRIES = 200_000
#: Factors of at most so many entries are still broadcast from executors.
BROADCAST_ENTRIES = 4_000_000
#: Factors of at most so many entries are arrays of the driver where many fits go side by side (8 bytes an entry, 192 MB).
HELD_ENTRIES = 24_000_000
#: Rows that all partitions together may send to the one task that merges their t largest.
HEAP_ROWS = 1_000_000
#: Up to so many topics, one aggregate holds all sums of a row; beyond it rows are (row, topic).
PACKED_TOPICS = 60


def choose_join(entries: int | None) -> str:
    """'local', 'broadcast' or 'shuffle' for the small side of a product."""
    if entries is not None and entries <= LOCAL_ENTRIES:
        return "local"
    return "broadcast" if entries is not None and entries <= BROADCAST_ENTRIES else "shuffle"


def heap_fits(spark: SparkSession, t: int) -> bool:
    """May the t largest come from a heap in each partition? Else a threshold is narrowed and filtered by."""
    return t <= LOCAL_ENTRIES and t * int(spark.conf.get("spark.sql.shuffle.partitions")) <= HEAP_ROWS


def choose_layout(k: int) -> str:
    return "packed" if k <= PACKED_TOPICS else "long"


def hinted(df: DataFrame, entries: int | None) -> DataFrame:
    return F.broadcast(df) if choose_join(entries) != "shuffle" else df


def plan_text(df: DataFrame) -> str:
    """The formatted plan, for assertions on exchanges and scans."""
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
