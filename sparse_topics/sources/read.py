"""Sources: the given tables, documents in common formats, matrices in exchange formats, a Python data source."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..operators.matrix import TermDoc


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_docs(spark: SparkSession, path: str, fmt: str = "parquet", id_col: str = "doc_id", text_col: str = "text", schema: str | None = None) -> DataFrame:
    """(doc_id, text) from parquet, orc, csv, json, or text with one document a line (ids by hash of file and line order)."""
    if fmt == "text":
        lines = spark.read.text(path)
        return lines.select(F.monotonically_increasing_id().alias("doc_id"), F.col("value").alias("text"))
    reader = spark.read.schema(schema or f"{id_col} long, {text_col} string") if fmt in ("csv", "json") else spark.read
    if fmt == "csv":
        reader = reader.option("header", True).option("multiLine", True).option("escape", '"')
    return reader.format(fmt).load(path).select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))


def _with_df(entries: DataFrame) -> TermDoc:
    per_row = entries.groupBy("term").agg(F.count(F.lit(1)).alias("df"))
    return TermDoc(entries.join(per_row, "term").select("term", "doc_id", "tf", "df"), "none")


def read_coo(spark: SparkSession, path: str, sep: str = " ") -> TermDoc:
    """Coordinate text: one 'row column value' a line, comment lines start with %."""
    parts = F.split(F.trim("value"), sep)
    lines = spark.read.text(path).where(~F.col("value").startswith("%") & (F.trim("value") != ""))
    return _with_df(lines.select(parts[0].alias("term"), parts[1].cast("long").alias("doc_id"), parts[2].cast("double").alias("tf")).where("tf > 0"))


def read_libsvm(spark: SparkSession, path: str) -> TermDoc:
    """SVMlight lines: one document a line, index:value pairs; the label is read as the document id."""
    fields = F.split(F.trim("value"), r"\s+")
    rows = spark.read.text(path).where(F.trim("value") != "").select(fields[0].cast("double").cast("long").alias("doc_id"), F.explode(F.slice(fields, 2, 1 << 30)).alias("p"))
    return _with_df(rows.select(F.split_part("p", F.lit(":"), F.lit(1)).alias("term"), "doc_id", F.split_part("p", F.lit(":"), F.lit(2)).cast("double").alias("tf")).where("tf > 0"))


class _Part(InputPartition):
    def __init__(self, start: int, stop: int):
        self.start, self.stop = start, stop


class BlockMatrixReader(DataSourceReader):
    def __init__(self, options: dict):
        self.terms, self.docs, self.parts = (int(options.get(k, d)) for k, d in (("terms", "100"), ("docs", "100"), ("partitions", "4")))
        self.blocks = int(options.get("blocks", "2"))

    def partitions(self) -> list[InputPartition]:
        step = -(-self.docs // self.parts)
        return [_Part(a, min(self.docs, a + step)) for a in range(0, self.docs, step)]

    def read(self, partition: _Part) -> Iterator[tuple]:
        for d in range(partition.start, partition.stop):
            for t in range(d % self.blocks, self.terms, self.blocks):
                yield f"t{t}", d, 1 + (t * 31 + d * 17) % 5


class BlockMatrixSource(DataSource):
    """Planted matrices for experiments: documents and terms of equal remainder form a block."""

    @classmethod
    def name(cls) -> str:
        return "block_matrix"

    def schema(self) -> str:
        return "term string, doc_id bigint, tf bigint"

    def reader(self, schema) -> DataSourceReader:
        return BlockMatrixReader(self.options)


def register_coo_source(spark: SparkSession) -> None:
    """Makes spark.read.format('block_matrix') available."""
    spark.dataSource.register(BlockMatrixSource)
