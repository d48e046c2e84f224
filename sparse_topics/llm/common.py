"""Shared helpers: the shared work folder, written intermediate tables, text expressions."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A word is a run of anything but space and the control characters tab to carriage return.
WORD = r"[^\x20\x09-\x0D]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


_own_dirs: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``. Where it is unset, a folder of our own if all
    run on this machine; a cluster has to name one."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        app = spark.sparkContext.applicationId
        if app not in _own_dirs:
            _own_dirs[app] = "file://" + tempfile.mkdtemp(prefix="sparse_topics_")
            atexit.register(shutil.rmtree, _own_dirs[app].removeprefix("file://"), True)
        found = _own_dirs[app]
    return found.rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def write_table(df: DataFrame, name: str) -> tuple[DataFrame, str]:
    """Write ``df`` as Parquet into the shared folder and read it back; this cuts the lineage and survives lost executors."""
    spark = df.sparkSession
    path = fresh_path(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path), path


def written(df: DataFrame, name: str) -> DataFrame:
    return write_table(df, name)[0]


def remove(spark: SparkSession, *paths: str) -> None:
    """Delete intermediate tables that no later plan reads."""
    for path in paths:
        p = spark._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def release(spark: SparkSession) -> None:
    """Let Spark's cleaner drop the shuffle files of plans that are finished."""
    import gc

    gc.collect()
    spark._jvm.System.gc()


def sliced(batches, rows: int = 500):
    """Batches of at most ``rows`` rows, for workers that hold something of every row of a batch. (Spark bounds the bytes
    that a batch carries to a worker, 64 MB by default; the session's settings are left alone.)"""
    for b in batches:
        for a in range(0, b.num_rows, rows):
            yield b.slice(a, rows)


def ascii_lower(col: Column) -> Column:
    return F.translate(col, UPPER, LOWER)


def words_of(text: Column) -> Column:
    """Array of words, A-Z lower-cased; null and empty texts give an empty array."""
    cut = F.split(ascii_lower(F.coalesce(text, F.lit(""))), r"[\x20\x09-\x0D]+")
    return F.filter(cut, lambda w: w != "")


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def hash60(*cols: Column, salt: str = "") -> Column:
    """60 hash bits as a long, from MD5, so that any SQL engine gives the same value; nulls count as empty."""
    text = F.concat(F.lit(salt), *[F.coalesce(c.cast("string"), F.lit("")) for c in cols])
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 15), 16, 10).cast("long")


def source_key(col: Column) -> Column:
    """A non-null key in code-point order of the source, null last."""
    return F.when(col.isNull(), F.lit("t")).otherwise(F.concat(F.lit("s"), col.cast("string")))


def remainder(id_col: Column, modulus: int) -> Column:
    """crc32 of the id as text, modulo; null ids count as empty text."""
    return F.crc32(F.coalesce(id_col.cast("string"), F.lit("")).cast("binary")) % modulus


def column_or_null(df: DataFrame, name: str, kind: str) -> Column:
    return F.col(name).cast(kind) if name in df.columns else F.lit(None).cast(kind)


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def file_system(uri: str):
    """(file system, path) of a folder that all executors reach."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


def make_folder(spark: SparkSession, uri: str) -> None:
    p = spark._jvm.org.apache.hadoop.fs.Path(uri)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).mkdirs(p)


class TaskFile:
    """A file that one task writes into a shared folder: under a name of the attempt, renamed when whole, so that a
    repeated task replaces it with the same bytes."""

    def __init__(self, uri: str, name: str, attempt: int):
        self.fs, base = file_system(uri)
        self.final, self.temp = f"{base}/{name}", f"{base}/.{name}.{attempt}"
        self.out, self.size = self.fs.open_output_stream(self.temp), 0

    def write(self, data: bytes) -> int:
        """Appends; gives the offset of what was written."""
        at = self.size
        self.out.write(data)
        self.size += len(data)
        return at

    def close(self) -> None:
        self.out.close()
        self.fs.move(self.temp, self.final)
