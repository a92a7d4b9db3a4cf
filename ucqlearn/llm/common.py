"""Helpers shared by the operators: shared workspace, table access and text batches."""

from __future__ import annotations

import ctypes
import time

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import shared_folder

SPACE = " \t\n\x0b\f\r"


class Workspace:
    """Written intermediate tables in the shared folder; they cut lineage and survive lost executors."""

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        self.root = shared_folder(spark, label)

    def path(self, name: str) -> str:
        return f"{self.root}/{name}"

    def put(self, df: DataFrame, name: str, rows: int | None = None, exchange: bool = False, each: int = 50_000) -> DataFrame:
        """``rows``: about how many rows a narrow table has, so that it isn't cut into many small files. ``exchange``
        keeps the work that makes the rows in all its tasks, where merging partitions would leave it to a few. ``each``: rows
        a file."""
        if rows is not None:
            df = df.repartition(max(1, -(-rows // each))) if exchange else few_files(df, rows, each)
        # no file that marks success: the driver would start two processes to make it, and its memory counts twice while one starts
        df.write.option("mapreduce.fileoutputcommitter.marksuccessfuljobs", "false").mode("overwrite").parquet(self.path(name))
        return self.get(name, df.schema)

    def get(self, name: str, schema) -> DataFrame:
        return self.spark.read.schema(schema).parquet(self.path(name))

    def drop(self, name: str = "") -> None:
        hadoop = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self.path(name) if name else self.root)
        hadoop.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(hadoop, True)


def few_files(df: DataFrame, rows: int, each: int = 50_000) -> DataFrame:
    """The same rows in fewer partitions, as a narrow result of ``rows`` rows needs no more. It only merges, and never
    moves rows between executors; the number of partitions grows with the rows."""
    return df.coalesce(max(1, -(-rows // each)))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ascii_lower(text: Column) -> Column:
    """Lower-cases A-Z only. Spark's own lower() is used where the text is pure ASCII, as it is the faster."""
    upper = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
    return F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(F.translate(text, upper, upper.lower()))


def space_words(text: Column) -> Column:
    """Array of the maximal runs without ASCII white space; empty for null or blank text."""
    bare = F.trim(text, F.lit(SPACE))
    return F.when(F.coalesce(F.length(bare), F.lit(0)) == 0, F.array().cast("array<string>")).otherwise(F.split(bare, "[\\x20\\x09-\\x0D]+"))


def small_batches(spark: SparkSession) -> None:
    """Batches of 8 MB to and from Python, so that its memory doesn't grow with the length of texts."""
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", "8m")


def _give_back() -> None:
    """Free memory of Arrow's pool and of the C library goes back to the system, where the C library can do so."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def lean(run, seconds: float = 0.25):
    """``run`` for mapInArrow, giving free memory back between batches, at most once in ``seconds``, and at the end. Python workers
    serve task after task, and would else each keep the most that any batch of any task has taken."""

    def eased(batches):
        last = time.monotonic()
        for batch in batches:
            yield batch
            del batch
            if time.monotonic() - last > seconds:
                _give_back()
                last = time.monotonic()

    def wrapped(batches):
        try:
            yield from run(eased(batches))
        finally:
            _give_back()

    return wrapped


def texts(column: pa.Array | pa.ChunkedArray) -> list[bytes]:
    """UTF-8 bytes of each value; null counts as empty."""
    return [x or b"" for x in column.cast(pa.binary()).to_pylist()]


def row_count(df: DataFrame) -> int:
    return df.agg(F.count(F.lit(1))).first()[0]
