"""Row ids. They need to be unique; density matters only where batches are cut from them."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .ucq import SpecError


def natural(df: DataFrame, column: str) -> DataFrame:
    """rid from a column that is checked to be unique and never null."""
    row = df.agg(F.count(F.lit(1)).alias("n"), F.count_distinct(column).alias("k")).first()
    if row.n != row.k:
        raise SpecError(f"{column} is not a unique id: {row.n} rows, {row.k} values")
    return df.withColumn("rid", F.col(column))


def ordered(df: DataFrame) -> DataFrame:
    """rid by order over all columns, from 0. One task orders all rows: for small tables and tests."""
    return df.withColumn("rid", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(*df.columns)).cast("long") - 1)


def ranked(df: DataFrame, by: list[str], store, name: str) -> DataFrame:
    """Dense rid in the order of ``by``, over all tasks: a range-partitioned sort is written, its parts are counted, and
    each row's place in its part is added to the rows before the part."""
    sorted_rows = df.repartitionByRange(*by).sortWithinPartitions(*by).withColumn("_part", F.spark_partition_id()).withColumn("_at", F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1)))
    written = store.write(name, sorted_rows)
    sizes = written.groupBy("_part").agg(F.count(F.lit(1)).alias("_n"))
    before = sizes.select("_part", (F.sum("_n").over(Window.partitionBy(F.lit(0)).orderBy("_part")) - F.col("_n")).alias("_before"))
    return written.join(F.broadcast(before), "_part").withColumn("rid", F.col("_before") + F.col("_at")).drop("_part", "_at", "_before")


def content_hash(df: DataFrame) -> DataFrame:
    """rid from a 64-bit hash of all columns, checked to be free of collisions and equal rows."""
    return natural(df.withColumn("rid", F.xxhash64(*df.columns)), "rid")


def monotonic(df: DataFrame, store, name: str) -> DataFrame:
    """Spark's increasing ids, written at once because computing them again may change them."""
    return store.write(name, df.withColumn("rid", F.monotonically_increasing_id()))
