"""Joins that Spark has no operator for, composed of those it has."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def salted_join(big: DataFrame, small: DataFrame, key: str, most_rows: int, salts: int = 16) -> DataFrame:
    """Inner join on ``key`` where keys with over ``most_rows`` rows of ``big`` are dealt to ``salts`` tasks, and their rows of
    ``small`` go to each of these. At most rows / most_rows keys are hot, and the list of them is joined like any table."""
    hot = big.groupBy(key).agg(F.count(F.lit(1)).alias("_n")).where(F.col("_n") > most_rows).select(key, F.lit(True).alias("_hot"))
    dealt = F.when(F.col("_hot"), F.pmod(F.xxhash64(*[F.col(c) for c in big.columns]), F.lit(salts)).cast("int")).otherwise(F.lit(0))
    left = big.join(hot, key, "left").withColumn("_salt", dealt).drop("_hot")
    copies = F.sequence(F.lit(0), F.when(F.col("_hot"), F.lit(salts - 1)).otherwise(F.lit(0)))
    right = small.join(hot, key, "left").withColumn("_salt", F.explode(copies)).drop("_hot")
    return left.join(right, [key, "_salt"]).drop("_salt")


def asof_join(left: DataFrame, right: DataFrame, by: str, at: str, value: str) -> DataFrame:
    """Each row of ``left`` with ``value`` from the last row of ``right`` of the same ``by`` whose ``at`` is not later, null if
    there is none. ``right`` has by, at and value. One sort by key and time, and no pairs."""
    kept = F.struct(*[F.col(c) for c in left.columns]).alias("_row")
    a = left.select(F.col(by).alias("_by"), F.col(at).alias("_at"), F.lit(1).alias("_side"), kept, F.lit(None).cast(dict(right.dtypes)[value]).alias("_value"))
    b = right.select(F.col(by).alias("_by"), F.col(at).alias("_at"), F.lit(0).alias("_side"), F.lit(None).cast(a.schema["_row"].dataType).alias("_row"), F.col(value).alias("_value"))
    order = Window.partitionBy("_by").orderBy("_at", "_side").rowsBetween(Window.unboundedPreceding, 0)
    return a.union(b).withColumn("_value", F.last("_value", ignorenulls=True).over(order)).where("_side = 1").select("_row.*", F.col("_value").alias(value))


def range_join(points: DataFrame, ranges: DataFrame, point: str, low: str, high: str, width: float) -> DataFrame:
    """Pairs with low <= point < high. Ranges are cut into buckets of ``width``, and points meet those of their own bucket only."""
    bucket = F.floor(F.col(point) / F.lit(width)).cast("long")
    spread = F.explode(F.sequence(F.floor(F.col(low) / F.lit(width)).cast("long"), F.floor(F.col(high) / F.lit(width)).cast("long")))
    cut = ranges.where(F.col(low) <= F.col(high)).withColumn("_bucket", spread)
    return points.withColumn("_bucket", bucket).join(cut, "_bucket").where((F.col(low) <= F.col(point)) & (F.col(point) < F.col(high))).drop("_bucket")
