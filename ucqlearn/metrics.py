"""Accuracy, error, curves and what is read off them."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def accuracy(scored: DataFrame) -> DataFrame:
    """One row: the share of rows whose ``pred`` is ``y``."""
    return scored.agg(F.avg((F.col("pred") == F.col("y")).cast("double")).alias("accuracy"))


def rmse(scored: DataFrame) -> DataFrame:
    return scored.agg(F.sqrt(F.avg((F.col("pred") - F.col("y")) * (F.col("pred") - F.col("y")))).alias("rmse"))


def row_values(loss) -> list:
    """What ``summary`` averages over rows with m0.. and y: the loss, and the squared error or whether the prediction is right."""
    m = [F.col(f"m{c}") for c in range(loss.classes)]
    pred = loss.predicted(m)
    return [loss.value(m, F.col("y")), (pred - F.col("y")) * (pred - F.col("y")) if loss.metric == "rmse" else (pred == F.col("y")).cast("double")]


def summary(scored: DataFrame, loss, by: list | None = None) -> DataFrame:
    """rows, loss, metric (rmse or accuracy) of rows with m0.. and y."""
    value, error = row_values(loss)
    metric = F.sqrt(F.avg(error)) if loss.metric == "rmse" else F.avg(error)
    aggs = [F.count(F.lit(1)).alias("rows"), F.avg(value).alias("loss"), metric.alias("metric")]
    return scored.groupBy(*by).agg(*aggs) if by else scored.agg(*aggs)


def with_time(history: DataFrame, costs: DataFrame) -> DataFrame:
    """Adds the running communication time to a curve: ``costs`` has method, epoch, seconds."""
    running = Window.partitionBy("method").orderBy("epoch").rowsBetween(Window.unboundedPreceding, 0)
    return history.join(costs.withColumn("time", F.sum("seconds").over(running)), ["method", "epoch"])


def time_to_target(curve: DataFrame, target: float, lower_is_better: bool) -> DataFrame:
    """method, epoch, time: where each curve first meets the target."""
    met = F.col("metric") <= target if lower_is_better else F.col("metric") >= target
    return curve.where(met).groupBy("method").agg(F.min("epoch").alias("epoch"), F.min("time").alias("time"))


def dp_drop(private: float, plain: float, lower_is_better: bool) -> float:
    return private - plain if lower_is_better else plain - private


def best_epoch(history: DataFrame, lower_is_better: bool) -> DataFrame:
    order = F.col("metric") if lower_is_better else F.col("metric").desc()
    ranked = history.withColumn("_k", F.row_number().over(Window.partitionBy("method").orderBy(order, "epoch")))
    return ranked.where("_k = 1").drop("_k")
