"""Differential privacy of labels and of the local updates, and what it spends."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .functions.columns import argmax, hash_uniform, laplace_from_uniform, vec_norm


def label_epsilon(lam: float) -> float:
    """Privacy of labels under Laplace noise of standard deviation ``lam`` on one-hot labels."""
    return 2 * math.sqrt(2) / lam


def label_lambda(epsilon: float) -> float:
    return 2 * math.sqrt(2) / epsilon


def noisy_labels(df: DataFrame, label: str, rid: str, classes: int, lam: float, seed: int | None = 0, y_range: tuple[float, float] | None = None) -> DataFrame:
    """Replaces the label before it is uploaded. Classes: noise on each place of the one-hot label, then the greatest place.
    One class stands for numbers: labels are clipped to ``y_range`` (low, high), which must be public, and get noise of standard
    deviation lam * (high - low) / 2, so that ``label_epsilon(lam)`` holds for them as well. ``seed`` None draws from the system;
    seeded noise is for tests only."""
    if seed is None:
        import secrets

        seed = secrets.randbits(62)
    if classes == 1:
        if y_range is None:
            raise ValueError("numeric labels need a bounded range")
        low, high = map(float, y_range)
        noise = laplace_from_uniform(hash_uniform(seed, F.col(rid), F.lit(0)), lam * (high - low) / 2)
        return df.withColumn(label, F.greatest(F.lit(low), F.least(F.lit(high), F.col(label).cast("double"))) + noise)
    places = [F.when(F.col(label) == c, 1.0).otherwise(0.0) + laplace_from_uniform(hash_uniform(seed, F.col(rid), F.lit(c)), lam) for c in range(classes)]
    return df.withColumn(label, argmax(places))


def numeric_label_epsilon(std: float, low: float, high: float) -> float:
    """Of noise of standard deviation ``std`` on numbers between low and high."""
    return (high - low) * math.sqrt(2) / std


def flip_rate(lam: float) -> float:
    """Share of binary labels that the noise changes: the difference of two Laplace draws exceeds 1."""
    b = lam / math.sqrt(2)
    return (0.5 + 1 / (4 * b)) * math.exp(-1 / b)


def clip(gradient: Column, most: float) -> Column:
    """The array scaled to an L2 norm of ``most`` at most."""
    norm = vec_norm(gradient)
    scale = F.least(F.lit(1.0), F.lit(float(most)) / F.greatest(norm, F.lit(1e-12)))
    return F.transform(gradient, lambda x: x * scale)


@dataclass(frozen=True)
class DpSpec:
    """Clipping norm and noise of local updates. ``unit`` is what one may add or remove unnoticed: a base row with all its joined
    rows, or one joined row. SGD clips the parts of that unit. ADMM folds, and clips folded parts under both units; a joined row
    can move such a part by twice the clip, and the noise is twice as large. What is clipped is the data's part of a
    gradient: the penalty's depends on no row, and is added afterwards. The epsilon is that of one table's releases."""

    clip: float = 1.0
    sigma: float = 1.0
    unit: str = "base_row"
    seed: int | None = 0

    def rng(self) -> np.random.Generator:
        return np.random.default_rng(self.seed)  # None: from the operating system


def add_noise(total: np.ndarray, dp: DpSpec, rng: np.random.Generator, times: float = 1.0) -> np.ndarray:
    """``times``: how many clips one unit can move the total by."""
    return total + rng.normal(0.0, dp.sigma * dp.clip * times, size=total.shape)


ORDERS = tuple(range(2, 65))


def _log_moment(alpha: int, rate: float, sigma: float) -> float:
    """Renyi divergence of order alpha of the subsampled Gaussian, times alpha - 1, by the binomial expansion."""
    if rate >= 1.0:
        return alpha * (alpha - 1) / (2 * sigma * sigma)
    logs = []
    for k in range(alpha + 1):
        term = math.lgamma(alpha + 1) - math.lgamma(k + 1) - math.lgamma(alpha - k + 1) + (alpha - k) * math.log1p(-rate) + k * math.log(rate)
        logs.append(term + k * (k - 1) / (2 * sigma * sigma))
    top = max(logs)
    return top + math.log(sum(math.exp(x - top) for x in logs))


def epsilon_spent(sigma: float, rate: float, steps: int, delta: float) -> float:
    """Epsilon of ``steps`` noisy steps, each on a share ``rate`` of the rows, by Renyi composition over integer orders."""
    if sigma <= 0:
        return math.inf
    return min(steps * _log_moment(a, rate, sigma) / (a - 1) + math.log(1 / delta) / (a - 1) for a in ORDERS)


def sigma_for(epsilon: float, rate: float, steps: int, delta: float) -> float:
    low, high = 0.05, 1e4
    for _ in range(80):
        mid = math.sqrt(low * high)
        low, high = (low, mid) if epsilon_spent(mid, rate, steps, delta) <= epsilon else (mid, high)
    return high


def sigma_asymptotic(epsilon: float, rate: float, steps: int, delta: float, c2: float = 2.0) -> float:
    """The known form c2 * rate * sqrt(steps * log(1/delta)) / epsilon; its constant is a parameter."""
    return c2 * rate * math.sqrt(steps * math.log(1 / delta)) / epsilon


def steps_taken(outer: int, inner: int = 1, local: int = 1) -> int:
    return outer * inner * local


def privacy_report(rowmap: DataFrame, names: list[str], epsilon: float, delta: float) -> DataFrame:
    """tbl, most_rows, group_epsilon: a base row takes part in up to ``most_rows`` joined rows, so that protection stated for
    a joined row weakens to that many times for a base row where joined rows are clipped."""
    parts = [rowmap.groupBy(f"r_{n}").count().agg(F.max("count").alias("most_rows")).select(F.lit(n).alias("tbl"), "most_rows") for n in names]
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    return out.select("tbl", "most_rows", (F.col("most_rows") * epsilon).alias("group_epsilon"), F.lit(delta).alias("joined_row_delta"))
