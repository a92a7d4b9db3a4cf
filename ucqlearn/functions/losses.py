"""Losses as column expressions: value, derivative by the margin, and the proximal step of ADMM."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .columns import argmax, log_loss, sigmoid, softmax


@dataclass(frozen=True)
class SquaredLoss:
    """(m - y)^2 / 2."""

    classes: int = 1
    metric = "rmse"

    def value(self, m: list[Column], y: Column) -> Column:
        return F.lit(0.5) * (m[0] - y) * (m[0] - y)

    def derivative(self, m: list[Column], y: Column) -> list[Column]:
        return [m[0] - y]

    def prox(self, df: DataFrame, rho: float) -> DataFrame:
        """Adds v0: the minimiser of loss(v) - mu v + rho/2 (m - v)^2, from columns m0, mu0, y."""
        return df.withColumn("v0", (F.col("y") + F.col("mu0") + F.lit(rho) * F.col("m0")) / F.lit(1.0 + rho))

    def predicted(self, m: list[Column]) -> Column:
        return m[0]


@dataclass(frozen=True)
class LogisticLoss:
    """log(1 + e^m) - y m for y in {0, 1}."""

    newton: int = 8
    classes: int = 1
    metric = "accuracy"

    def value(self, m, y):
        return log_loss(m[0], y)

    def derivative(self, m, y):
        return [sigmoid(m[0]) - y]

    def prox(self, df, rho):
        """Newton steps from m, each its own projection so that all stay in generated code. Where rho is small the slope
        nearly vanishes off the middle of the curve, so steps are clamped to its width, and there are more of them."""
        kept = df.columns
        df = df.withColumn("v0", F.col("m0"))
        for _ in range(self.newton if rho >= 0.5 else 2 * self.newton):
            p = sigmoid(F.col("v0"))
            step = (p - F.col("y") - F.col("mu0") - F.lit(rho) * (F.col("m0") - F.col("v0"))) / (p * (1 - p) + F.lit(rho))
            bound = F.lit(min(1.0 / rho, 4.0))
            df = df.select(*kept, (F.col("v0") - F.greatest(F.least(step, bound), -bound)).alias("v0"))
        return df

    def predicted(self, m):
        return (m[0] > 0).cast("double")


@dataclass(frozen=True)
class SoftmaxLoss:
    """Cross entropy of the softmax of the margins; y is a class number."""

    classes: int = 2
    newton: int = 6
    metric = "accuracy"

    def value(self, m, y):
        top = F.greatest(*m)
        total, own = F.lit(0.0), F.lit(0.0)
        for c, x in enumerate(m):
            total = total + F.exp(x - top)
            own = own + F.when(y == c, x).otherwise(F.lit(0.0))
        return F.log(total) + top - own

    def derivative(self, m, y):
        return [p - (y == c).cast("double") for c, p in enumerate(softmax(m))]

    def prox(self, df, rho):
        """Newton with the Hessian diag(p) - p p' + rho I, inverted by a rank-one formula; steps are clamped as above."""
        kept, k, bound = df.columns, self.classes, F.lit(min(1.0 / rho, 4.0))
        df = df.select(*kept, *[F.col(f"m{c}").alias(f"v{c}") for c in range(k)])
        for _ in range(self.newton if rho >= 0.5 else 3 * self.newton):
            v = [F.col(f"v{c}") for c in range(k)]
            df = df.select(*kept, *v, *[p.alias(f"_p{c}") for c, p in enumerate(softmax(v))])
            p = [F.col(f"_p{c}") for c in range(k)]
            e = [p[c] - (F.col("y") == c).cast("double") - F.col(f"mu{c}") - F.lit(rho) * (F.col(f"m{c}") - v[c]) for c in range(k)]
            df = df.select(*kept, *v, *p, *[x.alias(f"_e{c}") for c, x in enumerate(e)])
            top = sum((F.col(f"_p{c}") * F.col(f"_e{c}") / (F.col(f"_p{c}") + rho) for c in range(k)), F.lit(0.0))
            low = sum((F.lit(rho) * F.col(f"_p{c}") / (F.col(f"_p{c}") + rho) for c in range(k)), F.lit(0.0))
            df = df.withColumn("_r", top / low)
            step = [(F.col(f"_e{c}") + F.col(f"_p{c}") * F.col("_r")) / (F.col(f"_p{c}") + rho) for c in range(k)]
            df = df.select(*kept, *[(F.col(f"v{c}") - F.greatest(F.least(step[c], bound), -bound)).alias(f"v{c}") for c in range(k)])
        return df

    def predicted(self, m):
        return argmax(m).cast("double")
