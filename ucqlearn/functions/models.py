"""Local models. Parameters are small driver arrays; every pass over rows is a DataFrame plan."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .columns import dot

UNROLL = 64
SMALL = 16  # numbers of a clipped gradient, or of a net, that are summed as columns


def _batch_matrix(column: pa.Array, width: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(-1, width)


CHUNK = 1 << 14  # numbers in a row of partial sums


def _sum_by_shard(df: DataFrame, width: int, work) -> dict[int, np.ndarray]:
    """Sums of ``work(batch) -> {shard: flat array}`` over all batches. Every partition makes one array a shard, cut into chunks;
    equal chunks meet and are added up by tasks, so that the driver gets one array of ``width`` a shard, whatever the number of partitions."""

    def partial(batches):
        total: dict[int, np.ndarray] = {}
        for batch in batches:
            for s, v in work(batch).items():
                total[s] = total[s] + v if s in total else v
        for s, v in total.items():
            for at in range(0, len(v), CHUNK):
                yield pa.RecordBatch.from_arrays([pa.array([s], pa.int32()), pa.array([at], pa.int32()), pa.array([v[at : at + CHUNK].astype(np.float64).tobytes()], pa.binary())], names=["shard", "at", "v"])

    def added(batches):
        total: dict[tuple, np.ndarray] = {}
        for batch in batches:
            for s, at, v in zip(*[c.to_pylist() for c in batch.columns]):
                total[s, at] = total.get((s, at), 0) + np.frombuffer(v)
        if total:
            yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in total], pa.int32()), pa.array([k[1] for k in total], pa.int32()), pa.array([v.tobytes() for v in total.values()], pa.binary())], names=["shard", "at", "v"])

    schema = "shard int, at int, v binary"
    parts: dict[int, dict] = {}
    for r in df.mapInArrow(partial, schema).repartition(max(1, -(-width // CHUNK)), "shard", "at").mapInArrow(added, schema).collect():
        parts.setdefault(r.shard, {})[r.at] = np.frombuffer(bytes(r.v))
    return {s: np.concatenate([p[at] for at in sorted(p)]) for s, p in parts.items()}


def _shards(batch):
    """(shard, mask of its rows) in a batch whose first column is the shard."""
    shards = batch.column(0).to_numpy()
    return [(int(s), shards == s) for s in np.unique(shards)]


def _factor(norms: np.ndarray, clip: float | None) -> np.ndarray:
    return np.ones((len(norms), 1)) if clip is None else np.minimum(1.0, clip / np.maximum(norms, 1e-12))[:, None]


@dataclass(frozen=True)
class LinearModel:
    """u = x' theta, theta of shape (d, C)."""

    d: int
    classes: int = 1

    @property
    def size(self) -> int:
        return self.d * self.classes

    def start(self, seed: int = 0) -> np.ndarray:
        return np.zeros((self.d, self.classes))

    def forward(self, theta, x):
        return None, None, x @ theta

    def gradient_sum(self, theta, x, g, clip: float | None = None) -> np.ndarray:
        """Sum over rows of x outer g, each row's part of norm ``clip`` at most; a part's norm is |x| |g|, so no part is made."""
        norms = np.sqrt(np.einsum("ij,ij->i", x, x) * np.einsum("ij,ij->i", g, g)) if clip is not None else np.zeros(len(x))
        return (x.T @ (g * _factor(norms, clip))).reshape(-1)

    def predict(self, features: DataFrame, theta: np.ndarray) -> DataFrame:
        """rid, shard, u0..; ``features`` has rid, shard, x."""
        u = [x.alias(f"u{c}") for c, x in enumerate(self.outputs(F.col("x"), theta, F.col("shard")))]
        return features.select("rid", "shard", *u)

    def outputs(self, x, theta, shard) -> list:
        """A row's predictions; ``theta`` is one array, or a dict with one for each shard."""
        if not isinstance(theta, dict):
            return [dot(x, theta[:, c]) for c in range(self.classes)]
        return [F.coalesce(*[F.when(shard == s, dot(x, t[:, c])) for s, t in theta.items()]) for c in range(self.classes)]

    def gradient_columns(self) -> list:
        """Sums over rows of x outer g, when few enough to unroll; rows have x and g0.. ."""
        return [F.sum(F.get("x", F.lit(i)) * F.col(f"g{c}")).alias(f"s{i}_{c}") for i in range(self.d) for c in range(self.classes)]

    def row_columns(self, theta: np.ndarray, clip: float | None, rho: float) -> list:
        """Like ``gradient_columns``, for D = g + rho c u and with each row's part clipped."""
        x = [F.get("x", F.lit(i)) for i in range(self.d)]
        g = [F.col(f"g{c}") + (F.lit(rho) * F.col("c") * dot(F.col("x"), theta[:, c]) if rho else F.lit(0.0)) for c in range(self.classes)]
        factor = F.lit(1.0)
        if clip is not None:
            norm = F.sqrt(sum((v * v for v in x), F.lit(0.0))) * F.sqrt(sum((v * v for v in g), F.lit(0.0)))
            factor = F.least(F.lit(1.0), F.lit(float(clip)) / F.greatest(norm, F.lit(1e-12)))
        return [F.sum(x[i] * g[c] * factor).alias(f"s{i}_{c}") for i in range(self.d) for c in range(self.classes)]

    def partial_gradient(self, signal: DataFrame, theta: np.ndarray, clip: float | None = None) -> dict[int, np.ndarray]:
        """Unnormalised gradient of each shard from rows (shard, x, g0..)."""
        if self.size <= UNROLL and clip is None:
            rows = signal.groupBy("shard").agg(*self.gradient_columns()).collect()
            return {r.shard: np.array([r[f"s{i}_{c}"] for i in range(self.d) for c in range(self.classes)]).reshape(self.d, self.classes) for r in rows}
        return row_gradient_sums(self, signal, theta, clip)

    def gram(self, weighted: DataFrame) -> dict[int, np.ndarray]:
        """Sum of c x x' for each shard from rows (shard, x, c); symmetric, so only half is summed."""
        d = self.d
        if len(self.pairs) <= UNROLL:
            return {r.shard: self.gram_matrix(r.total) for r in weighted.groupBy("shard").agg(*self.gram_columns()).select("shard", F.array(*[f"a{i}_{j}" for i, j in self.pairs]).alias("total")).collect()}

        def work(batch):
            x, c = _batch_matrix(batch.column(1), d), batch.column(2).to_numpy().astype(float)
            return {s: ((x[at] * c[at, None]).T @ x[at]).reshape(-1) for s, at in _shards(batch)}

        return {s: v.reshape(d, d) for s, v in _sum_by_shard(weighted.select("shard", "x", "c"), d * d, work).items()}

    @property
    def pairs(self) -> list[tuple[int, int]]:
        return [(i, j) for i in range(self.d) for j in range(i, self.d)]

    def gram_columns(self) -> list:
        """Sums over rows of c x x', one half, when few enough to unroll; rows have x and c."""
        return [F.sum(F.col("c") * F.get("x", F.lit(i)) * F.get("x", F.lit(j))).alias(f"a{i}_{j}") for i, j in self.pairs]

    def gram_matrix(self, half) -> np.ndarray:
        a = np.zeros((self.d, self.d))
        for (i, j), v in zip(self.pairs, half):
            a[i, j] = a[j, i] = v
        return a

    def solve(self, gram: np.ndarray, moment: np.ndarray, rho: float, beta: float, n: int, extra: float = 0.0, before: np.ndarray | None = None) -> np.ndarray:
        """Minimiser of the folded ADMM objective. ``extra`` damps the step towards the predictions of ``before``."""
        left = beta * np.eye(self.d) + (rho + extra) / n * gram
        right = -moment / n + (extra / n * gram @ before if extra else 0.0)
        return np.linalg.lstsq(left, right, rcond=None)[0]


@dataclass(frozen=True)
class MlpModel:
    """d -> hidden -> C with one hidden layer; parameters in one flat array."""

    d: int
    hidden: int = 16
    classes: int = 1
    activation: str = "relu"

    @property
    def size(self) -> int:
        return self.d * self.hidden + self.hidden + self.hidden * self.classes + self.classes

    def start(self, seed: int = 0) -> np.ndarray:
        rng = np.random.default_rng(seed)
        a = rng.uniform(-1, 1, self.d * self.hidden) / np.sqrt(self.d)
        b = rng.uniform(-1, 1, self.hidden * self.classes) / np.sqrt(self.hidden)
        return np.concatenate([a, np.zeros(self.hidden), b, np.zeros(self.classes)])

    def split(self, theta):
        d, h, k = self.d, self.hidden, self.classes
        a, b, c, e = np.split(theta, [d * h, d * h + h, d * h + h + h * k])
        return a.reshape(d, h), b, c.reshape(h, k), e

    def forward(self, theta, x):
        w, b, v, c = self.split(theta)
        z = x @ w + b
        a = np.maximum(z, 0) if self.activation == "relu" else np.tanh(z)
        return z, a, a @ v + c

    def gradient_sum(self, theta, x, g, clip: float | None = None) -> np.ndarray:
        """Sum over rows of the gradient of g * u, each row's of norm ``clip`` at most. A row's norm comes from the norms of
        its layers' factors, so no row's gradient is made."""
        _, _, v, _ = self.split(theta)
        z, a, _ = self.forward(theta, x)
        dz = (g @ v.T) * ((z > 0) if self.activation == "relu" else 1 - a * a)
        square = lambda m: np.einsum("ij,ij->i", m, m)
        f = _factor(np.sqrt((square(x) + 1) * square(dz) + (square(a) + 1) * square(g)), clip)
        dz, g = dz * f, g * f
        return np.concatenate([(x.T @ dz).reshape(-1), dz.sum(axis=0), (a.T @ g).reshape(-1), g.sum(axis=0)])

    def _layers(self, theta):
        """Features, slopes and values of the hidden layer, and outputs, as columns of rows with x. What is missing is NaN, as in arrays."""
        w, b, v, c = self.split(theta)
        x = [F.coalesce(F.get("x", F.lit(i)), F.lit(math.nan)) for i in range(self.d)]
        z = [sum((x[i] * F.lit(float(w[i, j])) for i in range(self.d)), F.lit(0.0)) + F.lit(float(b[j])) for j in range(self.hidden)]
        if self.activation == "relu":
            a, slope = [F.when(m <= 0, F.lit(0.0)).otherwise(m) for m in z], [F.isnan(m) | (m <= 0) for m in z]
            slope = [F.when(off, F.lit(0.0)).otherwise(F.lit(1.0)) for off in slope]
        else:
            a = [F.tanh(m) for m in z]
            slope = [F.lit(1.0) - m * m for m in a]
        return x, a, slope, [sum((a[j] * F.lit(float(v[j, i])) for j in range(self.hidden)), F.lit(0.0)) + F.lit(float(c[i])) for i in range(self.classes)]

    def predict(self, features: DataFrame, theta: np.ndarray) -> DataFrame:
        """Small nets are columns, which generated code computes; others go through Python."""
        d, k = self.d, self.classes
        if self.size <= SMALL:
            return features.select("rid", "shard", *[u.alias(f"u{c}") for c, u in enumerate(self._layers(theta)[3])])

        def run(batches):
            for batch in batches:
                u = self.forward(theta, _batch_matrix(batch.column(2), d))[2]
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *[pa.array(u[:, c]) for c in range(k)]], names=["rid", "shard", *[f"u{c}" for c in range(k)]])

        return features.select("rid", "shard", "x").mapInArrow(run, f"rid {dict(features.dtypes)['rid']}, shard int, " + ", ".join(f"u{c} double" for c in range(k)))

    def row_columns(self, theta: np.ndarray, clip: float | None, rho: float) -> list:
        """Sums over rows of the gradient of D * u, in the order of the flat array, for D = g + rho c u and with each row's part clipped."""
        v = self.split(theta)[2]
        x, a, slope, u = self._layers(theta)
        g = [F.col(f"g{c}") + (F.lit(rho) * F.col("c") * u[c] if rho else F.lit(0.0)) for c in range(self.classes)]
        dz = [sum((g[c] * F.lit(float(v[j, c])) for c in range(self.classes)), F.lit(0.0)) * slope[j] for j in range(self.hidden)]
        factor = F.lit(1.0)
        if clip is not None:
            square = lambda m: sum((e * e for e in m), F.lit(0.0))
            norm = F.sqrt((square(x) + 1) * square(dz) + (square(a) + 1) * square(g))
            factor = F.least(F.lit(1.0), F.lit(float(clip)) / F.greatest(norm, F.lit(1e-12)))
        parts = [*[x[i] * m for i in range(self.d) for m in dz], *dz, *[m * e for m in a for e in g], *g]
        return [F.sum(p * factor).alias(f"p{i}") for i, p in enumerate(parts)]

    def partial_gradient(self, signal: DataFrame, theta: np.ndarray, clip: float | None = None) -> dict[int, np.ndarray]:
        return row_gradient_sums(self, signal, theta, clip)


def row_gradient_sums(model, signal: DataFrame, theta, clip: float | None = None, rho: float = 0.0, counts: dict[int, int] | None = None) -> dict[int, np.ndarray]:
    """Sum over rows of du/dtheta * D for each shard, each row's part clipped to L2 norm ``clip``; ``counts`` gets each shard's rows.

    ``signal`` has shard, x, g0.. and, with ``rho``, c. D is g, plus rho * c * u for the folded ADMM objective, u being
    the prediction under ``theta`` (one array, or a dict with one for each shard)."""
    d, k = model.d, model.classes
    shape = model.start().shape
    if model.size <= SMALL and not isinstance(theta, dict):
        sums = [*model.row_columns(theta, clip, rho), F.count(F.lit(1)).alias("n")]
        found = signal.groupBy("shard").agg(*sums).collect()
        if counts is not None:
            counts |= {r.shard: r.n for r in found}
        return {r.shard: np.array(r[1:-1], float).reshape(shape) for r in found}

    def work(batch):
        x = _batch_matrix(batch.column(1), d)
        g = np.column_stack([batch.column(2 + c).to_numpy() for c in range(k)])
        out = {}
        for s, at in _shards(batch):
            own = theta[s] if isinstance(theta, dict) else theta
            rows = g[at]
            if rho:
                rows = rows + rho * batch.column(2 + k).to_numpy()[at, None] * model.forward(own, x[at])[2]
            out[s] = np.append(model.gradient_sum(own, x[at], rows, clip), len(rows))
        return out

    wanted = signal.select("shard", "x", *[f"g{c}" for c in range(k)], *(["c"] if rho else []))
    found = _sum_by_shard(wanted, model.size + 1, work)
    if counts is not None:
        counts |= {s: int(v[-1]) for s, v in found.items()}
    return {s: v[:-1].reshape(shape) for s, v in found.items()}
