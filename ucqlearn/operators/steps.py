"""The three physical operators. The join operator stands in the server and sees ids, labels and predictions; the union
operator coordinates the shards of one table; the client operator works on a table's rows."""

from __future__ import annotations

from dataclasses import dataclass, replace
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.models import SMALL, UNROLL, LinearModel, row_gradient_sums


HASHED = 500_000  # rows a bucket may have to be joined by hash
FILE_ROWS = 1 << 17  # of the map in a file, where it isn't bucketed
OWN = "own_"  # before the names of the lead's shard and features where they lie beside the row map


@dataclass
class Block:
    """Client side of one table: rid, shard, x."""

    name: str
    rows: DataFrame
    model: object
    shards: int = 1
    bucketed: bool = False  # by rid, as the row map is
    lookup: str = "merge"  # how bucketed rows are joined


@dataclass
class Problem:
    """Everything a fit needs. ``rowmap`` has jid, r_<table>.. and y; ``folded`` is false where the tables are slices of the
    materialised join, whose row ids are joined rows."""

    spark: object
    blocks: list[Block]
    rowmap: DataFrame
    loss: object
    store: object
    n: int
    folded: bool = True
    known: dict[str, int] | None = None  # base rows in use, once counted
    lead: str | None = None  # the table by whose row ids the row map and that table's own rows are bucketed
    buckets: int = 0
    cut: "Problem | None" = None  # the slices of the materialised join, once they are written
    own: tuple = ()  # columns of the row map with the lead's shard and features, where a lead's row is in one joined row at most

    @property
    def used(self) -> dict[str, int]:
        """Base rows in use by table. Counted when first asked for; fits count what they send as they go."""
        if self.known is None:
            self.known = {n: self.rowmap.select(f"r_{n}").distinct().count() for n in self.names} if self.folded else {n: self.n for n in self.names}
        return self.known

    @property
    def lookup(self) -> str:
        """How a bucket's rows meet the lead's: by hash where a bucket is small, by sorting, which can spill, where it isn't."""
        return "shuffle_hash" if self.buckets and self.n <= self.buckets * HASHED else "merge"

    @property
    def layout(self) -> dict:
        """How rows of the map are written: in buckets of the lead's row ids, or as they come where the lead's rows lie beside them, as
        no round joins or folds those. One bucket is kept, as it moves little."""
        if self.own and self.buckets > 1:
            return {"file_rows": FILE_ROWS}
        return {"bucket_by": f"r_{self.lead}", "buckets": self.buckets}

    def beside(self, rows: DataFrame, name: str) -> bool:
        """Whether ``rows`` carry the shard and the features of this table, which then needs no join and no fold."""
        return bool(self.own) and name == self.lead and set(self.own) <= set(rows.columns)

    def own_shard(self):
        """The lead's shard in such rows."""
        return F.col(self.own[0]) if next(b for b in self.blocks if b.name == self.lead).shards > 1 else F.lit(0)

    def own_x(self):
        """The lead's features in such rows."""
        return F.col(self.own[1]) if self.own[1:] == (f"{OWN}x",) else F.array(*[F.col(c) for c in self.own[1:]])

    @property
    def names(self) -> list[str]:
        return [b.name for b in self.blocks]

    @property
    def classes(self) -> int:
        return self.loss.classes

    def vertical(self) -> "Problem":
        """Every table as one client."""
        return replace(self, blocks=[replace(b, rows=b.rows.withColumn("shard", F.lit(0)), shards=1) for b in self.blocks], cut=None)


class ClientOperator:
    """compute: predictions, partial gradients, Gram matrices and local solutions of one table."""

    def __init__(self, block: Block):
        self.block, self.model = block, block.model

    def predict(self, theta) -> DataFrame:
        """rid, u0..; ``theta`` is one array, or a dict with one for each shard."""
        if isinstance(theta, dict):
            parts = [self.model.predict(self.block.rows.where(F.col("shard") == s), t) for s, t in theta.items()]
            return reduce(DataFrame.unionByName, parts).drop("shard")
        return self.model.predict(self.block.rows, theta).drop("shard")

    def receive(self, signal: DataFrame) -> DataFrame:
        """Joins the server's signal (rid, g0.., c) to the rows it is for, unless it lies beside them."""
        if "x" in signal.columns:
            return signal
        return self.block.rows.join(signal.hint(self.block.lookup) if self.block.bucketed else signal, "rid")

    def gram(self, fan: DataFrame) -> dict[int, np.ndarray]:
        return self.model.gram(self.receive(fan).select("shard", "x", "c"))


class UnionOperator:
    """compute: sums of partial gradients, or the consensus of local parameters."""

    def __init__(self, block: Block):
        self.block = block

    @staticmethod
    def add(partials: dict[int, np.ndarray], shape) -> np.ndarray:
        return sum(partials.values(), np.zeros(shape))

    @staticmethod
    def consensus(thetas: dict[int, np.ndarray], duals: dict[int, np.ndarray], beta: float, rho: float, weight: int) -> np.ndarray:
        """Shrunk average of the shards' parameters and scaled duals."""
        mean = sum(thetas.values()) / len(thetas) + sum(duals.values()) / len(duals)
        return weight * rho * mean / (beta + weight * rho)


class JoinOperator:
    """gather, compute and scatter over the row map."""

    def __init__(self, problem: Problem):
        self.problem, self.classes = problem, problem.classes

    def predict(self, rowmap: DataFrame, clients: dict[str, ClientOperator], thetas: dict) -> dict:
        """Each table's predictions for ``gather``: rid, u0.., or columns where the table's rows lie beside the map."""
        made = {}
        for name, c in clients.items():
            beside = self.problem.beside(rowmap, name) and isinstance(c.model, LinearModel)
            made[name] = c.model.outputs(self.problem.own_x(), thetas[name], self.problem.own_shard()) if beside else c.predict(thetas[name])
        return made

    def replay(self, state: DataFrame, clients: dict[str, ClientOperator], thetas: list[dict]) -> DataFrame:
        """Adds u_<table>_<class>_<epoch> to the rows for each of ``thetas``, in one join a table. Linear tables only."""
        columns = lambda c, x, shard: [u.alias(f"u_{c.block.name}_{i}_{j}") for j, t in enumerate(thetas) for i, u in enumerate(c.model.outputs(x, t[c.block.name], shard))]
        for name, c in clients.items():
            if self.problem.beside(state, name):
                state = state.select("*", *columns(c, self.problem.own_x(), self.problem.own_shard()))
            else:
                state = state.join(c.block.rows.select(F.col("rid").alias(f"r_{name}"), *columns(c, F.col("x"), F.col("shard"))), f"r_{name}")
        return state

    def gather(self, rowmap: DataFrame, predictions: dict, keep: bool = False) -> DataFrame:
        """Adds m0.. to the rows: the sum of the tables' predictions. ``keep`` leaves each table's as u_<table>_<class>."""
        out = rowmap
        # the lead comes last: where another join has dealt the rows out anew, they come back to its buckets, in which they are folded
        for name, u in sorted(predictions.items(), key=lambda x: x[0] == self.problem.lead):
            if isinstance(u, list):
                out = out.select("*", *[x.alias(f"u_{name}_{c}") for c, x in enumerate(u)])
                continue
            u = u.hint(self.problem.lookup) if name == self.problem.lead else u  # as many rows as the map, and in its buckets: no broadcast
            out = out.join(u.select(F.col("rid").alias(f"r_{name}"), *[F.col(f"u{c}").alias(f"u_{name}_{c}") for c in range(self.classes)]), f"r_{name}")
        sums = [reduce(lambda a, b: a + b, [F.col(f"u_{n}_{c}") for n in predictions]).alias(f"m{c}") for c in range(self.classes)]
        parts = [f"u_{n}_{c}" for n in predictions for c in range(self.classes)] if keep else []
        return out.select(*rowmap.columns, *sums, *parts)

    def derivatives(self, scored: DataFrame) -> DataFrame:
        d = self.problem.loss.derivative([F.col(f"m{c}") for c in range(self.classes)], F.col("y"))
        return scored.select("*", *[x.alias(f"d{c}") for c, x in enumerate(d)])

    def fold(self, rows: DataFrame, name: str, columns: list, more: tuple = ()) -> DataFrame:
        """rid, g0.., c: values summed over the joined rows of each base row; before that each task sums its own rows. Where the table's
        rows lie beside the map there is nothing to sum, and their shard, x and the columns ``more`` stay with the signal."""
        rid = F.col(f"r_{name}").alias("rid")
        if self.problem.beside(rows, name):
            return rows.select(rid, self.problem.own_shard().alias("shard"), self.problem.own_x().alias("x"), *[x.alias(f"g{c}") for c, x in enumerate(columns)], F.lit(1).cast("long").alias("c"), *more)
        if not self.problem.folded:
            return rows.select(rid, *[x.alias(f"g{c}") for c, x in enumerate(columns)], F.lit(1).cast("long").alias("c"))
        return rows.groupBy(rid).agg(*[F.sum(x).alias(f"g{c}") for c, x in enumerate(columns)], F.count(F.lit(1)).alias("c"))


def partial_gradients(received: dict[str, DataFrame], blocks: list[Block], thetas: dict, clip: float | None = None, counts: dict[str, int] | None = None, also: dict[str, np.ndarray] | None = None) -> dict[str, dict[int, np.ndarray]]:
    """Each table's gradient by shard. The small ones of all tables, of linear models and nets, come from one Spark job: sums are made where the
    rows are, and the driver gets a row for each shard. ``counts`` gets the rows that each table received; ``also`` the sums of the
    columns also0.. of a table whose rows have some."""
    counts = {} if counts is None else counts
    out: dict[str, dict[int, np.ndarray]] = {}
    small = lambda b: b.model.size <= (UNROLL if isinstance(b.model, LinearModel) else SMALL)
    together = [b for b in blocks if small(b) and clip is None]
    if together:
        parts = []
        for b in together:
            rest = [F.coalesce(F.sum(c), F.lit(0.0)) for c in received[b.name].columns if c.startswith("also")]
            found = b.model.gradient_columns() if isinstance(b.model, LinearModel) else b.model.row_columns(thetas[b.name], None, 0.0)
            sums = [F.array(*found).alias("total"), F.count(F.lit(1)).alias("n"), F.array(*rest).cast("array<double>").alias("also")]
            parts.append(received[b.name].groupBy("shard").agg(*sums).select(F.lit(b.name).alias("tbl"), "shard", "total", "n", "also"))
        for r in reduce(DataFrame.unionByName, parts).collect():
            b = next(b for b in together if b.name == r.tbl)
            if also is not None and r.also:
                also[b.name] = also.get(b.name, 0.0) + np.array(r.also)
            counts[b.name] = counts.get(b.name, 0) + r.n
            out.setdefault(b.name, {})[r.shard] = np.array(r.total, float).reshape(b.model.start().shape)
    for b in blocks:
        if b not in together:
            rows: dict[int, int] = {}
            out[b.name] = row_gradient_sums(b.model, received[b.name], thetas[b.name], clip, counts=rows)
            counts[b.name] = sum(rows.values())
    for b in blocks:
        out.setdefault(b.name, {})
    return out


def gram_matrices(blocks: list[Block], fans: dict[str, DataFrame]) -> dict[str, tuple[dict[int, np.ndarray], int]]:
    """Each linear table's Gram matrices by shard, and how many of its rows have a fan-out. Those small enough to unroll come from one Spark job."""
    out: dict[str, tuple[dict, int]] = {}
    parts = []
    for b in blocks:
        if len(b.model.pairs) > UNROLL:
            out[b.name] = ClientOperator(b).gram(fans[b.name]), fans[b.name].count()
            continue
        out[b.name] = {}, 0
        sums = ClientOperator(b).receive(fans[b.name]).groupBy("shard").agg(*b.model.gram_columns(), F.count(F.lit(1)).alias("n"))
        parts.append(sums.select(F.lit(b.name).alias("tbl"), "shard", F.array(*[f"a{i}_{j}" for i, j in b.model.pairs]).alias("total"), "n"))
    for r in reduce(DataFrame.unionByName, parts).collect() if parts else []:
        grams, n = out[r.tbl]
        grams[r.shard] = next(b for b in blocks if b.name == r.tbl).model.gram_matrix(r.total)
        out[r.tbl] = grams, n + r.n
    return out
