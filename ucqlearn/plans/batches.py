"""Batches and splits by digests of the joined row's number, so that every engine and partitioning gives the same.

Split and batches use different streams of the digest, and every epoch draws its batches anew.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.columns import hash_number


def batch_id(jid: Column, n_batches: int, seed: int = 0, epoch: int = 0) -> Column:
    """A batch for each row, drawn independently for each seed and epoch."""
    return F.pmod(hash_number("batch", seed, epoch, jid), F.lit(n_batches).cast("long")).cast("int")


def is_test(jid: Column, share: int = 15, stream: str = "split") -> Column:
    return F.pmod(hash_number(stream, jid), F.lit(100).cast("long")) < share


def split(rowmap: DataFrame, share: int = 15, stream: str = "split") -> tuple[DataFrame, DataFrame]:
    """(train, test) rows of the map; another ``stream`` cuts a part of its own, such as one for validation."""
    held = is_test(F.col("jid"), share, stream)
    return rowmap.where(~held), rowmap.where(held)


def with_batches(rowmap: DataFrame, n_batches: int, seed: int = 0, epoch: int = 0) -> DataFrame:
    """Every row in one batch, bid."""
    return rowmap.withColumn("bid", batch_id(F.col("jid"), n_batches, seed, epoch))


def poisson_batches(rowmap: DataFrame, n_batches: int, seed: int = 0, epoch: int = 0) -> DataFrame:
    """Each row in each batch with probability 1 / n_batches, independently of all else: what the accountant's amplification
    by sampling asks for. A row comes in none, one or several batches; batches differ in size and may be empty."""
    share = F.lit(int((1 << 63) / n_batches)).cast("long")
    draw = lambda b: F.shiftrightunsigned(F.xxhash64(F.col("jid"), F.lit(seed), F.lit(epoch), b), 1) < share
    rounds = F.filter(F.sequence(F.lit(0), F.lit(n_batches - 1)), draw)
    return rowmap.withColumn("bid", F.explode(rounds))


def alpha(rowmap: DataFrame, names: list[str]) -> DataFrame:
    """tbl, alpha: over all batches, how many different base rows each touches. ``rowmap`` has bid."""
    per = rowmap.groupBy("bid").agg(*[F.count_distinct(f"r_{n}").alias(n) for n in names]).agg(*[F.sum(n).alias(n) for n in names])
    return per.select(F.explode(F.array(*[F.struct(F.lit(n).alias("tbl"), F.col(n).alias("alpha")) for n in names])).alias("p")).select("p.*")
