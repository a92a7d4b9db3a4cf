"""Toxicity: a linear classifier over character n-grams scaled by naive Bayes log-count ratios.

The labelled rows to learn from are a bounded sample (``most_labelled``, smallest hashes of doc_id first); every other step
covers all rows. The n-grams of whole texts are hashed into 2**bits buckets and counted once a text. On the sample, each
bucket's ratio is r = log((p + a) / |p|) - log((q + a) / |q|), p and q being the toxic and other texts that have it; buckets
whose ratio is far from 0 for its standard error are kept, and a logistic regression is fitted on presence times r.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Workspace, lean, small_batches
from .linear import SparseRows, fit_logistic, sigmoid

U = np.uint64


@dataclass(frozen=True)
class GramSpec:
    low: int = 4
    high: int = 6
    bits: int = 20

    def buckets(self, text: str) -> list[np.ndarray]:
        """Bucket of each n-gram, one array for each n. The text is lower-cased, its white space is made single spaces
        and one is put at both ends, so that n-grams know where words begin and end."""
        codes = np.frombuffer(f" {' '.join(text.lower().split())} ".encode("utf-32-le", "surrogatepass"), dtype=np.uint32).astype(U) + U(1)
        out, h, power = [], np.zeros(len(codes), dtype=U), 1
        for n in range(1, self.high + 1):
            k = len(codes) - n + 1
            if k <= 0:
                break
            h = h[:k] + codes[n - 1 :] * U(power)
            power = power * 0x9E3779B97F4A7C15 % (1 << 64)
            if n >= self.low:
                x = (h ^ (h >> U(29))) * U(0xBF58476D1CE4E5B9)
                out.append((((x ^ (x >> U(32))) * U(0x94D049BB133111EB)) >> U(64 - self.bits)).astype(np.int64))
        return out


def held_out(doc_id: Column) -> Column:
    return F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2


class ToxicityModel:
    """Weights by bucket (0 for buckets without a say) and an intercept."""

    def __init__(self, spec: GramSpec, weights: np.ndarray, intercept: float):
        self.spec, self.weights, self.intercept = spec, weights.astype(np.float32), intercept

    def score(self, text: str) -> float:
        found = [b[self.weights[b] != 0] for b in self.spec.buckets(text)]
        used = np.unique(np.concatenate([*found, np.zeros(0, dtype=np.int64)]))
        return float(sigmoid(self.intercept + float(self.weights[used].sum(dtype=np.float64))))


def _count_grams(spec: GramSpec):
    def run(batches):
        counts = np.zeros((2, 1 << spec.bits), dtype=np.int32)
        for batch in batches:
            for text, y in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                seen = np.unique(np.concatenate([*spec.buckets(text or ""), np.zeros(0, dtype=np.int64)]))
                counts[int(y == 1), seen] += 1
        used = np.flatnonzero(counts.any(axis=0))
        for at in range(0, len(used), 100_000):
            some = used[at : at + 100_000]
            yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(counts[1][some].astype(np.int64)), pa.array(counts[0][some].astype(np.int64))], names=["bucket", "p", "q"])

    return run


def _kept_grams(spec: GramSpec, place: np.ndarray):
    def run(batches):
        for batch in batches:
            lists = []
            for text in batch.column(0).to_pylist():
                found = place[np.concatenate([*spec.buckets(text or ""), np.zeros(0, dtype=np.int64)])]
                lists.append(np.unique(found[found >= 0]))
            yield pa.RecordBatch.from_arrays([pa.array(lists, pa.list_(pa.int32())), batch.column(1)], names=["ids", "toxic"])

    return run


def train_toxicity(spark, docs: DataFrame, labels: DataFrame, most_labelled: int = 20_000, spec: GramSpec = GramSpec(), smooth: float = 1.0, least_texts: int = 5, least_z: float = 3.5, most_grams: int = 60_000, l2: float = 1e-4) -> ToxicityModel:
    """Learns from rows of ``docs`` with a label (doc_id, toxic) that are not held out. Repeated and null labels count once or
    not at all. Without labels of both classes the model gives their share to every text."""
    known = labels.where("doc_id is not null and toxic in (0, 1)").where(~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    picked = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most_labelled)  # bounded, so it can be broadcast
    small_batches(spark)
    work = Workspace(spark, "toxicity")
    sample = work.put(docs.select("doc_id", "text").join(F.broadcast(picked), "doc_id").select("text", "toxic"), "sample", most_labelled, exchange=True, each=2_500)
    n = {r.toxic: r.n for r in sample.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    texts_p, texts_q = n.get(1, 0), n.get(0, 0)
    # one row of sums a bucket, and the buckets that come through the test are bounded by most_grams
    counts = sample.mapInArrow(lean(_count_grams(spec)), "bucket long, p long, q long").groupBy("bucket").agg(F.sum("p").alias("p"), F.sum("q").alias("q")).where(F.col("p") + F.col("q") >= least_texts)
    p, q = F.col("p") + smooth, F.col("q") + smooth
    ratio = F.log(p / F.lit(texts_p + 2 * smooth)) - F.log(q / F.lit(texts_q + 2 * smooth))
    error = F.sqrt(1 / p + 1 / q)
    kept = counts.select("bucket", ratio.alias("r"), (F.abs(ratio) / error).alias("z")).where(F.col("z") >= least_z).orderBy(F.col("z").desc(), "bucket").limit(most_grams).collect()
    buckets, ratios = np.array([k.bucket for k in kept], dtype=np.int64), np.array([k.r for k in kept])
    place = np.full(1 << spec.bits, -1, dtype=np.int32)
    place[buckets] = np.arange(len(kept))
    rows = sample.mapInArrow(lean(_kept_grams(spec, place)), "ids array<int>, toxic int").toArrow().combine_chunks()
    lists, y = rows.column("ids").combine_chunks(), rows.column("toxic").to_numpy().astype(float)
    ids, starts = lists.flatten().to_numpy(zero_copy_only=False), np.concatenate([[0], np.cumsum(lists.value_lengths().to_numpy(zero_copy_only=False))]).astype(np.int64)
    w, intercept = fit_logistic(SparseRows(ids, starts, ratios), y, len(kept), l2)
    work.drop()
    weights = np.zeros(1 << spec.bits, dtype=np.float32)
    weights[buckets] = w * ratios
    return ToxicityModel(spec, weights, intercept)


def score_toxicity(spark, docs: DataFrame, model: ToxicityModel) -> DataFrame:
    """Every column of ``docs`` in a struct ``row``, and score (0 to 1). Whole texts; null counts as empty."""
    from pyspark.sql.types import DoubleType, StructField, StructType

    small_batches(spark)
    shared = spark.sparkContext.broadcast((model.spec, model.weights, model.intercept))
    row_type = StructType([StructField(f.name, f.dataType, True) for f in docs.schema])

    def run(batches):
        own = ToxicityModel(*shared.value)
        for batch in batches:
            scores = [own.score(t or "") for t in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(1), pa.array(scores, pa.float64())], names=["row", "score"])

    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")
    return docs.select(F.col("text").alias("text"), row).mapInArrow(lean(run), StructType([StructField("row", row_type), StructField("score", DoubleType())]))
