"""Quality by co-training: one classifier sees the text, the other the page's metadata, and each labels for the other.

The text view is naive Bayes over the words, word pairs and runs of character kinds that a text has; the metadata view is naive
Bayes over language, source and recorded size. Neither sees anything of the other's columns. Both learn from sums of
counts alone, so a round is one pass over the whole table: every document without a label that one view is sure of adds its features, under
that label, to the counts of the other view. Only the labelled rows that a fit starts from are a bounded sample
(``most_labelled``). They are dealt into three: counts, calibration of the views, and combination of the calibrated views.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Workspace, small_batches, texts
from .linear import DenseRows, fit_logistic, sigmoid
from .rolling import Words, grouped

SHAPE_BITS, WORD_BITS, META_BITS = 14, 16, 14
BUFFER = 1 << 19
SHAPE = 5  # character kinds in a run
SMOOTH = 0.5
COLUMNS = ("text", "lang", "source", "n_chars")


def _kinds() -> bytes:
    """Letters and all bytes beyond ASCII are one kind, digits one and blanks one; other characters stand for themselves."""
    out = bytearray(range(256))
    for c in range(256):
        if c >= 128 or chr(c).isalpha():
            out[c] = ord("a")
        elif chr(c).isdigit():
            out[c] = ord("0")
        elif chr(c) in " \t\r\x0b\f":
            out[c] = ord(" ")
    return bytes(out)


KINDS = _kinds()
LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def shape_features(some: list[bytes]) -> list[np.ndarray]:
    """For each text the bucket of each run of ``SHAPE`` character kinds."""
    a = np.frombuffer(b"".join(some).translate(KINDS), dtype=np.uint8).astype(np.uint64)
    n = max(len(a) - SHAPE + 1, 0)
    h = np.zeros(n, dtype=np.uint64)
    for j in range(SHAPE):
        h = (h ^ a[j : j + n]) * np.uint64(0x100000001B3)
    h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h >> np.uint64(64 - SHAPE_BITS)).astype(np.int64)
    ends = np.cumsum([len(x) for x in some])
    return [h[e - len(x) : max(e - SHAPE + 1, e - len(x))] for e, x in zip(ends, some)]


def word_features(some: list[bytes]) -> list[np.ndarray]:
    """For each text the bucket of each word and each pair of words."""
    words = Words([x.translate(LOWER).split() for x in some])
    hashes = words.hashes()
    place, pairs = words.windows(hashes, 2)
    ones, twos = ((h >> np.uint64(64 - WORD_BITS)).astype(np.int64) for h in (hashes, pairs))
    cuts = np.searchsorted(place, words.first)
    return [np.concatenate([ones[a:b], twos[c:d]]) for a, b, c, d in zip(words.first, words.first[1:], cuts, cuts[1:])]


def meta_features(lang, source, n_chars) -> np.ndarray:
    """Buckets of the language, the source, both together, and the recorded size by powers of two."""
    size = -1 if n_chars is None else int(max(n_chars, 0)).bit_length()
    return np.array([zlib.crc32(repr(x).encode()) >> (32 - META_BITS) for x in (("lang", lang), ("source", source), ("both", lang, source), ("size", size))], dtype=np.int64)


#: name, bits and view of the groups of features.
GROUPS = (("shape", SHAPE_BITS, "text"), ("word", WORD_BITS, "text"), ("meta", META_BITS, "meta"))
VIEWS = ("text", "meta")


def features(rows):
    """Distinct buckets of each document (text, lang, source, n_chars), group by group, found without sorting them."""
    marks = [np.zeros(1 << bits, dtype=bool) for _, bits, _ in GROUPS]

    def distinct(seen: np.ndarray, found: np.ndarray) -> np.ndarray:
        if len(found) < 64:
            return np.unique(found)
        seen[found] = True
        out = np.flatnonzero(seen)
        seen[out] = False
        return out

    for some in grouped(rows, lambda r: len(r[0]), BUFFER):
        raw = [r[0] for r in some]
        for r, shape, word in zip(some, shape_features(raw), word_features(raw)):
            yield [distinct(m, f) for m, f in zip(marks, (shape, word, meta_features(*r[1:])))]


def no_counts() -> list[np.ndarray]:
    return [np.zeros((2, 1 << bits), dtype=np.float64) for _, bits, _ in GROUPS]


def ratios(counts: list[np.ndarray]) -> list[np.ndarray]:
    """Log ratio of each feature's smoothed share in good and in other documents."""
    shares = [np.log(c + SMOOTH) - np.log(c.sum(axis=1, keepdims=True) + SMOOTH * c.shape[1]) for c in counts]
    return [(s[1] - s[0]).astype(np.float32) for s in shares]


def margins(tables: list[np.ndarray], found: list[np.ndarray]) -> tuple[float, ...]:
    """Mean log ratio of the features of each group; 0 for a group without any."""
    return tuple(float(t[f].mean(dtype=np.float64)) if len(f) else 0.0 for t, f in zip(tables, found))


@dataclass
class Calibrated:
    """Logistic regression on the margins of a view's groups."""

    groups: tuple
    mean: np.ndarray
    scale: np.ndarray
    weights: np.ndarray
    intercept: float

    @classmethod
    def fit(cls, view: str, x: np.ndarray, y: np.ndarray, l2: float = 1e-3):
        groups = tuple(i for i, g in enumerate(GROUPS) if g[2] == view)
        x = x[:, groups]
        mean, scale = (x.mean(axis=0), x.std(axis=0)) if len(x) else (np.zeros(len(groups)), np.ones(len(groups)))
        scale[scale < 1e-9] = 1.0
        w, b = fit_logistic(DenseRows((x - mean) / scale), y, len(groups), l2)
        return cls(groups, mean, scale, w, b)

    def logit(self, x: np.ndarray) -> np.ndarray:
        return ((np.atleast_2d(x)[:, self.groups] - self.mean) / self.scale) @ self.weights + self.intercept


@dataclass
class QualityModel:
    tables: list
    text: Calibrated
    meta: Calibrated
    combine: np.ndarray
    intercept: float
    handed: list  # for each round: documents that the text view, and the metadata view, called (not good, good) for the other

    def score(self, x: np.ndarray):
        a, b = self.text.logit(x), self.meta.logit(x)
        return sigmoid(a), sigmoid(b), sigmoid(np.column_stack([a, b]) @ self.combine + self.intercept)


def _rows(batch, first: int = 0):
    return zip(texts(batch.column(first)), *[batch.column(first + i).to_pylist() for i in (1, 2, 3)])


_SUMS = "grp int, label int, bucket long, n long"


def _emit(counts, documents):
    """Non-zero counts, and under group -1 - view the number of documents."""
    out = [(g, label, np.flatnonzero(counts[g][label])) for g in range(len(GROUPS)) for label in (0, 1)]
    parts = [(np.full(len(b), g), np.full(len(b), label), b, counts[g][label][b].astype(np.int64)) for g, label, b in out]
    parts += [(np.array([-1 - v] * 2), np.array([0, 1]), np.zeros(2, dtype=np.int64), documents[v]) for v in range(2)]
    columns = [np.concatenate(c) for c in zip(*parts)]
    types = (pa.int32(), pa.int32(), pa.int64(), pa.int64())
    yield pa.RecordBatch.from_arrays([pa.array(c.astype(t.to_pandas_dtype()), t) for c, t in zip(columns, types)], names=[x.split()[0] for x in _SUMS.split(", ")])


def _label_counts(batches):
    """(text, lang, source, n_chars, quality) to the counts of both views."""
    counts, documents = no_counts(), np.zeros((2, 2), dtype=np.int64)
    for batch in batches:
        for found, y in zip(features(_rows(batch)), batch.column(4).to_pylist()):
            for c, f in zip(counts, found):
                c[y, f] += 1
            documents[:, y] += 1
    yield from _emit(counts, documents)


def _handing(shared, sure: float):
    """(text, lang, source, n_chars) of documents without a label to the counts that each view gets from the other."""

    def run(batches):
        tables, views = shared.value
        counts, documents = no_counts(), np.zeros((2, 2), dtype=np.int64)
        for batch in batches:
            for found in features(_rows(batch)):
                x = np.array([margins(tables, found)])
                for v, view in enumerate(VIEWS):
                    p = float(sigmoid(views[v].logit(x))[0])
                    if max(p, 1 - p) < sure:
                        continue
                    y = int(p >= 0.5)
                    documents[v, y] += 1
                    for g, (_, _, owner) in enumerate(GROUPS):
                        if owner != view:
                            counts[g][y, found[g]] += 1
        yield from _emit(counts, documents)

    return run


def _collected(sums: DataFrame) -> tuple[list[np.ndarray], np.ndarray]:
    """Counts and documents from ``_SUMS``: as many rows as there are buckets, whatever the table's size."""
    rows = sums.groupBy("grp", "label", "bucket").agg(F.sum("n").alias("n")).toArrow()
    g, label, bucket, n = (rows.column(i).to_numpy() for i in range(4))
    counts, documents = no_counts(), np.zeros((2, 2))
    for i, c in enumerate(counts):
        some = g == i
        c[label[some], bucket[some]] = n[some]
    for v in range(2):
        some = g == -1 - v
        documents[v, label[some]] = n[some]
    return counts, documents


def _margins(shared):
    def run(batches):
        tables = shared.value
        for batch in batches:
            x = np.array([margins(tables, found) for found in features(_rows(batch))]).reshape(-1, len(GROUPS))
            yield pa.RecordBatch.from_arrays([pa.array(list(x), pa.list_(pa.float64())), batch.column(4), batch.column(5)], names=["x", "quality", "fold"])

    return run


def train_quality(spark, docs: DataFrame, labels: DataFrame, most_labelled: int = 12_000, rounds: int = 2, sure: float = 0.95, trust: float = 1.0) -> QualityModel:
    """Learns from at most ``most_labelled`` labelled rows that are not held out (crc32 of doc_id mod 4 is 2), taken by the smallest
    hashes of doc_id, and from all other rows of ``docs``. Documents a view is ``sure`` of count for the other view; all that are handed
    over in a class weigh at most ``trust`` times what the labelled ones of that class do. Repeated labels count once,
    null labels not at all. Without labels every score is a half."""
    from .toxicity import held_out

    small_batches(spark)
    work = Workspace(spark, "quality")
    known = labels.where("doc_id is not null and quality in (0, 1)").where(~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max("quality").cast("int").alias("quality"))
    picked = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most_labelled)
    picked = work.put(picked.select("doc_id", "quality", (F.crc32(F.concat(F.lit("fold "), F.col("doc_id").cast("string")).cast("binary")) % 5).cast("int").alias("fold")), "picked")
    plain = docs.select("doc_id", *COLUMNS)
    # both joins broadcast at most most_labelled rows
    sample = work.put(plain.join(F.broadcast(picked), "doc_id").select(*COLUMNS, "quality", "fold"), "sample", most_labelled, exchange=True, each=2_500)
    pool = plain.join(F.broadcast(picked.select("doc_id")), "doc_id", "left_anti").select(*COLUMNS)
    base, labelled = _collected(sample.where("fold < 3").select(*COLUMNS, "quality").mapInArrow(_label_counts, _SUMS))
    fresh = sample.where("fold >= 3")
    counts, handed = base, []
    for turn in range(rounds + 1):
        tables = ratios(counts)
        rows = fresh.mapInArrow(_margins(spark.sparkContext.broadcast(tables)), "x array<double>, quality int, fold int").toPandas()
        x, y, fold = np.array(rows.x.tolist()).reshape(-1, len(GROUPS)), rows.quality.to_numpy(dtype=float), rows.fold.to_numpy()
        order = np.lexsort((*x.T, y))  # rows come in any order
        x, y, fold = x[order], y[order], fold[order]
        views = [Calibrated.fit(v, x[fold == 3], y[fold == 3]) for v in VIEWS]
        if turn == rounds:
            break
        more, documents = _collected(pool.mapInArrow(_handing(spark.sparkContext.broadcast((tables, views)), sure), _SUMS))
        handed.append(documents.astype(int).tolist())
        # what the text view called weighs in the metadata view's counts, and the other way round
        weight = np.minimum(1.0, trust * labelled[0] / np.maximum(documents, 1))
        counts = [b + m * weight[1 - VIEWS.index(owner)][:, None] for b, m, (_, _, owner) in zip(base, more, GROUPS)]
    logits = np.column_stack([v.logit(x[fold == 4]) for v in views]) if len(x) else np.zeros((0, 2))
    w, b = fit_logistic(DenseRows(logits), y[fold == 4], 2, 1e-4)
    work.drop()
    return QualityModel(tables, *views, w, b, handed)


def score_quality(spark, docs: DataFrame, model: QualityModel) -> DataFrame:
    """Every column of ``docs`` in a struct ``row``, and text_score, meta_score, score (0 to 1, higher: better). Null text counts
    as empty, and other nulls are values of their own."""
    from pyspark.sql.types import DoubleType, StructField, StructType

    small_batches(spark)
    shared = spark.sparkContext.broadcast(model)
    row_type = StructType([StructField(f.name, f.dataType, True) for f in docs.schema])
    schema = StructType([StructField("row", row_type), *[StructField(c, DoubleType()) for c in ("text_score", "meta_score", "score")]])

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            x = np.array([margins(shared.value.tables, found) for found in features(_rows(batch))])
            yield pa.RecordBatch.from_arrays([batch.column(4), *[pa.array(v, pa.float64()) for v in shared.value.score(x)]], names=["row", "text_score", "meta_score", "score"])

    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")
    return docs.select(*[F.col(c).alias(c) for c in COLUMNS], row).mapInArrow(run, schema)
