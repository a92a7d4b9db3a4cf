"""Benchmark decontamination: a broadcast hash set of test n-grams against every window of every document."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Workspace, lean, texts

# bytes that belong to a word after lower-casing A-Z: digits, a-z and everything beyond ASCII
_WORD = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))


def normal_words(text: bytes) -> list[bytes]:
    return text.translate(_WORD).split()


class BenchmarkIndex:
    """The windows of all items, by length: sorted 64-bit keys over word numbers, and the exact windows behind them."""

    def __init__(self, items: list[tuple[int, list[bytes]]], size: int):
        self.size = size
        self.number: dict[bytes, int] = {}
        self.windows: dict[int, dict[tuple[int, ...], set[int]]] = {}
        for item, words in items:
            ids = tuple(self.number.setdefault(w, len(self.number)) for w in words)
            if ids:
                n = min(size, len(ids))
                for i in range(len(ids) - n + 1):
                    self.windows.setdefault(n, {}).setdefault(ids[i : i + n], set()).add(item)
        rng = np.random.default_rng(20240229)
        self.factors = rng.integers(1, 1 << 63, size=size, dtype=np.uint64) | np.uint64(1)
        self.keys = {n: np.unique(self._hash(np.array(list(ws), dtype=np.uint64))) for n, ws in self.windows.items()}

    def _hash(self, rows: np.ndarray) -> np.ndarray:
        """rows: one window a row."""
        return ((rows + np.uint64(1)) * self.factors[: rows.shape[1]]).sum(axis=1, dtype=np.uint64)

    def scan(self, words: list[bytes]) -> tuple[np.ndarray, set[int]]:
        """Mask of the words inside an occurrence of a window, and the items that have one."""
        get = self.number.get
        ids = np.fromiter((get(w, -1) for w in words), dtype=np.int64, count=len(words))
        hit, items = np.zeros(len(words), dtype=bool), set()
        known = np.concatenate([[0], np.cumsum(ids >= 0)])
        for n, keys in self.keys.items():
            if len(ids) < n:
                continue
            place = np.flatnonzero(known[n:] - known[:-n] == n)  # windows of known words only
            if not len(place):
                continue
            total = np.zeros(len(place), dtype=np.uint64)
            for j in range(n):
                total += (ids[place + j].astype(np.uint64) + np.uint64(1)) * self.factors[j]
            at = np.minimum(np.searchsorted(keys, total), len(keys) - 1)
            for p in place[keys[at] == total]:
                found = self.windows[n].get(tuple(ids[p : p + n].tolist()))
                if found:
                    hit[p : p + n] = True
                    items |= found
        return hit, items


def _spans(mask: np.ndarray) -> list[tuple[int, int]]:
    edges = np.flatnonzero(np.diff(np.concatenate([[0], mask.astype(np.int8), [0]])))
    return list(zip(edges[::2].tolist(), edges[1::2].tolist()))


def without_words(text: bytes, spans: list[tuple[int, int]]) -> bytes:
    """The text with each span of words, and what lies inside it, replaced by a line break."""
    shown = text.translate(_WORD)
    starts, at = [], 0
    for w in shown.split():
        at = shown.index(w, at)
        starts.append((at, at + len(w)))
        at += len(w)
    out, at = [], 0
    for a, b in spans:
        out += [text[at : starts[a][0]], b"\n"]
        at = starts[b - 1][1]
    return b"".join([*out, text[at:]])


SCHEMA = "n_words long, n_hit long, items array<long>, spans array<struct<first:int,end:int>>, cleaned string"


def decontaminate(spark, docs: DataFrame, benchmark: DataFrame, size: int = 10, most_items: int = 2_000_000) -> DataFrame:
    """Every column of ``docs`` in a struct ``row``, and n_words, n_hit, items (distinct, ascending), spans of hit words, cleaned.

    ``cleaned`` is the text without its hit spans, null if nothing is hit. Null, empty and wordless texts have no
    words and no hits. Items without words, null items and repeated items have no effect of their own; an empty
    benchmark hits nothing. The windows of the benchmark are broadcast once, after a count: a benchmark of more
    than ``most_items`` windows is cut into parts of that size, scanned one after the other, so that memory stays bounded.
    """
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")
    wordy = benchmark.where("item_id is not null and text is not null").select("item_id", "text")
    sized = wordy.select(F.sum(F.octet_length("text") / 2 + 1).alias("n")).first()["n"] or 0
    parts = max(1, -(-int(sized) // most_items))
    out = None
    for part in range(parts):
        some = wordy if parts == 1 else wordy.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(parts)) == part)
        items = [(r.item_id, normal_words(r.text.encode())) for r in some.toLocalIterator()]
        shared = spark.sparkContext.broadcast(BenchmarkIndex(items, size))
        found = docs.select(F.col("text").alias("text"), row).mapInArrow(lean(_scanner(shared)), _with_row(docs)) if out is None else out.mapInArrow(lean(_rescanner(shared)), out.schema)
        out = found if part == parts - 1 else Workspace(spark, "leaks").put(found, "part")
    return out


def _with_row(docs: DataFrame):
    from pyspark.sql.types import StructField, StructType, _parse_datatype_string

    return StructType([StructField("row", StructType([StructField(f.name, f.dataType, True) for f in docs.schema])), *_parse_datatype_string(SCHEMA).fields])


def _arrow_rows(rows, found):
    """found: (n_words, mask, items, text) of each row."""
    counts, hits, items, spans, cleaned = [], [], [], [], []
    for n, mask, some, text in found:
        pieces = _spans(mask) if some else []
        counts.append(n)
        hits.append(int(mask.sum()))
        items.append(sorted(some))
        spans.append([{"first": a, "end": b} for a, b in pieces])
        cleaned.append(without_words(text, pieces).decode() if pieces else None)
    kind = pa.list_(pa.struct([("first", pa.int32()), ("end", pa.int32())]))
    return pa.RecordBatch.from_arrays(
        [rows, pa.array(counts, pa.int64()), pa.array(hits, pa.int64()), pa.array(items, pa.list_(pa.int64())), pa.array(spans, kind), pa.array(cleaned, pa.string())],
        names=["row", "n_words", "n_hit", "items", "spans", "cleaned"],
    )


def _scanner(shared):
    def run(batches):
        index = shared.value
        for batch in batches:
            found = []
            for text in texts(batch.column(0)):
                words = normal_words(text)
                found.append((len(words), *index.scan(words), text))
            yield _arrow_rows(batch.column(1), found)

    return run


def _rescanner(shared):
    """Adds the hits of a further part of the benchmark to rows that were scanned before."""

    def run(batches):
        index = shared.value
        for batch in batches:
            rows, found = batch.column(0), []
            for text, items, spans in zip(texts(rows.field("text")), batch.column(3).to_pylist(), batch.column(4).to_pylist()):
                words = normal_words(text)
                mask, more = index.scan(words)
                for s in spans:
                    mask[s["first"] : s["end"]] = True
                found.append((len(words), mask, more | set(items), text))
            yield _arrow_rows(rows, found)

    return run


def items_digest(items: list[int]) -> str:
    return hashlib.sha256(",".join(sorted(map(str, items))).encode()).hexdigest()
