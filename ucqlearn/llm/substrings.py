"""Removal of passages that an earlier document has, over a log-structured fingerprint index.

The index keeps sampled window fingerprints: the fingerprint (anchor) of a window of ``size`` words is the least hash of
the ``gram``-word runs in it, so that equal windows always have equal anchors and neighbours mostly share
theirs. A run of the index is an immutable table (anchor, doc_id, t), bucketed and sorted by anchor, with one count of buckets
for all runs. A new batch becomes a run; it is merge-joined bucket by bucket with the runs of the history, with no exchange of
either, and anchors that two documents share make candidates. Candidates are verified by 128-bit digests of the words of all their
windows under shared anchors. When the runs outnumber ``fanout`` they are merged into one.
"""

from __future__ import annotations

import hashlib
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Workspace, few_files, row_count, small_batches, texts
from .rolling import Words, covered, grouped, mix, sliding_min

BUFFER = 1 << 19
EACH = 10_000  # documents a file
LISTED = 1 << 20  # most ids that are broadcast
SKETCH = "doc_id long, t long, n_words long, same1 long, same2 long, kept_sha256 string, anchors array<long>"


def _anchor_windows(words: Words, size: int, gram: int):
    """(place, anchor) of each window of ``size`` words."""
    hashes = words.hashes()
    if words.n < size:
        return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.uint64)
    every = np.zeros(words.n, dtype=np.uint64)
    place, low = words.windows(hashes, gram)
    every[place] = mix(low ^ np.uint64(0x5851F42D4C957F2D))
    least = sliding_min(every, size - gram + 1)
    whole = np.flatnonzero(np.arange(words.n) + size <= words.first[words.doc + 1])
    return whole, least[whole]


def sketches(size: int, gram: int):
    """Arrow batches of (doc_id, text, t) to one row a document: word count, digests of the word sequence, and the
    distinct anchors of its windows."""

    def run(batches):
        for batch in batches:
            ids, tags = batch.column(0), batch.column(2)
            at = 0
            for some in grouped(texts(batch.column(1)), len, BUFFER):
                split = [x.split() for x in some]
                words = Words(split)
                place, anchor = _anchor_windows(words, size, gram)
                docs = words.doc[place]
                lists = [[]] * len(some)
                if len(place):
                    change = np.flatnonzero(np.concatenate([[True], (anchor[1:] != anchor[:-1]) | (docs[1:] != docs[:-1])]))
                    docs, anchor = docs[change], anchor[change]
                    bounds = np.searchsorted(docs, np.arange(len(some) + 1))
                    lists = [np.unique(anchor[a:b]).view(np.int64) for a, b in zip(bounds, bounds[1:])]
                same = words.documents()
                yield pa.RecordBatch.from_arrays(
                    [
                        ids.slice(at, len(some)),
                        tags.slice(at, len(some)),
                        pa.array([len(w) for w in split], pa.int64()),
                        pa.array(same[0]),
                        pa.array(same[1]),
                        pa.array([hashlib.sha256(b" ".join(w)).hexdigest() for w in split]),
                        pa.array(lists, pa.list_(pa.int64())),
                    ],
                    names=["doc_id", "t", "n_words", "same1", "same2", "kept_sha256", "anchors"],
                )
                at += len(some)

    return run


def candidate_windows(size: int, gram: int):
    """Arrow batches of (doc_id, t, text, anchors) to a row for each window whose anchor is among the anchors."""

    def run(batches):
        for batch in batches:
            rows = zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), texts(batch.column(2)), batch.column(3).to_pylist())
            for some in grouped(rows, lambda r: len(r[2]), BUFFER):
                words = Words([x[2].split() for x in some])
                place, anchor = _anchor_windows(words, size, gram)
                docs = words.doc[place]
                # an anchor counts in its own document only
                salt = mix(np.arange(len(some), dtype=np.uint64) + np.uint64(1))
                wanted = np.concatenate([np.array(x[3], dtype=np.int64).view(np.uint64) ^ salt[d] for d, x in enumerate(some)])
                keep = np.isin(anchor ^ salt[docs], wanted)
                place, docs = place[keep], docs[keep]
                if not len(place):
                    continue
                first, second = words.digests(place, place + size)
                ids, tags = np.array([x[0] for x in some], dtype=np.int64), np.array([x[1] for x in some], dtype=np.int64)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(first), pa.array(second), pa.array(ids[docs]), pa.array(tags[docs]), pa.array((place - words.first[docs]).astype(np.int32))],
                    names=["h1", "h2", "doc_id", "t", "place"],
                )

    return run


def _cut(size: int):
    def run(batches):
        for batch in batches:
            n, removed, digest, kept_text = [], [], [], []
            for text, places in zip(texts(batch.column(2)), batch.column(3).to_pylist()):
                words = text.split()
                gone = covered(np.array(places, dtype=np.int64), size, len(words))
                kept = b" ".join(w for w, g in zip(words, gone) if not g)
                n.append(len(words))
                removed.append(int(gone.sum()))
                digest.append(hashlib.sha256(kept).hexdigest())
                kept_text.append(kept.decode())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(n, pa.int64()), pa.array(removed, pa.int64()), pa.array(digest, pa.string()), pa.array(kept_text, pa.string())], names=["doc_id", "t", "n_words", "n_removed", "kept_sha256", "kept_text"])

    return run


class FingerprintIndex:
    """Bucketed, sorted, immutable runs of (anchor, doc_id, t), oldest first, with a merge of all runs beyond ``fanout``.

    Runs lie under ``folder`` and stay there; ``FingerprintIndex`` over a folder that has runs goes on with them.
    """

    COLUMNS = ("anchor", "doc_id", "t")

    def __init__(self, spark: SparkSession, folder: str, fanout: int = 2, buckets: int = 32):
        self.spark, self.folder, self.fanout, self.buckets = spark, folder.rstrip("/"), fanout, buckets
        self.runs, self.made = [], 0
        for name in _children(spark, self.folder):
            if name.startswith("run-"):
                number, self.buckets = (int(x) for x in name.split("-")[1:])
                self.runs.append((self._table(name), name))
                self.made = max(self.made, number)

    def _table(self, name: str) -> str:
        known = f"run_{uuid.uuid4().hex}"
        columns = ", ".join(f"{c} BIGINT" for c in self.COLUMNS)
        self.spark.sql(f"CREATE TABLE {known} ({columns}) USING parquet CLUSTERED BY (anchor) SORTED BY (anchor) INTO {self.buckets} BUCKETS LOCATION '{self.folder}/{name}'")
        return known

    def _write(self, rows: DataFrame) -> None:
        self.made += 1
        name = f"run-{self.made:06d}-{self.buckets}"
        known = self._table(name)
        rows.select(*self.COLUMNS).repartition(self.buckets, "anchor").sortWithinPartitions("anchor", "doc_id").write.insertInto(known)
        self.runs.append((known, name))

    def tables(self) -> list[DataFrame]:
        return [self.spark.table(known) for known, _ in self.runs]

    def ingest(self, batch: DataFrame) -> DataFrame:
        """Adds a batch (anchor, doc_id, t) and returns the candidate rows: those of the batch and of the history
        whose anchor lies in the batch and in two rows at least. Each anchor's rows are all kept. Call ``compact`` once they are read."""
        history = self.tables()
        self._write(batch)
        new = self.tables()[-1]
        flags = new.groupBy("anchor").agg((F.count(F.lit(1)) > 1).alias("f"))
        for old in history:
            seen = old.groupBy("anchor").agg(F.lit(True).alias("g"))
            flags = flags.join(seen, "anchor", "left").select("anchor", (F.col("f") | F.coalesce("g", F.lit(False))).alias("f"))
        shared = flags.where("f").select("anchor")
        found = new.join(shared, "anchor", "left_semi")
        for old in history:
            found = found.union(old.join(new.select("anchor"), "anchor", "left_semi"))
        return found

    def compact(self, force: bool = False) -> bool:
        """Merges all runs into one if there are more than ``fanout``."""
        if len(self.runs) < 2 or not (force or len(self.runs) > self.fanout):
            return False
        old, merged = list(self.runs), None
        for table in self.tables():
            merged = table if merged is None else merged.union(table)
        self.runs = []
        self._write(merged)
        for known, name in old:
            self.spark.sql(f"DROP TABLE {known}")
            _delete(self.spark, f"{self.folder}/{name}")
        return True


def _file_system(spark: SparkSession, path: str):
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return target, target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


def _children(spark: SparkSession, folder: str) -> list[str]:
    target, system = _file_system(spark, folder)
    return sorted(x.getPath().getName() for x in system.listStatus(target)) if system.exists(target) else []


def _delete(spark: SparkSession, path: str) -> None:
    target, system = _file_system(spark, path)
    system.delete(target, True)


class RepeatIndex:
    """Incremental removal of repeated passages: batches come in order of doc_id, each is compared with itself and all before it.

    ``folder`` keeps the index (anchors, and digests of whole documents) from batch to batch and from session to session.
    """

    DIGESTS = "same1 long, same2 long, first_id long"

    def __init__(self, spark: SparkSession, folder: str | None = None, size: int = 50, gram: int = 16, fanout: int = 2, documents: int = 0):
        """``documents``: about how many a batch has; it sets the number of buckets of a new index, and of files."""
        small_batches(spark)
        self.spark, self.size, self.gram, self.documents = spark, size, gram, max(documents, 1)
        self.work = Workspace(spark, "substrings")
        self.folder = (folder or self.work.path("index")).rstrip("/")
        self.anchors = FingerprintIndex(spark, f"{self.folder}/anchors", fanout, max(1, -(-documents // EACH)))
        self.batches = len(_children(spark, f"{self.folder}/digests"))

    def _known(self) -> DataFrame:
        """The first document of each word sequence in the history."""
        if not self.batches:
            return self.spark.createDataFrame([], self.DIGESTS)
        return self.spark.read.schema(self.DIGESTS).parquet(*[f"{self.folder}/digests/{i:06d}" for i in range(self.batches)])

    def ingest(self, batch: DataFrame, history: DataFrame | None = None) -> DataFrame:
        """doc_id, n_words, n_removed, kept_sha256, kept_text for each row of ``batch`` (doc_id, text). ``history`` has the rows of
        earlier batches (more rows do no harm); their doc_ids must be smaller. The result is written, and the index holds the batch."""
        work, size, gram, n, rows = self.work, self.size, self.gram, self.batches, self.documents
        keyed = _keyed(batch)
        sketch = work.put(keyed.mapInArrow(sketches(size, gram), SKETCH), f"sketch-{n}")
        # documents of one word sequence: all but the first lose everything, and only the first needs the index
        narrow = sketch.select("doc_id", "t", "n_words", "same1", "same2", "kept_sha256")
        whole = narrow.where(F.col("doc_id").isNotNull() & (F.col("n_words") >= size))
        firsts = whole.select("same1", "same2", F.col("doc_id").alias("first_id")).union(self._known()).groupBy("same1", "same2").agg(F.min("first_id").alias("first_id"))
        ruled = narrow.join(firsts, ["same1", "same2"], "left").select("doc_id", "t", "n_words", "same1", "same2", "kept_sha256", (F.col("first_id") < F.col("doc_id")).alias("copy"))
        ruled = work.put(ruled, f"ruled-{n}", rows, each=EACH)
        own = ruled.where("not copy and doc_id is not null").groupBy("same1", "same2").agg(F.min("doc_id").alias("first_id"))
        few_files(own, rows, EACH).write.mode("overwrite").parquet(f"{self.folder}/digests/{n:06d}")
        unique = sketch.select("doc_id", "t", "anchors", "n_words").join(ruled.where("copy").select("doc_id", "t").distinct(), ["doc_id", "t"], "left_anti")
        unique = unique.where(F.col("doc_id").isNotNull() & (F.col("n_words") >= size)).select("doc_id", "t", F.explode("anchors").alias("anchor"))
        found = self.anchors.ingest(unique)
        wanted = work.put(found.groupBy("doc_id", "t").agg(F.collect_set("anchor").alias("anchors")), f"wanted-{n}", rows, each=EACH)
        suspects = self._suspects(keyed if history is None else keyed.union(_keyed(history)), wanted, f"suspects-{n}")
        windows = suspects.mapInArrow(candidate_windows(size, gram), "h1 long, h2 long, doc_id long, t long, place int")
        shared = windows.groupBy("h1", "h2").agg(F.min("doc_id").alias("first_id"), F.max("doc_id").alias("last_id")).where("first_id < last_id").drop("last_id")
        # written, so that both sides of the join are plain shuffles and a window of very many documents can be split
        shared = work.put(shared, f"shared-{n}", rows, each=EACH)
        hits = windows.join(shared, ["h1", "h2"]).where("doc_id > first_id").groupBy("doc_id", "t").agg(F.collect_set("place").alias("places"))
        cut = suspects.select("doc_id", "t", "text").join(hits, ["doc_id", "t"]).select("doc_id", "t", "text", "places")
        cut = cut.mapInArrow(_cut(size), "doc_id long, t long, n_words long, n_removed long, kept_sha256 string, kept_text string")
        cut = cut.select("doc_id", "t", "n_removed", F.col("kept_sha256").alias("cut_sha256"), "kept_text")
        out = ruled.join(cut, ["doc_id", "t"], "left")
        copy = F.coalesce("copy", F.lit(False))
        result = out.select(
            "doc_id",
            "n_words",
            F.when(copy, F.col("n_words")).otherwise(F.coalesce("n_removed", F.lit(0))).cast("long").alias("n_removed"),
            F.when(copy, F.sha2(F.lit("").cast("binary"), 256)).otherwise(F.coalesce("cut_sha256", "kept_sha256")).alias("kept_sha256"),
            F.when(copy, F.lit("")).otherwise(F.col("kept_text")).alias("kept_text"),
        )
        result = work.put(result, f"result-{n}", rows, each=EACH)
        for name in ("sketch", "ruled", "wanted", "suspects", "shared"):
            work.drop(f"{name}-{n}")
        self.batches += 1
        self.anchors.compact()
        return result

    def _suspects(self, keyed: DataFrame, wanted: DataFrame, name: str) -> DataFrame:
        """doc_id, t, text, anchors of the wanted documents, each once. Where their ids can be broadcast, other texts aren't shuffled."""
        if row_count(wanted) <= LISTED:
            keyed = keyed.join(F.broadcast(wanted.select("doc_id", "t")), ["doc_id", "t"], "left_semi")
        texts_once = keyed.dropDuplicates(["doc_id", "t"])
        return self.work.put(texts_once.join(wanted, ["doc_id", "t"]).select("doc_id", "t", "text", "anchors"), name, self.documents, each=EACH)


def _keyed(docs: DataFrame) -> DataFrame:
    return docs.select("doc_id", "text", F.xxhash64(F.coalesce("text", F.lit(""))).alias("t"))


def remove_repeats(spark, docs: DataFrame, size: int = 50, gram: int = 16, batches: int = 3, fanout: int = 2) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256, kept_text for each row of ``docs``. Words are runs without ASCII white space.

    A word goes if a window of ``size`` words over it also starts in a document with a smaller doc_id. kept_text is
    null for a document that keeps all its words, as its text stays as it is. Null, empty and short texts lose
    nothing. A row without doc_id is never compared. Rows that repeat a doc_id count as the same document. The table goes through a
    ``RepeatIndex`` in batches, which are ranges of doc_id of about one size. Other columns are ignored.
    """
    rows = row_count(docs)
    cuts = docs.agg(F.percentile_approx("doc_id", [i / batches for i in range(1, batches)], 1000).alias("q")).first()["q"] if batches > 1 else []
    edges = [None, *sorted(set(cuts or [])), None]
    index, out = RepeatIndex(spark, None, size, gram, fanout, -(-rows // (len(edges) - 1))), None
    for low, high in zip(edges, edges[1:]):
        batch = docs.select("doc_id", "text")
        batch = batch if high is None else batch.where(F.col("doc_id").isNull() | (F.col("doc_id") <= high) if low is None else F.col("doc_id") <= high)
        batch, history = (batch, None) if low is None else (batch.where(F.col("doc_id") > low), docs.where(F.col("doc_id") <= low))
        found = index.ingest(batch, history)
        out = found if out is None else out.union(found)
    return out
