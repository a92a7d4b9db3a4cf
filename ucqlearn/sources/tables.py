"""Readers, shard catalogues and written artifacts."""

from __future__ import annotations

import atexit
import json
import re
import shutil
import tempfile
import uuid

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "labels")


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load_all(spark, sf_dir: str, names=TABLES) -> dict[str, DataFrame]:
    return {n: load_table(spark, sf_dir, n) for n in names}


def read(spark, path: str, format: str, schema=None, **options) -> DataFrame:
    """csv, json, orc or parquet, with a declared schema for the formats that have none of their own."""
    if schema is None and format in ("csv", "json"):
        raise ValueError(f"{format} needs a schema")
    reader = spark.read.format(format).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def shards(df: DataFrame, by: str, count: int) -> DataFrame:
    """The table with a shard column, by its key modulo ``count``."""
    return df.withColumn("shard", F.pmod(F.col(by), F.lit(count)).cast("int"))


def shards_from_paths(spark, paths: list[str], format: str = "parquet", schema=None) -> list[DataFrame]:
    return [read(spark, p, format, schema) for p in paths]


def shared_folder(spark: SparkSession, label: str) -> str:
    """A new folder's URI under spark.checkpoint.dir, which driver and executors share. Without that setting a local session, as
    in tests, gets a temporary one, and a cluster is refused. Folders of the file scheme are removed when the driver's Python ends."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base is None:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        base = tempfile.mkdtemp(prefix="ucqlearn_")
        atexit.register(shutil.rmtree, base, ignore_errors=True)
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(base)
    uri = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).makeQualified(path).toString()
    uri = f"{re.sub(r'^file:/+', 'file:///', uri).rstrip('/')}/{label}-{uuid.uuid4().hex[:12]}"
    if uri.startswith("file:///"):
        atexit.register(shutil.rmtree, uri.removeprefix("file://"), ignore_errors=True)
    return uri


class ArtifactStore:
    """Row maps, states and signals as parquet in the shared folder."""

    def __init__(self, spark: SparkSession, path: str | None = None):
        self.spark = spark
        self.root = path.rstrip("/") if path else shared_folder(spark, "store")
        self.made = 0

    def label(self, name: str) -> str:
        """A name that no other artifact has, so that plans over earlier ones stay readable."""
        self.made += 1
        return f"{name}-{self.made}"

    def write(self, name: str, df: DataFrame, partition_by: list[str] | None = None, bucket_by: str | None = None, buckets: int = 0, file_rows: int = 0) -> DataFrame:
        """With ``buckets`` the rows lie in that many files by the hash of ``bucket_by``, and artifacts of one count join and group by
        that column without an exchange. Rows that come in such parts already are not moved either. Without, they stay where they are
        and ``file_rows`` cuts a task's rows into files, so that many tasks can read what few have written."""
        if buckets:
            df = df.repartition(buckets, bucket_by)
        writer = df.write.mode("overwrite")
        writer = writer.partitionBy(*partition_by) if partition_by else writer
        if not buckets:
            writer = writer.option("maxRecordsPerFile", file_rows) if file_rows else writer
            writer.parquet(f"{self.root}/{name}")
            return self.read(name, df.schema)
        known = f"artifact_{uuid.uuid4().hex}"
        conf, key = self.spark.conf, "spark.sql.maxConcurrentOutputFileWriters"
        before = conf.get(key)
        if not partition_by:  # a task has one bucket's rows, so they need no sort by bucket before they are written
            conf.set(key, "2")
        try:
            writer.bucketBy(buckets, bucket_by).option("path", f"{self.root}/{name}").format("parquet").saveAsTable(known)
        finally:
            conf.set(key, before)
        return self.spark.table(known)

    def read(self, name: str, schema=None) -> DataFrame:
        found = self.spark.read.schema(schema) if schema is not None else self.spark.read
        return found.parquet(f"{self.root}/{name}")

    def drop(self, name: str = "") -> None:
        target = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{self.root}/{name}".rstrip("/"))
        target.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


BUCKET_BYTES = 2 << 20  # of the files behind a table, for each bucket of what is made from it
MOST_BUCKETS = 8192  # beyond that buckets grow


def bucket_count(df: DataFrame) -> int:
    """Buckets for artifacts of the size of ``df``, by the bytes of the files it is read from."""
    leaves = df._jdf.queryExecution().optimizedPlan().collectLeaves()
    sizes = [int(str(leaves.apply(i).stats().sizeInBytes())) for i in range(leaves.size())]
    known = sum(x for x in sizes if x < 1 << 60)  # of rows without files Spark knows no size
    return max(1, min(-(-known // BUCKET_BYTES), MOST_BUCKETS))


def parameter_rows(spark, thetas: dict[str, np.ndarray]) -> DataFrame:
    """tbl, i, j, value: one row for each parameter."""
    return step_rows(spark, [thetas]).drop("step")


def step_rows(spark, steps: list[dict[str, np.ndarray]]) -> DataFrame:
    """step (from 1), tbl, i, j, value: one row for each parameter of each step."""
    rows = [(s, n, int(i), int(j), float(v)) for s, thetas in enumerate(steps, 1) for n, t in thetas.items() for (i, j), v in np.ndenumerate(np.atleast_2d(t if t.ndim > 1 else t[:, None]))]
    return spark.createDataFrame(rows, "step int, tbl string, i int, j int, value double")


def save_model(spark, path: str, thetas: dict[str, np.ndarray], **about) -> None:
    parameter_rows(spark, thetas).coalesce(1).write.mode("overwrite").parquet(f"{path}/parameters")
    shapes = {n: list(t.shape) for n, t in thetas.items()}
    spark.createDataFrame([(json.dumps({"shapes": shapes} | about),)], "about string").coalesce(1).write.mode("overwrite").text(f"{path}/about")


def load_model(spark, path: str) -> tuple[dict[str, np.ndarray], dict]:
    about = json.loads(spark.read.text(f"{path}/about").first()[0])
    out = {n: np.zeros(s) for n, s in about.pop("shapes").items()}
    for r in spark.read.parquet(f"{path}/parameters").collect():
        t = out[r.tbl]
        if t.ndim == 1:
            t[r.i] = r.value
        else:
            t[r.i, r.j] = r.value
    return out, about
