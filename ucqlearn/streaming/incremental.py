"""Structured Streaming: the map and the fan-out kept up by new label rows, folded SGD by micro-batch, windows over events."""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.steps import ClientOperator, JoinOperator, UnionOperator, partial_gradients
from ..plans import mapping
from ..plans.ucq import UcqSpec
from ..sources.tables import ArtifactStore


def stream_row_map(ucq: UcqSpec, label_stream: DataFrame, extracts: dict[str, DataFrame]) -> DataFrame:
    """Row map of a stream of label-table extracts (rid, k_.., y) against the other tables' static extracts."""
    return mapping.build_row_map(ucq, {**extracts, ucq.label_table.name: label_stream})


def run_available(df: DataFrame, each, store: ArtifactStore, mode: str = "append") -> None:
    """Runs a query over what is there now, a batch at a time, with its progress in the shared folder."""
    writer = df.writeStream.outputMode(mode).foreachBatch(each).option("checkpointLocation", f"{store.root}/{store.label('progress')}")
    query = writer.trigger(availableNow=True).start()
    query.awaitTermination()
    if query.exception():
        raise query.exception()


def file_stream(spark, path: str, schema, files_per_batch: int = 1, format: str = "parquet") -> DataFrame:
    return spark.readStream.schema(schema).format(format).option("maxFilesPerTrigger", files_per_batch).load(path)


class FanOutState:
    """Counts by base row, written anew for each batch; a batch that comes twice is counted once."""

    def __init__(self, spark, store: ArtifactStore, name: str):
        self.spark, self.store, self.name, self.done, self.table = spark, store, name, -1, None

    def add(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id <= self.done:
            return
        fresh = mapping.fan_out(batch, self.name)
        total = fresh if self.table is None else self.table.union(fresh).groupBy("rid").agg(F.sum("c").alias("c"))
        self.table = self.store.write(self.store.label("fanout"), total)
        self.done = batch_id


def stream_fan_out(spark, ucq: UcqSpec, sf_dir: str, name: str, files: int = 4) -> DataFrame:
    """The fan-out of table ``name``, with the label table arriving as a stream of files."""
    store = ArtifactStore(spark)
    extracts = {t.name: mapping.extract_keys(t) for t in ucq.tables}
    label = extracts[ucq.label_table.name]
    arrived = store.label("arrived")
    label.repartition(files).write.parquet(f"{store.root}/{arrived}")
    stream = file_stream(spark, f"{store.root}/{arrived}", label.schema)
    state = FanOutState(spark, store, name)
    run_available(stream_row_map(ucq, stream, extracts), state.add, store)
    return state.table


class OnlineSgd:
    """One folded step for each micro-batch of joined rows."""

    def __init__(self, problem, eta: float = 0.1, beta: float = 1e-3):
        self.problem, self.eta, self.beta, self.steps = problem, eta, beta, 0
        self.thetas: dict[str, np.ndarray] = {b.name: b.model.start() for b in problem.blocks}

    def step(self, batch: DataFrame, batch_id: int = 0) -> None:
        join, k = JoinOperator(self.problem), self.problem.classes
        clients = {b.name: ClientOperator(b) for b in self.problem.blocks}
        scored = join.derivatives(join.gather(batch, {n: c.predict(self.thetas[n]) for n, c in clients.items()})).persist()
        n = scored.count()
        if n:
            received = {name: c.receive(join.fold(scored, name, [F.col(f"d{i}") for i in range(k)])) for name, c in clients.items()}
            parts = partial_gradients(received, self.problem.blocks, self.thetas)
            for name, t in self.thetas.items():
                self.thetas[name] = t - self.eta * (UnionOperator.add(parts[name], t.shape) / n + self.beta * t)
            self.steps += 1
        scored.unpersist()


def _timed(events: DataFrame) -> DataFrame:
    """Watermarks take timestamps with a zone only; the session's zone is read into those without."""
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def windows(events: DataFrame, kind: str = "tumbling", late: str = "1 hour", size: str = "1 day", slide: str = "6 hours", gap: str = "30 minutes") -> DataFrame:
    """Counts and sums of events by window and type; works on streams (with a watermark) and tables alike."""
    e = _timed(events).withWatermark("ts", late) if events.isStreaming else _timed(events)
    window = {"tumbling": lambda: F.window("ts", size), "sliding": lambda: F.window("ts", size, slide), "session": lambda: F.session_window("ts", gap)}[kind]()
    keys = [window.alias("w"), "event_type"] if kind != "session" else [window.alias("w"), "user_id"]
    return e.groupBy(*keys).agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *[k for k in keys if isinstance(k, str)], "n", "total")


def without_repeats(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each event_id once; a stream forgets ids beyond the watermark."""
    if not events.isStreaming:
        return events.dropDuplicates(["event_id"])
    return _timed(events).withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def running_features(events: DataFrame) -> DataFrame:
    """Per user, the count and mean value so far, by a stateful operator over a stream of events."""
    import pandas as pd

    def step(key, parts, state):
        n, total = state.get if state.exists else (0, 0.0)
        for p in parts:
            n, total = n + len(p), total + float(p["value"].sum())
        state.update((n, total))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "mean": [total / n if n else 0.0]})

    return events.select("user_id", "value").groupBy("user_id").applyInPandasWithState(step, "user_id long, n long, mean double", "n long, total double", "update", "NoTimeout")


def union_streams(parts: list[DataFrame]) -> DataFrame:
    """Shards of one table that arrive as several streams."""
    return reduce(DataFrame.unionByName, parts)
