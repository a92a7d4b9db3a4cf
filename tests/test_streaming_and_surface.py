"""Streams against their batch results, SQL views and functions, and the shape of plans."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from ucqlearn import queries, sqlsurface
from ucqlearn.plans import mapping, train
from ucqlearn.sources import workloads
from ucqlearn.sources.tables import ArtifactStore, load_table
from ucqlearn.streaming import incremental as inc

SMALL = "/root/testdata/sf0.001"


def test_stream_fan_out_is_the_batch_fan_out(spark):
    ucq = queries.shared(spark, SMALL)
    a, b = inc.stream_fan_out(spark, ucq, SMALL, "supplier"), mapping.fan_out(mapping.build_row_map(ucq), "supplier")
    assert a.exceptAll(b).count() == b.exceptAll(a).count() == 0
    state = inc.FanOutState(spark, ArtifactStore(spark), "supplier")
    rows = mapping.build_row_map(ucq)
    for batch_id in (0, 0, 1):  # a batch that comes again counts once
        state.add(rows, batch_id)
    assert state.table.agg(F.sum("c")).first()[0] == 2 * rows.count()


def test_online_sgd_learns(spark):
    ucq, loss = workloads.running_example(spark, SMALL, 2)
    p = train.make_problem(ucq, loss)
    store, online = ArtifactStore(spark), inc.OnlineSgd(p, eta=0.3)
    p.rowmap.repartition(4).write.parquet(f"{store.root}/rows")
    inc.run_available(inc.file_stream(spark, f"{store.root}/rows", p.rowmap.schema), online.step, store)
    zero = {b.name: b.model.start() for b in p.blocks}
    assert online.steps == 4 and train.evaluate(p, online.thetas).metric < 0.7 * train.evaluate(p, zero).metric
    one = inc.OnlineSgd(p, eta=0.3, beta=1e-3)
    one.step(p.rowmap)
    full = train.rel_sgd(p, eta=0.3, epochs=1, beta=1e-3, track=False).thetas
    assert all(np.abs(one.thetas[k] - full[k]).max() < 1e-9 for k in full)


@pytest.mark.parametrize("kind", ["tumbling", "sliding", "session"])
def test_windows_on_a_stream(spark, kind):
    events, store = load_table(spark, SMALL, "events"), ArtifactStore(spark)
    end = events.agg(F.max("ts")).first()[0]
    events.repartition(1).sortWithinPartitions("ts").write.parquet(f"{store.root}/events")
    # a last event far ahead closes all windows
    events.limit(1).withColumn("ts", F.lit(end).cast("timestamp_ntz") + F.expr("INTERVAL 90 DAY")).write.mode("append").parquet(f"{store.root}/events")
    stream, got = inc.file_stream(spark, f"{store.root}/events", events.schema, 10), []
    inc.run_available(inc.windows(stream, kind), lambda df, i: got.extend(df.collect()), store)
    want = inc.windows(events, kind).collect()
    key = lambda r: (r.start, r[2], r.n)
    assert {key(r) for r in want} <= {key(r) for r in got}


def test_repeats_and_state_on_a_stream(spark):
    events, store = load_table(spark, SMALL, "events").limit(200), ArtifactStore(spark)
    events.union(events.limit(50)).repartition(1).write.parquet(f"{store.root}/e")
    got = []
    inc.run_available(inc.without_repeats(inc.file_stream(spark, f"{store.root}/e", events.schema)), lambda df, i: got.extend(df.collect()), store)
    assert len(got) == 200 and inc.without_repeats(events.union(events)).count() == 200
    last = {}
    inc.run_available(inc.running_features(inc.file_stream(spark, f"{store.root}/e", events.schema)), lambda df, i: last.update({r.user_id: r.n for r in df.collect()}), store, "update")
    assert sum(last.values()) == 250


def test_sql_surface(spark):
    ucq, loss = workloads.running_example(spark, SMALL, 2)
    p = train.make_problem(ucq, loss)
    thetas = train.rel_sgd(p, eta=0.3, epochs=1, track=False).thetas
    names = sqlsurface.register(spark, p, thetas, "w0_")
    assert len(names) == 8 and spark.sql("SELECT sum(c) FROM w0_fanout_part").first()[0] == p.n
    by_sql = spark.sql("SELECT sum(a.u0 + b.u0 + c.u0) FROM w0_rowmap JOIN w0_pred_lineitem a ON r_lineitem = a.rid JOIN w0_pred_part b ON r_part = b.rid JOIN w0_pred_supplier c ON r_supplier = c.rid").first()[0]
    assert abs(by_sql - sqlsurface.predict(p, thetas).agg(F.sum("pred")).first()[0]) < 1e-6
    assert spark.sql("SELECT ucq_score(array(1.0D, 2.0D), array(0.5D, 0.25D))").first()[0] == 1.0
    assert [tuple(r) for r in spark.sql("SELECT * FROM explode_words('small red ring')").collect()] == [(0, "small"), (1, "red"), (2, "ring")]


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark):
    # extracts read keys only; filters reach the scan; the fold sums before it shuffles
    supplier = load_table(spark, SMALL, "supplier")
    t = plan(queries.merged_extracts_supplier(spark, SMALL))
    assert "s_acctbal" not in t.split("ReadSchema")[1]
    assert "PushedFilters: [IsNotNull(s_suppkey), GreaterThan(s_suppkey,5)]" in plan(supplier.where("s_suppkey > 5"))
    p, join, scored = queries.scored_w0(spark, SMALL)
    fold = plan(join.fold(join.derivatives(scored), "part", [F.col("d0")]))
    assert "partial_sum" in fold and "PythonUDF" not in fold and "ArrowEvalPython" not in fold
    ucq, loss = workloads.running_example(spark, SMALL)
    q = train.make_problem(ucq, loss)
    from ucqlearn.plans.batches import with_batches

    rows = q.store.write(q.store.label("b"), with_batches(q.rowmap, 4), partition_by=["bid"])
    assert "PartitionFilters: [isnotnull(bid" in plan(rows.where("bid = 2"))
