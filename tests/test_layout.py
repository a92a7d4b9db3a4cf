"""What keeps training fast on large tables: ids that don't raise errors, and rows that stay in their buckets."""

import math
import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from ucqlearn import queries
from ucqlearn.functions.models import MlpModel, row_gradient_sums
from ucqlearn.operators import steps
from ucqlearn.operators.steps import ClientOperator, JoinOperator
from ucqlearn.plans import train
from ucqlearn.sources import tables
from ucqlearn.sources.workloads import line_id, ratings

SF = "/root/testdata/sf0.01"


def tried_id():
    mul, add = F.try_multiply, F.try_add
    keys = add(mul(add(mul(add(mul(F.col("l_orderkey"), F.lit(20_000_003)), F.col("l_partkey")), F.lit(1009)), F.col("l_suppkey")), F.lit(8)), F.col("l_linenumber"))
    exact = add(mul(keys, F.lit(64)), F.col("l_quantity").cast("long"))
    return F.coalesce(F.when(exact >= 0, exact), F.xxhash64("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity").bitwiseOR(F.lit(-(1 << 63))))


def lines(spark, n, first):
    return spark.range(0, n, 1, 8).select((F.col("id") + first).alias("l_orderkey"), F.lit(7).cast("long").alias("l_partkey"), F.lit(3).cast("long").alias("l_suppkey"), F.lit(1).alias("l_linenumber"), F.lit(5.0).alias("l_quantity"))


def test_line_ids_around_the_largest_number(spark):
    odd = spark.createDataFrame([(-1, 5, 5, 1, 3.0), (1, -5, 5, 1, 3.0), (None, 5, 5, 1, 3.0), (2**62, 1, 1, 1, 1.0), (-(2**62), 1, 1, 1, 1.0), (0, 0, 0, 0, 0.0)], "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double")
    rows = lines(spark, 20_000, 885_000).union(odd)
    assert rows.where(~line_id().eqNullSafe(tried_id())).count() == 0
    assert 0 < rows.where(line_id() < 0).count() < 20_000


def test_line_ids_that_do_not_fit_raise_no_errors(spark):
    rows = lines(spark, 200_000, 3_000_000)

    def seconds(ids):
        began = time.time()
        rows.agg(F.bit_xor(ids)).collect()
        return time.time() - began

    seconds(line_id())
    assert seconds(line_id()) * 2 < seconds(tried_id())


def test_rounds_leave_the_label_tables_rows_in_their_buckets(spark):
    p = queries.problem(spark, SF).vertical()
    p.buckets = p.buckets or 1
    join, clients = JoinOperator(p), {b.name: ClientOperator(b) for b in p.blocks}
    scored = join.derivatives(join.gather(p.rowmap, {n: c.predict(c.model.start()) for n, c in clients.items()})).select("r_lineitem", "d0")
    held = train.persist_in_place(scored)
    try:
        plan = clients["lineitem"].receive(join.fold(held, "lineitem", [F.col("d0")]))._jdf.queryExecution().executedPlan().toString()
    finally:
        held.unpersist()
    assert "Exchange hashpartitioning(r_lineitem" not in plan and "Exchange hashpartitioning(rid" not in plan
    assert "SortMergeJoin" not in plan


def test_baselines_share_the_slices_of_one_problem(spark):
    p = queries.problem(spark, SF)
    made = p.store.made
    first = train.vfl_sgd(p, epochs=1, eta=0.4, track=False).thetas
    again = train.vfl_sgd(p, epochs=1, eta=0.4, track=False).thetas
    assert p.store.made == made + 1
    assert all((first[n] == again[n]).all() for n in first)
    half = train.on_rows(p, p.rowmap.where("jid % 2 = 0"))
    assert train.slices(half).rowmap.count() == half.n < p.n


def test_the_label_tables_rows_lie_beside_the_map(spark):
    from dataclasses import replace

    p = queries.problem(spark, SF, shards=2)
    assert p.own and p.rowmap.count() == p.n
    apart = replace(p, own=(), rowmap=p.rowmap.drop(*p.own))
    join, clients = JoinOperator(p), {b.name: ClientOperator(b) for b in p.blocks}
    scored = join.derivatives(join.gather(p.rowmap, join.predict(p.rowmap, clients, {n: c.model.start() for n, c in clients.items()})))
    plan = clients["lineitem"].receive(join.fold(scored, "lineitem", [F.col("d0")]))._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Join") == 2 and "Aggregate" not in plan  # the other two tables' predictions
    written, write = [], p.store.write
    p.store.write = lambda name, *a, **k: written.append(name) or write(name, *a, **k)
    for run in (
        lambda q: train.rel_sgd(q, epochs=2, eta=0.4),
        lambda q: train.rel_sgd(q, epochs=1, eta=0.4, batch_size=q.n // 3),
        lambda q: train.rel_admm(q, epochs=6, rho=0.5, inner_rounds=2),
        lambda q: train.rel_admm(q, epochs=2, rho=0.5, inner_rounds=2, serve="local"),
        lambda q: train.rel_admm_v(q, epochs=2, rho=0.5, schedule="sequential"),
    ):
        one, two = run(p), run(apart)
        assert all(abs(a - b).max() < 1e-9 for a, b in zip(one.thetas.values(), two.thetas.values()) if not isinstance(a, dict))
        assert all(abs(x - y) < 1e-9 for a, b in zip(one.history, two.history) for x, y in zip(a[3:], b[3:]))
        assert all(abs(x - y) < 1e-9 for x, y in zip(one.residuals, two.residuals)) and one.ledger.rows == two.ledger.rows
    assert sum(n.startswith("state") for n in written) == 1 + 6 + 2 + 2  # one for six epochs beside the map, one an epoch apart


def test_a_map_with_the_lead_beside_it_is_written_where_it_is(spark, monkeypatch):
    monkeypatch.setattr(tables, "BUCKET_BYTES", 1 << 18)
    monkeypatch.setattr(steps, "FILE_ROWS", 20_000)
    kinds, write = [], tables.ArtifactStore.write
    monkeypatch.setattr(tables.ArtifactStore, "write", lambda self, name, df, **k: kinds.append(k) or write(self, name, df, **k))
    p = queries.problem(spark, SF)
    assert p.buckets > 1 and len(kinds) == 1 and not kinds[0].get("buckets")
    assert len(p.rowmap.inputFiles()) >= 3 and p.rowmap.count() == p.n
    monkeypatch.undo()
    one = queries.problem(spark, SF)
    for run in (lambda q: train.rel_sgd(q, epochs=2, eta=0.4), lambda q: train.rel_sgd(q, epochs=1, eta=0.4, batch_size=q.n // 3), lambda q: train.rel_admm(q, epochs=5, rho=0.5), lambda q: train.vfl_sgd(q, epochs=1, eta=0.4)):
        a, b = run(p), run(one)
        assert all(abs(a.thetas[n] - b.thetas[n]).max() < 1e-9 for n in a.thetas) and a.ledger.rows == b.ledger.rows


def test_curves_come_from_the_rounds_own_jobs(spark):
    p = queries.problem(spark, SF)
    asked, evaluate = [], train.evaluate
    train.evaluate = lambda *a: asked.append(a) or evaluate(*a)
    try:
        with_curve = train.rel_sgd(p, epochs=3, eta=0.4, tests=p.rowmap.where("jid % 5 = 0"))
        assert len(asked) == 1 + 3  # the last epoch, and the test rows
        one_by_one = train.rel_sgd(p, epochs=3, eta=0.4, tests=p.rowmap.where("jid % 5 = 0"), patience=9)
    finally:
        train.evaluate = evaluate
    assert [h[:4] for h in with_curve.history] == [h[:4] for h in one_by_one.history]
    assert all(abs(x - y) < 1e-9 for a, b in zip(with_curve.history, one_by_one.history) for x, y in zip(a[4:], b[4:]))


@pytest.mark.parametrize("activation", ["relu", "tanh"])
def test_small_nets_are_columns_and_give_what_arrays_give(spark, activation):
    rng = np.random.default_rng(1)
    model, x, g = MlpModel(3, 2, 2, activation), rng.normal(size=(40, 3)), rng.normal(size=(40, 2))
    theta, shard, c = model.start(2), np.arange(40) % 2, np.arange(40) % 3 + 1.0
    rows = spark.createDataFrame([(i, int(shard[i]), x[i].tolist(), *g[i].tolist(), float(c[i])) for i in range(40)], "rid long, shard int, x array<double>, g0 double, g1 double, c double")
    predicted = model.predict(rows, theta)
    assert "MapInArrow" not in predicted._jdf.queryExecution().executedPlan().toString()
    u = model.forward(theta, x)[2]
    assert np.allclose([[r.u0, r.u1] for r in predicted.sort("rid").collect()], u)
    for clip, rho in ((None, 0.0), (None, 0.7), (0.2, 0.0), (0.2, 0.7)):
        found, counts = {}, {}
        found = row_gradient_sums(model, rows, theta, clip, rho, counts)
        for s in (0, 1):
            at = shard == s
            assert np.allclose(found[s], model.gradient_sum(theta, x[at], g[at] + rho * c[at, None] * u[at], clip)) and counts[s] == 20
    missing = spark.createDataFrame([(0, 0, [1.0, None, 2.0])], "rid long, shard int, x array<double>")
    assert math.isnan(model.predict(missing, theta).first().u0)


def test_ratings_label_lines_without_a_join_by_line(spark):
    line = ratings(spark, SF)[0].table("lineitem")
    plan = line.df._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Join ") == 2 and plan.count("l_quantity#") and "l_rid#" not in "".join(x for x in plan.splitlines() if "Join " in x)
    assert line.df.count() == line.df.select("l_rid").distinct().count()


def test_batches_are_written_without_digests_and_draw_what_sql_draws(spark, monkeypatch):
    import hashlib

    p = queries.problem(spark, SF)
    seen, write = [], tables.ArtifactStore.write
    monkeypatch.setattr(tables.ArtifactStore, "write", lambda self, name, df, **k: seen.append(write(self, name, df, **k)) or seen[-1])
    train.rel_sgd(p, epochs=1, eta=0.4, batch_size=p.n // 3, track=False)
    assert len(seen) == 1 and "jid" not in seen[0].columns and seen[0].count() == p.n
    number = lambda *x: int(hashlib.md5("|".join(map(str, x)).encode()).hexdigest()[:15], 16)
    n_batches = seen[0].agg(F.max("bid")).first()[0] + 1
    for r in seen[0].select("r_lineitem", "r_part", "r_supplier", "bid").limit(50).collect():
        assert r.bid == number("batch", 0, 1, number(r.r_lineitem, r.r_part, r.r_supplier)) % n_batches
