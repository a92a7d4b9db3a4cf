"""Parity with centralised training, invariants of folding and consensus, privacy, costs and edge cases."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from ucqlearn import cost, metrics, privacy, queries
from ucqlearn.functions import columns as fx
from ucqlearn.functions.losses import LogisticLoss, SoftmaxLoss, SquaredLoss
from ucqlearn.functions.models import LinearModel, MlpModel, row_gradient_sums
from ucqlearn.operators.steps import ClientOperator, JoinOperator, UnionOperator
from ucqlearn.plans import batches, mapping, rowids, train
from ucqlearn.plans.ucq import SpecError, TableSpec, UcqSpec
from ucqlearn.sources import workloads
from ucqlearn.sources.tables import ArtifactStore, load_model, read, save_model

SMALL, SF = "/root/testdata/sf0.001", "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def w0(spark):
    ucq, loss = workloads.running_example(spark, SMALL, 2)
    return train.make_problem(ucq, loss)


def flat(thetas):
    return np.concatenate([thetas[k].ravel() for k in sorted(thetas)])


# a hand-made example: keys repeat on both sides, one row is unused, one key is null, one table is in two parts


@pytest.fixture(scope="module")
def tiny(spark):
    orders = spark.createDataFrame([(0, "i1", "c1", 1.0, 2.0), (1, "i1", "c2", 2.0, 1.0), (2, "i2", "c1", 3.0, 0.0), (3, None, "c1", 4.0, 5.0)], "rid long, item string, card string, a double, y double")
    items = spark.createDataFrame([(0, "i1", 1.0), (1, "i1", 2.0), (2, "i2", 3.0), (3, "i9", 4.0)], "rid long, item string, b double")
    cards = [spark.createDataFrame([(0, "c1", 0.5)], "rid long, card string, c double"), spark.createDataFrame([(1, "c2", 1.5)], "rid long, card string, c double")]
    tables = [TableSpec("orders", orders, ["item", "card"], ["a"], "rid", "y"), TableSpec("items", items, ["item"], ["b"], "rid"), TableSpec.from_shards("cards", cards, keys=["card"], features=["c"], row_id="rid")]
    return UcqSpec(tables, [(("orders", "item"), ("items", "item")), (("orders", "card"), ("cards", "card"))])


def test_tiny_map_and_step(spark, tiny):
    want = [(0, 0, 0), (0, 1, 0), (1, 0, 1), (1, 1, 1), (2, 2, 0)]
    rows = mapping.build_row_map(tiny)
    assert sorted((r.r_orders, r.r_items, r.r_cards) for r in rows.collect()) == want
    assert {r.rid: r.c for r in mapping.fan_out(rows, "items", tiny.table("items")).collect()} == {0: 2, 1: 2, 2: 1, 3: 0}
    assert {r.rid: len(r.jids) for r in mapping.reverse_map(rows, "orders", materialize=True).collect()} == {0: 2, 1: 2, 2: 1}
    same = mapping.expand_union_of_joins(tiny)
    assert rows.exceptAll(same).count() == same.exceptAll(rows).count() == 0
    p = train.make_problem(tiny)
    step = train.rel_sgd(p, eta=0.1, epochs=1, beta=0.0, track=False).thetas
    a, b, c, y = [1, 1, 2, 2, 3], [1, 2, 1, 2, 3], [0.5, 0.5, 1.5, 1.5, 0.5], [2, 2, 1, 1, 0]
    for name, x in (("orders", a), ("items", b), ("cards", c)):
        assert step[name].item() == pytest.approx(0.1 * np.mean(np.array(x) * np.array(y)))


def test_spec_errors(spark, tiny):
    o, i = tiny.table("orders"), tiny.table("items")
    edge = [(("orders", "item"), ("items", "item"))]
    with pytest.raises(SpecError, match="falls apart"):
        UcqSpec([o, i], [])
    assert UcqSpec([o, i], [], allow_cross=True).order()[1] == ("items", [])
    with pytest.raises(SpecError, match="label"):
        UcqSpec([i], [])
    with pytest.raises(SpecError, match="no column"):
        UcqSpec([o, TableSpec("items", i.df, ["item"], ["zz"], "rid")], edge)
    with pytest.raises(SpecError, match="no number"):
        UcqSpec([o, TableSpec("items", i.df, ["item"], ["item"], "rid")], edge)
    with pytest.raises(SpecError, match="schemas"):
        TableSpec.from_shards("x", [o.df, i.df], keys=[], features=[], row_id="rid")
    with pytest.raises(SpecError, match="empty"):
        train.make_problem(UcqSpec([o, TableSpec("items", i.df.where("item = 'i9'"), ["item"], ["b"], "rid")], edge))
    with pytest.raises(SpecError, match="share an id"):
        mapping.merge_extracts([mapping.extract_keys(i)] * 2, check=True)


def test_composite_keys_and_one_table(spark, tiny):
    a = spark.createDataFrame([(0, 1, 1, 1.0, 1.0), (1, 1, 2, 2.0, 0.0)], "rid long, k int, l int, a double, y double")
    b = spark.createDataFrame([(0, 1, 1, 1.0), (1, 1, 3, 2.0)], "rid long, k int, l int, b double")
    ucq = UcqSpec([TableSpec("a", a, ["k", "l"], ["a"], "rid", "y"), TableSpec("b", b, ["k", "l"], ["b"], "rid")], [(("a", "k"), ("b", "k")), (("a", "l"), ("b", "l"))])
    assert [(r.r_a, r.r_b) for r in mapping.build_row_map(ucq).collect()] == [(0, 0)]
    alone = train.make_problem(UcqSpec([TableSpec("a", a, ["k"], ["a"], "rid", "y")], []))
    assert alone.n == 2 and train.rel_sgd(alone, epochs=1).history[0][3] == 2


def test_server_sees_no_features(w0, spark):
    ucq, _ = workloads.running_example(spark, SMALL, 2)
    features = {"z_l_quantity", "z_p_size", "z_s_acctbal", "p_size", "s_acctbal", "x"}
    mapping.assert_no_features(w0.rowmap, features)
    mapping.assert_no_features(mapping.extract_keys(ucq.table("part")), features)
    with pytest.raises(SpecError):
        mapping.assert_no_features(ucq.table("part").df, features)


def test_hashed_keys_give_the_same_map(spark, tiny):
    a, b = mapping.build_row_map(tiny), mapping.build_row_map(tiny, hash_keys=True, salt="s")
    assert a.exceptAll(b).count() == b.exceptAll(a).count() == 0


def test_row_ids(spark):
    df = spark.range(100).select((F.col("id") % 10).alias("a"), F.col("id").alias("b"))
    with pytest.raises(SpecError):
        rowids.natural(df, "a")
    store = ArtifactStore(spark)
    for out in (rowids.ordered(df), rowids.ranked(df, ["a", "b"], store, "ranked")):
        rows = sorted((r.rid, r.a, r.b) for r in out.collect())
        assert [r[0] for r in rows] == list(range(100)) and [r[1:] for r in rows] == sorted(r[1:] for r in rows)
    assert rowids.content_hash(df).select("rid").distinct().count() == rowids.monotonic(df, store, "m").select("rid").distinct().count() == 100


# parity


def test_sgd_parity(w0):
    for options in ({"epochs": 3}, {"epochs": 1, "batch_size": 1700}):
        runs = [m(w0, eta=0.3, track=False, **options).by_epoch for m in (train.centralized, train.vfl_sgd, train.rel_sgd_v, train.rel_sgd)]
        for other in runs[1:]:
            for a, b in zip(runs[0], other, strict=True):
                assert np.abs(flat(a) - flat(b)).max() < 1e-9


def test_admm_parity_and_optimum(w0):
    a, b = (m(w0, rho=0.5, epochs=4, track=False).by_epoch for m in (train.vfl_admm, train.rel_admm_v))
    assert max(np.abs(flat(x) - flat(y)).max() for x, y in zip(a, b, strict=True)) < 1e-8
    _, best = train.ridge_exact(w0)
    r = train.rel_admm_v(w0, rho=0.5, epochs=10)
    assert r.history[-1][5] < 1.01 * best and r.residuals[-1] < r.residuals[0]
    for schedule in ("sequential", "proximal"):
        assert train.rel_admm_v(w0, rho=0.5, epochs=8, schedule=schedule).history[-1][5] < (1.02 if schedule == "sequential" else 1.3) * best


def test_consensus_meets_the_vertical_update(spark):
    ucq, loss = workloads.ratings(spark, SMALL, 2)
    p = train.make_problem(ucq, loss)
    exact = train.rel_admm_v(p, rho=0.5, epochs=1, track=False).thetas
    gaps = [np.abs(flat(train.rel_admm(p, rho=0.5, epochs=1, inner_rounds=t, rho_inner=0.1, track=False).thetas) - flat(exact)).max() for t in (1, 5, 40)]
    assert gaps[2] < 1e-5 < gaps[0]
    local = train.rel_admm(p, rho=0.5, epochs=2, inner_rounds=40, rho_inner=0.1, serve="local", track=False).thetas
    assert all(len(t) == 2 and np.abs(t[0] - t[1]).max() < 1e-3 for t in local.values())
    printed = train.rel_admm(p, rho=0.5, epochs=1, inner_rounds=40, rho_inner=0.1, consensus_weight="tables", track=False).thetas
    assert np.abs(flat(printed) - flat(exact)).max() > gaps[2]


def test_shards_do_not_change_sgd(spark):
    found = []
    for q in (1, 4):
        ucq, loss = workloads.ratings(spark, SMALL, q)
        found.append(flat(train.rel_sgd(train.make_problem(ucq, loss), eta=0.2, epochs=2, track=False).thetas))
    ucq, loss = workloads.ratings(spark, SMALL, 1)
    for t in ucq.tables:
        t.df, t.shard, t.shards = workloads.uneven_shards(t.df.drop("shard"), t.row_id), "shard", 3  # the third has no row
    found.append(flat(train.rel_sgd(train.make_problem(ucq, loss), eta=0.2, epochs=2, track=False).thetas))
    assert max(np.abs(f - found[0]).max() for f in found) < 1e-9


def test_divergence_guard(spark):
    ucq, loss = workloads.correlated(spark, SMALL, 0.9)
    p = train.make_problem(ucq, loss)
    with pytest.raises(train.DivergenceError, match="sequential"):
        train.rel_admm_v(p, rho=0.1, epochs=12, track=False)
    _, best = train.ridge_exact(p)
    assert train.rel_admm_v(p, rho=0.5, epochs=10, schedule="sequential").history[-1][5] < 1.1 * best


def test_logistic_and_softmax_workloads(spark):
    ucq, loss = workloads.health(spark, SMALL)
    p = train.make_problem(ucq, loss)
    fit, tests = batches.split(p.rowmap)
    q = train.on_rows(p, fit)
    a = train.centralized(q, eta=0.5, epochs=8).history[-1][5]
    b = train.rel_admm_v(q, rho=1.0, epochs=4, tests=tests).history
    assert abs(b[-2][5] - a) < 0.03 and b[-1][2] == "test" and b[-1][5] > 0.68
    ucq, loss = workloads.reviews(spark, SMALL)
    p = train.make_problem(ucq, loss)
    runs = [m(p, eta=0.5, epochs=2, track=False).thetas for m in (train.vfl_sgd, train.rel_sgd_v)]
    assert np.abs(flat(runs[0]) - flat(runs[1])).max() < 1e-9
    assert train.rel_admm_v(p, rho=0.5, epochs=3).history[-1][5] > 0.4
    ucq, loss = workloads.reviews(spark, SMALL, natural=True)
    assert train.make_problem(ucq, loss).n == 87
    ucq, loss = workloads.stays(spark, SMALL)
    assert train.make_problem(ucq, loss).n == 8931


def test_net_workload(spark):
    ucq, loss, models = workloads.ratings_net(spark, SMALL, 2, hidden=4)
    p = train.make_problem(ucq, loss, models)
    a, b, c = (m(p, eta=0.05, epochs=2, seed=1).by_epoch[-1] for m in (train.centralized, train.rel_sgd_v, train.rel_sgd))
    assert np.abs(flat(a) - flat(b)).max() < 1e-9 and np.abs(flat(b) - flat(c)).max() < 1e-9
    r = train.rel_admm(p, rho=0.5, epochs=2, inner_rounds=2, steps=2, lr=0.05, guard=0)
    assert r.history[-1][5] < r.history[0][5]
    one = MlpModel(sum(t_.model.d for t_ in p.blocks), 4)
    assert len(train.centralized(p, arch="monolithic", model=one, eta=0.05, epochs=1).history) == 1


@pytest.mark.parametrize("activation", ["relu", "tanh"])
def test_net_gradient_by_differences(activation):
    rng = np.random.default_rng(0)
    model, x, g = MlpModel(3, 5, 2, activation), rng.normal(size=(7, 3)), rng.normal(size=(7, 2))
    theta = model.start(3) + 0.01
    grad = model.gradient_sum(theta, x, g)
    for i in range(model.size):
        e = np.zeros(model.size)
        e[i] = 1e-6
        slope = ((g * model.forward(theta + e, x)[2]).sum() - (g * model.forward(theta - e, x)[2]).sum()) / 2e-6
        assert abs(slope - grad[i]) < 1e-5


def test_loss_derivatives_and_prox(spark):
    rows = [(float(m), float(y)) for m in (-6, -1, 0, 0.5, 4) for y in (0, 1, 2)]
    df = spark.createDataFrame(rows, "m0 double, y double").withColumn("m1", -F.col("m0")).withColumn("m2", F.lit(0.3))
    h = 1e-5
    for loss in (SquaredLoss(), LogisticLoss(), SoftmaxLoss(3)):
        k = loss.classes
        some = df.where("y < 2") if isinstance(loss, LogisticLoss) else df
        m = [F.col(f"m{c}") for c in range(k)]
        for c in range(k):
            up, down = ([x + F.lit(s * h) if i == c else x for i, x in enumerate(m)] for s in (1, -1))
            slope = (loss.value(up, F.col("y")) - loss.value(down, F.col("y"))) / (2 * h)
            assert some.agg(F.max(F.abs(slope - loss.derivative(m, F.col("y"))[c]))).first()[0] < 1e-6
        for rho in (0.05, 0.5, 2.0):
            out = loss.prox(some.select("y", *[f"m{c}" for c in range(k)], *[F.lit(0.2 * c - 0.1).alias(f"mu{c}") for c in range(k)]), rho)
            d = loss.derivative([F.col(f"v{c}") for c in range(k)], F.col("y"))
            gap = F.greatest(*[F.abs(d[c] - F.col(f"mu{c}") - rho * (F.col(f"m{c}") - F.col(f"v{c}"))) for c in range(k)], F.lit(0.0))
            assert out.agg(F.max(gap)).first()[0] < 1e-5


def test_softmax_of_two_agrees_with_logistic(spark):
    df = spark.createDataFrame([(1.5, 1.0), (-0.3, 0.0), (2.0, 0.0)], "m double, y double")
    a = LogisticLoss().value([F.col("m")], F.col("y"))
    b = SoftmaxLoss(2).value([F.lit(0.0), F.col("m")], F.col("y"))
    assert df.agg(F.max(F.abs(a - b))).first()[0] < 1e-12


# ledger and costs


def test_ledger_meets_closed_forms(w0):
    n, used = w0.n, [w0.used[b.name] for b in w0.blocks]
    a = train.rel_admm_v(w0, epochs=2, track=False).ledger
    assert a.rounds(1) == cost.rounds("rel_admm_v", n, n) and a.values(1) == cost.volume("rel_admm_v", n, 3, 1, used=used)
    v = train.vfl_admm(w0, epochs=1, track=False).ledger
    assert v.values(1) == cost.volume("vfl_admm", n, 3) and a.values(1) < v.values(1)
    s = train.vfl_sgd(w0, epochs=1, batch_size=2000, track=False).ledger
    assert (s.rounds(1), s.values(1)) == (cost.rounds("vfl_sgd", n, 2000), cost.volume("vfl_sgd", n, 3))
    m = batches.alpha(batches.with_batches(w0.rowmap, 3, 0, 1), w0.names)
    alphas = {r.tbl: r.alpha for r in m.collect()}
    order = [alphas[b.name] for b in w0.blocks]
    f = train.rel_sgd_v(w0, epochs=1, batch_size=2000, track=False).ledger
    assert f.values(1) == cost.volume("rel_sgd_v", n, 3, 1, alphas=order) and sum(used) <= sum(order) <= 3 * n
    c = train.rel_sgd_v(w0, epochs=1, batch_size=2000, track=False, send_counts="per_batch").ledger
    assert c.values(1) == cost.volume("rel_sgd_v", n, 3, 1, alphas=order, send_counts="per_batch")
    sizes, shards = [b.model.size for b in w0.blocks], [b.shards for b in w0.blocks]
    full = train.rel_admm(w0, epochs=1, inner_rounds=10, track=False).ledger
    assert full.values(1) == cost.volume("rel_admm", n, 3, 1, used=used, parameters=sizes, shards=shards) and full.rounds(1) == 11
    q = train.rel_sgd(w0, epochs=1, batch_size=2000, track=False).ledger
    assert q.values(1) == cost.volume("rel_sgd", n, 3, 1, order, parameters=sizes, shards=shards, n_batches=3) and q.rounds(1) == 6


def test_published_communication_figures():
    assert cost.comm_time(10, 0) == pytest.approx(1.36) and cost.batches(3_200_000, 10_000) == 320 and cost.batches(2_900_000, 10_000) == 290
    epoch = cost.comm_time(cost.rounds("vfl_sgd", 2_900_000, 10_000), 4 * cost.volume("vfl_sgd", 2_900_000, 5, 2))
    assert 3 * epoch > 130
    assert privacy.label_epsilon(0.5) == pytest.approx(5.657, abs=1e-3) and privacy.label_lambda(privacy.label_epsilon(0.7)) == pytest.approx(0.7)


def test_admm_needs_less_time(spark, w0):
    a, b = train.rel_admm_v(w0, rho=0.5, epochs=6), train.vfl_admm(w0, rho=0.5, epochs=6)
    s = train.rel_sgd_v(w0, eta=0.5, epochs=3, batch_size=600)
    frames, costs = [], []
    for r in (a, b, s):
        frames += [(h[0], h[1], h[5]) for h in r.history]
        costs += [(r.method, h[1], cost.comm_time(r.ledger.rounds(h[1]), r.ledger.bytes(h[1]))) for h in r.history]
    curve = metrics.with_time(spark.createDataFrame(frames, "method string, epoch int, metric double"), spark.createDataFrame(costs, "method string, epoch int, seconds double"))
    met = {r.method: r.time for r in metrics.time_to_target(curve, 0.12, True).collect()}
    assert met["rel_admm_v"] < met["vfl_admm"] < met["rel_sgd_v"]
    assert {r.method for r in metrics.best_epoch(curve, True).collect()} == set(met)


# privacy


def test_label_noise(spark):
    df = spark.range(40000).select("id", (F.col("id") % 2).cast("int").alias("y"))
    noisy = privacy.noisy_labels(df, "y", "id", 2, 0.5, seed=1).withColumnRenamed("y", "z").join(df, "id")
    share = noisy.agg(F.avg((F.col("z") != F.col("y")).cast("double"))).first()[0]
    assert abs(share - privacy.flip_rate(0.5)) < 0.005 and abs(privacy.flip_rate(0.5) - 0.0713) < 1e-4
    spread = privacy.noisy_labels(spark.range(40000).select("id", F.lit(0.0).alias("y")), "y", "id", 1, 0.5, seed=1, y_range=(-1.0, 1.0)).agg(F.stddev("y")).first()[0]
    assert abs(spread - 0.5) < 0.02
    with pytest.raises(ValueError):
        privacy.noisy_labels(df, "y", "id", 1, 0.5)
    assert privacy.noisy_labels(df, "y", "id", 2, 0.5, seed=None).count() == 40000


def test_epochs_draw_new_batches(spark):
    """Pairs of batches in two epochs fill the table evenly, seeds differ, and no batch of a hundred is empty."""
    rows = spark.range(40_000).select(F.col("id").alias("jid"))
    two = rows.select(batches.batch_id(F.col("jid"), 20, 0, 1).alias("a"), batches.batch_id(F.col("jid"), 20, 0, 2).alias("b"), batches.batch_id(F.col("jid"), 20, 1, 1).alias("c"), batches.is_test(F.col("jid")).alias("t"))
    for x, y in (("a", "b"), ("a", "c")):
        pairs = [r.n for r in two.groupBy(x, y).agg(F.count(F.lit(1)).alias("n")).collect()]
        assert len(pairs) == 400 and 50 < min(pairs) and max(pairs) < 160  # 100 expected
    for n in (20, 50, 100):
        sizes = [r["count"] for r in rows.where(~batches.is_test(F.col("jid"))).select(batches.batch_id(F.col("jid"), n, 3, 4).alias("b")).groupBy("b").count().collect()]
        assert len(sizes) == n and max(sizes) < 1.5 * min(sizes)
    assert abs(two.agg(F.avg(F.col("t").cast("double"))).first()[0] - 0.15) < 0.01


def test_poisson_batches(spark):
    """Each batch has its share, rows are drawn independently in each, and some rows are in none."""
    rows = spark.range(20_000).select(F.col("id").alias("jid"))
    drawn = batches.poisson_batches(rows, 5, 1, 2).persist()
    sizes = {r.bid: r["count"] for r in drawn.groupBy("bid").count().collect()}
    assert set(sizes) == set(range(5)) and all(abs(n - 4000) < 300 for n in sizes.values())
    times = {r["count"]: r.n for r in drawn.groupBy("jid").count().groupBy("count").agg(F.count(F.lit(1)).alias("n")).collect()}
    assert abs(times[1] / 20_000 - 5 * 0.2 * 0.8**4) < 0.02 and abs(times[2] / 20_000 - 10 * 0.04 * 0.8**3) < 0.02
    assert drawn.select("jid").distinct().count() < 20_000
    drawn.unpersist()


def test_private_rounds_follow_the_accounted_law(w0):
    """An empty or small batch is a round like any other, divided by the expected size; a joined row costs ADMM twice the noise."""
    r = train.rel_sgd(w0, eta=0.1, epochs=2, batch_size=2000, track=False, dp=privacy.DpSpec(sigma=1.0, unit="joined_row", seed=5))
    assert r.ledger.rounds(1) == 2 * 3
    spread = {}
    for unit in ("base_row", "joined_row"):
        fits = [flat(train.rel_admm_v(w0, rho=0.5, epochs=1, inner="descent", steps=1, lr=1.0, track=False, guard=0, dp=privacy.DpSpec(1.0, 400.0, unit, s)).thetas) for s in range(4)]
        spread[unit] = np.std(np.array(fits), axis=0).mean()
    assert abs(spread["joined_row"] / spread["base_row"] - 2) < 0.02


def test_numeric_labels_keep_their_range(spark):
    df = spark.createDataFrame([(i, float(v)) for i, v in enumerate([-50, 1, 5, 900] * 2000)], "id long, y double")
    quiet = privacy.noisy_labels(df, "y", "id", 1, 1e-9, seed=1, y_range=(1.0, 5.0))
    assert quiet.agg(F.min("y"), F.max("y")).first()[0] == pytest.approx(1.0) and quiet.agg(F.max("y")).first()[0] == pytest.approx(5.0)
    noise = privacy.noisy_labels(df.where("y = 5"), "y", "id", 1, 0.5, seed=1, y_range=(1.0, 5.0)).agg(F.stddev("y")).first()[0]
    assert abs(noise - 1.0) < 0.1 and privacy.numeric_label_epsilon(1.0, 1.0, 5.0) == pytest.approx(privacy.label_epsilon(0.5))


def test_ids_of_large_keys(spark):
    """Keys of a hundred times the largest given table."""
    from ucqlearn.sources.workloads import line_id

    rows = [(k, p, s, n, 7.0) for k in (5, 999_999, 1_000_000, 10_000_000, 6_000_000_000) for p in (1, 199_999_999) for s in (3, 9_999_999) for n in (1, 2)]
    df = spark.createDataFrame(rows, "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double")
    assert df.select(line_id().alias("i")).where("i is not null").distinct().count() == len(rows)


def test_wide_models_sum_without_a_matrix_a_row(spark):
    """768 features and 5 classes: Gram matrix, gradient and clipped gradient against numpy."""
    d, k, n = 768, 5, 600
    rng = np.random.default_rng(1)
    x, g, c = rng.normal(size=(n, d)), rng.normal(size=(n, k)), rng.integers(1, 4, n)
    rows = [(i % 2, x[i].tolist(), *g[i].tolist(), int(c[i])) for i in range(n)]
    df = spark.createDataFrame(rows, "shard int, x array<double>, " + ", ".join(f"g{i} double" for i in range(k)) + ", c long").repartition(5)
    model = LinearModel(d, k)
    grams = model.gram(df.select("shard", "x", "c"))
    for s in (0, 1):
        at = np.arange(n) % 2 == s
        assert np.allclose(grams[s], (x[at] * c[at, None]).T @ x[at])
        assert np.allclose(model.partial_gradient(df, model.start())[s], x[at].T @ g[at])
        norms = np.linalg.norm(x[at], axis=1) * np.linalg.norm(g[at], axis=1)
        want = x[at].T @ (g[at] * np.minimum(1, 3 / norms)[:, None])
        assert np.allclose(model.partial_gradient(df, model.start(), 3.0)[s], want)


def test_clipped_net_gradients_row_by_row():
    rng = np.random.default_rng(2)
    model, x, g = MlpModel(3, 5, 2), rng.normal(size=(9, 3)), rng.normal(size=(9, 2))
    theta = model.start(1)
    rows = [model.gradient_sum(theta, x[i : i + 1], g[i : i + 1]) for i in range(9)]
    want = sum(r * min(1.0, 0.7 / np.linalg.norm(r)) for r in rows)
    assert np.allclose(model.gradient_sum(theta, x, g, 0.7), want)


def test_accountant():
    e = privacy.epsilon_spent
    assert e(1.0, 0.1, 10, 1e-5) < e(1.0, 0.1, 100, 1e-5) and e(2.0, 0.1, 100, 1e-5) < e(1.0, 0.1, 100, 1e-5) < e(1.0, 0.2, 100, 1e-5)
    assert e(0.0, 0.1, 1, 1e-5) == math.inf
    s = privacy.sigma_for(1.0, 0.05, 200, 1e-5)
    assert e(s, 0.05, 200, 1e-5) <= 1.0 < e(0.98 * s, 0.05, 200, 1e-5)
    assert e(1.3, 1.0, 1, 1e-5) == pytest.approx(min(a / (2 * 1.69) + math.log(1e5) / (a - 1) for a in privacy.ORDERS))
    assert privacy.sigma_asymptotic(1, 0.1, 100, 1e-5) > 0 and privacy.steps_taken(3, 2, 5) == 30


def test_private_training(w0, spark):
    plain = flat(train.rel_sgd(w0, eta=0.3, epochs=2, track=False).thetas)
    off = privacy.DpSpec(clip=1e9, sigma=0.0)
    assert np.abs(flat(train.rel_sgd(w0, eta=0.3, epochs=2, track=False, dp=off).thetas) - plain).max() < 1e-8
    assert np.abs(flat(train.rel_sgd(w0, eta=0.3, epochs=2, track=False, dp=privacy.DpSpec(clip=1e9, sigma=0.0, unit="joined_row")).thetas) - plain).max() < 1e-8
    noisy = [train.rel_sgd(w0, eta=0.3, epochs=2, dp=privacy.DpSpec(clip=1.0, sigma=1.0, seed=s, unit="joined_row")) for s in (1, 2)]
    assert np.abs(flat(noisy[0].thetas) - flat(noisy[1].thetas)).max() > 0
    assert noisy[0].history[-1][5] < noisy[0].history[0][5]  # still learns
    admm = train.rel_admm(w0, rho=0.5, epochs=2, inner_rounds=2, steps=2, dp=privacy.DpSpec(clip=50.0, sigma=0.1), guard=0)
    assert math.isfinite(admm.history[-1][5])
    descent = train.rel_admm_v(w0, rho=0.5, epochs=2, inner="descent", steps=60, lr=0.8, track=False).thetas
    exact = train.rel_admm_v(w0, rho=0.5, epochs=2, track=False).thetas
    assert np.abs(flat(descent) - flat(exact)).max() < 1e-3
    assert metrics.dp_drop(0.5, 0.4, True) == pytest.approx(0.1)


def test_noise_has_the_stated_spread():
    dp = privacy.DpSpec(clip=2.0, sigma=1.5)
    draws = privacy.add_noise(np.zeros(200_000), dp, dp.rng())
    assert abs(draws.std() - 3.0) < 0.03


# the rest


def test_models_are_saved(spark, tmp_path, w0):
    t = {"a": np.array([[1.0, 2.0]]), "b": np.array([3.0, 4.0, 5.0])}
    save_model(spark, f"file://{tmp_path}/m", t, loss="squared")
    back, about = load_model(spark, f"file://{tmp_path}/m")
    assert about == {"loss": "squared"} and all((back[k] == t[k]).all() and back[k].shape == t[k].shape for k in t)
    with pytest.raises(ValueError):
        read(spark, "x", "csv")


def test_search_and_repeats(w0):
    best, tried = train.grid_search(lambda **s: train.rel_sgd_v(w0, epochs=1, **s), {"eta": [0.01, 0.5]})
    assert best == {"eta": 0.5} and len(tried) == 2
    assert len(train.repeat(lambda seed: train.rel_sgd_v(w0, epochs=1, batch_size=3000, seed=seed))) == 1
    early = train.rel_sgd_v(w0, eta=1e-6, epochs=9, tol=0.1, patience=1)
    assert len(early.history) < 9


def test_constant_feature_and_columns(spark):
    df = workloads.scaled(spark.createDataFrame([(1.0, 2.0), (1.0, 4.0)], "a double, b double"), ["a", "b"])
    assert [(r.z_a, r.z_b) for r in df.collect()] == [(0.0, -1.0), (0.0, 1.0)]
    t = spark.createDataFrame([("Hello, hello World",), ("",), (None,)], "t string")
    vectors = [r.v for r in t.select(fx.hash_text(F.col("t"), 8).alias("v")).collect()]
    assert len(vectors[0]) == 8 and abs(sum(x * x for x in vectors[0])) > 0 and vectors[1] == [0.0] * 8
    long = [float(i) for i in range(100)]
    x = spark.createDataFrame([(long,)], "x array<double>")
    assert x.select(fx.dot(F.col("x"), long)).first()[0] == x.select(fx.dot(F.col("x"), long, unroll=100)).first()[0] == sum(i * i for i in range(100))
    assert UnionOperator.add({}, (2, 1)).shape == (2, 1) and LinearModel(3, 2).size == 6


def test_label_epsilon_reads_orders(spark):
    rows = queries.QUERIES["label_epsilon"](spark, "/root/testdata/sf0.001").collect()
    assert sum(r.labels for r in rows) == spark.read.parquet("/root/testdata/sf0.001/orders.parquet").count()
    assert all(r.most_spent >= r.epsilon for r in rows)


def test_accountant_takes_its_rates_from_orders(spark):
    units = spark.read.parquet("/root/testdata/sf0.001/orders.parquet").select("o_custkey").distinct().count()
    rows = queries.QUERIES["privacy_accountant"](spark, "/root/testdata/sf0.001").collect()
    assert {r.rate for r in rows} == {8 / units, 64 / units}


def test_rounds_leave_the_lead_where_it_is(spark):
    p = train.make_problem(*workloads.running_example(spark, SMALL, shards=1))
    b, join = p.blocks[0], JoinOperator(p)
    client = ClientOperator(b)
    scored = join.gather(p.rowmap, {b.name: client.predict(b.model.start())})
    received = client.receive(join.fold(scored, b.name, [F.col("m0")]))
    assert "Exchange" not in received._jdf.queryExecution().executedPlan().toString()


def test_clipped_linear_sums_as_columns(spark):
    rng = np.random.default_rng(1)
    x, g = rng.normal(size=(50, 2)), rng.normal(size=50)
    df = spark.createDataFrame([(0, x[i].tolist(), float(g[i])) for i in range(50)], "shard int, x array<double>, g0 double")
    counts = {}
    got = LinearModel(2).partial_gradient(df, np.zeros((2, 1)), clip=0.7)[0]
    part = x * g[:, None]
    want = (part * np.minimum(1, 0.7 / np.linalg.norm(part, axis=1))[:, None]).sum(axis=0)
    assert np.abs(got[:, 0] - want).max() < 1e-9
    row_gradient_sums(LinearModel(2), df, np.zeros((2, 1)), 0.7, counts=counts)
    assert counts == {0: 50}
