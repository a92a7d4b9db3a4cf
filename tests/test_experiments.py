"""Which method wins, and how measures move: the reported behaviour on small runs."""

import pytest

from ucqlearn import experiments
from ucqlearn.plans import batches, train

SMALL = "/root/testdata/sf0.001"


def last(df):
    out = {}
    for r in df.collect():
        out[r.method] = r
    return out


def test_vertical_methods_agree_and_admm_sends_less(spark):
    r = last(experiments.compare(spark, SMALL, "w0", "vertical", epochs=4, n_batches=3, seeds=(0,)))
    assert all(abs(x.metric - r["centralized"].metric) < 0.02 for x in r.values())
    assert r["rel_admm_v"].time < r["vfl_admm"].time < r["vfl_sgd"].time and r["rel_sgd_v"].n_values < r["vfl_sgd"].n_values


def test_full_scenario(spark):
    r = last(experiments.compare(spark, SMALL, "w0", "full", epochs=4, n_batches=12, inner_rounds=4, seeds=(0,)))
    assert abs(r["rel_admm"].metric - r["centralized"].metric) < 0.05 and r["rel_admm"].time < r["rel_sgd"].time
    assert r["rel_admm"].rounds < r["rel_sgd"].rounds


@pytest.mark.parametrize("method", ["rel_sgd_v", "rel_admm_v"])
def test_privacy_costs_accuracy(spark, method):
    plain = last(experiments.compare(spark, SMALL, "w1", "vertical", epochs=2, n_batches=1, seeds=(0,), methods=[method]))
    private = last(experiments.compare(spark, SMALL, "w1", "vertical", True, epochs=2, n_batches=1, seeds=(0,), methods=[method]))
    assert private[method].metric < plain[method].metric + 0.02


def test_tuning_takes_the_better_of_the_grid_on_rows_apart(spark):
    ucq, loss, models = experiments.workload(spark, SMALL, "w0", 1)
    p = train.make_problem(ucq, loss, models)
    p = train.on_rows(p, batches.split(p.rowmap)[0])
    fit_rows, held = batches.split(p.rowmap, stream="validation")
    assert fit_rows.count() + held.count() == p.n and 0.1 < held.count() / p.n < 0.2
    found = experiments.tune(p, "rel_sgd_v", 1, {"batch_size": None, "beta": 1e-3}, etas=(0.01, 0.5))
    assert found == {"eta": 0.5}


def test_a_method_stopped_by_its_guard_has_no_rows(spark, monkeypatch):
    def stopped(*args, **options):
        raise train.DivergenceError("grows")

    monkeypatch.setitem(train.METHODS, "rel_admm_v", stopped)
    r = last(experiments.compare(spark, SMALL, "w0", "vertical", epochs=1, n_batches=1, seeds=(0,), methods=["rel_admm_v", "rel_sgd_v"]))
    assert set(r) == {"rel_sgd_v"}
