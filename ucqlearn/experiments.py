"""The experiments: every method on a workload and scenario, with and without privacy, over a modelled network.

    python -m ucqlearn.experiments --sf /root/testdata/sf0.001 --workload w0 --scenario full --private
"""

from __future__ import annotations

import argparse
import math

from pyspark.sql import DataFrame

from . import cost, metrics, privacy
from .plans import batches, train
from .sources import workloads

SCENARIOS = {
    "vertical": ("centralized", "vfl_sgd", "vfl_admm", "rel_sgd_v", "rel_admm_v"),
    "full": ("centralized", "rel_sgd", "rel_admm"),
}
#: Chosen from the printed ranges: learning rates 0.01 to 0.5, penalties 0.1 to 2.
GRID_ETA, GRID_RHO = (0.01, 0.05, 0.1, 0.5), (0.1, 0.5, 1.0, 2.0)
EPSILON, DELTA, CLIP, LABEL_STD = 1.0, 1e-5, 1.0, 0.5
#: Public ranges that numeric labels are clipped to before they are noised: stars, and the planted score.
RANGES = {"w0": (-4.0, 6.0), "w3": (1.0, 5.0), "w4": (1.0, 5.0)}


def workload(spark, sf_dir: str, name: str, shards: int, label_std: float | None = None, seed: int = 0):
    """(problem, models) of a workload; with ``label_std`` its labels are noised before they leave their table."""
    if name == "w4":
        ucq, loss, models = workloads.ratings_net(spark, sf_dir, shards)
    else:
        (ucq, loss), models = workloads.WORKLOADS[name](spark, sf_dir, shards=shards), None
    if label_std is not None:
        t = ucq.label_table
        classes = {"accuracy": max(2, loss.classes), "rmse": 1}[loss.metric]
        t.df = privacy.noisy_labels(t.df, t.label, t.row_id, classes, label_std, seed, y_range=RANGES.get(name))
    return ucq, loss, models


def tune(p: train.Problem, method: str, epochs: int, options: dict, etas=GRID_ETA, rhos=GRID_RHO, seed: int = 0) -> dict:
    """The learning rate or penalty with the best metric on a validation part of the training rows, as eta or rho. Runs that
    diverge lose."""
    fit_rows, held = batches.split(p.rowmap, stream="validation")
    part = train.on_rows(p, fit_rows)
    fixed = {k: v for k, v in options.items() if k not in ("eta", "rho")}
    name, values = ("rho", rhos) if method.endswith(("admm", "admm_v")) else ("eta", etas)
    best, _ = train.grid_search(lambda **s: train.METHODS[method](part, epochs=epochs, seed=seed, tests=held, **fixed, **s), {name: list(values)}, p.loss.metric == "rmse")
    return best


def compare(spark, sf_dir: str, name: str = "w0", scenario: str = "vertical", private: bool = False, epochs: int = 10, n_batches: int = 90, eta: float | None = 0.5, rho: float | None = 0.5, beta: float = 1e-3, inner_rounds: int = 10, seeds=(0, 1, 2), network: str = "us_uk", methods=None, tune_epochs: int = 1) -> DataFrame:
    """method, epoch, metric (held-out, mean over seeds), time (seconds of modelled communication so far), rounds, n_values.

    Batches are a share of the joined rows, so that the number of rounds does not grow with the tables. ``eta`` or ``rho`` None is
    tuned for each method on a validation part of the clean training rows, over ``tune_epochs`` epochs. A method that its guard
    stops has no rows. Private runs clip and noise the local updates so that all of them together spend epsilon 1, and noise
    labels once."""
    shards = 1 if scenario == "vertical" else 2
    clean_ucq, loss, models = workload(spark, sf_dir, name, shards)
    clean = train.make_problem(clean_ucq, loss, models)
    fit_rows, tests = batches.split(clean.rowmap)
    clean_fit = train.on_rows(clean, fit_rows)
    curves: dict[tuple, list[float]] = {}
    costs: dict[tuple, tuple] = {}
    tuned: dict[str, dict] = {}
    for seed in seeds:
        p = clean_fit
        if private:
            noisy, loss, models = workload(spark, sf_dir, name, shards, LABEL_STD, seed)
            whole = train.make_problem(noisy, loss, models, store=clean.store)
            p = train.on_rows(whole, batches.split(whole.rowmap)[0])
        size = None if n_batches <= 1 else math.ceil(p.n / n_batches)
        for method in methods or SCENARIOS[scenario]:
            admm = method.endswith(("admm", "admm_v"))
            options = {"rho": rho, "inner_rounds": inner_rounds} if admm else {"eta": eta, "batch_size": size}
            if (rho if admm else eta) is None:
                if method not in tuned:
                    tuned[method] = tune(clean_fit, method, tune_epochs, options | {"beta": beta})
                options |= tuned[method]
            if private and method != "centralized":
                local = 5 if admm else 1
                steps = privacy.steps_taken(epochs * (1 if admm else max(1, n_batches)), inner_rounds if method == "rel_admm" else 1, local)
                sigma = privacy.sigma_for(EPSILON, 1.0 if admm else 1.0 / max(1, n_batches), steps, DELTA)
                options["dp"] = privacy.DpSpec(CLIP, sigma, "joined_row" if not admm else "base_row", seed)
                if admm:  # noise moves the residual up and down, which is no divergence
                    options |= {"steps": local, "lr": 0.5 if eta is None else eta, "guard": 0}
            try:
                r = train.METHODS[method](p, epochs=epochs, beta=beta, seed=seed, tests=tests, **options)
            except train.DivergenceError:
                continue
            for _, epoch, split, _, _, metric in r.history:
                if split == "test":
                    curves.setdefault((method, epoch), []).append(metric)
                    costs[method, epoch] = (cost.comm_time(r.ledger.rounds(epoch), r.ledger.bytes(epoch), network), r.ledger.rounds(epoch), r.ledger.values(epoch))
    history = spark.createDataFrame([(m, e, sum(v) / len(v)) for (m, e), v in curves.items()], "method string, epoch int, metric double")
    spent = spark.createDataFrame([(m, e, *c) for (m, e), c in costs.items()], "method string, epoch int, seconds double, rounds long, n_values long")
    return metrics.with_time(history, spent).select("method", "epoch", "metric", "time", "rounds", "n_values").orderBy("method", "epoch")


def main() -> None:
    from pyspark.sql import SparkSession

    parser = argparse.ArgumentParser(description=__doc__, formatter_class=argparse.RawDescriptionHelpFormatter)
    parser.add_argument("--sf", default="/root/testdata/sf0.001")
    parser.add_argument("--workload", default="w0", choices=[*workloads.WORKLOADS, "w4"])
    parser.add_argument("--scenario", default="vertical", choices=list(SCENARIOS))
    parser.add_argument("--network", default="us_uk", choices=list(cost.NETWORKS))
    parser.add_argument("--private", action="store_true")
    parser.add_argument("--epochs", type=int, default=10)
    parser.add_argument("--batches", type=int, default=90)
    parser.add_argument("--eta", type=float, help="tuned when not given")
    parser.add_argument("--rho", type=float, help="tuned when not given")
    parser.add_argument("--seeds", type=int, default=3)
    a = parser.parse_args()
    spark = SparkSession.builder.appName("experiments").getOrCreate()
    compare(spark, a.sf, a.workload, a.scenario, a.private, a.epochs, a.batches, a.eta, a.rho, seeds=range(a.seeds), network=a.network).show(1000, False)


if __name__ == "__main__":
    main()
