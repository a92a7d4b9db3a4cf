"""Views and functions for use from SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from .functions.columns import name_words
from .operators.steps import ClientOperator, Problem
from .plans import mapping
from .sources.tables import parameter_rows


def register(spark, problem: Problem, thetas: dict | None = None, prefix: str = "") -> list[str]:
    """Temp views: rowmap, fanout_<table>, and with parameters pred_<table> and parameters. Returns their names."""
    made = {f"{prefix}rowmap": problem.rowmap}
    for b in problem.blocks:
        made[f"{prefix}fanout_{b.name}"] = mapping.fan_out(problem.rowmap, b.name)
        if thetas:
            made[f"{prefix}pred_{b.name}"] = ClientOperator(b).predict(thetas[b.name])
    if thetas:
        made[f"{prefix}parameters"] = parameter_rows(spark, thetas)
    for name, df in made.items():
        df.createOrReplaceTempView(name)
    register_functions(spark)
    return list(made)


def register_functions(spark) -> None:
    """ucq_score(features, theta) in the JVM, and explode_words(name) as a table function."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION ucq_score(x ARRAY<DOUBLE>, theta ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(x, theta, (a, b) -> a * b), 0.0D, (s, v) -> s + v)")

    @F.udtf(returnType="pos int, word string")
    class ExplodeWords:
        def eval(self, name: str):
            for i, w in enumerate((name or "").split()):
                yield i, w

    spark.udtf.register("explode_words", ExplodeWords)


def predict(problem: Problem, thetas: dict):
    """Scores of all joined rows from the tables' own predictions; features stay with their tables."""
    from .operators.steps import JoinOperator

    join = JoinOperator(problem)
    scored = join.gather(problem.rowmap, {b.name: ClientOperator(b).predict(thetas[b.name]) for b in problem.blocks})
    return scored.select(*problem.rowmap.columns, problem.loss.predicted([F.col(f"m{c}") for c in range(problem.classes)]).alias("pred"))


__all__ = ["register", "register_functions", "predict", "name_words"]
