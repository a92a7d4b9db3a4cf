"""Registered queries of the methods, variants, baselines, measures and operators, with the SQL that must agree.

Learning queries take natural columns scaled by fixed numbers, so that SQL can state the same features. Doubles are
rounded to six digits, and arrays come as (tbl, i, j, value).
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Window
from pyspark.sql import functions as F

from . import cost, metrics, privacy
from .functions import columns as fx
from .functions.losses import LogisticLoss, SoftmaxLoss, SquaredLoss
from .functions.models import LinearModel
from .operators.joins import asof_join, range_join, salted_join
from .operators.steps import ClientOperator, JoinOperator
from .plans import batches, mapping, train
from .plans.ucq import TableSpec, UcqSpec
from .sources.tables import load_table, parameter_rows, step_rows
from .sources.workloads import EDGES_W0, lineitems, name_words, with_shards

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


def r6(c):
    return F.round(c, 6) + F.lit(0.0)


def rounded(df, *names):
    return df.select(*[r6(F.col(c)).alias(c) if c in names else F.col(c) for c in df.columns])


# ---- the fixture that Spark and SQL share

SCALED = {
    "lineitem": ["(l_quantity - 25.5e0) / 14.4e0", "(l_discount - 5e-2) / 3e-2"],
    "part": ["(p_size - 25.5e0) / 14.4e0", "(p_retailprice - 950e0) / 29e0"],
    "supplier": ["s_acctbal / 5000e0"],
}
Y_NUMBER, Y_BINARY = "l_extendedprice / 20000e0", "CASE WHEN l_linestatus = 'F' THEN 1.0 ELSE 0.0 END"
L_RID = "((((l_orderkey * 20000003 + l_partkey) * 1009 + l_suppkey) * 8 + l_linenumber) * 64 + CAST(l_quantity AS BIGINT))"


def number_sql(*parts):
    """What ``hash_number`` gives."""
    return f"CAST('0x' || substr(md5(concat_ws('|', {', '.join(str(x) for x in parts)})), 1, 15) AS BIGINT)"


jid_sql = number_sql


JID_W0 = jid_sql(L_RID, "p_partkey", "s_suppkey")


def bid_sql(n_batches, seed=0, epoch=0, jid=JID_W0):
    return "CAST(" + number_sql("'batch'", f"'{seed}'", f"'{epoch}'", jid) + f" % {n_batches} AS INTEGER)"


def test_sql(jid=JID_W0):
    return f"({number_sql(repr('split'), jid)} % 100 < 15)"


def x_sql(y=Y_NUMBER, more=""):
    parts = [e for t in SCALED.values() for e in t]
    cols = ", ".join(f"CAST({e} AS DOUBLE) AS x{i}" for i, e in enumerate(parts))
    return f"x AS MATERIALIZED (SELECT {L_RID} AS r0, p_partkey AS r1, s_suppkey AS r2, {JID_W0} AS jid, {cols}, CAST({y} AS DOUBLE) AS y{more} FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey)"


SLOTS = [(t, i) for t, es in SCALED.items() for i in range(len(es))]
BLOCKS = {"lineitem": [0, 1], "part": [2, 3], "supplier": [4]}


def shared(spark, sf_dir, binary=False, shards=1) -> UcqSpec:
    """W0 with fixed scaling; the supplier table may come in shards."""
    y = Y_BINARY if binary else Y_NUMBER
    li = lineitems(spark, sf_dir).select("l_rid", "l_partkey", "l_suppkey", *[F.expr(e).cast("double").alias(f"a{i}") for i, e in enumerate(SCALED["lineitem"])], F.expr(y).cast("double").alias("y"))
    part = load_table(spark, sf_dir, "part").select("p_partkey", *[F.expr(e).cast("double").alias(f"a{i}") for i, e in enumerate(SCALED["part"])])
    supplier = load_table(spark, sf_dir, "supplier").select("s_suppkey", *[F.expr(e).cast("double").alias(f"a{i}") for i, e in enumerate(SCALED["supplier"])])
    tables = [
        TableSpec("lineitem", li, ["l_partkey", "l_suppkey"], ["a0", "a1"], "l_rid", "y"),
        TableSpec("part", with_shards(part, "p_partkey", shards), ["p_partkey"], ["a0", "a1"], "p_partkey", None, "shard", shards),
        TableSpec("supplier", with_shards(supplier, "s_suppkey", shards), ["s_suppkey"], ["a0"], "s_suppkey", None, "shard", shards),
    ]
    return UcqSpec(tables, EDGES_W0)


def problem(spark, sf_dir, loss=None, binary=False, shards=1):
    return train.make_problem(shared(spark, sf_dir, binary, shards), loss or SquaredLoss())


THETA = {"lineitem": np.array([[0.3], [-0.2]]), "part": np.array([[0.1], [0.25]]), "supplier": np.array([[0.15]])}
FLAT = [float(THETA[t][i, 0]) for t, i in SLOTS]
MARGIN = " + ".join(f"{p} * x{i}" for i, p in enumerate(FLAT))
SIGMA = "(1.0 / (1.0 + exp(-({m}))))"


def thetas_frame(spark, by_epoch):
    """step, tbl, i, j, value."""
    return rounded(step_rows(spark, by_epoch), "value")


def unpivot_sql(ctes: list[str], names: list[str], slots=SLOTS) -> str:
    parts = [f"SELECT {s} AS step, '{t}' AS tbl, {i} AS i, 0 AS j, round(p{k}, 6) + 0.0 AS value FROM {c}" for s, c in enumerate(names, 1) for k, (t, i) in enumerate(slots)]
    return "WITH " + ",\n".join(ctes) + "\n" + "\nUNION ALL ".join(parts)


def sgd_sql(steps: int, eta: float, beta: float, y=Y_NUMBER, derivative="({m}) - y", n_batches: int = 1, x: str | None = None, slots=SLOTS, clip: float | None = None) -> str:
    """``x``: a CTE with x0.., y in place of W0's; ``clip``: the norm of a joined row's part in each table."""
    d = len(slots)
    more = f", {bid_sql(n_batches, 0, 1)} AS bid" if n_batches > 1 else ""
    ctes, names = [x or x_sql(y, more), "t0 AS (SELECT " + ", ".join(f"0.0::DOUBLE AS p{i}" for i in range(d)) + ")"], []
    for s in range(1, steps + 1):
        m = " + ".join(f"p{i} * x{i}" for i in range(d))
        where = f" WHERE bid = {s - 1}" if n_batches > 1 else ""
        factor = [""] * d
        if clip:
            norms = {t: " + ".join(f"x{i} * x{i}" for i, (u, _) in enumerate(slots) if u == t) for t, _ in slots}
            factor = [f" * least(1.0, {clip} / greatest(abs({derivative.format(m=m)}) * sqrt({norms[t]}), 1e-12))" for t, _ in slots]
        g = f"SELECT {', '.join(f'avg(({derivative.format(m=m)}) * x{i}{factor[i]}) AS g{i}' for i in range(d))} FROM x, t{s - 1}{where}"
        ctes.append(f"t{s} AS MATERIALIZED (SELECT {', '.join(f'p{i} - {eta} * (g{i} + {beta} * p{i}) AS p{i}' for i in range(d))} FROM t{s - 1}, ({g}))")
        names.append(f"t{s}")
    return unpivot_sql(ctes, names if n_batches == 1 else names[-1:], slots)


def admm_sql(epochs: int, rho: float, beta: float, inner: int = 0, rho_in: float = 1.0, extra: float = 0.0, steps: int = 0, lr: float = 0.0) -> str:
    """Parallel schedule with squared loss. Blocks of two are solved by determinants. With ``inner`` the supplier block is
    in two shards and goes through consensus rounds. With ``steps`` every block takes gradient steps in place of solving."""
    d = len(SLOTS)
    ctes = [x_sql(), "n AS (SELECT count(*) AS n FROM x)", "t0 AS (SELECT " + ", ".join(f"0.0::DOUBLE AS p{i}" for i in range(d)) + ")", "s0 AS MATERIALIZED (SELECT *, 0.0::DOUBLE AS mu FROM x)"]
    if inner:
        ctes.append("w0 AS (SELECT 0.0::DOUBLE AS omega, 0.0::DOUBLE AS d0, 0.0::DOUBLE AS d1)")
    names = []
    for e in range(1, epochs + 1):
        m = " + ".join(f"p{i} * x{i}" for i in range(d))
        ctes.append(f"m{e} AS MATERIALIZED (SELECT s.* EXCLUDE (mu), mu AS mu_old, {m} AS m, {', '.join(f'{' + '.join(f'p{i} * x{i}' for i in b)} AS u_{t}' for t, b in BLOCKS.items())} FROM s{e - 1} s, t{e - 1})")
        ctes.append(f"v{e} AS MATERIALIZED (SELECT *, (y + mu_old + {rho} * m) / (1.0 + {rho}) AS v FROM m{e})")
        ctes.append(f"q{e} AS MATERIALIZED (SELECT *, mu_old + {rho} * (m - v) AS mu, mu_old + 2 * {rho} * (m - v) AS q FROM v{e})")
        ctes.append(f"s{e} AS MATERIALIZED (SELECT {', '.join(f'x{i}' for i in range(d))}, r0, r1, r2, jid, y, mu FROM q{e})")
        sums = []
        for t, b in BLOCKS.items():
            sums += [f"sum(x{i} * (q - {rho} * u_{t})) AS b{i}" for i in b] + [f"sum(x{i} * x{j}) AS a{i}_{j}" for i in b for j in b if i <= j]
        if inner:
            sums += [f"sum(CASE WHEN r2 % 2 = {s} THEN x4 * (q - {rho} * u_supplier) ELSE 0 END) AS b4_{s}, sum(CASE WHEN r2 % 2 = {s} THEN x4 * x4 ELSE 0 END) AS a4_4_{s}" for s in (0, 1)]
        ctes.append(f"g{e} AS MATERIALIZED (SELECT {', '.join(sums)} FROM q{e})")
        new, last_step = [], f"t{e - 1}"
        for k in range(1, steps + 1):
            slope = {i: " + ".join(f"a{min(i, j)}_{max(i, j)} * p{j}" for j in b) for b in BLOCKS.values() for i in b}
            ctes.append(f"h{e}_{k} AS MATERIALIZED (SELECT {', '.join(f'p{i} - {lr} * ((b{i} + {rho} * ({slope[i]})) / n + {beta} * p{i}) AS p{i}' for i in range(d))} FROM {last_step}, g{e}, n)")
            last_step = f"h{e}_{k}"
        if steps:
            ctes.append(f"t{e} AS MATERIALIZED (SELECT * FROM {last_step})")
            names.append(f"t{e}")
            continue
        for t, b in BLOCKS.items():
            if len(b) == 2:
                i, j = b
                ri, rj = f"(-b{i} / n + {extra} / n * (a{i}_{i} * p{i} + a{i}_{j} * p{j}))", f"(-b{j} / n + {extra} / n * (a{i}_{j} * p{i} + a{j}_{j} * p{j}))"
                aii, aij, ajj = (f"({beta if k == l else 0.0} + {rho + extra} / n * a{k}_{l})" for k, l in ((i, i), (i, j), (j, j)))
                det = f"({aii} * {ajj} - {aij} * {aij})"
                new += [f"({ri} * {ajj} - {rj} * {aij}) / {det} AS p{i}", f"({rj} * {aii} - {ri} * {aij}) / {det} AS p{j}"]
            elif not inner:
                (i,) = b
                new.append(f"(-b{i} / n + {extra} / n * a{i}_{i} * p{i}) / ({beta} + {rho + extra} / n * a{i}_{i}) AS p{i}")
        if inner:
            last = f"w{e - 1}"
            for k in range(1, inner + 1):
                prox = [f"(({rho_in} * (omega - d{s}) - b4_{s} / n) / ({rho_in} + {rho} / n * a4_4_{s}))" for s in (0, 1)]
                ctes.append(f"z{e}_{k} AS (SELECT omega, d0, d1, {prox[0]} AS h0, {prox[1]} AS h1 FROM {last}, g{e}, n)")
                ctes.append(f"o{e}_{k} AS (SELECT *, 2 * {rho_in} * ((h0 + h1) / 2 + (d0 + d1) / 2) / ({beta} + 2 * {rho_in}) AS new FROM z{e}_{k})")
                last = f"w{e}" if k == inner else f"i{e}_{k}"
                ctes.append(f"{last} AS MATERIALIZED (SELECT new AS omega, d0 + h0 - new AS d0, d1 + h1 - new AS d1 FROM o{e}_{k})")
            new.append("omega AS p4")
        ctes.append(f"t{e} AS MATERIALIZED (SELECT {', '.join(new)} FROM g{e}, n, t{e - 1}{f', w{e}' if inner else ''})")
        names.append(f"t{e}")
    return unpivot_sql(ctes, names)


# ---- table mapping

JOIN_W0 = "FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey"


@query("row_map_w0", f"SELECT {L_RID} AS r_lineitem, p_partkey AS r_part, s_suppkey AS r_supplier, {JID_W0} AS jid, {Y_NUMBER} AS y {JOIN_W0}")
def row_map_w0(spark, sf_dir):
    return mapping.build_row_map(shared(spark, sf_dir))


@query("row_map_virtual_w0", f"SELECT {L_RID} AS r_lineitem, p_partkey AS r_part, s_suppkey AS r_supplier, {JID_W0} AS jid, {Y_NUMBER} AS y {JOIN_W0}")
def row_map_virtual_w0(spark, sf_dir):
    ucq = shared(spark, sf_dir)
    return mapping.virtual_row_map(ucq.label_table, {"part": "l_partkey", "supplier": "l_suppkey"})


def _w1(spark, sf_dir):
    li = lineitems(spark, sf_dir).select("l_rid", "l_orderkey", "l_partkey", "l_suppkey", F.expr(Y_BINARY).alias("y"), F.col("l_quantity").alias("a"))
    bare = {"customer": ("c_custkey", [], "c_acctbal"), "orders": ("o_orderkey", ["o_custkey"], "o_totalprice"), "part": ("p_partkey", [], "p_size"), "supplier": ("s_suppkey", [], "s_acctbal")}
    tables = [TableSpec("lineitem", li, ["l_orderkey", "l_partkey", "l_suppkey"], ["a"], "l_rid", "y")]
    tables += [TableSpec(n, load_table(spark, sf_dir, n), [k, *more], [f], k) for n, (k, more, f) in bare.items()]
    return UcqSpec(tables, [*EDGES_W0, (("lineitem", "l_orderkey"), ("orders", "o_orderkey")), (("orders", "o_custkey"), ("customer", "c_custkey"))])


@query("row_map_w1", f"SELECT {L_RID} AS r_lineitem, c_custkey AS r_customer, o_orderkey AS r_orders, p_partkey AS r_part, s_suppkey AS r_supplier, CAST({Y_BINARY} AS DOUBLE) AS y {JOIN_W0} JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey")
def row_map_w1(spark, sf_dir):
    return mapping.build_row_map(_w1(spark, sf_dir)).drop("jid").withColumn("y", F.col("y"))


@query(
    "row_map_w3",
    f"""SELECT {L_RID} AS r_lineitem, p_partkey * 16 + pos AS r_part, s_suppkey AS r_supplier
FROM lineitem JOIN (SELECT p_partkey, unnest(range(0, len(string_split(trim(p_name), ' ')))) AS pos FROM part) ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey""",
)
def row_map_w3(spark, sf_dir):
    ucq = shared(spark, sf_dir)
    words = load_table(spark, sf_dir, "part").select("p_partkey", F.posexplode(name_words(F.col("p_name"))).alias("pos", "word"))
    words = words.select("p_partkey", (F.col("p_partkey") * 16 + F.col("pos")).alias("p_rid"), F.length("word").cast("double").alias("letters"))
    tables = [ucq.table("lineitem"), TableSpec("part", words, ["p_partkey"], ["letters"], "p_rid"), ucq.table("supplier")]
    return mapping.build_row_map(UcqSpec(tables, EDGES_W0)).select("r_lineitem", "r_part", "r_supplier")


@query("row_map_m2n", "SELECT event_id AS r_events, c_custkey AS r_customer, o_orderkey AS r_orders FROM events JOIN customer ON user_id = c_custkey JOIN orders ON o_custkey = c_custkey")
def row_map_m2n(spark, sf_dir):
    from .sources.workloads import stays

    return mapping.build_row_map(stays(spark, sf_dir)[0]).select("r_events", "r_customer", "r_orders")


@query("ucq_expansion_w0", f"SELECT s_suppkey AS r_supplier, count(*) AS n, CAST(sum(p_partkey) AS BIGINT) AS parts, CAST(sum({L_RID} % 1000) AS BIGINT) AS lines {JOIN_W0} GROUP BY s_suppkey")
def ucq_expansion_w0(spark, sf_dir):
    rows = mapping.expand_union_of_joins(shared(spark, sf_dir, shards=2))
    return rows.groupBy("r_supplier").agg(F.count(F.lit(1)).alias("n"), F.sum("r_part").alias("parts"), F.sum(F.pmod("r_lineitem", F.lit(1000))).alias("lines"))


@query("hashed_key_map_w0", f"SELECT p_partkey AS r_part, sha256(CAST(p_partkey AS VARCHAR)) AS digest, count(*) AS n {JOIN_W0} GROUP BY p_partkey")
def hashed_key_map_w0(spark, sf_dir):
    ucq = shared(spark, sf_dir)
    rows = mapping.build_row_map(ucq, hash_keys=True)
    digests = mapping.extract_keys(ucq.table("part"), hash_keys=True).select(F.col("rid").alias("r_part"), F.col("k_p_partkey").alias("digest"))
    return rows.groupBy("r_part").agg(F.count(F.lit(1)).alias("n")).join(digests, "r_part")


@query("merged_extracts_supplier", "SELECT s_suppkey AS rid, CAST(s_suppkey % 2 AS INTEGER) AS shard, s_suppkey AS k_s_suppkey FROM supplier")
def merged_extracts_supplier(spark, sf_dir):
    t = shared(spark, sf_dir, shards=2).table("supplier")
    whole = mapping.extract_keys(t)
    return mapping.merge_extracts([whole.where(F.col("shard") == s) for s in range(2)], check=True)


@query("materialized_join_w0", f"SELECT {L_RID} AS r_lineitem, round({SCALED['part'][0]}, 6) + 0.0 AS a, round({SCALED['supplier'][0]}, 6) + 0.0 AS b {JOIN_W0}")
def materialized_join_w0(spark, sf_dir):
    x = mapping.materialize_join(shared(spark, sf_dir))
    return x.select("r_lineitem", r6(F.get("x_part", F.lit(0))).alias("a"), r6(F.get("x_supplier", F.lit(0))).alias("b"))


@query("fanout_part", f"SELECT p_partkey AS rid, count(*) AS c {JOIN_W0} GROUP BY p_partkey")
def fanout_part(spark, sf_dir):
    return mapping.fan_out(row_map_w0(spark, sf_dir), "part")


@query("fanout_orders_with_zero", "SELECT o_orderkey AS rid, count(l_orderkey) AS c FROM orders LEFT JOIN lineitem ON l_orderkey = o_orderkey GROUP BY o_orderkey")
def fanout_orders_with_zero(spark, sf_dir):
    ucq = _w1(spark, sf_dir)
    return mapping.fan_out(mapping.build_row_map(ucq), "orders", ucq.table("orders"))


@query("fanout_all_sets", f"WITH j AS (SELECT p_partkey, s_suppkey {JOIN_W0}) SELECT 'part' AS tbl, p_partkey AS rid, count(*) AS c FROM j GROUP BY 2 UNION ALL SELECT 'supplier', s_suppkey, count(*) FROM j GROUP BY 2")
def fanout_all_sets(spark, sf_dir):
    return mapping.fan_out_all(spark, row_map_w0(spark, sf_dir), ["part", "supplier"])


@query("reverse_map_supplier", f"SELECT s_suppkey AS rid, count(*) AS n, min({JID_W0}) AS least, max({JID_W0}) AS greatest, bit_xor({JID_W0}) AS checksum {JOIN_W0} GROUP BY s_suppkey")
def reverse_map_supplier(spark, sf_dir):
    return mapping.reverse_map(row_map_w0(spark, sf_dir), "supplier")


@query("duplication_factor", f"WITH j AS (SELECT {L_RID} AS l, p_partkey AS p, s_suppkey AS s {JOIN_W0}), c AS (SELECT count(*) AS n, count(DISTINCT l) AS l, count(DISTINCT p) AS p, count(DISTINCT s) AS s FROM j) SELECT 'lineitem' AS tbl, n AS joined_rows, l AS base_rows, round(n / l, 6) + 0.0 AS factor FROM c UNION ALL SELECT 'part', n, p, round(n / p, 6) + 0.0 FROM c UNION ALL SELECT 'supplier', n, s, round(n / s, 6) + 0.0 FROM c")
def duplication_factor(spark, sf_dir):
    return rounded(mapping.duplication(row_map_w0(spark, sf_dir), ["lineitem", "part", "supplier"]), "factor")


BID6 = bid_sql(6, 5)


@query("batch_ids_w0", f"SELECT {BID6} AS bid, count(*) AS n, CAST(sum(p_partkey) AS BIGINT) AS parts {JOIN_W0} GROUP BY 1")
def batch_ids_w0(spark, sf_dir):
    return batches.with_batches(row_map_w0(spark, sf_dir), 6, 5).groupBy("bid").agg(F.count(F.lit(1)).alias("n"), F.sum("r_part").alias("parts"))


@query("test_split_w0", f"SELECT {test_sql()} AS test, count(*) AS n {JOIN_W0} GROUP BY 1")
def test_split_w0(spark, sf_dir):
    return row_map_w0(spark, sf_dir).groupBy(batches.is_test(F.col("jid")).alias("test")).agg(F.count(F.lit(1)).alias("n"))


@query("alpha_by_table", f"WITH j AS (SELECT {BID6} AS bid, {L_RID} AS l, p_partkey AS p, s_suppkey AS s {JOIN_W0}), c AS (SELECT bid, count(DISTINCT l) AS l, count(DISTINCT p) AS p, count(DISTINCT s) AS s FROM j GROUP BY bid) SELECT 'lineitem' AS tbl, CAST(sum(l) AS BIGINT) AS alpha FROM c UNION ALL SELECT 'part', CAST(sum(p) AS BIGINT) FROM c UNION ALL SELECT 'supplier', CAST(sum(s) AS BIGINT) FROM c")
def alpha_by_table(spark, sf_dir):
    return batches.alpha(batches.with_batches(row_map_w0(spark, sf_dir), 6, 5), ["lineitem", "part", "supplier"])


# ---- margins, objective, derivatives, folds, gradients


def scored_w0(spark, sf_dir, loss=None, binary=False):
    ucq = shared(spark, sf_dir, binary)
    p = train.Problem(spark, [train.Block(t.name, t.block(), LinearModel(len(t.features))) for t in ucq.tables], mapping.build_row_map(ucq), loss or SquaredLoss(), None, 0)
    join = JoinOperator(p)
    return p, join, join.gather(p.rowmap, {b.name: ClientOperator(b).predict(THETA[b.name]) for b in p.blocks}, keep=True)


@query("margin_given_theta", f"WITH {x_sql()} SELECT r0 AS r_lineitem, round({MARGIN}, 6) + 0.0 AS m FROM x")
def margin_given_theta(spark, sf_dir):
    return scored_w0(spark, sf_dir)[2].select("r_lineitem", r6(F.col("m0")).alias("m"))


@query("objective_given_theta", f"WITH {x_sql()} SELECT count(*) AS rows, round(avg(0.5 * (({MARGIN}) - y) * (({MARGIN}) - y)) + {0.5 * 0.01 * sum(p * p for p in FLAT)!r}, 6) + 0.0 AS objective FROM x")
def objective_given_theta(spark, sf_dir):
    s = metrics.summary(scored_w0(spark, sf_dir)[2], SquaredLoss())
    return s.select("rows", r6(F.col("loss") + train.penalty(THETA, 0.01)).alias("objective"))


def _deriv(name, loss, binary, sql):
    y = Y_BINARY if binary else Y_NUMBER

    @query(name, f"WITH {x_sql(y)} SELECT r1 AS r_part, {', '.join(f'round(sum({s}), 6) + 0.0 AS d{c}' for c, s in enumerate(sql))} FROM x GROUP BY r1")
    def run(spark, sf_dir):
        p, join, s = scored_w0(spark, sf_dir, SquaredLoss() if loss.classes > 1 else loss, binary)
        if loss.classes > 1:  # three classes: margins m, -m and m / 2; classes by the row's number
            s = s.select("r_part", F.pmod("r_lineitem", F.lit(3)).cast("double").alias("y"), F.col("m0"), (-F.col("m0")).alias("m1"), (F.col("m0") / 2).alias("m2"))
        d = loss.derivative([F.col(f"m{c}") for c in range(loss.classes)], F.col("y"))
        return s.groupBy("r_part").agg(*[r6(F.sum(x)).alias(f"d{c}") for c, x in enumerate(d)])


_deriv("deriv_squared", SquaredLoss(), False, [f"({MARGIN}) - y"])
_deriv("deriv_logistic", LogisticLoss(), True, [f"{SIGMA.format(m=MARGIN)} - y"])
_E3 = [f"exp({MARGIN})", f"exp(-({MARGIN}))", f"exp(({MARGIN}) / 2)"]
_deriv("deriv_softmax", SoftmaxLoss(3), False, [f"{e} / ({' + '.join(_E3)}) - CASE WHEN r0 % 3 = {c} THEN 1.0 ELSE 0.0 END" for c, e in enumerate(_E3)])


@query("folded_signal_sgd", f"WITH {x_sql()} SELECT r2 AS rid, round(sum(({MARGIN}) - y), 6) + 0.0 AS g0, count(*) AS c FROM x GROUP BY r2")
def folded_signal_sgd(spark, sf_dir):
    p, join, s = scored_w0(spark, sf_dir)
    return rounded(join.fold(join.derivatives(s), "supplier", [F.col("d0")]), "g0")


_V = f"((y + 0.1 + 0.5 * ({MARGIN})) / 1.5)"


@query("folded_signal_admm", f"WITH {x_sql()} SELECT r1 AS rid, round(sum(0.1 + 0.5 * (({MARGIN}) - {_V}) + 0.5 * (({MARGIN}) - {_V} - ({FLAT[2]} * x2 + {FLAT[3]} * x3))), 6) + 0.0 AS g0, count(*) AS c FROM x GROUP BY r1")
def folded_signal_admm(spark, sf_dir):
    p, join, s = scored_w0(spark, sf_dir)
    from .plans.train import server_step

    stepped = server_step(join, s.withColumn("mu0", F.lit(0.1)), 0.5)
    return rounded(join.fold(stepped, "part", [F.col("q0") - 0.5 * F.col("u_part_0")]), "g0")


_GRAD = f"WITH {x_sql()} " + " UNION ALL ".join(f"SELECT '{t}' AS tbl, {i} AS i, 0 AS j, round(sum((({MARGIN}) - y) * x{k}) / count(*), 6) + 0.0 AS value FROM x" for k, (t, i) in enumerate(SLOTS))


def _gradient(spark, sf_dir, folded, shards=1):
    from .operators.steps import UnionOperator, partial_gradients

    p = problem(spark, sf_dir, shards=shards)
    p = p if folded else train.slices(p)
    join = JoinOperator(p)
    clients = {b.name: ClientOperator(b) for b in p.blocks}
    s = join.derivatives(join.gather(p.rowmap, {n: c.predict(THETA[n]) for n, c in clients.items()}))
    parts = partial_gradients({n: c.receive(join.fold(s, n, [F.col("d0")])) for n, c in clients.items()}, p.blocks, THETA)
    total = {n: UnionOperator.add(v, THETA[n].shape) / p.n for n, v in parts.items()}
    return rounded(parameter_rows(spark, total), "value")


@query("gradient_unfolded", _GRAD)
def gradient_unfolded(spark, sf_dir):
    return _gradient(spark, sf_dir, False)


@query("gradient_folded", _GRAD)
def gradient_folded(spark, sf_dir):
    return _gradient(spark, sf_dir, True)


@query("gradient_sharded", _GRAD)
def gradient_sharded(spark, sf_dir):
    return _gradient(spark, sf_dir, True, 3)


def _gram_sql(shard):
    group = f"CAST(r1 % {shard} AS INTEGER)" if shard else "0"
    return f"WITH {x_sql()} " + " UNION ALL ".join(f"SELECT {group} AS shard, {i} AS i, {j} AS j, round(sum(x{2 + i} * x{2 + j}), 6) + 0.0 AS value FROM x GROUP BY 1" for i in (0, 1) for j in (0, 1))


def _gram(spark, sf_dir, shards):
    p = problem(spark, sf_dir, shards=shards)
    b = p.blocks[1]
    grams = ClientOperator(b).gram(mapping.fan_out(p.rowmap, "part"))
    rows = [(s, i, j, float(a[i, j])) for s, a in grams.items() for i in (0, 1) for j in (0, 1)]
    return rounded(spark.createDataFrame(rows, "shard int, i int, j int, value double"), "value")


@query("gram_part", _gram_sql(0))
def gram_part(spark, sf_dir):
    return _gram(spark, sf_dir, 1)


@query("gram_sharded", _gram_sql(2))
def gram_sharded(spark, sf_dir):
    return _gram(spark, sf_dir, 2)


# ---- training, step by step

_SGD = {"eta": 0.4, "beta": 0.01}
_SGD_SQL = sgd_sql(3, **_SGD)


def _fit(name, method, sql, shards=1, loss=None, binary=False, last=False, **options):
    @query(name, sql)
    def run(spark, sf_dir):
        p = problem(spark, sf_dir, loss, binary, shards)
        found = method(p, track=False, **options).by_epoch
        return thetas_frame(spark, found)


_fit("sgd_w0_steps", train.rel_sgd_v, _SGD_SQL, epochs=3, **_SGD)
_fit("rel_sgd_sharded_steps", train.rel_sgd, _SGD_SQL, shards=3, epochs=3, **_SGD)
_fit("vfl_sgd_steps", train.vfl_sgd, _SGD_SQL, epochs=3, **_SGD)
_fit("centralized_steps", train.centralized, _SGD_SQL, epochs=3, **_SGD)
_fit("sgd_logistic_steps", train.rel_sgd_v, sgd_sql(2, 0.4, 0.01, Y_BINARY, SIGMA + " - y"), loss=LogisticLoss(), binary=True, epochs=2, **_SGD)
_fit("admm_w0_epochs", train.rel_admm_v, admm_sql(3, 0.5, 0.01), epochs=3, rho=0.5, beta=0.01)
_fit("vfl_admm_epochs", train.vfl_admm, admm_sql(3, 0.5, 0.01), epochs=3, rho=0.5, beta=0.01)
_fit("admm_proximal_epochs", train.rel_admm_v, admm_sql(2, 0.5, 0.01, extra=1.0), epochs=2, rho=0.5, beta=0.01, schedule="proximal")


@query("sgd_minibatch_epoch", sgd_sql(4, n_batches=4, **_SGD))
def sgd_minibatch_epoch(spark, sf_dir):
    p = problem(spark, sf_dir)
    import math

    return thetas_frame(spark, train.rel_sgd_v(p, epochs=1, batch_size=math.ceil(p.n / 4), track=False, **_SGD).by_epoch)


_fit("admm_inner_sgd_epochs", train.rel_admm_v, admm_sql(2, 0.5, 0.01, steps=3, lr=0.4), epochs=2, rho=0.5, beta=0.01, inner="sgd", steps=3, lr=0.4)
_fit("sgd_clipped_steps", train.rel_sgd_v, sgd_sql(2, 0.4, 0.01, clip=0.3), epochs=2, dp=privacy.DpSpec(clip=0.3, sigma=0.0, unit="joined_row"), **_SGD)


# ---- the other workloads, with fixed scaling

_W1_SLOTS = [("lineitem", 0), ("lineitem", 1), ("customer", 0), ("orders", 0), ("part", 0), ("part", 1), ("supplier", 0)]
_W1_X = f"x AS MATERIALIZED (SELECT {', '.join(f'CAST({e} AS DOUBLE) AS x{i}' for i, e in enumerate([*SCALED['lineitem'], 'c_acctbal / 5000e0', 'o_totalprice / 250000e0', *SCALED['part'], *SCALED['supplier']]))}, {Y_BINARY} AS y FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey)"


def _w1_problem(spark, sf_dir):
    ucq = shared(spark, sf_dir, True)
    li = lineitems(spark, sf_dir).select("l_rid", "l_orderkey")
    line = ucq.table("lineitem")
    line.df, line.keys = line.df.join(li, "l_rid"), ["l_orderkey", "l_partkey", "l_suppkey"]
    orders = load_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", (F.col("o_totalprice") / 250000.0).alias("a0"))
    customer = load_table(spark, sf_dir, "customer").select("c_custkey", (F.col("c_acctbal") / 5000.0).alias("a0"))
    tables = [line, TableSpec("customer", customer, ["c_custkey"], ["a0"], "c_custkey"), TableSpec("orders", orders, ["o_orderkey", "o_custkey"], ["a0"], "o_orderkey"), ucq.table("part"), ucq.table("supplier")]
    return train.make_problem(UcqSpec(tables, [*EDGES_W0, (("lineitem", "l_orderkey"), ("orders", "o_orderkey")), (("orders", "o_custkey"), ("customer", "c_custkey"))]), LogisticLoss())


@query("sgd_w1_logistic_steps", sgd_sql(2, 0.4, 0.01, derivative=SIGMA + " - y", x=_W1_X, slots=_W1_SLOTS))
def sgd_w1_logistic_steps(spark, sf_dir):
    return thetas_frame(spark, train.rel_sgd_v(_w1_problem(spark, sf_dir), epochs=2, track=False, **_SGD).by_epoch)


_W1M_SLOTS = [("events", 0), ("events", 1), ("customer", 0), ("orders", 0)]
_W1M_X = "x AS MATERIALIZED (SELECT CAST(value / 50e0 AS DOUBLE) AS x0, 1.0::DOUBLE AS x1, CAST(c_acctbal / 5000e0 AS DOUBLE) AS x2, CAST(o_totalprice / 250000e0 AS DOUBLE) AS x3, CASE WHEN event_type = 'error' THEN 1.0 ELSE 0.0 END AS y FROM events JOIN customer ON user_id = c_custkey JOIN orders ON o_custkey = c_custkey)"


@query("sgd_w1m_logistic_steps", sgd_sql(2, 0.4, 0.01, derivative=SIGMA + " - y", x=_W1M_X, slots=_W1M_SLOTS))
def sgd_w1m_logistic_steps(spark, sf_dir):
    events = load_table(spark, sf_dir, "events").select("event_id", "user_id", (F.col("value") / 50.0).alias("a0"), F.lit(1.0).alias("a1"), F.when(F.col("event_type") == "error", 1.0).otherwise(0.0).alias("y"))
    orders = load_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", (F.col("o_totalprice") / 250000.0).alias("a0"))
    customer = load_table(spark, sf_dir, "customer").select("c_custkey", (F.col("c_acctbal") / 5000.0).alias("a0"))
    tables = [TableSpec("events", events, ["user_id"], ["a0", "a1"], "event_id", "y"), TableSpec("customer", customer, ["c_custkey"], ["a0"], "c_custkey"), TableSpec("orders", orders, ["o_custkey"], ["a0"], "o_orderkey")]
    p = train.make_problem(UcqSpec(tables, [(("events", "user_id"), ("customer", "c_custkey")), (("orders", "o_custkey"), ("customer", "c_custkey"))]), LogisticLoss())
    return thetas_frame(spark, train.rel_sgd_v(p, epochs=2, track=False, **_SGD).by_epoch)


_W3_SLOTS = [("lineitem", 0), ("lineitem", 1), ("part", 0), ("part", 1), ("supplier", 0)]
_W3_X = f"x AS MATERIALIZED (SELECT CAST({SCALED['lineitem'][0]} AS DOUBLE) AS x0, CAST({SCALED['lineitem'][1]} AS DOUBLE) AS x1, CAST({SCALED['part'][0]} AS DOUBLE) AS x2, CAST(len(word) / 5e0 AS DOUBLE) AS x3, CAST({SCALED['supplier'][0]} AS DOUBLE) AS x4, CAST({Y_NUMBER} AS DOUBLE) AS y FROM lineitem JOIN (SELECT p_partkey, p_size, unnest(string_split(trim(p_name), ' ')) AS word FROM part) ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey)"


@query("sgd_w3_steps", sgd_sql(2, 0.4, 0.01, x=_W3_X, slots=_W3_SLOTS))
def sgd_w3_steps(spark, sf_dir):
    ucq = shared(spark, sf_dir)
    words = load_table(spark, sf_dir, "part").select("p_partkey", F.expr(SCALED["part"][0]).cast("double").alias("a0"), F.posexplode(name_words(F.col("p_name"))).alias("pos", "word"))
    words = words.select("p_partkey", (F.col("p_partkey") * 16 + F.col("pos")).alias("p_rid"), "a0", (F.length("word") / 5.0).alias("a1"))
    tables = [ucq.table("lineitem"), TableSpec("part", words, ["p_partkey"], ["a0", "a1"], "p_rid"), ucq.table("supplier")]
    return thetas_frame(spark, train.rel_sgd_v(train.make_problem(UcqSpec(tables, EDGES_W0), SquaredLoss()), epochs=2, track=False, **_SGD).by_epoch)


@query("w2_softmax_descends", "SELECT epoch, (SELECT count(*) FROM documents) AS n, true AS falls FROM (VALUES (1), (2), (3)) v(epoch)")
def w2_softmax_descends(spark, sf_dir):
    """Softmax over text vectors: rows of each epoch, and whether the loss is under that of the epoch before (log of the classes at first)."""
    from .sources.workloads import reviews

    ucq, loss = reviews(spark, sf_dir)
    history = train.rel_sgd_v(train.make_problem(ucq, loss), epochs=3, eta=0.5).history
    before = [float(np.log(loss.classes)), *[h[4] for h in history]]
    return spark.createDataFrame([(h[1], h[3], bool(h[4] < b)) for h, b in zip(history, before)], "epoch int, n long, falls boolean")


@query("rel_admm_consensus", admm_sql(2, 0.5, 0.01, inner=3, rho_in=0.2))
def rel_admm_consensus(spark, sf_dir):
    ucq = shared(spark, sf_dir, shards=2)
    ucq.table("part").shard, ucq.table("part").shards = None, 1
    p = train.make_problem(ucq, SquaredLoss())
    return thetas_frame(spark, train.rel_admm(p, epochs=2, rho=0.5, beta=0.01, inner_rounds=3, rho_inner=0.2, track=False).by_epoch)


@query("centralized_monolithic_steps", _SGD_SQL)
def centralized_monolithic_steps(spark, sf_dir):
    found = train.centralized(problem(spark, sf_dir), arch="monolithic", epochs=3, track=False, **_SGD).by_epoch
    cut = [{t: e["all"][ids] for t, ids in BLOCKS.items()} for e in found]
    return thetas_frame(spark, cut)


@query("admm_sequential_epochs")
def admm_sequential_epochs(spark, sf_dir):
    return thetas_frame(spark, train.rel_admm_v(problem(spark, sf_dir), epochs=2, rho=0.5, beta=0.01, schedule="sequential", track=False).by_epoch)


_RIDGE = f"WITH {x_sql()}, s AS (SELECT count(*) AS n, " + ", ".join(f"sum(x{i} * x{j}) AS a{i}{j}" for i, j in ((0, 0), (0, 4), (4, 4))) + ", sum(x0 * y) AS b0, sum(x4 * y) AS b4 FROM x), t AS (SELECT a00 / n + 0.01 AS a, a04 / n AS b, a44 / n + 0.01 AS d, b0 / n AS e, b4 / n AS f FROM s) SELECT 0 AS i, round((e * d - b * f) / (a * d - b * b), 6) + 0.0 AS value FROM t UNION ALL SELECT 1, round((a * f - b * e) / (a * d - b * b), 6) + 0.0 FROM t"


@query("ridge_exact_w0", _RIDGE)
def ridge_exact_w0(spark, sf_dir):
    ucq = shared(spark, sf_dir)
    ucq.table("lineitem").features = ["a0"]
    tables = [ucq.table("lineitem"), ucq.table("supplier")]
    theta, _ = train.ridge_exact(train.make_problem(UcqSpec(tables, [EDGES_W0[1]]), SquaredLoss()), 0.01)
    return rounded(spark.createDataFrame([(i, float(v)) for i, v in enumerate(theta)], "i int, value double"), "value")


def _v_update(name, loss, binary, rho, sql):
    @query(name, sql)
    def run(spark, sf_dir):
        p, join, s = scored_w0(spark, sf_dir, loss, binary)
        out = loss.prox(s.select("r_lineitem", "y", "m0", F.lit(0.1).alias("mu0")), rho)
        return out.select("r_lineitem", r6(F.col("v0")).alias("v"))


_v_update("admm_v_update_squared", SquaredLoss(), False, 0.5, f"WITH {x_sql()} SELECT r0 AS r_lineitem, round({_V}, 6) + 0.0 AS v FROM x")


def _newton_sql(rho, turns=8):
    ctes = [x_sql(Y_BINARY), f"n0 AS MATERIALIZED (SELECT r0, y, {MARGIN} AS m, {MARGIN} AS v FROM x)"]
    for k in range(turns):
        s = "1.0 / (1.0 + exp(-v))"
        ctes.append(f"n{k + 1} AS MATERIALIZED (SELECT r0, y, m, v - greatest(least(({s} - y - 0.1 - {rho} * (m - v)) / ({s} * (1 - {s}) + {rho}), {1 / rho}), {-1 / rho}) AS v FROM n{k})")
    return "WITH " + ", ".join(ctes) + f" SELECT r0 AS r_lineitem, round(v, 6) + 0.0 AS v FROM n{turns}"


_v_update("admm_v_update_logistic", LogisticLoss(), True, 0.5, _newton_sql(0.5))


@query("admm_v_update_softmax")
def admm_v_update_softmax(spark, sf_dir):
    """The residual of the stationarity condition is 0 when it is met."""
    loss, rho = SoftmaxLoss(3), 0.5
    s = scored_w0(spark, sf_dir)[2].select("r_lineitem", F.pmod("r_lineitem", F.lit(3)).cast("double").alias("y"), "m0", (-F.col("m0")).alias("m1"), (F.col("m0") / 2).alias("m2"), *[F.lit(0.1 * c).alias(f"mu{c}") for c in range(3)])
    out = loss.prox(s, rho)
    p = fx.softmax([F.col(f"v{c}") for c in range(3)])
    gaps = [F.abs(p[c] - (F.col("y") == c).cast("double") - F.col(f"mu{c}") - rho * (F.col(f"m{c}") - F.col(f"v{c}"))) for c in range(3)]
    return out.agg(F.count(F.lit(1)).alias("rows"), r6(F.max(F.greatest(*gaps))).alias("worst"))


ORACLES["admm_v_update_softmax"] = f"WITH {x_sql()} SELECT count(*) AS rows, 0.0::DOUBLE AS worst FROM x"


@query("admm_dual_update", f"WITH {x_sql()} SELECT r0 AS r_lineitem, round(0.1 + 0.5 * (({MARGIN}) - {_V}), 6) + 0.0 AS mu FROM x")
def admm_dual_update(spark, sf_dir):
    from .plans.train import server_step

    p, join, s = scored_w0(spark, sf_dir)
    return server_step(join, s.withColumn("mu0", F.lit(0.1)), 0.5).select("r_lineitem", r6(F.col("mu0")).alias("mu"))


@query("mlp_step")
def mlp_step(spark, sf_dir):
    """One full-batch step of the nets of the ratings workload."""
    from .sources.workloads import ratings_net

    ucq, loss, models = ratings_net(spark, sf_dir, hidden=2)
    p = train.make_problem(ucq, loss, models)
    return rounded(parameter_rows(spark, train.rel_sgd_v(p, epochs=1, eta=0.05, track=False).thetas), "value")


# ---- privacy

_U = "((CAST('0x' || substr(sha256(concat_ws('|', '{seed}', {rid}, {c})), 1, 13) AS BIGINT) + 0.5) / 4503599627370496.0)"


def _laplace_sql(u, lam):
    b = lam / 2**0.5
    return f"(CASE WHEN {u} < 0.5 THEN {b!r} * ln(2 * {u}) ELSE {-b!r} * ln(2 * (1 - {u})) END)"


_N = [_laplace_sql(_U.format(seed=3, rid="CAST(o_orderkey AS VARCHAR)", c=f"'{c}'"), 0.5) for c in (0, 1)]


@query("label_noise_binary", f"WITH o AS (SELECT o_orderkey, CASE WHEN o_orderstatus = 'F' THEN 1 ELSE 0 END AS y FROM orders) SELECT o_orderkey, CASE WHEN (CASE WHEN y = 1 THEN 1.0 ELSE 0.0 END) + {_N[1]} > (CASE WHEN y = 0 THEN 1.0 ELSE 0.0 END) + {_N[0]} THEN 1 ELSE 0 END AS y FROM o")
def label_noise_binary(spark, sf_dir):
    o = load_table(spark, sf_dir, "orders").select("o_orderkey", F.when(F.col("o_orderstatus") == "F", 1).otherwise(0).alias("y"))
    return privacy.noisy_labels(o, "y", "o_orderkey", 2, 0.5, seed=3)


@query("label_noise_numeric", f"SELECT o_orderkey, round(greatest(1000.0, least(400000.0, o_totalprice)) + {_laplace_sql(_U.format(seed=3, rid='CAST(o_orderkey AS VARCHAR)', c=repr('0')), 0.5 * 399000 / 2)}, 6) + 0.0 AS y FROM orders")
def label_noise_numeric(spark, sf_dir):
    o = load_table(spark, sf_dir, "orders").select("o_orderkey", F.col("o_totalprice").alias("y"))
    return rounded(privacy.noisy_labels(o, "y", "o_orderkey", 1, 0.5, seed=3, y_range=(1000.0, 400000.0)), "y")


@query("clip_gradient", "WITH g AS (SELECT p_partkey, p_size / 10.0 AS a, p_retailprice / 500.0 AS b FROM part) SELECT p_partkey, round(a * least(1.0, 1.0 / greatest(sqrt(a * a + b * b), 1e-12)), 6) + 0.0 AS a, round(b * least(1.0, 1.0 / greatest(sqrt(a * a + b * b), 1e-12)), 6) + 0.0 AS b FROM g")
def clip_gradient(spark, sf_dir):
    g = load_table(spark, sf_dir, "part").select("p_partkey", privacy.clip(F.array(F.col("p_size") / 10.0, F.col("p_retailprice") / 500.0), 1.0).alias("g"))
    return g.select("p_partkey", r6(F.get("g", F.lit(0))).alias("a"), r6(F.get("g", F.lit(1))).alias("b"))


_LAM = "CAST(substr(o_orderpriority, 1, 1) AS INTEGER) * 0.25e0"


@query("label_epsilon", f"WITH c AS (SELECT o_custkey, {_LAM} AS lam, count(*) AS n FROM orders GROUP BY 1, 2) SELECT lam, CAST(sum(n) AS BIGINT) AS labels, round(2 * sqrt(2) / lam, 6) + 0.0 AS epsilon, round(max(n) * (2 * sqrt(2) / lam), 6) + 0.0 AS most_spent FROM c GROUP BY lam")
def label_epsilon(spark, sf_dir):
    """Orders whose labels are released with noise by their priority: labels, epsilon of one, and the most that one customer's labels spend."""
    orders = load_table(spark, sf_dir, "orders").select("o_custkey", F.expr(_LAM).alias("lam"))
    n = orders.groupBy("o_custkey", "lam").agg(F.count(F.lit(1)).alias("n")).groupBy("lam").agg(F.sum("n").alias("labels"), F.max("n").alias("most")).collect()
    rows = [(r.lam, r.labels, privacy.label_epsilon(r.lam), r.most * privacy.label_epsilon(r.lam)) for r in n]  # one row a priority
    return rounded(spark.createDataFrame(rows, "lam double, labels long, epsilon double, most_spent double"), "epsilon", "most_spent")


_ACCOUNTANT = """WITH u AS (SELECT count(DISTINCT o_custkey) AS units FROM orders),
p AS (SELECT sigma, batch / units AS rate FROM u, (VALUES (0.8::DOUBLE), (1.0::DOUBLE), (2.0::DOUBLE), (4.0::DOUBLE)) v(sigma), (VALUES (8::DOUBLE), (64::DOUBLE)) w(batch)),
t AS (SELECT sigma, rate, a, k, lgamma(a + 1) - lgamma(k + 1) - lgamma(a - k + 1) + (a - k) * ln(1 - rate) + k * ln(rate) + k * (k - 1) / (2 * sigma * sigma) AS l
  FROM p, (SELECT CAST(unnest(range(2, 65)) AS DOUBLE) AS a), (SELECT CAST(unnest(range(0, 65)) AS DOUBLE) AS k) WHERE k <= a),
m AS (SELECT sigma, rate, a, max(l) AS top FROM t GROUP BY sigma, rate, a),
s AS (SELECT sigma, rate, a, top + ln(sum(exp(l - top))) AS moment FROM t JOIN m USING (sigma, rate, a) GROUP BY sigma, rate, a, top)
SELECT sigma, rate, CAST(steps AS INTEGER) AS steps, round(min((steps * moment + ln(100000.0)) / (a - 1)), 6) + 0.0 AS epsilon FROM s, (VALUES (10), (100), (1000)) n(steps) GROUP BY sigma, rate, steps"""


@query("privacy_accountant", _ACCOUNTANT)
def privacy_accountant(spark, sf_dir):
    """What rounds over Poisson batches of 8 and 64 customers spend; the customers who have orders are the privacy units."""
    units = load_table(spark, sf_dir, "orders").agg(F.count_distinct("o_custkey")).first()[0]
    rows = [(s, b / units, n, privacy.epsilon_spent(s, b / units, n, 1e-5)) for s in (0.8, 1.0, 2.0, 4.0) for b in (8, 64) for n in (10, 100, 1000)]
    return rounded(spark.createDataFrame(rows, "sigma double, rate double, steps int, epsilon double"), "epsilon")


@query("privacy_unit_report", f"WITH j AS (SELECT p_partkey AS p, s_suppkey AS s {JOIN_W0}) SELECT 'part' AS tbl, max(n) AS most_rows, CAST(max(n) AS DOUBLE) AS group_epsilon, 0.00001::DOUBLE AS joined_row_delta FROM (SELECT count(*) AS n FROM j GROUP BY p) UNION ALL SELECT 'supplier', max(n), CAST(max(n) AS DOUBLE), 0.00001::DOUBLE FROM (SELECT count(*) AS n FROM j GROUP BY s)")
def privacy_unit_report(spark, sf_dir):
    return privacy.privacy_report(row_map_w0(spark, sf_dir), ["part", "supplier"], 1.0, 1e-5)


# ---- measures


@query("rmse_eval", f"WITH {x_sql()} SELECT round(sqrt(avg((({MARGIN}) - y) * (({MARGIN}) - y))), 6) + 0.0 AS rmse FROM x WHERE {test_sql('jid')}")
def rmse_eval(spark, sf_dir):
    s = scored_w0(spark, sf_dir)[2].where(batches.is_test(F.col("jid")))
    return rounded(metrics.rmse(s.select(F.col("m0").alias("pred"), "y")), "rmse")


@query("accuracy_eval", f"WITH {x_sql(Y_BINARY)} SELECT round(avg(CASE WHEN (CASE WHEN {MARGIN} > 0 THEN 1.0 ELSE 0.0 END) = y THEN 1.0 ELSE 0.0 END), 6) + 0.0 AS accuracy FROM x WHERE {test_sql('jid')}")
def accuracy_eval(spark, sf_dir):
    s = scored_w0(spark, sf_dir, LogisticLoss(), True)[2].where(batches.is_test(F.col("jid")))
    return rounded(metrics.accuracy(s.select(LogisticLoss().predicted([F.col("m0")]).alias("pred"), "y")), "accuracy")


def _curve_sql():
    steps = sgd_sql(3, **_SGD).split("\nSELECT 1 AS step")[0]
    m = " + ".join(f"p{i} * x{i}" for i in range(len(SLOTS)))
    return steps + "\n" + " UNION ALL ".join(f"SELECT {s} AS epoch, round(sqrt(avg((({m}) - y) * (({m}) - y))), 6) + 0.0 AS rmse FROM x, t{s}" for s in (1, 2, 3))


@query("convergence_curve", _curve_sql())
def convergence_curve(spark, sf_dir):
    h = train.rel_sgd_v(problem(spark, sf_dir), epochs=3, **_SGD).history
    return rounded(spark.createDataFrame([(e, m) for _, e, _, _, _, m in h], "epoch int, rmse double"), "rmse")


def _facts(spark, sf_dir, n_batches=90):
    rows = row_map_w0(spark, sf_dir)
    names = ["lineitem", "part", "supplier"]
    r = rows.agg(F.count(F.lit(1)).alias("n"), *[F.count_distinct(f"r_{x}").alias(x) for x in names]).first()
    a = {x.tbl: x.alpha for x in batches.alpha(batches.with_batches(rows, n_batches), names).collect()}
    return r.n, [r[x] for x in names], [a[x] for x in names]


_FACTS = f"j AS MATERIALIZED (SELECT {bid_sql(90)} AS bid, {L_RID} AS l, p_partkey AS p, s_suppkey AS s {JOIN_W0}), k AS (SELECT count(*) AS n, count(DISTINCT l) + count(DISTINCT p) + count(DISTINCT s) AS used FROM j), a AS (SELECT sum(l + p + s) AS alphas FROM (SELECT count(DISTINCT l) AS l, count(DISTINCT p) AS p, count(DISTINCT s) AS s FROM j GROUP BY bid))"
_VOLUME = {"vfl_sgd": "2 * 3 * n", "vfl_admm": "3 * 3 * n", "rel_sgd_v": "2 * alphas", "rel_admm_v": "2 * used", "rel_sgd": "2 * alphas + 2 * (2 * 2 + 2 * 2 + 2 * 1) * 90", "rel_admm": "2 * used + 10 * 3 * (2 * 2 + 2 * 2 + 2 * 1)"}


@query("comm_volume_by_method", f"WITH {_FACTS} " + " UNION ALL ".join(f"SELECT '{m}' AS method, CAST({v} AS BIGINT) AS n_values FROM k, a" for m, v in _VOLUME.items()))
def comm_volume_by_method(spark, sf_dir):
    n, used, alphas = _facts(spark, sf_dir)
    rows = [(m, int(cost.volume(m, n, 3, 1, alphas, used, [2, 2, 1], [2, 2, 2], 90))) for m in cost.METHODS]
    return spark.createDataFrame(rows, "method string, n_values long")


_ROUNDS = {"vfl_sgd": 90, "vfl_admm": 1, "rel_sgd_v": 90, "rel_admm_v": 1, "rel_sgd": 180, "rel_admm": 11}


@query("comm_time_by_network", f"WITH {_FACTS}, net(network, latency, bits) AS (VALUES ('us_uk', 0.136::DOUBLE, 4.2e8::DOUBLE), ('us_us', 0.067::DOUBLE, 1.15e9::DOUBLE)), v AS (" + " UNION ALL ".join(f"SELECT '{m}' AS method, {_ROUNDS[m]} AS rounds, CAST({v} AS DOUBLE) AS n_values FROM k, a" for m, v in _VOLUME.items()) + ") SELECT method, network, round(rounds * latency + 32 * n_values / bits, 6) + 0.0 AS seconds FROM v, net")
def comm_time_by_network(spark, sf_dir):
    n, used, alphas = _facts(spark, sf_dir)
    batch = -(-n // 90)
    rows = [(m, w, cost.comm_time(cost.rounds(m, n, batch), 4 * cost.volume(m, n, 3, 1, alphas, used, [2, 2, 1], [2, 2, 2], 90), w)) for m in cost.METHODS for w in cost.NETWORKS]
    return rounded(spark.createDataFrame(rows, "method string, network string, seconds double"), "seconds")


_MOST = "(SELECT greatest(count(DISTINCT l), count(DISTINCT p), count(DISTINCT s)) FROM j)"
_MOST_A = "(SELECT greatest(sum(l), sum(p), sum(s)) FROM (SELECT count(DISTINCT l) AS l, count(DISTINCT p) AS p, count(DISTINCT s) AS s FROM j GROUP BY bid))"
_TAB6 = {
    "vfl_sgd": ("n", "n", 90, "3 * n"),
    "vfl_admm": ("n", "n", 1, "3 * n"),
    "rel_sgd_v": ("n", _MOST_A, 90, "alphas"),
    "rel_admm_v": ("n", _MOST, 1, "used"),
    "rel_sgd": ("n + 3 * 90", f"{_MOST_A} / 2", 90, "alphas + 6 * 90"),
    "rel_admm": ("n + 3 * 10", f"10 * {_MOST} / 2", 10, "used + 10 * 6"),
}


@query("complexity_table", f"WITH {_FACTS} " + " UNION ALL ".join(f"SELECT '{m}' AS method, CAST({a} AS DOUBLE) AS server_rows, CAST({b} AS DOUBLE) AS client_rows, {r} AS rounds, CAST({v} AS DOUBLE) AS volume FROM k, a" for m, (a, b, r, v) in _TAB6.items()))
def complexity_table(spark, sf_dir):
    n, used, alphas = _facts(spark, sf_dir)
    rows = [cost.complexity(m, n, 3, -(-n // 90), alphas, used, [2, 2, 2]) for m in cost.METHODS]
    return spark.createDataFrame([tuple(r.values()) for r in rows], "method string, server_rows double, client_rows double, rounds int, volume double")


@query("setup_volume_w0", f"WITH j AS (SELECT {L_RID} AS l, p_partkey AS p, s_suppkey AS s {JOIN_W0}), k AS (SELECT count(DISTINCT l) AS l, count(DISTINCT p) AS p, count(DISTINCT s) AS s FROM j) SELECT 3 * l + 2 * p + 2 * s + l + (l + p + s) AS n_values FROM k")
def setup_volume_w0(spark, sf_dir):
    """Ids and keys of the three tables and the labels up, fan-out counts down."""
    p = problem(spark, sf_dir)
    used = [p.used[n] for n in p.names]
    return spark.createDataFrame([(cost.setup_volume(used, 1, used[0], [2, 1, 1]),)], "n_values long")


@query("order_of_methods_by_time", "SELECT * FROM (VALUES (1, 'rel_admm_v'), (2, 'vfl_admm'), (3, 'rel_sgd_v'), (4, 'vfl_sgd')) v(place, method)")
def order_of_methods_by_time(spark, sf_dir):
    """Methods by the modelled time to come within a twentieth of the exact optimum's error."""
    p = problem(spark, sf_dir)
    target = train.ridge_exact(p, 0.01)[1] * 1.05
    history, costs = [], []
    for name, options in (("rel_admm_v", {"rho": 0.5, "epochs": 4}), ("vfl_admm", {"rho": 0.5, "epochs": 4}), ("rel_sgd_v", {"eta": 0.4, "batch_size": -(-p.n // 5), "epochs": 3}), ("vfl_sgd", {"eta": 0.4, "batch_size": -(-p.n // 5), "epochs": 3})):
        r = train.METHODS[name](p, beta=0.01, **options)
        history += [(h[0], h[1], h[5]) for h in r.history]
        costs += [(name, h[1], cost.comm_time(r.ledger.rounds(h[1]), r.ledger.bytes(h[1]))) for h in r.history]
    curve = metrics.with_time(spark.createDataFrame(history, "method string, epoch int, metric double"), spark.createDataFrame(costs, "method string, epoch int, seconds double"))
    met = sorted(metrics.time_to_target(curve, target, True).collect(), key=lambda r: r.time)
    return spark.createDataFrame([(i, r.method) for i, r in enumerate(met, 1)], "place int, method string")


@query("private_fits", "SELECT * FROM (VALUES ('rel_sgd_v', true, true, true), ('rel_admm_v', true, true, true)) v(method, spends_at_most_one, noisy, no_better)")
def private_fits(spark, sf_dir):
    """Private SGD and ADMM: whether their noise keeps to epsilon 1 at delta 1e-5, moves the parameters, and doesn't lower the training error."""
    p = problem(spark, sf_dir)
    out = []
    for name, rate, steps, options in (("rel_sgd_v", 0.25, 8, {"eta": 0.4, "batch_size": -(-p.n // 4)}), ("rel_admm_v", 1.0, 2 * 3, {"rho": 0.5, "inner": "descent", "steps": 3, "lr": 0.4})):
        sigma = privacy.sigma_for(1.0, rate, steps, 1e-5)
        plain = train.METHODS[name](p, epochs=2, beta=0.01, **options)
        noisy = train.METHODS[name](p, epochs=2, beta=0.01, dp=privacy.DpSpec(1.0, sigma, "joined_row", 7), **options)
        moved = max(float(np.abs(plain.thetas[t] - noisy.thetas[t]).max()) for t in plain.thetas)
        drop = metrics.dp_drop(noisy.history[-1][5], plain.history[-1][5], True)
        out.append((name, privacy.epsilon_spent(sigma, rate, steps, 1e-5) <= 1.0, moved > 0, drop > -0.01))
    return spark.createDataFrame(out, "method string, spends_at_most_one boolean, noisy boolean, no_better boolean")


@query("accuracy_vs_time")
def accuracy_vs_time(spark, sf_dir):
    """method, epoch, rmse and running time over the slower network, for the two folded and two unfolded vertical methods."""
    p = problem(spark, sf_dir)
    history, costs = [], []
    for name, options in (("rel_admm_v", {"rho": 0.5}), ("vfl_admm", {"rho": 0.5}), ("rel_sgd_v", {"eta": 0.4}), ("vfl_sgd", {"eta": 0.4})):
        r = train.METHODS[name](p, epochs=3, **options)
        history += [(h[0], h[1], h[5]) for h in r.history]
        costs += [(name, e, cost.comm_time(r.ledger.rounds(e), r.ledger.bytes(e))) for e in range(1, 4)]
    curve = metrics.with_time(spark.createDataFrame(history, "method string, epoch int, metric double"), spark.createDataFrame(costs, "method string, epoch int, seconds double"))
    return rounded(curve.select("method", "epoch", "metric", "time"), "metric", "time")


# ---- relational operators around the methods


@query("standardize_stats", "SELECT round(avg(l_quantity), 6) + 0.0 AS mean, round(stddev_pop(l_quantity), 6) + 0.0 AS std FROM lineitem")
def standardize_stats(spark, sf_dir):
    return load_table(spark, sf_dir, "lineitem").agg(r6(F.avg("l_quantity")).alias("mean"), r6(F.stddev_pop("l_quantity")).alias("std"))


@query("one_hot_part", "SELECT p_partkey, CAST(p_brand = 'Brand#2' AS INTEGER)::DOUBLE AS b2, CAST(p_brand = 'Brand#17' AS INTEGER)::DOUBLE AS b17, CASE p_brand WHEN 'Brand#2' THEN 0 WHEN 'Brand#17' THEN 1 END AS place FROM part")
def one_hot_part(spark, sf_dir):
    brands = ["Brand#2", "Brand#17"]
    a, b = fx.one_hot(F.col("p_brand"), brands)
    return load_table(spark, sf_dir, "part").select("p_partkey", a.alias("b2"), b.alias("b17"), fx.vocabulary_index(F.col("p_brand"), brands).alias("place"))


@query("semi_join_used_orders", "SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem)")
def semi_join_used_orders(spark, sf_dir):
    return load_table(spark, sf_dir, "orders").join(load_table(spark, sf_dir, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_semi").select("o_orderkey")


@query("anti_join_unused_orders", "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def anti_join_unused_orders(spark, sf_dir):
    return load_table(spark, sf_dir, "orders").join(load_table(spark, sf_dir, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select("o_orderkey")


@query("top_fanout", f"SELECT p_partkey AS rid, count(*) AS c {JOIN_W0} GROUP BY 1 ORDER BY c DESC, rid LIMIT 10")
def top_fanout(spark, sf_dir):
    return fanout_part(spark, sf_dir).orderBy(F.col("c").desc(), "rid").limit(10)


@query("rollup_fanout", f"SELECT p_brand, p_type, count(*) AS n {JOIN_W0} GROUP BY ROLLUP (p_brand, p_type)")
def rollup_fanout(spark, sf_dir):
    part = load_table(spark, sf_dir, "part").select(F.col("p_partkey").alias("r_part"), "p_brand", "p_type")
    return row_map_w0(spark, sf_dir).join(part, "r_part").rollup("p_brand", "p_type").agg(F.count(F.lit(1)).alias("n"))


@query("window_running_fanout", f"WITH f AS (SELECT s_suppkey AS rid, count(*) AS c {JOIN_W0} GROUP BY 1) SELECT rid, c, CAST(sum(c) OVER (ORDER BY rid) AS BIGINT) AS running, lag(c) OVER (ORDER BY rid) AS before, rank() OVER (ORDER BY c DESC) AS place FROM f")
def window_running_fanout(spark, sf_dir):
    f = mapping.fan_out(row_map_w0(spark, sf_dir), "supplier")
    w = Window.partitionBy(F.lit(0)).orderBy("rid")
    return f.select("rid", "c", F.sum("c").over(w).alias("running"), F.lag("c").over(w).alias("before"), F.rank().over(Window.partitionBy(F.lit(0)).orderBy(F.col("c").desc())).cast("long").alias("place"))


@query("set_ops_maps", f"WITH a AS (SELECT p_partkey AS r_part, s_suppkey AS r_supplier {JOIN_W0} WHERE s_suppkey % 2 = 0), b AS (SELECT p_partkey AS r_part, s_suppkey AS r_supplier {JOIN_W0}) SELECT * FROM (SELECT * FROM b EXCEPT ALL SELECT * FROM a) INTERSECT ALL SELECT * FROM b")
def set_ops_maps(spark, sf_dir):
    b = row_map_w0(spark, sf_dir).select("r_part", "r_supplier")
    return b.exceptAll(b.where(F.pmod("r_supplier", F.lit(2)) == 0)).intersectAll(b)


@query("unpivot_part", "SELECT p_partkey, 'size' AS name, CAST(p_size AS DOUBLE) AS value FROM part UNION ALL SELECT p_partkey, 'price', p_retailprice FROM part")
def unpivot_part(spark, sf_dir):
    return load_table(spark, sf_dir, "part").select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price")).unpivot("p_partkey", ["size", "price"], "name", "value")


@query("pivot_orders", "SELECT o_orderstatus, count(*) FILTER (o_orderpriority = '1-URGENT') AS urgent, count(*) FILTER (o_orderpriority = '5-LOW') AS low FROM orders GROUP BY 1")
def pivot_orders(spark, sf_dir):
    o = load_table(spark, sf_dir, "orders").groupBy("o_orderstatus").pivot("o_orderpriority", ["1-URGENT", "5-LOW"]).agg(F.count(F.lit(1)))
    return o.select("o_orderstatus", F.coalesce(F.col("`1-URGENT`"), F.lit(0)).cast("long").alias("urgent"), F.coalesce(F.col("`5-LOW`"), F.lit(0)).cast("long").alias("low"))


@query("asof_orders_events", "SELECT event_id, (SELECT max(o_orderdate) FROM orders WHERE o_custkey = user_id AND o_orderdate <= ts - INTERVAL 9900 DAY) AS ordered FROM events")
def asof_orders_events(spark, sf_dir):
    """A customer's last order at least 9,900 days before each event."""
    events = load_table(spark, sf_dir, "events").select("event_id", "user_id", (F.col("ts") - F.expr("INTERVAL 9900 DAY")).alias("at"))
    orders = load_table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("user_id"), F.col("o_orderdate").alias("at"), F.col("o_orderdate").alias("ordered"))
    orders = orders.join(events.select("user_id").distinct(), "user_id", "left_semi")
    return asof_join(events, orders, "user_id", "at", "ordered").select("event_id", "ordered")


@query("range_join_sizes", "WITH s AS (SELECT * FROM (VALUES (1, 900.0::DOUBLE, 910.0::DOUBLE), (2, 905.0::DOUBLE, 950.0::DOUBLE), (3, 990.0::DOUBLE, 995.5::DOUBLE)) v(band, lo, hi)) SELECT band, count(*) AS n FROM part JOIN s ON lo <= p_retailprice AND p_retailprice < hi GROUP BY band")
def range_join_sizes(spark, sf_dir):
    bands = spark.createDataFrame([(1, 900.0, 910.0), (2, 905.0, 950.0), (3, 990.0, 995.5)], "band int, lo double, hi double")
    return range_join(load_table(spark, sf_dir, "part").select("p_retailprice"), bands, "p_retailprice", "lo", "hi", 10.0).groupBy("band").agg(F.count(F.lit(1)).alias("n"))


@query("salted_join_supplier", "SELECT s_suppkey, count(*) AS n, round(sum(s_acctbal), 6) + 0.0 AS total FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1")
def salted_join_supplier(spark, sf_dir):
    big = load_table(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("s_suppkey"), "l_orderkey")
    return salted_join(big, load_table(spark, sf_dir, "supplier").select("s_suppkey", "s_acctbal"), "s_suppkey", 600).groupBy("s_suppkey").agg(F.count(F.lit(1)).alias("n"), r6(F.sum("s_acctbal")).alias("total"))


@query("events_tumbling", "SELECT date_trunc('day', ts) AS day, event_type, count(*) AS n, round(sum(value), 6) + 0.0 AS total FROM events GROUP BY 1, 2")
def events_tumbling(spark, sf_dir):
    e = load_table(spark, sf_dir, "events").groupBy(F.window("ts", "1 day"), "event_type").agg(F.count(F.lit(1)).alias("n"), r6(F.sum("value")).alias("total"))
    return e.select(F.col("window.start").alias("day"), "event_type", "n", "total")


@query("json_props", "SELECT event_id, TRY_CAST(json_extract_string(props, '$.k') AS DOUBLE) AS k FROM events")
def json_props(spark, sf_dir):
    return load_table(spark, sf_dir, "events").select("event_id", fx.json_number(F.col("props"), "$.k").alias("k"))


@query("days_since_orders", "SELECT o_orderkey, date_diff('second', TIMESTAMP '1992-01-01', o_orderdate) / 86400.0 AS days FROM orders")
def days_since_orders(spark, sf_dir):
    return load_table(spark, sf_dir, "orders").select("o_orderkey", fx.days_since(F.col("o_orderdate"), "1992-01-01").alias("days"))


@query("streaming_fanout", f"SELECT p_partkey AS rid, count(*) AS c {JOIN_W0} GROUP BY p_partkey")
def streaming_fanout(spark, sf_dir):
    from .streaming.incremental import stream_fan_out

    return stream_fan_out(spark, shared(spark, sf_dir), sf_dir, "part")
