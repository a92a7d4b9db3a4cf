"""The experiment workloads on the given tables, with planted labels."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.columns import hash_uniform, logistic_from_uniform, name_words, one_hot, standardize
from ..functions.losses import LogisticLoss, SoftmaxLoss, SquaredLoss
from ..functions.models import LinearModel, MlpModel
from ..plans.rowids import ranked
from ..plans.ucq import TableSpec, UcqSpec
from .tables import load_table


def scaled(df: DataFrame, columns: list[str]) -> DataFrame:
    """z_<column>: centred and scaled by the table's own mean and deviation, from one pass."""
    r = df.agg(*[f(F.col(c).cast("double")).alias(f"{k}_{c}") for c in columns for k, f in (("m", F.avg), ("s", F.stddev_pop))]).first()
    return df.select("*", *[standardize(F.col(c).cast("double"), r[f"m_{c}"] or 0.0, r[f"s_{c}"] or 0.0).alias(f"z_{c}") for c in columns])


def line_id() -> Column:
    """A lineitem's id from its keys and quantity, which tell the given rows apart and can be stated in SQL. Where the number
    would not fit, a negative 63-bit hash of them takes its place; two rows in 2**32 or so may then share one, and
    ``lineitems`` with a store numbers all rows densely instead."""
    mul, add = F.try_multiply, F.try_add
    keys = add(mul(add(mul(add(mul(F.col("l_orderkey"), F.lit(20_000_003)), F.col("l_partkey")), F.lit(1009)), F.col("l_suppkey")), F.lit(8)), F.col("l_linenumber"))
    tried = add(mul(keys, F.lit(64)), F.col("l_quantity").cast("long"))
    # an overflow that is tried raises and catches an error in the JVM, which takes many times the work of a row; so its size is told first
    o, p, s, n, q = (F.col(c) for c in ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity"))
    about = (((o.cast("double") * 20_000_003 + p) * 1009 + s) * 8 + n) * 64 + q
    positive = (o >= 0) & (p >= 0) & (s >= 0) & (n >= 0) & (q >= 0)
    plain = (((o * 20_000_003 + p) * 1009 + s) * 8 + n) * 64 + q.cast("long")
    exact = F.when(positive & (about < 9.2e18), plain).when(positive & (about > 9.3e18), F.lit(None).cast("long")).otherwise(tried)
    hashed = F.xxhash64("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity").bitwiseOR(F.lit(-(1 << 63)))
    return F.coalesce(F.when(exact >= 0, exact), hashed)


def lineitems(spark, sf_dir: str, store=None) -> DataFrame:
    """The lines with l_rid; with an artifact store their ids are dense numbers in the order of all columns."""
    lines = load_table(spark, sf_dir, "lineitem")
    if store is not None:
        return ranked(lines, lines.columns, store, store.label("lines")).withColumnRenamed("rid", "l_rid").withColumn("one", F.lit(1.0))
    return lines.withColumn("l_rid", line_id()).withColumn("one", F.lit(1.0))


def with_shards(df: DataFrame, key: str, count: int) -> DataFrame:
    return df.withColumn("shard", F.pmod(F.col(key), F.lit(count)).cast("int"))


def uneven_shards(df: DataFrame, key: str, share: float = 0.9) -> DataFrame:
    return df.withColumn("shard", (F.pmod(F.col(key), F.lit(100)) >= share * 100).cast("int"))


def _spec(name, df, keys, features, row_id, shards, label=None) -> TableSpec:
    return TableSpec(name, with_shards(df, row_id, shards), keys, features, row_id, label, "shard", shards)


LINE = ["z_l_quantity", "z_l_discount", "z_l_tax", "one"]
EDGES_W0 = [(("lineitem", "l_partkey"), ("part", "p_partkey")), (("lineitem", "l_suppkey"), ("supplier", "s_suppkey"))]


def _bases(spark, sf_dir):
    li = scaled(lineitems(spark, sf_dir), ["l_quantity", "l_discount", "l_tax"])
    part = scaled(load_table(spark, sf_dir, "part"), ["p_size", "p_retailprice"])
    supplier = scaled(load_table(spark, sf_dir, "supplier"), ["s_acctbal"])
    return li, part, supplier


def _scored(li: DataFrame, part: DataFrame, supplier: DataFrame, orders: DataFrame | None = None) -> DataFrame:
    """The lines with their score: fixture only, through a join that training never sees."""
    out = li.join(part.select("p_partkey", "z_p_size", "z_p_retailprice"), li.l_partkey == F.col("p_partkey")).join(supplier.select("s_suppkey", "z_s_acctbal"), F.col("l_suppkey") == F.col("s_suppkey"))
    score = 1 + F.col("z_l_quantity") + 0.5 * F.col("z_p_size") - 0.3 * F.col("z_p_retailprice") + 0.4 * F.col("z_s_acctbal")
    if orders is not None:
        out = out.join(orders.select("o_orderkey", "z_o_totalprice"), F.col("l_orderkey") == F.col("o_orderkey"))
        score = score - 0.7 * F.col("z_o_totalprice")
    return out.select(*[li[c] for c in li.columns], score.alias("score"))


def running_example(spark, sf_dir: str, shards: int = 2, seed: int = 0, noise: float = 0.1) -> tuple[UcqSpec, object]:
    """W0: items of an order joined with parts and with a supplier table held by several branches."""
    li, part, supplier = _bases(spark, sf_dir)
    wave = (hash_uniform(seed, F.col("l_rid"), "n") - 0.5) * 12**0.5
    li = _scored(li, part, supplier).withColumn("y", F.col("score") + noise * wave).drop("score")
    tables = [
        _spec("lineitem", li, ["l_partkey", "l_suppkey"], LINE, "l_rid", 1, "y"),
        _spec("part", part, ["p_partkey"], ["z_p_size", "z_p_retailprice"], "p_partkey", 1),
        _spec("supplier", supplier, ["s_suppkey"], ["z_s_acctbal"], "s_suppkey", shards),
    ]
    return UcqSpec(tables, EDGES_W0), SquaredLoss()


def health(spark, sf_dir: str, shards: int = 1, seed: int = 0, natural: bool = False) -> tuple[UcqSpec, object]:
    """W1: five tables, binary label."""
    li, part, supplier = _bases(spark, sf_dir)
    orders = scaled(load_table(spark, sf_dir, "orders"), ["o_totalprice"])
    customer = scaled(load_table(spark, sf_dir, "customer"), ["c_acctbal"])
    segments = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
    hot = one_hot(F.col("c_mktsegment"), segments)
    customer = customer.select("*", *[h.alias(f"seg{i}") for i, h in enumerate(hot)])
    if natural:
        li = li.withColumn("y", (F.col("l_linestatus") == "F").cast("double"))
    else:
        noisy = F.col("score") - 1 + logistic_from_uniform(hash_uniform(seed, F.col("l_rid"), "n"))
        li = _scored(li, part, supplier, orders).withColumn("y", (noisy > 0).cast("double")).drop("score")
    tables = [
        _spec("lineitem", li, ["l_orderkey", "l_partkey", "l_suppkey"], LINE, "l_rid", shards, "y"),
        _spec("customer", customer, ["c_custkey"], ["z_c_acctbal", *[f"seg{i}" for i in range(5)]], "c_custkey", shards),
        _spec("orders", orders, ["o_orderkey", "o_custkey"], ["z_o_totalprice"], "o_orderkey", shards),
        _spec("part", part, ["p_partkey"], ["z_p_size", "z_p_retailprice"], "p_partkey", shards),
        _spec("supplier", supplier, ["s_suppkey"], ["z_s_acctbal"], "s_suppkey", shards),
    ]
    return UcqSpec(tables, [*EDGES_W0, (("lineitem", "l_orderkey"), ("orders", "o_orderkey")), (("orders", "o_custkey"), ("customer", "c_custkey"))]), LogisticLoss()


def stays(spark, sf_dir: str, shards: int = 1) -> tuple[UcqSpec, object]:
    """W1m: orders and events of a customer, many to many; is an event an error?"""
    events = load_table(spark, sf_dir, "events").withColumn("hour", F.hour("ts").cast("double")).withColumn("one", F.lit(1.0))
    events = scaled(events, ["value", "hour"]).withColumn("y", (F.col("event_type") == "error").cast("double"))
    orders = scaled(load_table(spark, sf_dir, "orders"), ["o_totalprice"])
    customer = scaled(load_table(spark, sf_dir, "customer"), ["c_acctbal"])
    tables = [
        _spec("events", events, ["user_id"], ["z_value", "z_hour", "one"], "event_id", shards, "y"),
        _spec("customer", customer, ["c_custkey"], ["z_c_acctbal"], "c_custkey", shards),
        _spec("orders", orders, ["o_custkey"], ["z_o_totalprice"], "o_orderkey", shards),
    ]
    return UcqSpec(tables, [(("events", "user_id"), ("customer", "c_custkey")), (("orders", "o_custkey"), ("customer", "c_custkey"))]), LogisticLoss()


def reviews(spark, sf_dir: str, shards: int = 1, classes: int = 5, natural: bool = False) -> tuple[UcqSpec, object]:
    """W2: documents with a text vector and a summary of their source. Planted classes are quintiles of a projection of the vector
    plus the size; the natural variant takes the two quality labels."""
    docs = load_table(spark, sf_dir, "documents").select("doc_id", "lang", "source", F.log1p(F.col("n_chars").cast("double")).alias("size"))
    vectors = load_table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("x"))
    n_vec = vectors.agg(F.max("vec_id")).first()[0] + 1
    docs = scaled(docs.withColumn("vec_key", F.pmod("doc_id", F.lit(n_vec))), ["size"]).withColumn("one", F.lit(1.0))
    langs = ["de", "en", "es", "fr"]
    docs = docs.select("*", *[h.alias(f"lang_{v}") for v, h in zip(langs, one_hot(F.col("lang"), langs))])
    if natural:
        docs = docs.join(load_table(spark, sf_dir, "labels").select("doc_id", F.col("quality").alias("y")), "doc_id")
        classes = 2
    else:
        weights = F.array(*[F.lit(float((7 * i * i + 3 * i) % 11 - 5)) for i in range(64)])
        projection = F.aggregate(F.zip_with("x", weights, lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
        planted = docs.select("doc_id", "vec_key", "z_size").join(vectors.select(F.col("vec_id").alias("vec_key"), projection.alias("p")), "vec_key").select("doc_id", (F.col("p") + F.col("z_size")).alias("s"))
        cuts = planted.agg(F.percentile_approx("s", [i / classes for i in range(1, classes)], 10000).alias("q")).first()["q"]
        level = sum(((F.col("s") > c).cast("int") for c in cuts), F.lit(0))
        docs = docs.join(planted.select("doc_id", level.alias("y")), "doc_id")
    source = load_table(spark, sf_dir, "documents").groupBy("source").agg(F.avg("n_chars").alias("mean_size"), F.count(F.lit(1)).cast("double").alias("rows"))
    source = scaled(source.withColumn("src_id", F.regexp_extract("source", "([0-9]+)$", 1).cast("long")), ["mean_size", "rows"])
    tables = [
        _spec("documents", docs, ["vec_key", "source"], ["z_size", *[f"lang_{v}" for v in langs], "one"], "doc_id", shards, "y"),
        _spec("embeddings", vectors, ["vec_id"], ["x"], "vec_id", shards),
        _spec("sources", source, ["source"], ["z_mean_size", "z_rows"], "src_id", shards),
    ]
    return UcqSpec(tables, [(("documents", "vec_key"), ("embeddings", "vec_id")), (("documents", "source"), ("sources", "source"))]), SoftmaxLoss(classes)


def ratings(spark, sf_dir: str, shards: int = 1, seed: int = 0) -> tuple[UcqSpec, object]:
    """W3: ratings of parts that come once for each word of their name (keys repeat on both sides), and suppliers as users."""
    li, part, supplier = _bases(spark, sf_dir)
    wave = (hash_uniform(seed, F.col("l_rid"), "n") - 0.5) * 12**0.5
    rated = F.greatest(F.lit(1.0), F.least(F.lit(5.0), F.round(3 + 0.6 * (F.col("score") - 1 + 0.1 * wave))))
    li = _scored(li, part, supplier).withColumn("y", rated).drop("score")
    words = part.select("p_partkey", "z_p_size", "z_p_retailprice", F.posexplode(name_words(F.col("p_name"))).alias("pos", "word"))
    words = scaled(words.withColumn("p_rid", F.col("p_partkey") * 16 + F.col("pos")).withColumn("letters", F.length("word").cast("double")), ["letters"])
    tables = [
        _spec("lineitem", li, ["l_partkey", "l_suppkey"], LINE, "l_rid", shards, "y"),
        _spec("part", words, ["p_partkey"], ["z_p_size", "z_p_retailprice", "z_letters"], "p_rid", shards),
        _spec("supplier", supplier, ["s_suppkey"], ["z_s_acctbal"], "s_suppkey", shards),
    ]
    return UcqSpec(tables, EDGES_W0), SquaredLoss()


def ratings_net(spark, sf_dir: str, shards: int = 1, hidden: int = 16, activation: str = "relu"):
    """W4: W3 with a small net for each table. Returns (spec, loss, models)."""
    ucq, loss = ratings(spark, sf_dir, shards)
    return ucq, loss, {t.name: MlpModel(len(t.features), hidden, 1, activation) for t in ucq.tables}


def correlated(spark, sf_dir: str, w: float = 0.6, shards: int = 1) -> tuple[UcqSpec, object]:
    """Features that correlate across tables although each is centred: the parallel schedule may diverge here."""
    customer = scaled(load_table(spark, sf_dir, "customer"), ["c_acctbal"])
    orders = load_table(spark, sf_dir, "orders").join(customer.select("c_custkey", "z_c_acctbal"), F.col("o_custkey") == F.col("c_custkey"))
    mixed = lambda key: w * F.col("z_c_acctbal") + (1 - w * w) ** 0.5 * (hash_uniform(5, key, "c") - 0.5) * 12**0.5
    orders = scaled(orders.withColumn("f", mixed(F.col("o_orderkey"))), ["f"])
    li = lineitems(spark, sf_dir).join(orders.select("o_orderkey", "z_c_acctbal", F.col("z_f").alias("of")), F.col("l_orderkey") == F.col("o_orderkey"))
    li = scaled(li.withColumn("f", mixed(F.col("l_rid"))), ["f"])
    li = li.withColumn("y", F.col("z_f") - 0.7 * F.col("of") + 0.4 * F.col("z_c_acctbal") + 0.1 * (hash_uniform(6, F.col("l_rid"), "n") - 0.5) * 12**0.5)
    tables = [
        _spec("lineitem", li.select("l_rid", "l_orderkey", "z_f", "y"), ["l_orderkey"], ["z_f"], "l_rid", shards, "y"),
        _spec("orders", orders.select("o_orderkey", "o_custkey", "z_f"), ["o_orderkey", "o_custkey"], ["z_f"], "o_orderkey", shards),
        _spec("customer", customer, ["c_custkey"], ["z_c_acctbal"], "c_custkey", shards),
    ]
    return UcqSpec(tables, [(("lineitem", "l_orderkey"), ("orders", "o_orderkey")), (("orders", "o_custkey"), ("customer", "c_custkey"))]), SquaredLoss()


WORKLOADS = {"w0": running_example, "w1": health, "w1m": stays, "w2": reviews, "w3": ratings}
__all__ = ["WORKLOADS", "LinearModel", "MlpModel", "running_example", "health", "stays", "reviews", "ratings", "ratings_net", "correlated"]
