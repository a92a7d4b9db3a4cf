"""Table mapping: which base rows make up each joined row, from ids and keys alone."""

from __future__ import annotations

from functools import reduce
from itertools import product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.columns import hash_key, hash_number
from .ucq import SpecError, TableSpec, UcqSpec


def extract_keys(table: TableSpec, hash_keys: bool = False, salt: str | None = None, beside: dict | None = None) -> DataFrame:
    """rid, shard, key columns and, if the table has it, y. Nothing else leaves the client; a scan reads these columns only.
    ``beside``: columns that lie beside the map for the client's own use."""
    keys = [(hash_key(F.col(k), salt) if hash_keys else F.col(k)).alias(f"k_{k}") for k in table.keys]
    shard = F.col(table.shard).cast("int") if table.shard else F.lit(0)
    label = [F.col(table.label).cast("double").alias("y")] if table.label else []
    return table.df.select(F.col(table.row_id).alias("rid"), shard.alias("shard"), *keys, *label, *[x.alias(n) for n, x in (beside or {}).items()])


def merge_extracts(parts: list[DataFrame], check: bool = False) -> DataFrame:
    """One extract of a table's shards; with ``check`` a repeated row id is an error."""
    merged = reduce(DataFrame.unionByName, parts)
    if check and merged.groupBy("rid").count().where("count > 1").limit(1).count():
        raise SpecError("two rows of the shards share an id")
    return merged


def build_row_map(ucq: UcqSpec, extracts: dict[str, DataFrame] | None = None, hash_keys: bool = False, salt: str | None = None, broadcast_rows: int = 0, carried: tuple = ()) -> DataFrame:
    """r_<table> for every table, y, and jid: a number made of a joined row's ids, for batches and splits. ``carried``: columns of
    extracts that stay beside them.

    Equi-joins of the extracts, from the label table on; the optimizer picks each join's strategy. Null keys join nothing.
    """
    extracts = extracts or {t.name: extract_keys(t, hash_keys, salt) for t in ucq.tables}
    out = None
    for name, on in ucq.order():
        part = extracts[name]
        part = part.select(F.col("rid").alias(f"r_{name}"), *[F.col(c).alias(f"{name}__{c}") for c in part.columns if c.startswith("k_")], *(["y"] if "y" in part.columns else []), *[c for c in part.columns if c in carried])
        if out is None:
            out = part
        elif on:
            match = [F.col(f"{name}__k_{own}") == F.col(f"{other}__k_{key}") for own, (other, key) in on]
            out = out.join(part, reduce(lambda a, b: a & b, match))
        else:
            out = out.crossJoin(part)
    ids = [f"r_{t.name}" for t in ucq.tables]
    return out.select(joined_number([F.col(i) for i in ids]).alias("jid"), *ids, "y", *carried)


def one_to_one(ucq: UcqSpec) -> bool:
    """Whether every other table is reached by its own row id, so that a row of the label table is in one joined row at most."""
    return all(len(on) == 1 and on[0][0] == ucq.table(name).row_id for name, on in ucq.order()[1:])


def joined_number(ids):
    """A number below 2**60 from row ids: equal for equal ids in any engine, and spread like a digest. Two joined rows may share one,
    which makes them go to one batch and side of the split; nothing joins on it."""
    return hash_number(*ids)


def virtual_row_map(label: TableSpec, refers: dict[str, str]) -> DataFrame:
    """The map when every other table is reached by its own row id: the label table's key columns are the map, and nothing
    is joined. ``refers``: table -> key column of the label table. Dangling references must be excluded by the caller."""
    ids = [F.col(label.row_id).alias(f"r_{label.name}"), *[F.col(k).alias(f"r_{t}") for t, k in refers.items()]]
    return label.df.select(joined_number([F.col(label.row_id), *[F.col(k) for k in refers.values()]]).alias("jid"), *ids, F.col(label.label).cast("double").alias("y"))


def fan_out(rowmap: DataFrame, name: str, table: TableSpec | None = None) -> DataFrame:
    """rid, c: how many joined rows use each base row. With the table, unused rows are listed with 0."""
    used = rowmap.groupBy(F.col(f"r_{name}").alias("rid")).agg(F.count(F.lit(1)).alias("c"))
    if table is None:
        return used
    return table.df.select(F.col(table.row_id).alias("rid")).join(used, "rid", "left").select("rid", F.coalesce("c", F.lit(0)).cast("long").alias("c"))


def fan_out_all(spark, rowmap: DataFrame, names: list[str]) -> DataFrame:
    """tbl, rid, c for all tables in one pass over the map (grouping sets)."""
    ids = [F.col(f"r_{n}") for n in names]
    sets = rowmap.groupingSets([[i] for i in ids], *ids).agg(*[F.grouping(i).alias(f"g_{n}") for n, i in zip(names, ids)], F.count(F.lit(1)).alias("c"))
    named = F.coalesce(*[F.when(F.col(f"g_{n}") == 0, F.lit(n)) for n in names])
    return sets.select(named.alias("tbl"), F.coalesce(*ids).alias("rid"), "c")


def reverse_map(rowmap: DataFrame, name: str, materialize: bool = False) -> DataFrame:
    """rid with the size, least, greatest and checksum of its joined rows' numbers; ``materialize`` lists them (debugging only)."""
    rid, jid = F.col(f"r_{name}").alias("rid"), F.col("jid")
    if materialize:
        return rowmap.groupBy(rid).agg(F.sort_array(F.collect_list(jid)).alias("jids"))
    return rowmap.groupBy(rid).agg(F.count(F.lit(1)).alias("n"), F.min(jid).alias("least"), F.max(jid).alias("greatest"), F.bit_xor(jid).alias("checksum"))


def materialize_join(ucq: UcqSpec) -> DataFrame:
    """The joined table itself, x_<table> and y. Baselines and tests only."""
    out = build_row_map(ucq)
    for t in ucq.tables:
        out = out.join(t.block().select(F.col("rid").alias(f"r_{t.name}"), F.col("x").alias(f"x_{t.name}")), f"r_{t.name}")
    return out


def expand_union_of_joins(ucq: UcqSpec) -> DataFrame:
    """The row map as the union, over all choices of one shard a table, of the shards' joins; bag semantics."""
    extracts = {t.name: extract_keys(t) for t in ucq.tables}
    parts = []
    for chosen in product(*[range(t.shards) for t in ucq.tables]):
        parts.append(build_row_map(ucq, {t.name: extracts[t.name].where(F.col("shard") == s) for t, s in zip(ucq.tables, chosen)}))
    return reduce(DataFrame.unionByName, parts)


def duplication(rowmap: DataFrame, names: list[str]) -> DataFrame:
    """tbl, joined_rows, base_rows, factor: how often a used base row is repeated by the join."""
    counts = rowmap.agg(F.count(F.lit(1)).alias("n"), *[F.count_distinct(f"r_{x}").alias(f"n_{x}") for x in names])
    pairs = F.explode(F.array(*[F.struct(F.lit(x).alias("tbl"), F.col(f"n_{x}").alias("base_rows")) for x in names])).alias("p")
    return counts.select("n", pairs).select("p.tbl", F.col("n").alias("joined_rows"), "p.base_rows", (F.col("n") / F.col("p.base_rows")).alias("factor"))


def assert_no_features(df: DataFrame, features: set[str]) -> None:
    """Fails if a server-side plan scans a feature column; columns that the scans leave out don't count."""
    leaves = df._jdf.queryExecution().sparkPlan().collectLeaves()
    for i in range(leaves.size()):
        output = leaves.apply(i).output()
        found = {output.apply(j).name() for j in range(output.size())} & features
        if found:
            raise SpecError(f"the server reads feature columns: {', '.join(sorted(found))}")
