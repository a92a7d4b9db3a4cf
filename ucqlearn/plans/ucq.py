"""Description of a union of conjunctive queries over sharded tables, checked before anything runs."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, NumericType


class SpecError(ValueError):
    """The description can't be trained on as it is."""


@dataclass
class TableSpec:
    """One organisation's table. ``df`` has a unique ``row_id`` column, the keys, the features (numbers, or one array of
    doubles) and, for one table of the query, the label. ``shard`` names an int column of shard numbers, or None for one shard."""

    name: str
    df: DataFrame
    keys: list[str]
    features: list[str]
    row_id: str
    label: str | None = None
    shard: str | None = None
    shards: int = 1
    d: int = field(init=False, default=0)

    @classmethod
    def from_shards(cls, name: str, parts: list[DataFrame], **more) -> "TableSpec":
        """A table held in parts by several clients; all parts must have one schema."""
        kinds = {tuple(sorted(p.dtypes)) for p in parts}
        if len(kinds) != 1:
            raise SpecError(f"{name}: its shards have different schemas")
        tagged = [p.withColumn("shard", F.lit(i)) for i, p in enumerate(parts)]
        return cls(name, reduce(DataFrame.unionByName, tagged), shard="shard", shards=len(parts), **more)

    def check(self) -> None:
        kinds = {f.name: f.dataType for f in self.df.schema}
        wanted = [self.row_id, *self.keys, *self.features, *([self.label] if self.label else []), *([self.shard] if self.shard else [])]
        if missing := [c for c in wanted if c not in kinds]:
            raise SpecError(f"{self.name} has no column {', '.join(missing)}")
        for c in self.features:
            if not isinstance(kinds[c], (NumericType, ArrayType)):
                raise SpecError(f"{self.name}.{c} is no number: encode it first")
        arrays = [c for c in self.features if isinstance(kinds[c], ArrayType)]
        if arrays and len(self.features) > 1:
            raise SpecError(f"{self.name}: an array of features stands alone")

    def block(self) -> DataFrame:
        """Client side: rid, shard, x."""
        shard = F.col(self.shard).cast("int") if self.shard else F.lit(0)
        kinds = {f.name: f.dataType for f in self.df.schema}
        if len(self.features) == 1 and isinstance(kinds[self.features[0]], ArrayType):
            x = F.col(self.features[0]).cast("array<double>")
        else:
            x = F.array(*[F.col(c).cast("double") for c in self.features]).cast("array<double>")
        return self.df.select(F.col(self.row_id).alias("rid"), shard.alias("shard"), x.alias("x"))


@dataclass
class UcqSpec:
    """Equi-joins of the tables: ``edges`` has ((table, key), (table, key)) pairs; several pairs between two tables are one
    composite key."""

    tables: list[TableSpec]
    edges: list[tuple[tuple[str, str], tuple[str, str]]]
    allow_cross: bool = False

    def __post_init__(self):
        self.validate()

    def table(self, name: str) -> TableSpec:
        return next(t for t in self.tables if t.name == name)

    @property
    def label_table(self) -> TableSpec:
        return next(t for t in self.tables if t.label)

    def validate(self) -> None:
        names = [t.name for t in self.tables]
        if len(set(names)) != len(names):
            raise SpecError("two tables have one name")
        for t in self.tables:
            t.check()
        if sum(t.label is not None for t in self.tables) != 1:
            raise SpecError("exactly one table must have the label")
        for side in (s for e in self.edges for s in e):
            if side[0] not in names or side[1] not in self.table(side[0]).keys:
                raise SpecError(f"{side[0]}.{side[1]} is no declared key")
        if not self.allow_cross and len(self.order()) < len(names):
            raise SpecError("the join graph falls apart: name the missing keys or allow a cross join")

    def order(self) -> list[tuple[str, list[tuple[str, tuple[str, str]]]]]:
        """Tables in the order in which they can be joined, from the label table on, each with its (own key, (table, key)) pairs."""
        done, out = [self.label_table.name], [(self.label_table.name, [])]
        while True:
            for t in self.tables:
                if t.name in done:
                    continue
                on = [(b[1], a) for a, b in self.edges if b[0] == t.name and a[0] in done] + [(a[1], b) for a, b in self.edges if a[0] == t.name and b[0] in done]
                if on:
                    done.append(t.name)
                    out.append((t.name, on))
                    break
            else:
                rest = [t.name for t in self.tables if t.name not in done]
                return out + [(n, []) for n in rest] if self.allow_cross else out
