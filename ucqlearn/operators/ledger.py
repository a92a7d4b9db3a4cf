"""What crosses between server, coordinators and clients."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame

SCHEMA = "epoch int, round int, phase string, tbl string, payload string, n_values long, rounds int"


@dataclass
class Ledger:
    """One row for each message kind and round: ``n_values`` numbers both ways; ``rounds`` is what it adds to the count."""

    width: int = 4
    rows: list[tuple] = field(default_factory=list)

    def add(self, epoch: int, round_: int, phase: str, tbl: str, payload: str, n_values: int, rounds: int = 0) -> None:
        self.rows.append((epoch, round_, phase, tbl, payload, int(n_values), rounds))

    def rounds(self, epoch: int | None = None, phase: str | None = None) -> int:
        return sum(r[6] for r in self.rows if (epoch is None or r[0] == epoch) and (phase is None or r[2] == phase))

    def values(self, epoch: int | None = None, phase: str | None = None) -> int:
        return sum(r[5] for r in self.rows if (epoch is None or r[0] == epoch) and (phase is None or r[2] == phase))

    def bytes(self, epoch: int | None = None) -> int:
        return self.width * self.values(epoch)

    def frame(self, spark) -> DataFrame:
        return spark.createDataFrame(self.rows, SCHEMA)
