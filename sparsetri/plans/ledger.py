"""What a run reads and keeps: passes over the edges, rows carried between them, degree queries; and the abort on too much.

Passes are not taken on trust: for every table that a run keeps, the ledger counts how often its plan reads the edge files."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import DataFrame

from .store import stored


class SpaceBudgetExceeded(RuntimeError):
    pass


@dataclass
class SpaceGuard:
    """Stops a run that keeps more than c times what is expected; by Markov this adds 1/c to the failure probability."""

    expected_rows: float
    c: float = 10

    def check(self, rows: int) -> None:
        if rows > self.c * self.expected_rows:
            raise SpaceBudgetExceeded(f"{rows} rows kept, more than {self.c:g} times the expected {self.expected_rows:g}")


def file_reads(df: DataFrame) -> list[str]:
    """The folders that a plan reads, one entry for each time it does."""
    leaves = df._jdf.queryExecution().optimizedPlan().collectLeaves()
    files = [leaves.apply(i) for i in range(leaves.size()) if leaves.apply(i).nodeName() == "LogicalRelation"]
    return [leaf.relation().location().rootPaths().mkString(",") for leaf in files]


@dataclass
class PassLedger:
    """The only way from a run to its edges: every scan() is a pass.  Where the edges are one written table, reads() has the truth.

    The number of edges is a statistic of that table (a count of Parquet rows comes from footers) and no pass."""

    edges: DataFrame
    n: int = 2
    guard: SpaceGuard | None = None
    scans: list[str] = field(default_factory=list)
    kept: dict[str, int] = field(default_factory=dict)
    oracle_queries: int = 0
    read: dict[str, int] = field(default_factory=dict)

    def __post_init__(self):
        own = file_reads(self.edges)
        self.home = own[0] if len(own) == 1 else None

    def scan(self, stage: str) -> DataFrame:
        self.scans.append(stage)
        return self.edges

    def keep(self, what: str, df: DataFrame) -> DataFrame:
        """df as a written table, its rows and its reads of the edges noted."""
        self.read[what] = file_reads(df).count(self.home)
        out = stored(df, f"pass-{what}")
        self.kept[what] = out.count()
        if self.guard:
            self.guard.check(sum(self.kept.values()))
        return out

    @property
    def reads(self) -> int:
        """Scans of the edges in the plans of all that was kept; 0 where the edges are no written table."""
        return sum(self.read.values())

    @property
    def passes(self) -> int:
        return len(self.scans)

    @property
    def retained_bits(self) -> int:
        """Two ids and one counter a row."""
        return sum(self.kept.values()) * 3 * max(1, math.ceil(math.log2(max(2, self.n))))
