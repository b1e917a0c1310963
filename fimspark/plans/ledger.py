"""What a run moved: rows, items (cells), bytes and blocks of each phase, and its seconds."""

from __future__ import annotations

import time
from contextlib import contextmanager
from dataclasses import dataclass, field, replace
from itertools import takewhile

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

CELL_BYTES = 4


@dataclass
class CostLedger:
    block: int = 4096
    entries: list[tuple[str, int, int, float]] = field(default_factory=list)
    #: Off, only what is known anyway is entered, and nothing is counted for it.
    on: bool = True
    watched: list[tuple[str, Observation]] = field(default_factory=list)

    def add(self, phase: str, rows: int, cells: int, seconds: float = 0.0) -> None:
        self.entries.append((phase, int(rows), int(cells), float(seconds)))

    def measure(self, phase: str, df: DataFrame, seconds: float = 0.0) -> None:
        """Rows and cells of a table of rows with items, by a job of its own."""
        if not self.on:
            return
        n, c = df.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.size("items")), F.lit(0))).first()
        self.add(phase, n, c, seconds)

    def watch(self, phase: str, df: DataFrame) -> DataFrame:
        """df, whose rows and cells are counted on their way by the job that reads them; settle() enters them when it is done."""
        if not self.on:
            return df
        seen = Observation()
        self.watched.append((phase, seen))
        return df.observe(seen, F.count(F.lit(1)).alias("n"), F.coalesce(F.sum(F.size("items")), F.lit(0)).alias("cells"))

    def settle(self) -> None:
        while self.watched:  # databases that are mined side by side settle at the same time: each entry is taken once
            try:
                phase, seen = self.watched.pop(0)
            except IndexError:
                return
            self.add(phase, seen.get["n"], seen.get["cells"])

    def planned(self) -> CostLedger:
        """The entries of the plan for the table itself: all before its large groups were projected again."""
        return replace(self, entries=[*takewhile(lambda e: e[0] != "projected again", self.entries)], watched=[])

    def written(self) -> int:
        """Cells of all that was written or sent between stages: everything but the source's own rows."""
        return sum(c for p, _, c, _ in self.entries if p != "ranked")

    @contextmanager
    def timed(self, phase: str):
        began = time.perf_counter()
        yield
        self.add(phase, 0, 0, time.perf_counter() - began)

    def cells(self, phase: str) -> int:
        return sum(c for p, _, c, _ in self.entries if p == phase)

    def expansion(self) -> float:
        """Projected cells over source cells."""
        source = self.cells("ranked")
        return (self.cells("projected") + self.cells("projected again") + self.cells("head")) / source if source else 0.0

    def to_frame(self, spark: SparkSession) -> DataFrame:
        rows = [(p, r, c, c * CELL_BYTES, -(-c * CELL_BYTES // self.block), s) for p, r, c, s in self.entries]
        return spark.createDataFrame(rows, "phase string, rows long, cells long, bytes long, blocks long, seconds double")
