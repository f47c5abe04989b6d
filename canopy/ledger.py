"""Ledger of rounds and words: one row for each step of a run."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

COLUMNS = "stage string, phase int, iter int, op string, rounds long, rows_in long, rows_out long, max_per_key long, words long, ms long"


@dataclass
class Ledger:
    rows: list[tuple] = field(default_factory=list)
    started: float = field(default_factory=time.time)

    def add(self, stage: str, op: str, phase: int = 0, iter: int = 0, rounds: int = 1, rows_in: int = 0, rows_out: int = 0, max_per_key: int = 0, width: int = 1) -> None:
        self.rows.append((stage, phase, iter, op, rounds, int(rows_in or 0), int(rows_out or 0), int(max_per_key or 0), int((rows_out or 0) * width), int((time.time() - self.started) * 1000)))

    def rounds(self, stage: str | None = None) -> int:
        return sum(r[4] for r in self.rows if stage in (None, r[0]))

    def peak_words(self) -> int:
        return max((r[8] for r in self.rows), default=0)

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, COLUMNS)
