"""Results of loops."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession


@dataclass
class Run:
    """state: spaces at rest by name; log: one dict per sweep."""

    spark: SparkSession
    state: dict[str, DataFrame] = field(default_factory=dict)
    log: list[dict] = field(default_factory=list)
    reason: str = ""
    spec: object = None
    kept: list[DataFrame] = field(default_factory=list)

    def release(self) -> None:
        """Frees what the run keeps in memory or on disk; states that are read after that are computed again."""
        for df in self.kept:
            df.unpersist(blocking=True)

    @property
    def sweeps(self) -> int:
        return len(self.log)

    @property
    def metrics(self) -> DataFrame:
        """sweep, evaluated, enabled, moved, residual, shift, sse, exchanged_rows, secs, stop_reason; one row per sweep."""
        names = ("evaluated", "enabled", "moved", "residual", "shift", "sse", "exchanged_rows", "secs")
        rows = [(i + 1, *(float(x[n]) if x.get(n) is not None else None for n in names), self.reason if i + 1 == len(self.log) else None) for i, x in enumerate(self.log)]
        return self.spark.createDataFrame(rows, "sweep int, " + ", ".join(f"{n} double" for n in names) + ", stop_reason string")

    def explain(self) -> str:
        return str(self.spec) if self.spec is not None else "\n".join(map(str, self.log))


class Clock:
    def __init__(self) -> None:
        self.at = time.perf_counter()

    def lap(self) -> float:
        now = time.perf_counter()
        out, self.at = now - self.at, now
        return out
