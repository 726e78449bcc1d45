"""When a loop stops, which tuples of a sweep run, and how shards exchange updates."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Stop:
    """Reached when any of its rules holds; a loop also stops when it is quiet."""

    rules: tuple[tuple[str, float], ...] = ()

    @staticmethod
    def quiet() -> Stop:
        return Stop((("quiet", 0.0),))

    @staticmethod
    def center_shift(delta: float = 1e-4) -> Stop:
        return Stop((("shift", delta),))

    @staticmethod
    def switch_fraction(theta: float = 1e-4) -> Stop:
        return Stop((("switched", theta),))

    @staticmethod
    def residual(r: float = 1e-10) -> Stop:
        return Stop((("residual", r),))

    @staticmethod
    def eps(e: float = 1e-6) -> Stop:
        return Stop((("change", e),))

    @staticmethod
    def max_iter(n: int) -> Stop:
        return Stop((("sweeps", float(n)),))

    @staticmethod
    def any(*stops: Stop) -> Stop:
        return Stop(tuple(r for s in stops for r in s.rules))

    def reason(self, seen: dict[str, float]) -> str | None:
        """seen: sweeps so far, and the measures of the last sweep."""
        if seen.get("enabled") == 0 and seen.get("full", 1):
            return "quiet"
        for name, bound in self.rules:
            value = seen.get(name)
            if value is not None and (value >= bound if name == "sweeps" else value < bound):
                return name
        return None


@dataclass(frozen=True)
class Schedule:
    """Any order of tuples is legal, so any subset may run in a sweep; quiet is only declared after a full one."""

    kind: str = "full"
    share: float = 1.0
    seed: int = 0

    @staticmethod
    def full() -> Schedule:
        return Schedule()

    @staticmethod
    def frontier() -> Schedule:
        return Schedule("frontier")

    @staticmethod
    def sample(p: float, seed: int = 0) -> Schedule:
        return Schedule("sample", p, seed)

    @staticmethod
    def priority(top: float) -> Schedule:
        """Tuples whose pending change is at least this share of the largest."""
        return Schedule("priority", top)

    @staticmethod
    def alternating() -> Schedule:
        return Schedule("alternating")

    def runs(self, key: Column, sweep: int, pending: Column | None = None, largest: float = 0.0) -> Column:
        if self.kind == "sample":
            return F.pmod(F.xxhash64(key, F.lit(self.seed), F.lit(sweep)), F.lit(1_000_000)) < int(self.share * 1_000_000)
        if self.kind == "alternating":
            return F.pmod(key, F.lit(2)) == sweep % 2
        if self.kind == "priority" and pending is not None:
            return F.abs(pending) >= self.share * largest
        return F.lit(True)

    @property
    def partial(self) -> bool:
        return self.kind in ("sample", "priority", "alternating")


@dataclass(frozen=True)
class Exchange:
    """buffered: summed deltas; master: deltas per shard to the driver; indirect: recomputed from what shards hold;
    immediate: no buffer (serial execution only)."""

    kind: str = "buffered"
    sweeps: int = 1
    how: str = field(default="serial")

    @staticmethod
    def buffered(sweeps: int = 1) -> Exchange:
        return Exchange("buffered", sweeps)

    @staticmethod
    def master(sweeps: int = 1) -> Exchange:
        return Exchange("master", sweeps)

    @staticmethod
    def indirect(sweeps: int = 1) -> Exchange:
        return Exchange("indirect", sweeps)

    @staticmethod
    def immediate() -> Exchange:
        return Exchange("immediate")
