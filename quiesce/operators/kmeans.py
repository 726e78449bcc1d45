"""k-Means: the classic two-step loop and the move program in its derived forms.

The move program's tuples are (cluster m, point x). A tuple is enabled if m is
strictly closer to x than the cluster that holds x; its body moves x. Grouped by
point, only the closest cluster matters; sharded by point, a shard needs its own
points and a copy of the k centres. Centres are kept as sums and counts, so a move
is -x, -1 and +x, +1, and several moves add up.

Two layouts: ``separate`` keeps coordinates and assignment in two tables keyed by
point, ``localized`` in one row; both also materialised, packed in blocks of arrays
(``packed``). Three exchanges: ``buffered`` sums the moves of a
sweep, ``master`` brings the sums of each shard to the driver, ``indirect`` ignores
moves and recomputes sizes and sums from the assignment. All are crossed freely, and
a shard may run several local sweeps on its own copy between exchanges.

Only k * (d + 1) numbers reach the driver in a sweep (k per shard with ``master``).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import last_nearest, nearest, sqdist
from ..plans.policy import Exchange, Stop
from ..plans.runtime import Clock, Run
from ..plans.storage import Dealt, States, free_shuffles, joined_in_place
from .packed import Kernel, _whole, pack_points, sweep_points, totals, unpack_points

#: Above so many distance terms the unrolled expression outgrows the JIT; an Arrow kernel takes over.
UNROLLED = 256

#: cluster: (size, sums), and for an empty cluster that is kept its last centre as a third part
Centres = dict[int, tuple]


def dims(points: DataFrame) -> list[str]:
    return sorted((c for c in points.columns if c[:1] == "x" and c[1:].isdigit()), key=lambda c: int(c[1:]))


def initial(points: DataFrame, k: int, init: str = "random_assign", seed: int = 0, start: str | None = None, centres: list[list[float]] | None = None) -> DataFrame:
    """Adds c. random_assign: by hash; mod: by hash of the id without seed; column: as in ``start``; sample, given: nearest centre."""
    if init == "random_assign":
        return points.withColumn("c", F.pmod(F.xxhash64("pid", F.lit(seed)), F.lit(k)).cast("int"))
    if init == "mod":
        number = F.col("pid") if points.schema["pid"].dataType.simpleString() in ("bigint", "int") else F.xxhash64("pid")
        return points.withColumn("c", F.pmod(number, F.lit(k)).cast("int"))
    if init == "column":
        return points.withColumn("c", F.col(start).cast("int"))
    if init == "sample":
        rows = points.select(*dims(points), F.xxhash64("pid", F.lit(seed)).alias("h")).distinct().orderBy("h").limit(k).collect()
        centres = [[float(v) for v in r[:-1]] for r in rows]
    if not centres:
        raise ValueError(f"init {init!r} needs centres")
    xs = dims(points)
    return points.withColumn("c", nearest([(m, sqdist(xs, c)) for m, c in enumerate(centres)])["m"])


def summed(assigned: DataFrame, by: str = "c") -> Centres:
    """Sizes and sums recomputed from the assignment: the assertion that couples a centre to its points."""
    xs = dims(assigned)
    rows = assigned.groupBy(by).agg(F.count(F.lit(1)).alias("n"), *(F.sum(x).alias(x) for x in xs)).collect()
    return {r[by]: (r["n"], [r[x] for x in xs]) for r in rows}


def means(centres: Centres) -> list[tuple[int, list[float]]]:
    return [(m, [s / v[0] for s in v[1]] if v[0] else v[2]) for m, v in sorted(centres.items()) if v[0] or len(v) > 2]


def centre_frame(run_spark, centres: Centres, xs: list[str]) -> DataFrame:
    rows = [(m, centres[m][0], *map(float, at)) for m, at in means(centres)]
    return run_spark.createDataFrame(rows, "m int, n long, " + ", ".join(f"c{j} double" for j in range(len(xs))))


def _choose(rows: DataFrame, centres: Centres, tie: str) -> DataFrame:
    """Adds c2, the cluster after the sweep."""
    xs, at = dims(rows), means(centres)
    ds = {m: sqdist(xs, c) for m, c in at}
    if tie == "last":  # the classic loop: no cluster has a claim, of equals the last wins
        return rows.withColumn("c2", last_nearest(list(ds.items()))["m"])
    rows = rows.withColumns({f"_d{m}": d for m, d in ds.items()})
    own = F.coalesce(*(F.when(F.col("c") == m, F.col(f"_d{m}")) for m in ds))
    best = nearest([(m, F.col(f"_d{m}")) for m in ds])
    rows = rows.withColumns({"_best": best, "_own": own})
    return rows.withColumn("c2", F.when(F.col("_best.d") < F.coalesce("_own", F.lit(float("inf"))), F.col("_best.m")).otherwise(F.col("c"))).drop("_best", "_own", *(f"_d{m}" for m in ds))


def _choose_block(rows: DataFrame, centres: Centres, tie: str) -> DataFrame:
    """The same for many centres or dimensions: matrix blocks from Arrow batches."""
    xs = dims(rows)
    kernel = Kernel(centres, means(centres), len(xs), False, tie, "indirect", 1, "")
    schema = rows.select("*", F.lit(0).alias("c2")).schema
    where = [rows.columns.index(x) for x in xs], rows.columns.index("c")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = np.stack([b.column(i).to_numpy(zero_copy_only=False).astype(float) for i in where[0]])
            c2 = kernel.choose(x, b.column(where[1]).to_numpy(zero_copy_only=False).astype(np.int32))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(c2, pa.int32())], [*b.schema.names, "c2"])

    return rows.mapInArrow(run, schema)


def _exchange(rows: DataFrame, centres: Centres, exchange: Exchange) -> tuple[Centres, int, int]:
    """New centres, moved points, exchanged rows. rows: x.., c, c2.

    One aggregate over the pairs (from, to): at most k * k rows, and with ``master`` so
    many of each task. Without ``indirect`` only moved points are summed.
    """
    xs = dims(rows)
    sums = [F.sum(x).alias(x) for x in xs]
    if exchange.kind == "indirect":
        got = rows.groupBy("c2").agg(F.count(F.lit(1)).alias("n"), F.count(F.when(F.col("c") != F.col("c2"), 1)).alias("moved"), *sums).collect()
        return {r["c2"]: (r["n"], [r[x] for x in xs]) for r in got}, sum(r["moved"] for r in got), len(got)
    moves = rows.filter(F.col("c") != F.col("c2"))
    by = ["c", "c2"]
    if exchange.kind == "master":
        moves, by = moves.withColumn("task", F.spark_partition_id()), ["task", *by]
    got = moves.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), *sums).collect()
    new = dict(centres)
    for r in got:
        for m, sign in ((r["c"], -1), (r["c2"], 1)):
            n, s = new.get(m, (0, [0] * len(xs)))[:2]
            new[m] = (n + sign * r["n"], [a + sign * r[x] for a, x in zip(s, xs)])
    return new, sum(r["n"] for r in got), len(got)


def _shift(old: Centres, new: Centres) -> float:
    a, b = dict(means(old)), dict(means(new))
    return max((sum((p - q) ** 2 for p, q in zip(a[m], b[m])) ** 0.5 for m in a if m in b), default=0.0)


def _reseed(engine, centres: Centres, k: int, empty: str, old: Centres) -> Centres:
    gone = [m for m in range(k) if not centres.get(m, (0,))[0]]
    if not gone or empty == "drop":
        return {m: v for m, v in centres.items() if v[0]}
    if empty == "keep":  # the last centre stays a candidate, without points
        at = dict(means(old))
        return {m: v for m, v in centres.items() if v[0]} | {m: (0, [0] * len(at[m]), at[m]) for m in gone if m in at}
    rows = engine.rows()  # reseed: the farthest points from their centres
    xs = dims(rows)
    own = F.coalesce(*(F.when(F.col("c2") == m, sqdist(xs, c)) for m, c in means(centres)))
    far = rows.select(*xs, own.alias("d")).orderBy(F.desc("d"), *xs).limit(len(gone)).collect()
    return {m: v for m, v in centres.items() if v[0]} | {m: (0, [0] * len(xs), [float(r[x]) for x in xs]) for m, r in zip(gone, far)}


class _Columns:
    """Points as wide rows, swept by unrolled expressions; ``separate`` keeps the assignment in a table of its own,
    dealt out as the coordinates are, so that a sweep joins the two without a shuffle."""

    def __init__(self, points: DataFrame, xs: list[str], layout: str, tie: str, exchange: Exchange) -> None:
        self.states, self.xs, self.layout, self.tie, self.exchange = States(), xs, layout, tie, exchange
        rows = points.select("pid", *xs, "c")
        self.fixed = []
        if layout == "separate":
            # coordinates of their own table are read in every sweep, so they are no state that a later one replaces
            self.fixed = [rows.persist(StorageLevel.MEMORY_AND_DISK_DESER)]
            self.dealt = Dealt(self.fixed[0])
            self.work, mark = self.dealt.rows, F.hash("pid")
            self.base = self.dealt.known(self.work.select("shard", "at", mark.alias("mark"), *xs))
            self.assign = self.dealt.known(self.work.select("shard", "at", mark.alias("of"), "c"))
        else:
            self.work = self.states.next(rows)
        self.total = self.work.count()
        free_shuffles((self.fixed or self.states.held)[0])

    def start(self) -> Centres:
        return summed(self.work)

    def _joined(self, left: DataFrame) -> DataFrame:
        """``left`` (shard, at, mark, ..) with c and of. Places follow the order of rows: a part that was lost and read again in another order must not go unseen."""
        same = F.when(F.col("mark") == F.col("of"), F.col("c")).otherwise(F.raise_error(F.lit("a lost part of the points came back in another order")).cast("int"))
        return left.join(self.assign, ["shard", "at"]).withColumn("c", same).drop("mark")

    def sweep(self, held: Centres) -> tuple[Centres, int, int]:
        rows = self._joined(self.base) if self.fixed else self.work
        wide = len(held) * len(self.xs) > UNROLLED
        with joined_in_place(rows.sparkSession):
            self.moved = self.states.next((_choose_block if wide else _choose)(rows, held, self.tie))
        return _exchange(self.moved, held, self.exchange)

    def rows(self) -> DataFrame:
        return self.moved

    def settle(self) -> None:
        if self.fixed:
            self.assign = self.dealt.known(self.moved.select("shard", "at", "of", F.col("c2").alias("c")))
        else:
            self.work = self.moved.select("pid", *self.xs, F.col("c2").alias("c"))

    def kept(self) -> list[DataFrame]:
        return [*self.states.held, *self.fixed]

    def final(self) -> DataFrame:
        self.states.close()
        return (self._joined(self.dealt.rows.select("shard", "at", F.hash("pid").alias("mark"), "pid")) if self.fixed else self.work).select("pid", "c")


class _Blocks:
    """Points packed in blocks. ``localized_blocks`` carries the clusters with the coordinates; ``separate_blocks``
    keeps them in a table of blocks of their own, which lies beside that of the coordinates and is joined in each sweep."""

    def __init__(self, points: DataFrame, xs: list[str], layout: str, tie: str, exchange: Exchange, local: str) -> None:
        self.states, self.xs, self.tie, self.exchange, self.local = States(10), xs, tie, exchange, local
        self.separate = layout == "separate_blocks"
        self.pid = points.schema["pid"].dataType.simpleString()
        self.whole = _whole(points, xs)
        packed = pack_points(points, xs).persist(StorageLevel.MEMORY_AND_DISK_DESER)
        self.packed = packed
        self.total = packed.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
        free_shuffles(packed)
        self.static = ("shard", "at") if self.separate else ("x",)
        self.dealt = Dealt(packed) if self.separate else None
        if self.separate:
            self.base = self.dealt.known(self.dealt.rows.select("shard", "at", "x"))
        self.work = self._placed(self.dealt.rows if self.separate else packed)
        self.k = 0

    def _kernel(self, held: Centres, kind: str, sweeps: int = 1) -> Kernel:
        return Kernel(held, means(held), len(self.xs), self.whole, self.tie, kind, sweeps, self.local)

    def _read(self, got: list, width: int) -> dict[int, tuple]:
        d, out = len(self.xs) + 1, {}
        flat = [0] * (width * d + 1)
        for r in got:
            flat[r["pos"]] += r["v"]
        for m in range(width):
            out[m] = (int(flat[m * d]), flat[m * d + 1 : (m + 1) * d])
        return out, int(flat[-1])

    def _placed(self, blocks: DataFrame) -> DataFrame:
        rows = blocks.select("block", *self.static, "c")
        return self.dealt.known(rows) if self.separate else rows

    def _joined(self) -> DataFrame:
        return self.base.join(self.work, ["shard", "at"]) if self.separate else self.work

    def start(self) -> Centres:
        """Sums of the assignment as it is: a sweep whose kernel moves nothing."""
        top = self.work.select("c").mapInArrow(_largest, "m int").agg(F.max("m")).first()[0]
        width = 0 if top is None else top + 1
        if not width:
            return {}
        still = self._kernel({m: (0, [0] * len(self.xs), [0.0] * len(self.xs)) for m in range(width)}, "indirect")
        still.choose = lambda x, c: c
        with joined_in_place(self.work.sparkSession):
            got, _ = self._read(totals(sweep_points(self._joined(), still, ())), width)
        return {m: v for m, v in got.items() if v[0]}

    def sweep(self, held: Centres) -> tuple[Centres, int, int]:
        kernel = self._kernel(held, self.exchange.kind, self.exchange.sweeps)
        with joined_in_place(self.work.sparkSession):
            self.swept = self.states.next(sweep_points(self._joined(), kernel, self.static))
        got = totals(self.swept, ("block",) if self.exchange.kind == "master" else ())
        change, moved = self._read(got, kernel.width)
        if self.exchange.kind == "indirect":
            return {m: v for m, v in change.items() if v[0]}, moved, len(got)
        new = dict(held)
        for m, (n, s) in change.items():
            a = new.get(m, (0, [0] * len(self.xs)))
            new[m] = (a[0] + n, [p + q for p, q in zip(a[1], s)], *a[2:]) if n or any(s) or m in new else a
        return {m: v for m, v in new.items() if v[0] or len(v) > 2 or m in held}, moved, len(got)

    def rows(self) -> DataFrame:
        """Wide rows again, for what needs single points."""
        flat = unpack_points(self.packed.select("block", "pids").join(self.swept.select("block", "c"), "block"), self.pid)
        return self.given.join(flat.withColumnRenamed("c", "c2"), "pid")

    def settle(self) -> None:
        self.work = self._placed(self.swept)

    def kept(self) -> list[DataFrame]:
        return [*self.states.held, self.packed]

    def final(self) -> DataFrame:
        self.states.close()
        return unpack_points(self.packed.select("block", "pids").join(self.work.select("block", "c"), "block"), self.pid)


def _largest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        tops = [int(np.frombuffer(c.as_buffer(), np.int32).max(initial=-1)) for c in b.column(0)]
        if tops:
            yield pa.RecordBatch.from_arrays([pa.array([max(tops)], pa.int32())], ["m"])


def _blocks_of_ids(points: DataFrame, shards: int) -> DataFrame:
    """Contiguous ranges of pids, four for a shard, dealt out whole by hash in one shuffle. Some ids are drawn as bounds only."""
    drawn = sorted(r[0] for r in points.filter("pid is not null").select("pid").orderBy(F.rand(0)).limit(256 * shards).collect())
    bounds = drawn[:: max(1, len(drawn) // (4 * shards))][1 : 4 * shards]

    def place(low: int, high: int) -> Column:
        if low == high:
            return F.lit(low)
        mid = (low + high) // 2
        return F.when(F.col("pid") <= F.lit(bounds[mid]), place(low, mid)).otherwise(place(mid + 1, high))

    return points.withColumn("_p", place(0, len(bounds))).repartition(shards, "_p").drop("_p")


LAYOUTS = ("separate", "localized", "separate_blocks", "localized_blocks")


def kmeans(
    points: DataFrame, k: int, *, layout: str = "localized", exchange: str | Exchange = "buffered", shards: int | None = None, split: str = "value", sweeps_per_exchange: int = 1, local: str = "serial",
    init: str = "random_assign", seed: int = 0, start: str | None = None, centres: list[list[float]] | None = None, tie: str = "stay", empty: str = "keep", stop: Stop | None = None, max_sweeps: int = 500, track_sse: bool = False,
) -> Run:
    """Run with state centers(m, n, c0..) and assign(pid, c).

    layout: wide rows (separate, localized) or packed blocks (separate_blocks, localized_blocks),
    which several sweeps between exchanges need, since a block is then the shard.
    split: value, range, block (contiguous blocks of pids, dealt out by hash), any (round robin).
    """
    if k < 1:
        raise ValueError("k must be at least 1")
    kind = exchange.kind if isinstance(exchange, Exchange) else exchange
    if kind not in ("buffered", "master", "indirect"):
        raise ValueError(f"no exchange {kind!r} in sweeps; an immediate exchange is what kmeans_serial does")
    if layout not in LAYOUTS:
        raise ValueError(f"no layout {layout!r}")
    xs, spark = dims(points), points.sparkSession
    how = exchange if isinstance(exchange, Exchange) else Exchange(exchange, sweeps_per_exchange)
    stop = stop or Stop.quiet()
    if how.sweeps > 1 and not layout.endswith("blocks"):
        layout += "_blocks"
    log, clock = [], Clock()
    if points.filter(" or ".join(f"{x} is null" for x in xs)).head(1):
        raise ValueError("some points have null coordinates")
    if shards:
        if split == "range":
            points = points.repartitionByRange(shards, "pid")
        elif split == "any":
            points = points.repartition(shards)
        elif split == "block":
            points = _blocks_of_ids(points, shards)
        else:
            points = points.repartition(shards, "pid")
    rows = initial(points, k, init, seed, start, centres).select("pid", *xs, "c")
    engine = _Blocks(rows, xs, layout, tie, how, local) if layout.endswith("blocks") else _Columns(rows, xs, layout, tie, how)
    engine.given = points
    held = engine.start()
    if any(v != v for _, s, *_ in held.values() for v in s):  # a NaN shows in a sum
        raise ValueError("some points have NaN coordinates")
    total, reason = engine.total, "sweeps"
    for sweep in range(1, max_sweeps + 1):
        new, moved, sent = engine.sweep(held)
        if empty == "reseed" or any(not new.get(m, (0,))[0] for m in held):
            new = _reseed(engine, new, k, empty, held)
        d = len(xs) + 1
        seen = {"sweeps": sweep, "evaluated": total * len(held), "enabled": moved, "moved": moved, "switched": moved / max(1, total), "shift": _shift(held, new), "exchanged_rows": sent, "exchanged_bytes": sent * 8 * (1 if layout.endswith("blocks") else d), "secs": clock.lap()}
        if track_sse:
            seen["sse"] = _sse(engine.rows(), new, xs)
        log.append(seen)
        held = new
        engine.settle()
        if why := stop.reason(seen):
            reason = why
            break
    final = engine.final()
    if how.kind != "indirect" and how.sweeps > 1:  # running sums of many stale moves: settle them with the truth
        held = engine.start()
    return Run(spark, {"centers": centre_frame(spark, held, xs), "assign": final}, log, reason, kept=engine.kept())


def _sse(rows: DataFrame, centres: Centres, xs: list[str]) -> float:
    own = F.coalesce(*(F.when(F.col("c2") == m, sqdist(xs, c)) for m, c in means(centres)))
    return rows.agg(F.sum(own)).first()[0]


def kmeans_classic(points: DataFrame, k: int, *, init: str = "random_assign", seed: int = 0, start: str | None = None, centres: list[list[float]] | None = None, tie: str = "last", empty: str = "keep", stop: Stop | None = None, max_sweeps: int = 500) -> Run:
    """Assign every point, then recompute every mean, until nothing changes."""
    return kmeans(points, k, layout="localized", exchange="indirect", init=init, seed=seed, start=start, centres=centres, tie=tie, empty=empty, stop=stop, max_sweeps=max_sweeps)


#: The measured variants are materialised; the last four are the same before that step.
PRESETS = {
    "k1": {"layout": "separate_blocks", "exchange": "buffered"},
    "k2": {"layout": "separate_blocks", "exchange": "indirect"},
    "k3": {"layout": "localized_blocks", "exchange": "indirect"},
    "k4": {"layout": "localized_blocks", "exchange": "buffered"},
    "k5": {"layout": "localized_blocks", "exchange": "master"},
    "separate_buffered": {"layout": "separate", "exchange": "buffered"},
    "separate_indirect": {"layout": "separate", "exchange": "indirect"},
    "localized_indirect": {"layout": "localized", "exchange": "indirect"},
    "localized_buffered": {"layout": "localized", "exchange": "buffered"},
}


def kmeans_serial(rows: list[tuple], k: int, order=None, max_sweeps: int = 1000) -> tuple[list[int], list[float], int]:
    """The move program one tuple at a time on (coordinates, cluster) rows: assignment, error after each move, sweeps.

    Truth for small data; ``order`` permutes the tuples (point, cluster) of a sweep.
    """
    x = np.array([r[0] for r in rows], float)
    c = np.array([r[1] for r in rows])
    n = np.bincount(c, minlength=k).astype(float)
    s = np.zeros((k, x.shape[1]))
    np.add.at(s, c, x)

    def error() -> float:
        return float(((x - (s / np.maximum(n, 1)[:, None])[c]) ** 2).sum())

    errors, sweeps = [error()], 0
    tuples = [(i, m) for i in range(len(x)) for m in range(k)]
    for sweeps in range(1, max_sweeps + 1):
        quiet = True
        for i, m in tuples if order is None else [tuples[j] for j in order(len(tuples))]:
            a = c[i]
            if m == a or n[m] == 0 or n[a] <= 1:
                continue
            if ((x[i] - s[m] / n[m]) ** 2).sum() < ((x[i] - s[a] / n[a]) ** 2).sum():
                s[a] -= x[i]
                n[a] -= 1
                s[m] += x[i]
                n[m] += 1
                c[i], quiet = m, False
                errors.append(error())
        if quiet:
            break
    return c.tolist(), errors, sweeps


def assign(points: DataFrame, centers: DataFrame) -> DataFrame:
    """pid, c: the nearest of the centres (m, c0..), which are few and collected."""
    xs = dims(points)
    at = [(r["m"], [r[f"c{j}"] for j in range(len(xs))]) for r in centers.orderBy("m").collect()]
    return points.select("pid", nearest([(m, sqdist(xs, c)) for m, c in at])["m"].alias("c"))


def sse(points: DataFrame, assigned: DataFrame, centers: DataFrame) -> DataFrame:
    """One row: the summed squared distance of points to their centre."""
    xs = dims(points)
    rows = points.join(assigned, "pid").join(F.broadcast(centers), F.col("c") == F.col("m"))
    d = sum(((F.col(x) - F.col(f"c{j}")) * (F.col(x) - F.col(f"c{j}")) for j, x in enumerate(xs)), F.lit(0.0))
    return rows.agg(F.sum(d).alias("sse"))


def enabled_tuples(points: DataFrame, assigned: DataFrame, centers: DataFrame, slack: float = 1e-9) -> DataFrame:
    """One row: how many (cluster, point) tuples could still move."""
    xs = dims(points)
    at = [(r["m"], [r[f"c{j}"] for j in range(len(xs))]) for r in centers.collect()]
    rows = points.join(assigned, "pid").withColumns({f"_d{m}": sqdist(xs, c) for m, c in at})
    own = F.coalesce(*(F.when(F.col("c") == m, F.col(f"_d{m}")) for m, _ in at))
    return rows.agg(F.coalesce(F.sum(sum((F.when(F.col(f"_d{m}") < own - slack, 1).otherwise(0) for m, _ in at), F.lit(0))), F.lit(0)).cast("long").alias("enabled"))
