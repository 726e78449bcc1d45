"""PageRank as a program of pending differences, in its derived forms.

Every edge (u, v) remembers the rank of u that it last passed on. It is enabled if
the rank has changed since by more than ``tol``; its body adds d (pr[u] - old) /
dout[u] to pr[v] and remembers pr[u]. Updates are additive, so any order, batch or
stale copy leads to the same fixpoint, and after any batch
pr[v] = (1 - d) / N + d * sum of old / dout over the in-edges of v.

Forms: memory per ``vertex`` (all out-edges of a vertex run together), per ``edge`` in
a table of its own that is joined by the edge's address in each sweep, ``embedded`` in
the edge row, or ``adjacency``: arrays of (u, old) by target, packed in blocks. Edges
dealt out by target (``pull``, one writer per rank), by source (``push``), at random
(``split``), or left where they are (``any``); the last three need two-level sums.

Vertices without out-edges spread their rank over all others: ``expand`` adds those
edges, ``fold`` replaces them by one scalar per sweep and a correction, ``sample``
draws one target per sweep, ``leak`` leaves the rank where it is. All edges that ``expand``
adds for a vertex run together and remember the same rank, in every schedule. Beyond
``EXPANDED_LIMIT`` rows, ``beyond="group"`` (as in all presets) therefore keeps one memory
for them, that of the vertex, and adds what they pass on as a group: no edge is left
out, and from there on the program is the folded one. ``beyond="refuse"`` raises an error.

Ranks are joined to edges by key: a broadcast only if their size is below
``broadcast_bytes``, checked from the count, else shuffled on both sides.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.policy import Schedule, Stop
from ..plans.runtime import Clock, Run
from ..plans.storage import States
from ..sources.tables import degrees, vertices_of
from .packed import pack_edges, sweep_edges, unpack_edges

EXPANDED_LIMIT = 10**8
BROADCAST_BYTES = 256 << 20
SHARD_EDGES = 100_000


def rank_exact(edges: list[tuple[int, int]], vertices: list[int], d: float = 0.85, dangling: str = "fold") -> dict[int, float]:
    """Dense solution for small graphs."""
    at = {v: i for i, v in enumerate(vertices)}
    n = len(at)
    a = np.zeros((n, n))
    for u, v in set(edges):
        a[at[v], at[u]] = 1
    out = a.sum(axis=0)
    if dangling != "leak":
        for j in np.flatnonzero(out == 0):
            a[:, j] = 1
            a[j, j] = 0
    out = a.sum(axis=0)
    m = a / np.where(out == 0, 1, out)
    return dict(zip(vertices, np.linalg.solve(np.eye(n) - d * m, np.full(n, (1 - d) / n)).tolist()))


def rank_serial(edges: list[tuple[int, int]], vertices: list[int], d: float = 0.85, tol: float = 1e-12, order=None, passes: int = 10_000, dangling: str = "expand") -> dict[int, float]:
    """One tuple at a time in the given order: the reference meaning of the program."""
    edges = sorted(set(edges))
    if dangling != "leak":
        have = {u for u, _ in edges}
        edges += [(u, v) for u in vertices if u not in have for v in vertices if v != u]
    dout: dict[int, int] = {}
    for u, _ in edges:
        dout[u] = dout.get(u, 0) + 1
    pr, old = {v: (1 - d) / len(vertices) for v in vertices}, dict.fromkeys(range(len(edges)), 0.0)
    for _ in range(passes):
        quiet = True
        for i in range(len(edges)) if order is None else order(len(edges)):
            u, v = edges[i]
            if abs(pr[u] - old[i]) > tol:
                now = pr[u]  # a self-loop passes on what it had before its own update
                pr[v] += d * (now - old[i]) / dout[u]
                old[i], quiet = now, False
        if quiet:
            break
    return pr


def _checked(edges: DataFrame, d: float, n: int, folds: bool) -> None:
    if not 0 < d < 1:
        raise ValueError("d must lie between 0 and 1")
    if edges.filter("u is null or v is null").head(1):
        raise ValueError("an edge has a null end")
    if folds and n < 2:
        raise ValueError("folding needs at least two vertices")


def expand(edges: DataFrame, vertices: DataFrame, n: int, beyond: str = "refuse") -> DataFrame | None:
    """Edges from each vertex without out-edges to every other; beyond a limit of rows refused, or None to ``group`` them."""
    ends = vertices.join(edges.select(F.col("u").alias("id")).distinct(), "id", "left_anti")
    count = ends.count()
    if count * (n - 1) > EXPANDED_LIMIT:
        if beyond == "group":
            return None
        raise ValueError(f"{count * (n - 1)} added edges; fold them instead")
    more = ends.select(F.col("id").alias("u")).join(F.broadcast(vertices.select(F.col("id").alias("v"))), F.expr("u <> v"))
    return edges.unionByName(more)


def _small(n: int, row_bytes: int, limit: int) -> bool:
    return n * row_bytes <= limit


def rank(
    edges: DataFrame, vertices: DataFrame | None = None, *, variant: str | None = None, memory: str = "vertex", orientation: str = "pull", dangling: str = "fold", d: float = 0.85, tol: float = 0.0, shards: int | None = None,
    index: bool = False, sweeps_per_exchange: int = 1, schedule: Schedule | None = None, stop: Stop | None = None, max_sweeps: int = 200, broadcast_bytes: int = BROADCAST_BYTES, known: DataFrame | None = None, beyond: str = "refuse",
) -> Run:
    """Run with state ranks(id, pr), vertices(id, pr, old, inv_dout) and edges(u, v [, seen]).

    known: ranks (id, pr) from an earlier run, for ``adjacency``; they only shorten the way (see ``_packed``).
    """
    if variant:
        given = {"d": d, "tol": tol, "schedule": schedule, "stop": stop, "max_sweeps": max_sweeps, "broadcast_bytes": broadcast_bytes, "beyond": "group"} | ({"shards": shards} if shards else {})
        return rank(edges, vertices, **(given | PRESETS[variant] | ({"sweeps_per_exchange": sweeps_per_exchange} if sweeps_per_exchange > 1 else {})))
    if sweeps_per_exchange > 1 and memory != "adjacency":
        raise ValueError("several sweeps between exchanges need edges packed in blocks: memory='adjacency'")
    spark, clock, schedule, stop = edges.sparkSession, Clock(), schedule or Schedule.full(), stop or Stop.residual()
    edges = edges.select("u", "v").distinct().persist()
    given = edges
    vertices = (vertices.select("id") if vertices is not None else vertices_of(edges)).distinct().persist()
    n = vertices.count()
    _checked(edges, d, n, dangling == "fold")
    if n == 0:
        return Run(spark, {"ranks": spark.createDataFrame([], "id long, pr double")}, [], "quiet")
    if dangling == "expand":
        added = expand(edges, vertices, n, beyond)
        edges, dangling = (edges, "fold") if added is None else (added, dangling)
    small = _small(n, 40, broadcast_bytes)
    if memory == "adjacency":
        if small:
            run = _packed(edges, vertices, n, orientation, dangling, d, tol, shards, sweeps_per_exchange, schedule, stop, max_sweeps, clock, known)
            vertices.unpersist()
            given.unpersist()
            return run
        if sweeps_per_exchange > 1:
            raise ValueError(f"{n} ranks are too many to replicate for several sweeps between exchanges")
        memory = "embedded"  # the same tuples (u, v, old) as rows, for ranks that no task can hold
    first = (1 - d) / n
    state = vertices.join(degrees(edges).withColumnRenamed("u", "id"), "id", "left").select("id", F.lit(first).alias("pr"), F.lit(0.0).alias("old"), F.when(F.col("dout") > 0, 1 / F.col("dout")).alias("inv_dout"))
    states, edge_states = States(), States()
    state = states.next(state)
    parts = shards or max(1, min(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-edges.count() // SHARD_EDGES)))
    if orientation == "split":
        edges = edges.repartition(parts)
    elif orientation == "push":
        edges = edges.repartition(parts, "u")
    elif orientation == "pull":
        edges = edges.repartition(parts, "v")
    keys = ["u", "v"]
    if index:  # a position for each tuple, by which its memory is addressed; it fixes no order
        edges, keys = edges.withColumn("at", F.monotonically_increasing_id()), ["at"]
    if memory == "embedded":
        edges = edges.withColumn("seen", F.lit(0.0))
    edges = edge_states.next(edges)
    olds = States()
    old = olds.next(edges.select(*keys, F.lit(0.0).alias("seen"))) if memory == "edge" else None
    log, reason = [], "sweeps"
    stubs_pending = first * state.filter("inv_dout is null").count()
    for sweep in range(1, max_sweeps + 1):
        pending = F.col("pr") - F.col("old")
        largest = state.agg(F.max(F.abs(pending))).first()[0] if schedule.kind == "priority" else 0.0
        runs = schedule.runs(F.col("id"), sweep, pending, largest or 0.0) & (F.abs(pending) > tol)
        if memory in ("edge", "embedded"):
            sources = state.select(F.col("id").alias("u"), "pr", "inv_dout", runs.alias("go"))
            # the memory is a space of its own, found by the edge's address, or part of the tuple
            held = edges.join(old, keys) if memory == "edge" else edges
            met = held.join(F.broadcast(sources) if small else sources, "u")
            go = F.col("go") & (F.abs(F.col("pr") - F.col("seen")) > tol)
            passed = met.select(*edges.columns, *(["seen"] if memory == "edge" else []), F.when(go, F.col("pr")).otherwise(F.col("seen")).alias("now"), "inv_dout")
            passed = (olds if memory == "edge" else edge_states).next(passed)
            deltas = passed.filter("now <> seen").select("v", (F.lit(d) * (F.col("now") - F.col("seen")) * F.col("inv_dout")).alias("x"))
            if memory == "edge":
                old = passed.select(*keys, F.col("now").alias("seen"))
            else:
                edges = passed.select("u", "v", *(["at"] if index else []), F.col("now").alias("seen"))
        else:
            active = state.filter(runs & F.col("inv_dout").isNotNull()).select(F.col("id").alias("u"), (F.lit(d) * pending * F.col("inv_dout")).alias("x"))
            deltas = edges.join(F.broadcast(active) if small else active, "u").select("v", "x")
        if orientation in ("split", "push", "any"):  # several writers: sums per task first
            deltas = deltas.groupBy(F.spark_partition_id().alias("task"), "v").agg(F.sum("x").alias("x"))
        add = deltas.groupBy(F.col("v").alias("id")).agg(F.sum("x").alias("x"))
        fires = F.when(runs, F.col("pr")).otherwise(F.col("old"))
        new = state.join(add, "id", "left")
        stub = F.col("inv_dout").isNull() & runs
        if dangling == "fold":
            # a full sweep takes what the last sweep's statistics found pending, so it needs no job of its own
            lone = state.agg(F.coalesce(F.sum(F.when(stub, pending)), F.lit(0.0))).first()[0] if schedule.partial or tol > 0 else stubs_pending
            extra = F.lit(d) * (F.lit(lone / (n - 1)) - F.when(stub, pending / (n - 1)).otherwise(0.0))
        elif dangling == "sample":
            extra = F.coalesce("drawn", F.lit(0.0))
            new = new.join(_draws(state.filter(stub), vertices, n, d, sweep), "id", "left")
        else:
            extra = F.lit(0.0)
        new = states.next(new.select("id", (F.col("pr") + F.coalesce("x", F.lit(0.0)) + extra).alias("pr"), fires.alias("old"), "inv_dout"))
        left = F.abs(F.col("pr") - F.col("old"))
        lone = F.when(F.col("inv_dout").isNull(), F.col("pr") - F.col("old")).otherwise(0.0)
        stat = new.agg(F.sum(F.when(left > tol, 1).otherwise(0)).alias("enabled"), F.sum(left).alias("residual"), F.sum("pr").alias("mass"), F.sum(lone).alias("lone"), F.count(F.lit(1)).alias("n")).first()
        log.append({"sweeps": sweep, "full": not schedule.partial, "evaluated": stat["n"], "enabled": stat["enabled"], "residual": stat["residual"], "change": stat["residual"], "mass": stat["mass"], "exchanged_rows": stat["n"], "exchanged_bytes": stat["n"] * 16, "secs": clock.lap()})
        state, stubs_pending = new, stat["lone"] or 0.0
        if why := stop.reason(log[-1]):
            reason = why
            break
    vertices.unpersist()
    given.unpersist()
    for s in (states, edge_states, olds):
        s.close()
    kept = edges.join(old, keys).select("u", "v", "seen") if memory == "edge" else edges
    return Run(spark, {"ranks": state.select("id", "pr"), "vertices": state, "edges": kept}, log, reason)


def _packed(edges: DataFrame, vertices: DataFrame, n: int, orientation: str, dangling: str, d: float, tol: float, shards: int | None, sweeps: int, schedule: Schedule, stop: Stop, max_sweeps: int, clock: Clock, known: DataFrame | None = None) -> Run:
    """The tuples (u, old) of a target as arrays in blocks; ranks, checked to be few, are replicated in each sweep.

    The driver holds two numbers for each vertex, so a sweep is one job without shuffle:
    blocks add to the ranks of their targets and remember what they passed on.

    ``known`` ranks q start the program as if every edge had passed q / dout on before: then
    pr = (1 - d) / N + d * sum of q / dout, which is where the invariant puts it.
    """
    if dangling == "sample":
        raise ValueError("drawn targets need memory='vertex'")
    spark = edges.sparkSession
    ids = np.sort(vertices.select("id").toArrow().column(0).to_numpy())
    place = spark.sparkContext.broadcast(ids)

    def dense(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array(np.searchsorted(place.value, b.column(i).to_numpy()).astype(np.int32)) for i in (0, 1)], ["u", "v"])

    parts = shards or max(1, min(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-edges.count() // SHARD_EDGES)))
    by = "u" if orientation == "push" else "v"
    # ranges of targets, so that a block writes few ranks; a target of very many edges spans blocks, whose sums are added
    dealt = edges.repartitionByRange(parts, by, "u", "v").sortWithinPartitions(by) if orientation in ("pull", "push") else edges.repartition(parts)
    states = States(10)
    blocks = states.next(pack_edges(dealt.mapInArrow(dense, "u int, v int"), by))
    out = degrees(edges).toArrow()
    inv = np.zeros(n)
    inv[np.searchsorted(ids, out.column("u").to_numpy())] = 1.0 / out.column("dout").to_numpy()
    stub = inv == 0
    first = (1 - d) / n
    pr, old = np.full(n, first), np.zeros(n)
    if known is not None:
        got = known.select("id", "pr").toArrow()
        old[np.searchsorted(ids, got.column("id").to_numpy())] = got.column("pr").to_numpy()
        blocks = states.next(_remember(blocks, spark.sparkContext.broadcast(old)))
        pr = np.full(n, first)
        pr = pr + d * _passed(blocks, spark.sparkContext.broadcast((old * inv,)), n)
        if dangling == "fold":
            pr = pr + d * (old[stub].sum() - np.where(stub, old, 0.0)) / (n - 1)
    log, reason = [], "sweeps"
    for sweep in range(1, max_sweeps + 1):
        pending = pr - old
        runs = None
        if schedule.kind == "alternating":
            runs = ids % 2 == sweep % 2
        elif schedule.kind == "sample":
            runs = np.random.default_rng([schedule.seed, sweep]).random(n) < schedule.share
        elif schedule.kind == "priority":
            runs = np.abs(pending) >= schedule.share * np.abs(pending).max(initial=0.0)
        fires = np.abs(pending) > tol if runs is None else runs & (np.abs(pending) > tol)
        swept = states.next(sweep_edges(blocks, spark.sparkContext.broadcast((pr, inv, runs)), d, tol, sweeps))
        new = pr.copy()
        told = swept.select("at", "x").toArrow()
        for at, x in zip(told.column(0), told.column(1)):
            to = np.frombuffer(at.as_buffer(), np.int32)
            new[to] += np.frombuffer(x.as_buffer(), np.float64)
        if dangling == "fold":
            lone = np.where(stub & fires, pending, 0.0)
            new += d * (lone.sum() - lone) / (n - 1)
        old = np.where(fires, pr, old)
        pr, blocks = new, swept.select("block", "u", "v", "old")
        left = np.abs(pr - old)
        residual, enabled = float(left.sum()), int((left > tol).sum())
        if sweeps > 1:  # edges of a vertex remember different values
            gap = _passed(blocks, spark.sparkContext.broadcast((pr, inv)), n, 1)
            residual, enabled = float(gap.sum() + left[stub].sum()), int((gap > tol).sum() + (left[stub] > tol).sum())
        log.append({"sweeps": sweep, "full": not schedule.partial, "evaluated": n, "enabled": enabled, "residual": residual, "change": residual, "mass": float(pr.sum()), "exchanged_rows": n, "exchanged_bytes": sum(len(a.as_buffer()) * 3 for a in told.column(0)), "secs": clock.lap()})
        if why := stop.reason(log[-1]):
            reason = why
            break
    states.close()
    table = pa.table({"id": ids, "pr": pr, "old": old, "inv_dout": pa.array(inv, mask=stub)})
    state = spark.createDataFrame(table)
    return Run(spark, {"ranks": state.select("id", "pr"), "vertices": state, "edges": unpack_edges(blocks, ids)}, log, reason)


def _remember(blocks: DataFrame, values) -> DataFrame:
    """Blocks whose edges have passed on the given values of their sources."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            old = [values.value[np.frombuffer(u.as_buffer(), np.int32)].tobytes() for u in b.column("u")]
            yield pa.RecordBatch.from_arrays([b.column("block"), b.column("u"), b.column("v"), pa.array(old, pa.binary())], ["block", "u", "v", "old"])

    return blocks.mapInArrow(run, "block long, u binary, v binary, old binary")


def _passed(blocks: DataFrame, shared, n: int, gaps: int = 0) -> np.ndarray:
    """Per target the sum of a value of the sources; with ``gaps``, of |pr - memory| / dout. One array of n per task is sent."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(n)
        for b in batches:
            for i in range(b.num_rows):
                u, v = (np.frombuffer(b.column(c)[i].as_buffer(), np.int32) for c in ("u", "v"))
                x = np.abs(shared.value[0][u] - np.frombuffer(b.column("old")[i].as_buffer(), np.float64)) * shared.value[1][u] if gaps else shared.value[0][u]
                total += np.bincount(v, x, n)
        yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], ["x"])

    parts = blocks.mapInArrow(run, "x binary").toArrow().column(0)
    return sum((np.frombuffer(x.as_buffer(), np.float64) for x in parts), np.zeros(n))


def _draws(stubs: DataFrame, vertices: DataFrame, n: int, d: float, sweep: int) -> DataFrame:
    """One target for each folded vertex: the vertex whose hash is next on a ring of buckets.

    The whole pending rank goes to the target, so the mean over draws is the folded
    update; a draw that hits the vertex itself moves on to the next bucket.
    """
    ring = vertices.select("id", F.pmod(F.xxhash64("id"), F.lit(n)).alias("slot")).groupBy("slot").agg(F.min("id").alias("id"))
    drawn = stubs.select(F.col("id").alias("me"), (F.lit(d) * (F.col("pr") - F.col("old"))).alias("x"), F.pmod(F.xxhash64("id", F.lit(sweep)), F.lit(n)).alias("slot"))
    hits = drawn.join(ring, "slot", "left").withColumn("id", F.coalesce("id", F.lit(None)))
    lost = hits.filter("id is null or id = me").agg(F.coalesce(F.sum("x"), F.lit(0.0))).first()[0]
    good = hits.filter("id is not null and id <> me").groupBy("id").agg(F.sum("x").alias("drawn"))
    # draws without a target are spread evenly, so that no rank is lost
    return vertices.select("id").join(good, "id", "left").select("id", (F.coalesce("drawn", F.lit(0.0)) + F.lit(lost / n)).alias("drawn"))


def rank_classic(edges: DataFrame, vertices: DataFrame | None = None, *, d: float = 0.85, max_iter: int = 50, eps: float = 0.0, dangling: str = "fold") -> Run:
    """Synchronous iteration from 1 / N over whole contributions."""
    spark, clock = edges.sparkSession, Clock()
    edges = edges.select("u", "v").distinct().persist()
    vertices = vertices.select("id").distinct() if vertices is not None else vertices_of(edges)
    n = vertices.count()
    _checked(edges, d, n, dangling == "fold")
    states, log, reason = States(), [], "sweeps"
    state = states.next(vertices.join(degrees(edges).withColumnRenamed("u", "id"), "id", "left").select("id", F.lit(1.0 / n).alias("pr"), "dout"))
    for sweep in range(1, max_iter + 1):
        add = edges.join(state.filter("dout is not null").select(F.col("id").alias("u"), (F.col("pr") / F.col("dout")).alias("x")), "u").groupBy(F.col("v").alias("id")).agg(F.sum("x").alias("x"))
        lone = state.agg(F.coalesce(F.sum(F.when(F.col("dout").isNull(), F.col("pr"))), F.lit(0.0))).first()[0] if dangling == "fold" else 0.0
        own = F.when(F.col("dout").isNull(), F.col("pr")).otherwise(0.0) if dangling == "fold" else F.lit(0.0)
        new = state.join(add, "id", "left").select("id", (F.lit((1 - d) / n) + F.lit(d) * (F.coalesce("x", F.lit(0.0)) + (F.lit(lone) - own) / max(1, n - 1))).alias("pr"), "dout", F.col("pr").alias("_was"))
        new = states.next(new)
        change = new.agg(F.sum(F.abs(F.col("pr") - F.col("_was")))).first()[0]
        state = new.drop("_was")
        log.append({"sweeps": sweep, "evaluated": n, "change": change, "residual": change, "enabled": n, "secs": clock.lap()})
        if change <= eps:
            reason = "eps"
            break
    return Run(spark, {"ranks": state.select("id", "pr")}, log, reason)


#: The forms of the program, each with options of its own: p3..p13 before reduction, r1..r4 the measured variants.
PRESETS: dict[str, dict] = {
    "vertex_delta": {"memory": "vertex", "orientation": "push", "dangling": "expand"},
    "edge_delta": {"memory": "edge", "orientation": "any", "dangling": "expand"},
    "pull": {"memory": "edge", "orientation": "pull", "dangling": "expand"},
    "push": {"memory": "edge", "orientation": "push", "dangling": "expand"},
    "split": {"memory": "edge", "orientation": "split", "dangling": "expand", "shards": 8},
    "localized": {"memory": "embedded", "orientation": "any", "dangling": "expand"},
    "folded": {"memory": "edge", "orientation": "any", "dangling": "fold"},
    "expanded": {"memory": "vertex", "orientation": "pull", "dangling": "expand"},
    "materialized": {"memory": "edge", "orientation": "any", "index": True, "dangling": "expand"},
    "pull_shards": {"memory": "edge", "orientation": "pull", "shards": 8, "dangling": "expand"},
    "pull_local_shards": {"memory": "embedded", "orientation": "pull", "shards": 8, "dangling": "expand"},
    "adjacency": {"memory": "adjacency", "orientation": "pull", "dangling": "expand"},
    "r1": {"memory": "edge", "orientation": "split", "dangling": "fold", "shards": 8},
    "r2": {"memory": "embedded", "orientation": "split", "dangling": "fold", "shards": 8},
    "r3": {"memory": "edge", "orientation": "pull", "dangling": "fold", "shards": 8},
    "r4": {"memory": "adjacency", "orientation": "pull", "dangling": "fold"},
}


def invariant_error(run: Run, edges: DataFrame, d: float = 0.85) -> float:
    """Largest |pr - (1 - d)/N - d sum old/dout| where vertices remember; rank passed on by folded vertices included."""
    state = run.state["vertices"]
    n = state.count()
    sources = state.filter("inv_dout is not null").select(F.col("id").alias("u"), "old", "inv_dout")
    kept = run.state["edges"]
    joined = kept.join(sources, "u").select("v", (F.col("seen") * F.col("inv_dout")).alias("x")) if "seen" in kept.columns else edges.select("u", "v").distinct().join(sources, "u").select("v", (F.col("old") * F.col("inv_dout")).alias("x"))
    given = joined.groupBy(F.col("v").alias("id")).agg(F.sum("x").alias("x"))
    stubs = F.col("inv_dout").isNull()
    lone = state.agg(F.coalesce(F.sum(F.when(stubs, F.col("old"))), F.lit(0.0))).first()[0]
    want = F.lit((1 - d) / n) + F.lit(d) * (F.coalesce("x", F.lit(0.0)) + (F.lit(lone) - F.when(stubs, F.col("old")).otherwise(0.0)) / max(1, n - 1))
    return state.join(given, "id", "left").agg(F.max(F.abs(F.col("pr") - want))).first()[0]
