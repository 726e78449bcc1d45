"""Materialised reservoirs: tuples packed in blocks of arrays, swept by vector kernels.

A block holds some thousand tuples as one row of binary columns, so a sweep reads and
writes few rows however many tuples there are, and the state that a sweep rewrites is
four bytes for a point or eight for an edge. Blocks are bounded (``POINTS``, ``EDGES``),
so a kernel never holds more than a block.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

POINTS = 1 << 16
EDGES = 1 << 18


def _whole(df: DataFrame, xs: list[str]) -> bool:
    """Whether all coordinates are integers, whose sums are then exact."""
    return all(df.schema[x].dataType.simpleString() in ("bigint", "int", "smallint", "tinyint") for x in xs)


def _narrow(x: np.ndarray) -> np.ndarray:
    """Whole numbers in as few bytes each as hold all of them."""
    if x.dtype.kind == "i" and x.size:
        low, high = x.min(), x.max()
        for kind in (np.int8, np.int16, np.int32):
            if np.iinfo(kind).min <= low and high <= np.iinfo(kind).max:
                return x.astype(kind)
    return x


def _coordinates(data, n: int, d: int, kind: type) -> np.ndarray:
    """The d coordinates of a block's n points, as ``kind``; how wide they are kept follows from the length."""
    wide = len(data) // max(1, n * d)
    return np.frombuffer(data, f"i{wide}" if kind is np.int64 and wide in (1, 2, 4) else kind).reshape(d, -1).astype(kind, copy=False)


def _deflated(ids: pa.Array) -> bytes:
    out, codec = pa.BufferOutputStream(), next((c for c in ("zstd", "lz4") if pa.Codec.is_available(c)), None)
    with pa.ipc.new_stream(out, pa.schema([("pid", ids.type)]), options=pa.ipc.IpcWriteOptions(compression=codec)) as to:
        to.write_batch(pa.RecordBatch.from_arrays([ids], ["pid"]))
    return out.getvalue().to_pybytes()


def pack_points(points: DataFrame, xs: list[str], rows: int = POINTS) -> DataFrame:
    """block, n, x (coordinates by column), c (clusters), pids (a compressed batch). points: pid, xs, c."""
    kind = np.int64 if _whole(points, xs) else np.float64

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n, k, part = [], 0, 0, 0

        def close(got: list[pa.RecordBatch], number: int) -> pa.RecordBatch:
            t = pa.Table.from_batches(got).combine_chunks()
            x = np.stack([t.column(f"{c}").to_numpy() for c in xs]).astype(kind)
            ids = t.column("pid").chunk(0) if t.num_rows else pa.array([], t.schema.field("pid").type)
            return pa.RecordBatch.from_pydict(
                {
                    "block": pa.array([(part << 32) + number], pa.int64()), "n": pa.array([t.num_rows], pa.int32()), "x": pa.array([_narrow(x).tobytes()], pa.binary()),
                    "c": pa.array([t.column("c").to_numpy().astype(np.int32).tobytes()], pa.binary()), "pids": pa.array([_deflated(ids)], pa.binary()),
                }
            )

        for b in batches:
            if b.num_rows:
                part = b.column("part")[0].as_py()
                held.append(b)
                n += b.num_rows
            if n >= rows:
                yield close(held, k)
                held, n, k = [], 0, k + 1
        if held:
            yield close(held, k)

    rows_in = points.select("pid", *xs, "c", F.spark_partition_id().cast("long").alias("part"))
    return rows_in.mapInArrow(run, "block long, n int, x binary, c binary, pids binary")


def unpack_points(blocks: DataFrame, pid: str) -> DataFrame:
    """pid, c from rows of block, pids, c."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                ids = pa.ipc.open_stream(b.column("pids")[i].as_buffer()).read_next_batch().column(0)
                yield pa.RecordBatch.from_arrays([ids, pa.array(np.frombuffer(b.column("c")[i].as_py(), np.int32))], ["pid", "c"])

    return blocks.select("pids", "c").mapInArrow(run, f"pid {pid}, c int")


class Kernel:
    """One sweep over a block: which cluster each point joins, and what that changes."""

    def __init__(self, centres: dict[int, tuple], at: list[tuple[int, list[float]]], d: int, whole: bool, tie: str, kind: str, sweeps: int, how: str) -> None:
        self.names, self.c = np.array([m for m, _ in at], np.int32), np.array([v for _, v in at], float).reshape(-1, d)
        self.d, self.kind, self.tie, self.whole, self.sweeps, self.how = d, np.int64 if whole else np.float64, tie, whole, sweeps, how
        self.full = kind == "indirect"
        self.width = int(max(centres, default=0)) + 1
        self.n0, self.s0 = np.zeros(self.width), np.zeros((self.width, d))
        for m, v in centres.items():
            self.n0[m], self.s0[m] = v[0], [float(x) for x in v[1]]

    def distances(self, x: np.ndarray, c: np.ndarray) -> np.ndarray:
        out = np.zeros((x.shape[1], len(c)))
        for j in range(self.d):
            out += (x[j][:, None] - c[None, :, j]) ** 2
        return out

    def choose(self, x: np.ndarray, c: np.ndarray) -> np.ndarray:
        d = self.distances(x, self.c)
        if self.tie == "last":
            return self.names[len(self.names) - 1 - d[:, ::-1].argmin(axis=1)]
        best = d.argmin(axis=1)
        place = np.full(max(self.width, int(c.max(initial=0)) + 1), -1)
        place[self.names] = np.arange(len(self.names))
        mine = place[c]
        own = np.where(mine >= 0, d[np.arange(len(c)), np.maximum(mine, 0)], np.inf)
        return np.where(d[np.arange(len(c)), best] < own, self.names[best], c).astype(np.int32)

    def local(self, x: np.ndarray, c: np.ndarray) -> np.ndarray:
        """Several sweeps on the block's own copy of sizes and sums.

        frozen: moves are seen after a sweep; serial: those of a chunk, tested again one at a time, at once.
        """
        n, s, c = self.n0.copy(), self.s0.copy(), c.copy()
        step = x.shape[1] if self.how == "frozen" else 1024
        for _ in range(self.sweeps):
            moved = 0
            for at in range(0, x.shape[1], step):
                part, own = x[:, at : at + step], c[at : at + step]
                with np.errstate(divide="ignore", invalid="ignore"):
                    centre = s / n[:, None]
                d = np.where(n[None, :] > 0, self.distances(part, np.nan_to_num(centre)), np.inf)
                best = d.argmin(axis=1)
                go = np.flatnonzero(d[np.arange(len(own)), best] < d[np.arange(len(own)), own])
                if self.how == "frozen":
                    np.add.at(s, own[go], -part[:, go].T)
                    np.add.at(n, own[go], -1)
                    np.add.at(s, best[go], part[:, go].T)
                    np.add.at(n, best[go], 1)
                    own[go], moved = best[go], moved + len(go)
                    continue
                moved += self._in_turn(part, own, go, n, s)
            if not moved:
                break
        return c

    def _in_turn(self, part: np.ndarray, own: np.ndarray, go: np.ndarray, n: np.ndarray, s: np.ndarray) -> int:
        """Tests the points of ``go`` again, each after the moves of those before it, and moves them in place.

        A window of points decides as the state before it tells; running sums of these moves give the state that each
        point meets. All up to the first that decides otherwise there have decided as they do one at a time.
        """
        moved, at, step = 0, 0, 64
        most = max(1, (1 << 18) // max(1, s.size))
        while at < len(go):
            rows = go[at : at + min(step, most)]
            p, a = part[:, rows].T.astype(float), own[rows]
            each = np.arange(len(rows))

            def decide(sums: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
                with np.errstate(divide="ignore", invalid="ignore"):
                    now = np.where(sizes > 0, ((p[:, None, :] - sums / sizes[:, :, None]) ** 2).sum(axis=2), np.inf)
                b = now.argmin(axis=1)
                return b, (now[each, b] < now[each, a]) & (np.broadcast_to(sizes, now.shape)[each, a] > 1)

            guess, goes = decide(s[None], n[None])
            w = np.flatnonzero(goes)
            sums, sizes = np.zeros((len(rows) + 1, *s.shape)), np.zeros((len(rows) + 1, len(n)))
            sums[0], sizes[0] = s, n
            sums[w + 1, a[w]], sizes[w + 1, a[w]] = -p[w], -1
            sums[w + 1, guess[w]], sizes[w + 1, guess[w]] = p[w], 1
            sums, sizes = sums.cumsum(axis=0), sizes.cumsum(axis=0)
            b, moves = decide(sums[:-1], sizes[:-1])
            other = np.flatnonzero((moves != goes) | (moves & (b != guess)))
            done = int(other[0]) if len(other) else len(rows)
            s[:], n[:] = sums[done], sizes[done]
            took = np.flatnonzero(moves[:done])
            own[rows[took]] = b[took]
            moved += len(took)
            if done < len(rows):  # the state before this one is right, so its own decision is
                if moves[done]:
                    i, to = a[done], b[done]
                    s[i], n[i], s[to], n[to] = s[i] - p[done], n[i] - 1, s[to] + p[done], n[to] + 1
                    own[rows[done]] = to
                    moved += 1
                done += 1
            step = step * 2 if done == len(rows) else max(8, step // 2)
            at += done
        return moved

    def block(self, x: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """New clusters; then per cluster its size and sums (changes of them unless all are recomputed), at the end the moves."""
        new = self.local(x, c) if self.sweeps > 1 else self.choose(x, c)
        move = np.flatnonzero(new != c)
        out = np.zeros((self.width, self.d + 1), self.kind)
        top = np.abs(x).max(initial=0)
        exact = not self.whole or float(top) * x.shape[1] < 2**53  # sums of whole numbers below that are exact as doubles
        for label, sign, rows in ((new, 1, slice(None) if self.full else move), (c, -1, slice(0, 0) if self.full else move)):
            of = label[rows]
            out[:, 0] += sign * np.bincount(of, minlength=self.width)[: self.width]
            if not exact:
                order = np.argsort(of, kind="stable")
                bounds = np.searchsorted(of[order], np.arange(self.width + 1))
            for j in range(self.d):
                if exact:
                    out[:, j + 1] += (sign * np.bincount(of, x[j][rows], self.width)[: self.width]).astype(self.kind)
                else:
                    sums = np.concatenate((np.zeros(1, np.int64), np.cumsum(x[j][rows][order])))
                    out[:, j + 1] += sign * (sums[bounds[1:]] - sums[bounds[:-1]])
        return new, np.append(out.ravel(), self.kind(len(move)))


def sweep_points(blocks: DataFrame, kernel: Kernel, static: tuple[str, ...]) -> DataFrame:
    """block, static columns, c after the sweep, part (see ``Kernel.block``)."""
    number = "bigint" if kernel.whole else "double"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind, offsets = pa.int64() if kernel.whole else pa.float64(), pa.array([0, kernel.width * (kernel.d + 1) + 1], pa.int32())
        for b in batches:
            for i in range(b.num_rows):  # a block at a time, so that the results of a task's blocks are not held together
                given = np.frombuffer(b.column("c")[i].as_buffer(), np.int32)
                c, part = kernel.block(_coordinates(b.column("x")[i].as_buffer(), len(given), kernel.d, kernel.kind), given)
                yield pa.RecordBatch.from_arrays(
                    [b.column("block").slice(i, 1), *(b.column(s).slice(i, 1) for s in static), pa.array([c.astype(np.int32).tobytes()], pa.binary()), pa.ListArray.from_arrays(offsets, pa.array(part, kind))],
                    ["block", *static, "c", "part"],
                )

    kinds = {f.name: f.dataType.simpleString() for f in blocks.schema}
    return blocks.mapInArrow(run, f"block long, {''.join(f'{s} {kinds[s]}, ' for s in static)}c binary, part array<{number}>")


def totals(swept: DataFrame, by: tuple[str, ...] = ()) -> list:
    """pos and sum of all blocks' parts: k (d + 1) + 1 rows, for each value of ``by``."""
    return swept.select(*by, F.posexplode("part").alias("pos", "v")).groupBy(*by, "pos").agg(F.sum("v").alias("v")).collect()


# ---- graphs


def pack_edges(edges: DataFrame, by: str, size: int = EDGES) -> DataFrame:
    """block, u, v, old: index arrays of edges (u and v are dense positions), memory at zero.

    Rows of one partition that is sorted by ``by`` are cut into blocks of ``size`` edges, so
    a vertex of very many edges spans several blocks.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n, k, part = [], 0, 0, 0

        def close(got: list[pa.RecordBatch], number: int) -> pa.RecordBatch:
            u, v = (np.concatenate([b.column(i).to_numpy() for b in got]).astype(np.int32) for i in (0, 1))
            return pa.RecordBatch.from_pydict({"block": pa.array([(part << 32) + number], pa.int64()), "u": pa.array([u.tobytes()], pa.binary()), "v": pa.array([v.tobytes()], pa.binary()), "old": pa.array([np.zeros(len(u)).tobytes()], pa.binary())})

        for b in batches:
            if b.num_rows:
                part = b.column(2)[0].as_py()
                held.append(b)
                n += b.num_rows
            if n >= size:
                yield close(held, k)
                held, n, k = [], 0, k + 1
        if held:
            yield close(held, k)

    return edges.select("u", "v", F.spark_partition_id().cast("long").alias("part")).mapInArrow(run, "block long, u binary, v binary, old binary")


def sweep_edges(blocks: DataFrame, shared, d: float, tol: float, sweeps: int) -> DataFrame:
    """The blocks with new memories, and ``at``, ``x``: what each block adds to which ranks.

    shared: broadcast of (pr, inv_dout, which sources run or None). With several sweeps
    a block's own additions reach its own edges at once, and other blocks afterwards.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pr, inv, runs = shared.value
        for b in batches:
            olds, ats, xs = [], [], []
            for i in range(b.num_rows):
                u, v = (np.frombuffer(b.column(c)[i].as_buffer(), np.int32) for c in ("u", "v"))
                old = np.frombuffer(b.column("old")[i].as_buffer(), np.float64).copy()
                to, place = np.unique(v, return_inverse=True)
                now, total = pr[u], np.zeros(len(to))
                if sweeps > 1:
                    where = np.minimum(np.searchsorted(to, u), len(to) - 1)
                    own = to[where] == u
                for _ in range(sweeps):
                    gap = now - old
                    go = np.abs(gap) > tol
                    if runs is not None:
                        go &= runs[u]
                    if not go.any():
                        break
                    add = np.bincount(place, np.where(go, d * gap * inv[u], 0.0), len(to))
                    total += add
                    old[go] = now[go]
                    if sweeps > 1:
                        now[own] += add[where[own]]
                olds.append(old.tobytes())
                ats.append(to.astype(np.int32).tobytes())
                xs.append(total.tobytes())
            yield pa.RecordBatch.from_arrays([b.column("block"), b.column("u"), b.column("v"), *(pa.array(c, pa.binary()) for c in (olds, ats, xs))], ["block", "u", "v", "old", "at", "x"])

    return blocks.mapInArrow(run, "block long, u binary, v binary, old binary, at binary, x binary")


def unpack_edges(blocks: DataFrame, ids: np.ndarray) -> DataFrame:
    """u, v, seen by vertex id; ids: of the dense positions."""
    table = blocks.sparkSession.sparkContext.broadcast(ids)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                u, v = (table.value[np.frombuffer(b.column(c)[i].as_buffer(), np.int32)] for c in ("u", "v"))
                yield pa.RecordBatch.from_arrays([pa.array(u), pa.array(v), pa.array(np.frombuffer(b.column("old")[i].as_buffer(), np.float64))], ["u", "v", "seen"])

    return blocks.select("u", "v", "old").mapInArrow(run, "u long, v long, seen double")
