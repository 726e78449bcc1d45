"""Approximate nearest neighbours by an inverted multi-index.

Unit vectors are cut in two halves, and each half has its own codebook of ``words``
centroids (k-means on at most ``sample`` vectors, those with the least hash of their
id; every vector is indexed). A cell is a pair of centroids, one for each half. For a
query, cells are taken from a heap by the sum of its two squared distances, until they
hold ``enough`` different vectors. The cells' entries, copies included, are reranked by
the exact cosine in double precision.

``enough`` is learned: ``probes`` of the queries (different vectors, those with the
least hash) are compared with all vectors in one pass, and it is the least number with
which their visits would have met the share ``recall`` of their true neighbours. So
vectors with structure are searched in a few cells, and vectors without any in as many
as the recall takes, at every size.

Entries live on shelves: runs of cells of about ``shelf_rows`` rows; a cell of more rows
is dealt out over several shelves. A query goes only to the shelves of the cells that it
visits, with a bitmap of these. Queries with equal vectors are asked once. Shelves answer
with their ``k`` + 1 best, which are merged; then each asking id drops itself.

Defined results: vectors that are null, zero, of another length than most, or that hold
null or non-finite components take no part, nor do rows without id; a query's own id is
never its neighbour; equal scores go by the smaller id; repeated query ids are asked
once, by any of their vectors that is first by value; an id that several rows repeat is
one candidate, by its best row; fewer than ``k`` candidates give fewer rows; an empty
table gives an empty result; extra columns are ignored, whatever their names.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import stash

WORDS = 64
SAMPLE = 16_384
#: Queries that are also answered by looking at every vector, to learn how far others must go.
PROBES = 128


def _matrix(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(column), -1)


def _unit(x: np.ndarray) -> np.ndarray:
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def kmeans(x: np.ndarray, k: int, sweeps: int = 15, seed: int = 3) -> np.ndarray:
    x = np.unique(x, axis=0)
    c = x[np.random.default_rng(seed).permutation(len(x))[:k]]
    for _ in range(sweeps):
        near = nearest(x, c)
        sums = np.zeros_like(c)
        np.add.at(sums, near, x)
        n = np.bincount(near, minlength=len(c))[:, None]
        c = np.where(n > 0, sums / np.maximum(n, 1), c)
    return c


def distances(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return (x * x).sum(axis=1)[:, None] - 2 * x @ c.T + (c * c).sum(axis=1)[None, :]


def nearest(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return np.concatenate([distances(x[at : at + 4096], c).argmin(axis=1) for at in range(0, len(x), 4096)]) if len(x) else np.zeros(0, np.int64)


class Codebooks:
    def __init__(self, x: np.ndarray, words: int) -> None:
        self.half = x.shape[1] // 2
        self.first, self.second = kmeans(x[:, : self.half], words), kmeans(x[:, self.half :], words)

    def cells(self, x: np.ndarray) -> np.ndarray:
        return nearest(x[:, : self.half], self.first) * len(self.second) + nearest(x[:, self.half :], self.second)

    def to_centroids(self, q: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Squared distances from the halves of a unit vector to the centroids."""
        return distances(q[None, : self.half], self.first)[0], distances(q[None, self.half :], self.second)[0]

    def visit(self, q: np.ndarray, held: np.ndarray, enough: int) -> list[int]:
        """Cells in order of summed distance until they hold ``enough`` of ``held``. q: one unit vector."""
        a, b = self.to_centroids(q)
        ia, ib = np.argsort(a, kind="stable"), np.argsort(b, kind="stable")
        a, b, ia, ib = a[ia].tolist(), b[ib].tolist(), ia.tolist(), ib.tolist()
        n, m, width = len(a), len(b), len(self.second)
        counts, out, got = held, [], 0
        heap = [(a[0] + b[0], 0, 0)]
        while heap and got < enough:
            _, i, j = heapq.heappop(heap)
            cell = ia[i] * width + ib[j]
            out.append(cell)
            got += counts[cell]
            # (i, j + 1) follows (i, j); (i + 1, 0) follows (i, 0): each pair enters once
            if j + 1 < m:
                heapq.heappush(heap, (a[i] + b[j + 1], i, j + 1))
            if j == 0 and i + 1 < n:
                heapq.heappush(heap, (a[i + 1] + b[0], i + 1, 0))
        return out


def usable(vector: Column) -> Column:
    """True where all components are finite numbers and one is not zero."""
    fine = F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return F.coalesce(vector.isNotNull() & fine & F.exists(vector, lambda x: x != 0), F.lit(False))


def _best(entries: np.ndarray, ids: np.ndarray, cells: np.ndarray | None, queries: np.ndarray, wanted: list[np.ndarray] | None, k: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(query, rows, scores): the k best entries of each query, of those in its wanted cells if there are any cells."""
    norms = np.sqrt((entries * entries).sum(axis=1))
    for at in range(0, len(queries), 64):
        part = queries[at : at + 64]
        rough = (entries @ part.T) / norms[:, None]
        for j, q in enumerate(part):
            rows = np.arange(len(entries)) if cells is None else np.flatnonzero(wanted[at + j][cells])
            if not len(rows):
                continue
            near = rough[rows, j]
            if len(rows) > k:
                bar = np.partition(near, len(rows) - k)[len(rows) - k]
                rows = rows[near >= bar - 1e-9 * np.abs(q).max()]
            # the same order of additions for each row, so that equal vectors have equal scores
            exact = (entries[rows] * q).sum(axis=1) / (norms[rows] * np.sqrt((q * q).sum()))
            order = np.lexsort((ids[rows], -exact))[:k]
            yield at + j, rows[order], exact[order]


def _enough(entries: DataFrame, probes: np.ndarray, own: np.ndarray, books, held: np.ndarray, recall: float, k: int) -> int:
    """Different vectors that a visit must hold to meet the share ``recall`` of the probes' true neighbours."""
    asked = entries.sparkSession.sparkContext.broadcast(probes)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                x, ids, cells = _matrix(b.column("v")), b.column("id").to_numpy(), b.column("cell").to_numpy()
                got = [(np.full(len(rows), q), ids[rows], cells[rows], s) for q, rows, s in _best(x, ids, None, asked.value, None, k + 1)]
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*got)], ["q", "id", "cell", "score"])

    near = entries.select("id", "v", "cell").mapInArrow(run, "q long, id long, cell int, score double")
    best = Window.partitionBy("q").orderBy(F.desc("score"), "id")
    rows = near.withColumn("r", F.row_number().over(best)).filter(F.col("r") <= k + 1).collect()  # at most probes * (k + 1)
    need = []
    for q in range(len(probes)):
        a, b = books.to_centroids(_unit(probes[q][None])[0])
        order = np.argsort((a[:, None] + b[None, :]).ravel(), kind="stable")
        until = np.empty(len(order), np.int64)
        until[order] = np.cumsum(held[order])
        need += [int(until[r["cell"]]) for r in sorted((r for r in rows if r["q"] == q and r["id"] != own[q]), key=lambda r: r["r"])[:k]]
    return int(np.quantile(need, recall, method="higher")) if need else 1


def shelves(rows_in_cell: np.ndarray, shelf_rows: int) -> tuple[np.ndarray, np.ndarray]:
    """For each cell its first shelf and on how many shelves it is dealt out."""
    first, splits, shelf, filled = np.zeros(len(rows_in_cell), np.int64), np.ones(len(rows_in_cell), np.int64), 0, 0
    for cell, n in enumerate(rows_in_cell.tolist()):
        if n > shelf_rows:
            splits[cell] = -(-n // shelf_rows)
            shelf += 1 if filled else 0
            first[cell], shelf, filled = shelf, shelf + splits[cell], 0
            continue
        if filled + n > shelf_rows:
            shelf, filled = shelf + 1, 0
        first[cell], filled = shelf, filled + n
    return first, splits


def search(vectors: DataFrame, asks: Column, row_id: str = "vec_id", vector: str = "embedding", k: int = 5, words: int = WORDS, recall: float = 0.95, probes: int = PROBES, sample: int = SAMPLE, shelf_rows: int = 20_000) -> DataFrame:
    """query_id, rank, vec_id, score for the rows where ``asks`` is true, against all rows."""
    spark = vectors.sparkSession
    schema = "query_id long, rank int, vec_id long, score double"
    good = vectors.select(F.col(row_id).cast("long").alias("id"), F.col(vector).alias("v"), asks.alias("asks")).filter(usable(F.col("v")) & F.col("id").isNotNull())
    lengths = good.groupBy(F.size("v").alias("d")).agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "d").first()
    if lengths is None or lengths["d"] < 2:
        return spark.createDataFrame([], schema)
    good = good.filter(F.size("v") == lengths["d"]).select("id", F.col("v").cast("array<double>").alias("v"), "asks")
    drawn = good.select(F.xxhash64("id").alias("h"), "v").orderBy("h").limit(sample).select("v").toArrow()
    books = spark.sparkContext.broadcast(Codebooks(_unit(_matrix(drawn.column(0))), words))
    n_cells = len(books.value.first) * len(books.value.second)

    def index(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                cells = books.value.cells(_unit(_matrix(b.column(1))))
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(cells, pa.int32())], ["id", "v", "cell"])

    entries = stash(good.select("id", "v").mapInArrow(index, "id long, v array<double>, cell int"))
    rows, held = np.zeros(n_cells, np.int64), np.zeros(n_cells, np.int64)  # of each cell: a bounded table
    different = entries.groupBy("cell", F.xxhash64("v").alias("h")).agg(F.count(F.lit(1)).alias("n"))
    for r in different.groupBy("cell").agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("u")).collect():
        rows[r["cell"]], held[r["cell"]] = r["n"], r["u"]

    # two hashes stand for a vector; equal vectors are asked once
    marks = [F.xxhash64("v").alias("h1"), F.xxhash64("v", F.lit(1)).alias("h2")]
    asking = good.filter("asks").groupBy(F.col("id").alias("q")).agg(F.min("v").alias("v")).select("q", "v", *marks)
    kinds = stash(asking.groupBy("h1", "h2").agg(F.min("v").alias("v"), F.min("q").alias("q")))
    picked = kinds.orderBy("h1", "h2").limit(probes).select("v", "q").toArrow()
    if not picked.num_rows:
        return spark.createDataFrame([], schema)
    enough = _enough(entries, _matrix(picked.column("v")), picked.column("q").to_numpy(), books.value, held, recall, k)
    first, splits = shelves(rows, shelf_rows)
    plan = spark.sparkContext.broadcast((held.tolist(), first, splits, enough))

    def shelve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _, first, splits, _ = plan.value
        for b in batches:
            cells, ids = b.column("cell").to_numpy(), b.column("id").to_numpy()
            mixed = (ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(33)
            yield pa.RecordBatch.from_arrays([pa.array(first[cells] + (mixed % splits[cells].astype(np.uint64)).astype(np.int64)), b.column("id"), b.column("v"), b.column("cell")], ["shelf", "id", "v", "cell"])

    def route(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, first, splits, enough = plan.value
        for b in batches:
            to, row, maps = [], [], []
            for i, q in enumerate(_unit(_matrix(b.column("v"))) if b.num_rows else ()):
                cells = np.array(books.value.visit(q, held, enough))
                bits = np.zeros(n_cells, np.uint8)
                bits[cells] = 1
                there = np.unique(np.repeat(first[cells], splits[cells]) + np.concatenate([np.arange(n) for n in splits[cells]]))
                to += there.tolist()
                row += [i] * len(there)
                maps += [np.packbits(bits, bitorder="little").tobytes()] * len(there)
            at = pa.array(row, pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(to, pa.int64()), *(b.column(c).take(at) for c in ("h1", "h2", "v")), pa.array(maps, pa.binary())], ["shelf", "h1", "h2", "v", "cells"])

    def rerank(left: pa.Table, right: pa.Table) -> pa.Table:
        got = []
        if left.num_rows and right.num_rows:
            ids, cells = left.column("id").to_numpy(), left.column("cell").to_numpy()
            wanted = [np.unpackbits(np.frombuffer(m, np.uint8), bitorder="little").astype(bool) for m in right.column("cells").to_pylist()]
            got = [(np.full(len(r), q), ids[r], s) for q, r, s in _best(_matrix(left.column("v")), ids, cells, _matrix(right.column("v")), wanted, k + 1)]
        q, found, score = (np.concatenate(c) for c in zip(*got)) if got else (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
        at = pa.array(q)
        return pa.Table.from_arrays([right.column("h1").take(at), right.column("h2").take(at), pa.array(found, pa.int64()), pa.array(score, pa.float64())], ["h1", "h2", "vec_id", "score"])

    shelved = entries.mapInArrow(shelve, "shelf long, id long, v array<double>, cell int")
    routed = kinds.select("h1", "h2", "v").mapInArrow(route, "shelf long, h1 long, h2 long, v array<double>, cells binary")
    near = shelved.groupBy("shelf").cogroup(routed.groupBy("shelf")).applyInArrow(rerank, "h1 long, h2 long, vec_id long, score double")
    near = near.groupBy("h1", "h2", "vec_id").agg(F.max("score").alias("score"))
    best = Window.partitionBy("h1", "h2").orderBy(F.desc("score"), "vec_id")
    near = near.withColumn("r", F.row_number().over(best)).filter(F.col("r") <= k + 1)  # at most (k + 1) for each shelf met before
    lists = near.groupBy("h1", "h2").agg(F.sort_array(F.collect_list(F.struct("r", "vec_id", "score"))).alias("all"))
    others = F.slice(F.filter("all", lambda x: x["vec_id"] != F.col("q")), 1, k)
    out = asking.select("q", "h1", "h2").join(lists, ["h1", "h2"]).select("q", F.posexplode(others).alias("p", "x"))
    return out.select(F.col("q").alias("query_id"), (F.col("p") + 1).alias("rank"), F.col("x.vec_id").alias("vec_id"), F.col("x.score").alias("score"))
