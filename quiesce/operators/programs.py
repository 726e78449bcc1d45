"""Sorting, sparse products, shards and the measures of small worked programs."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.storage import States

# ---- sorting


def sort_builtin(df: DataFrame, value: str = "value") -> DataFrame:
    """slot, value by the range shuffle sort; slots are dense, from 0, without a global window.

    The sorted rows are numbered inside their partition; one row per partition, its
    size, gives the offset.
    """
    return number(df.select(value).orderBy(value), "slot").select("slot", F.col(value).alias("value"))


def number(ordered: DataFrame, name: str) -> DataFrame:
    """Adds dense positions from 0 in the order of the partitions of ``ordered``, which is kept for both reads."""
    rows = ordered.withColumns({"_at": F.monotonically_increasing_id()}).persist()
    low = (1 << 33) - 1
    part = F.shiftright("_at", 33).cast("int")
    sizes = {r["p"]: r["n"] for r in rows.groupBy(part.alias("p")).agg(F.count(F.lit(1)).alias("n")).collect()}  # one row per partition
    before, total = [], 0
    for p in range(max(sizes, default=-1) + 1):
        before.append(total)
        total += sizes.get(p, 0)
    start = F.element_at(F.lit(before or [0]), part + 1)
    return rows.withColumn(name, start.cast("long") + F.col("_at").bitwiseAND(F.lit(low))).drop("_at")


def sort_neighbours(df: DataFrame, limit: int | None = None) -> DataFrame:
    """Settle loop over neighbouring slots, alternating parity, so that no slot is written twice in a sweep.

    At most n sweeps; a demonstration for small inputs. df: slot (dense from 0), value.
    """
    states, n = States(4), df.count()
    state, still = states.next(df.select("slot", "value")), 0
    for sweep in range(limit or n + 2):
        pair = F.floor((F.col("slot") + sweep % 2) / 2)
        both = Window.partitionBy("pair")
        ranked = state.withColumn("pair", pair).withColumns({"low": F.min("value").over(both), "high": F.max("value").over(both), "first": F.min("slot").over(both), "n": F.count(F.lit(1)).over(both)})
        new = ranked.select("slot", F.when(F.col("n") == 1, F.col("value")).when(F.col("slot") == F.col("first"), F.col("low")).otherwise(F.col("high")).alias("value"), (F.col("value") != F.when(F.col("slot") == F.col("first"), F.col("low")).otherwise(F.col("high"))).alias("_swap"))
        new = states.next(new)
        still = 0 if new.filter("_swap").head(1) else still + 1
        state = new.drop("_swap")
        if still == 2:  # both parities at rest
            break
    states.close()
    return state


def sort_all_pairs(df: DataFrame, limit: int = 10_000, broadcast_rows: int = 1_000_000) -> DataFrame:
    """Settle loop over all pairs of slots with exclusive bodies: a batch runs only swaps that share no slot.

    Each enabled pair draws a priority and runs if it is the least at both of its slots, so
    some pair always runs. Every sweep looks at n^2 pairs, so this is for tiny inputs: more
    than ``broadcast_rows`` slots are refused. The state is cut in every sweep, because a
    sweep reads it three times and its plan would otherwise triple.
    """
    if df.count() > broadcast_rows:
        raise ValueError("all pairs of so many slots; use sort_builtin")
    states = States(1)
    state = states.next(df.select("slot", "value"))
    for sweep in range(limit):
        a, b = state.toDF("i", "vi"), state.toDF("j", "vj")
        pairs = a.join(F.broadcast(b), F.expr("i < j and vi > vj")).withColumn("p", F.struct(F.xxhash64("i", "j", F.lit(sweep)).alias("h"), "i", "j"))
        ends = pairs.select("p", "vi", "vj", F.explode(F.array("i", "j")).alias("slot"))
        least = ends.withColumn("best", F.min("p").over(Window.partitionBy("slot"))).filter("p = best")
        run = least.withColumn("wins", F.count(F.lit(1)).over(Window.partitionBy("p"))).filter("wins = 2")
        write = run.select("slot", F.when(F.col("slot") == F.col("p.i"), F.col("vj")).otherwise(F.col("vi")).alias("put"))
        new = states.next(state.join(write, "slot", "left").select("slot", F.coalesce("put", "value").alias("value"), F.col("put").isNotNull().alias("_w")))
        quiet = not new.filter("_w").head(1)
        state = new.drop("_w")
        if quiet:
            break
    states.close()
    return state


# ---- sparse products; matrices are i, j, val


def matmul(a: DataFrame, b: DataFrame) -> DataFrame:
    """Once-loop over the non-zero (i, k, j): one join on k, one sum on (i, j)."""
    right = b.select(F.col("i").alias("k"), F.col("j"), F.col("val").alias("w"))
    return a.select("i", F.col("j").alias("k"), "val").join(right, "k").groupBy("i", "j").agg(F.sum(F.col("val") * F.col("w")).alias("val"))


def to_row_lists(a: DataFrame, chunk: int = 10_000) -> DataFrame:
    """i, part, cols, vals: compressed rows; a long row is cut into parts by column."""
    return a.groupBy("i", F.floor(F.col("j") / chunk).alias("part")).agg(F.sort_array(F.collect_list(F.struct("j", "val"))).alias("e")).select("i", "part", F.col("e.j").alias("cols"), F.col("e.val").alias("vals"))


def to_padded(a: DataFrame) -> DataFrame:
    """i, kk, j, val: position in the row; rows shorter than the longest are padded when read as a block."""
    return a.select("i", (F.row_number().over(Window.partitionBy("i").orderBy("j")) - 1).alias("kk"), "j", "val")


def to_jagged(a: DataFrame) -> DataFrame:
    """length, i, kk, j, val: diagonals kk over rows that have one, longest rows first."""
    sizes = a.groupBy("i").agg(F.count(F.lit(1)).alias("length"))
    return to_padded(a).join(sizes, "i").select("length", "i", "kk", "j", "val")


def pack_rows(a: DataFrame, layout: str, columns: np.ndarray, size: int = 1 << 18, parts: int | None = None) -> DataFrame:
    """Blocks of about ``size`` non-zeros in a layout: rows, lengths, cols, vals as binary arrays; a row may span blocks.

    row_lists: row after row. padded: one array for each position in the row, as long as
    the block has rows, short rows filled up with zeros. jagged: the same over rows sorted
    by falling length, only as long as there are rows with that position. ``columns`` are
    the sorted keys of the other matrix; columns that it lacks are zero and fall away.
    """
    keys = a.sparkSession.sparkContext.broadcast(columns)

    def close(i: np.ndarray, j: np.ndarray, val: np.ndarray) -> pa.RecordBatch:
        rows, first, lengths = np.unique(i, return_index=True, return_counts=True)
        if layout != "row_lists":
            order = np.argsort(-lengths, kind="stable") if layout == "jagged" else np.arange(len(rows))
            rows, first, lengths = rows[order], first[order], lengths[order]
            cols, vals = [], []
            for kk in range(int(lengths.max())):  # the loop over positions is outside, rows are inside
                if layout == "jagged":
                    at = first[: int((lengths > kk).sum())] + kk
                    cols.append(j[at])
                    vals.append(val[at])
                else:
                    has = lengths > kk
                    at = np.minimum(first + kk, len(j) - 1)
                    cols.append(np.where(has, j[at], 0))
                    vals.append(np.where(has, val[at], 0))
            j, val = np.concatenate(cols), np.concatenate(vals)
        return pa.RecordBatch.from_pydict({c: pa.array([x.tobytes()], pa.binary()) for c, x in (("rows", rows), ("lengths", lengths.astype(np.int64)), ("cols", j.astype(np.int32)), ("vals", val.astype(np.float64)))})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for b in batches:
            i, j, val = (b.column(c).to_numpy(zero_copy_only=False) for c in range(3))
            at = np.minimum(np.searchsorted(keys.value, j), max(0, len(keys.value) - 1))
            there = keys.value[at] == j if len(keys.value) else np.zeros(len(j), bool)
            held.append((i[there].astype(np.int64), at[there], val[there]))
            n += int(there.sum())
            if n >= size:
                yield close(*(np.concatenate(x) for x in zip(*held)))
                held, n = [], 0
        if n:
            yield close(*(np.concatenate(x) for x in zip(*held)))

    dealt = a.select("i", "j", "val")
    dealt = (dealt.repartitionByRange(parts, "i", "j") if parts else dealt.repartitionByRange("i", "j")).sortWithinPartitions("i", "j")
    return dealt.mapInArrow(run, "rows binary, lengths binary, cols binary, vals binary")


def _times(rows: np.ndarray, lengths: np.ndarray, cols: np.ndarray, vals: np.ndarray, dense: np.ndarray, layout: str) -> np.ndarray:
    """The block's part of the product, in the order of the layout."""
    if layout == "row_lists":
        return np.add.reduceat(vals[:, None] * dense[cols], np.cumsum(lengths) - lengths, axis=0)
    out, at = np.zeros((len(rows), dense.shape[1])), 0
    for kk in range(int(lengths.max())):
        n = int((lengths > kk).sum()) if layout == "jagged" else len(rows)
        out[:n] += vals[at : at + n, None] * dense[cols[at : at + n]]
        at += n
    return out


def spmm(a: DataFrame, b: DataFrame, layout: str, bound: int = 256 << 20) -> DataFrame:
    """i, c0..: a(i, j, val) times a dense multi-vector b(j, c0..), with a in a layout: coo, row_lists, padded or jagged.

    The dense side is replicated if it takes at most ``bound`` bytes; beyond that, and for coo, it is joined by key.
    """
    cs = [c for c in b.columns if c != "j"]
    if layout == "coo" or b.count() * 8 * (len(cs) + 1) > bound:
        return a.join(b, "j").groupBy("i").agg(*(F.sum(F.col("val") * F.col(c)).alias(c) for c in cs))
    got = b.select("j", *(F.col(c).cast("double") for c in cs)).orderBy("j").toArrow()
    dense = a.sparkSession.sparkContext.broadcast(np.stack([got.column(c).to_numpy() for c in cs], axis=1) if got.num_rows else np.zeros((0, len(cs))))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = (np.int64, np.int64, np.int32, np.float64)
        for batch in batches:
            for k in range(batch.num_rows):
                rows, lengths, cols, vals = (np.frombuffer(batch.column(c)[k].as_buffer(), t) for c, t in enumerate(kinds))
                out = _times(rows, lengths, cols, vals, dense.value, layout)
                yield pa.RecordBatch.from_arrays([pa.array(rows), *(pa.array(out[:, c]) for c in range(len(cs)))], ["i", *cs])

    parts = pack_rows(a, layout, got.column("j").to_numpy()).mapInArrow(run, "i long, " + ", ".join(f"{c} double" for c in cs))
    return parts.groupBy("i").agg(*(F.sum(c).alias(c) for c in cs))  # rows that span blocks


# ---- shards


def shard_of(key: Column, parts: int, how: str = "value", low: float = 0, high: float = 1) -> Column:
    """value: by hash; range: equal intervals of [low, high], the last one closed."""
    if how == "range":
        width = (high - low) / parts or 1
        return F.least(F.lit(parts - 1), F.greatest(F.lit(0), F.floor((key - low) / width))).cast("int")
    return F.pmod(F.xxhash64(key), F.lit(parts)).cast("int")


def covers(key: Column, parts: int, low: float, high: float, margin: float) -> Column:
    """Shards of an overlapping cover by range: a tuple near a bound is in both shards, so only combines that may repeat are legal."""
    a, b = shard_of(key - margin, parts, "range", low, high), shard_of(key + margin, parts, "range", low, high)
    return F.sequence(a, b)


def once_covered(reservoir: DataFrame, shards: Column, address: list[str], delta: Column, combine: str = "min") -> DataFrame:
    """``once`` over shards that overlap: each shard combines what it holds, then shards are combined."""
    if combine not in ("min", "max"):
        raise ValueError("a tuple in two shards would add its update twice")
    how = {"min": F.min, "max": F.max}[combine]
    rows = reservoir.select(*address, delta.alias("delta"), F.explode(shards).alias("_shard"))
    return rows.groupBy("_shard", *address).agg(how("delta").alias("value")).groupBy(*address).agg(how("value").alias("value"))


def shared_addresses(edges: DataFrame, shard: Column, address: str = "v") -> DataFrame:
    """address, shards: those that more than one shard touches, which must be exchanged."""
    return edges.select(F.col(address).alias("address"), shard.alias("s")).groupBy("address").agg(F.countDistinct("s").alias("shards")).filter("shards > 1")


# ---- once-loop and measures


def once(reservoir: DataFrame, address: list[str], delta: Column, combine: str = "sum") -> DataFrame:
    """Every tuple's body once, in any order: deltas combined for each address."""
    how = {"sum": F.sum, "min": F.min, "max": F.max}[combine]
    return reservoir.select(*address, delta.alias("delta")).groupBy(*address).agg(how("delta").alias("value"))


def settle(state: DataFrame, step, enabled: Column, max_sweeps: int = 1000, every: int = 5) -> tuple[DataFrame, int]:
    """Repeats ``step`` until a whole scan finds no enabled tuple; the state and the sweeps."""
    states = States(every)
    state = states.next(state)
    for sweep in range(max_sweeps):
        if not state.filter(enabled).head(1):
            return state, sweep
        state = states.next(step(state))
    return state, max_sweeps
