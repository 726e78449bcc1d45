"""Best-fit packing of texts into sequences of fixed length, under conflicts.

A text of more than ``capacity`` words is cut into pieces of that size and a rest.
Two pieces conflict if they have the same source or come from copies of one text
(equal after runs of blanks became one space). Bins are ordered by what is left in
them and carry a bitmap of their sources and one of their duplicate clusters. A
piece goes to the tightest bin that has room and no conflict: the search starts at
the smallest residual that is large enough and moves to the next larger one until a
compatible bin is found; only if there is none does a new bin open. Pieces come in
order of falling size.

Pieces are dealt out to shards by a hash of the row and of its number among equal rows,
each of about ``shard`` texts, and packed there, so a hot source or row is spread evenly. Only ids, sources, sizes
and cluster hashes are shuffled, never texts.

Defined results: an empty or null text is one piece that takes one place; a null
source conflicts with nothing; rows that repeat are packed each, never into one bin
(they are copies); an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401  (rank)
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import blocks_for, text_or_empty
from .exact_dedup import normalised


class Bins:
    """Open bins by residual; ``place`` puts one piece into the tightest compatible one."""

    def __init__(self, capacity: int) -> None:
        self.capacity = capacity
        self.present = 0  # bit r: some bin has residual r
        self.levels: dict[int, dict[int, list[int]]] = defaultdict(lambda: defaultdict(list))
        self.total: Counter[int] = Counter()
        self.with_source: Counter[tuple[int, int]] = Counter()  # (residual, source bit)
        self.sources: list[int] = []
        self.clusters: list[int] = []
        self.members: list[list[int]] = []  # bits of the sources in a bin
        self.filled: list[int] = []

    def _find(self, size: int, source: int, cluster: int) -> tuple[int, int] | None:
        r, open_levels = size, self.present >> size
        while open_levels:
            skip = (open_levels & -open_levels).bit_length() - 1
            r, open_levels = r + skip, open_levels >> skip
            if self.with_source[r, source] < self.total[r]:
                for bitmap, bins in self.levels[r].items():
                    if bitmap & source:
                        continue
                    for at in range(len(bins) - 1, -1, -1):
                        if not self.clusters[bins[at]] & cluster:
                            return r, bins.pop(at)
            r, open_levels = r + 1, open_levels >> 1
        return None

    def _list(self, bin_: int, r: int, sign: int) -> None:
        self.total[r] += sign
        for s in self.members[bin_]:
            self.with_source[r, s] += sign

    def place(self, size: int, source: int, cluster: int) -> tuple[int, int]:
        """(bin, place in it). source, cluster: one bit each, or 0 for no conflict."""
        found = self._find(size, source, cluster)
        if found is None:
            r, bin_ = self.capacity, len(self.sources)
            self.sources.append(0)
            self.clusters.append(0)
            self.members.append([])
            self.filled.append(0)
        else:
            r, bin_ = found
            self._list(bin_, r, -1)
            same = self.levels[r]
            if not same[self.sources[bin_]]:
                del same[self.sources[bin_]]
            if not self.total[r]:
                self.present &= ~(1 << r)
        self.sources[bin_] |= source
        self.clusters[bin_] |= cluster
        if source:
            self.members[bin_].append(source)
        left = r - size
        self.levels[left][self.sources[bin_]].append(bin_)
        self._list(bin_, left, 1)
        self.present |= 1 << left
        self.filled[bin_] += 1
        return bin_, self.filled[bin_] - 1


def pack_shard(size: list[int], source: list, cluster: list[int], capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """Bins and places of pieces, in the order given."""
    bit_of_source: dict = {}
    more = {c for c, n in Counter(cluster).items() if n > 1}
    bit_of_cluster: dict[int, int] = {}
    bins = Bins(capacity)
    out = np.zeros((2, len(size)), np.int64)
    for i, (n, s, c) in enumerate(zip(size, source, cluster)):
        sb = 0 if s is None else bit_of_source.setdefault(s, 1 << len(bit_of_source))
        cb = bit_of_cluster.setdefault(c, 1 << len(bit_of_cluster)) if c in more else 0
        out[:, i] = bins.place(n, sb, cb)
    return out[0], out[1]


def words_in(text: Column) -> Column:
    return F.regexp_count(text, F.lit(r"[^ \x09-\x0D]+"))


def pack(docs: DataFrame, row_id: str = "doc_id", text: str = "text", source: str = "source", size: Column | None = None, capacity: int = 2048, shard: int = 25_000) -> DataFrame:
    """One row per piece: doc_id, piece, start, size (both in words), bin_id, slot (place in the bin).

    ``size`` may be another measure of a text's length, such as its number of tokens.
    """
    kind = docs.schema[row_id].dataType.simpleString()
    shards = blocks_for(docs.count(), shard)
    t = text_or_empty(text)
    rows = docs.select(F.col(row_id).alias("doc_id"), F.col(source).cast("string").alias("source"), F.xxhash64(normalised(text)).alias("cluster"), F.greatest(F.lit(1), size if size is not None else words_in(t)).cast("long").alias("n"))
    # rows that repeat are counted where they are, then told apart by a number, so that they spread over all shards
    same = ["doc_id", "source", "cluster", "n"]
    heaps = rows.groupBy(*same, F.spark_partition_id().alias("p")).agg(F.count(F.lit(1)).alias("copies"))
    before = F.sum("copies").over(Window.partitionBy(*same).orderBy("p").rowsBetween(Window.unboundedPreceding, -1))  # a row per task at most
    heaps = heaps.withColumn("first", F.coalesce(before, F.lit(0)))
    rows = heaps.select(*same, F.explode(F.sequence(F.col("first"), F.col("first") + F.col("copies") - 1)).alias("copy"))
    rows = rows.withColumn("shard", F.pmod(F.xxhash64(*same, "copy"), F.lit(shards))).drop("copy")

    def run(key: tuple, table: pa.Table) -> pa.Table:
        n = table.column("n").to_numpy()
        pieces = -(-n // capacity)
        row = np.repeat(np.arange(len(n)), pieces)
        piece = np.arange(len(row)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
        sizes = np.minimum(capacity, n[row] - piece * capacity)
        cluster = table.column("cluster").to_numpy()
        # ties by content, so that the result does not depend on the order of arrival
        ids = pa.compute.rank(table.column("doc_id"), tiebreaker="dense", null_placement="at_end").to_numpy()
        order = np.lexsort((piece, cluster[row], ids[row], -sizes))
        row, piece, sizes = row[order], piece[order], sizes[order]
        sources = table.column("source").to_pylist()
        bins, slots = pack_shard(sizes.tolist(), [sources[i] for i in row], cluster[row].tolist(), capacity)
        return pa.Table.from_arrays(
            [table.column("doc_id").take(pa.array(row)), pa.array(piece, pa.int32()), pa.array(piece * capacity, pa.int64()), pa.array(sizes, pa.int64()), pa.array((int(key[0].as_py()) << 32) + bins, pa.int64()), pa.array(slots, pa.int32())],
            ["doc_id", "piece", "start", "size", "bin_id", "slot"],
        )

    return rows.groupBy("shard").applyInArrow(run, f"doc_id {kind}, piece int, start long, size long, bin_id long, slot int")


def fill(packed: DataFrame, capacity: int = 2048) -> DataFrame:
    """One row: bins, pieces, and the share of all places that is filled."""
    bins = packed.groupBy("bin_id").agg(F.sum("size").alias("used"), F.count(F.lit(1)).alias("pieces"))
    return bins.agg(F.count(F.lit(1)).alias("bins"), F.coalesce(F.sum("pieces"), F.lit(0)).alias("pieces"), (F.sum("used") / (F.count(F.lit(1)) * capacity)).alias("filled"))
