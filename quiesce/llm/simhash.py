"""Near duplicates by SimHash fingerprints, pivot distance tables and components.

1. *Fingerprints.* Word shingles of the whole text, hashed by XXH64; a bit is set
   where more than half of the hashes set it.
2. *Classes.* Equal fingerprints are one class from here on, named by its least
   id, so copies never meet in pairs.
3. *Cover.* The fingerprint is cut into ``parts`` ranges of bits. Two fingerprints
   with at most ``radius`` differing bits agree on at least ``parts - radius`` of
   them, so dealing classes out by every choice of that many parts brings each
   linked pair together somewhere: no link is lost. ``parts`` grows with the
   number of classes, so that groups stay small at every size.
4. *Pivot tables.* Each task holds the Hamming distances from its fingerprints to
   many reference fingerprints. By the triangle inequality two fingerprints within
   ``radius`` differ by at most ``radius`` in every coordinate. In a group of more
   than 64 rows these are sorted by the coordinate that spreads most, so only a window
   of partners is looked at; the other coordinates discard pairs; survivors are
   verified exactly.
5. *Components.* A task reports a spanning forest of the links in each chunk of its groups,
   rooted at least ids, never all pairs. Blocks of links shrink to forests in the same
   way; stars are then contracted until no label changes.

Groups over ``hot`` rows are cut by position along the spread coordinate into
tiles that overlap by the window, so that no task gets an unbounded group.

Wider fingerprints (``words`` of 64 bits) and radii that a cover cannot serve are dealt
out by keys of randomly drawn bits instead, so many that a pair at the full radius is
missed with a probability of at most ``miss``; nearer pairs are missed far less often.

Defined results: a null text is empty; texts without words have fingerprint zero and
link like any other; fewer words than a shingle make one shingle; an empty table gives
an empty result; ids are whole numbers; rows that repeat an id are listed each and link as one; rows
with a null id get the component of the others of their class, and where a class has
no id, it has no links and a null component; extra columns are ignored, whatever their
names.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import blocks_for, cut

_CHUNK = 1 << 16


def fingerprint(text: str | None, width: int = 4, seed: int = 42, words: int = 1) -> np.ndarray:
    """``words`` times 64 bits. The first word takes the hashes as they are, further ones take them mixed again."""
    parts = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not parts:
        return np.zeros(words, np.uint64)
    joined = b" ".join(parts)
    n = len(parts)
    ends = np.cumsum(np.fromiter(map(len, parts), np.int64, n) + 1) - 1
    starts = [0, *(ends[:-1] + 1).tolist()]
    stops = ends[width - 1 :].tolist() or [len(joined)]
    digest = xxhash.xxh64_intdigest
    m = len(stops)
    hashes = np.fromiter((digest(joined[a:b], seed) for a, b in zip(starts, stops)), np.uint64, m)
    ones = np.zeros((words, 64), np.int64)
    for at in range(0, m, _CHUNK):
        x = hashes[at : at + _CHUNK]
        for k in range(words):
            if k:
                x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9) + np.uint64(k)
                x = x ^ (x >> np.uint64(27))
            ones[k] += np.unpackbits(x.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int32)
    return np.packbits(ones * 2 > m, axis=1, bitorder="little").view(np.uint64).ravel()


def _signed(x: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(x).view(np.int64)


def fingerprints(docs: DataFrame, row_id: str = "doc_id", text: str = "text", width: int = 4, seed: int = 42, words: int = 1) -> DataFrame:
    """doc_id and f0..: the bits as signed integers."""
    kind = docs.schema[row_id].dataType.simpleString()
    names = [f"f{k}" for k in range(words)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = np.array([fingerprint(t.as_py(), width, seed, words) for t in b.column(1)], np.uint64).reshape(-1, words)
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(_signed(fps[:, k])) for k in range(words))], ["doc_id", *names])

    return docs.select(F.col(row_id).alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, f"doc_id {kind}, " + ", ".join(f"{c} long" for c in names))


def pivots(n: int, words: int = 1, seed: int = 7) -> np.ndarray:
    """Reference fingerprints; the last eight differ from zero in a range of bits each, and tell the weights of ranges apart."""
    out = np.random.default_rng(seed).integers(0, 2**63, (n, words), dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    out[-8:] = 0
    for i in range(8):
        bits = np.zeros(64 * words, np.uint8)
        bits[i * 8 * words : (i + 1) * 8 * words] = 1
        out[n - 8 + i] = np.packbits(bits, bitorder="little").view(np.uint64)
    return out


def _apart(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.bitwise_count(a ^ b).sum(axis=-1, dtype=np.int16)


def pivot_table(fps: np.ndarray, refs: np.ndarray) -> np.ndarray:
    """Hamming distances of each fingerprint to each reference."""
    return np.stack([_apart(fps, r[None]) for r in refs], axis=1)


def _links_of_group(fps: np.ndarray, refs: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """A star forest (member, root), as places, that spans the links among different fingerprints.

    Components grow from one fingerprint at a time, which looks at those that no component
    holds yet: in the window of the coordinate that spreads most, less what other
    coordinates discard, then by distance. Crowded groups are used up in a few looks.
    """
    n, table = len(fps), pivot_table(fps, refs)
    lead = int(np.argmax(table.var(axis=0)))
    order = np.argsort(table[:, lead], kind="stable")
    f, t, at = fps[order], table[order], table[order, lead]
    free, rest = np.ones(n, bool), np.arange(n)
    member, roots = [], []
    for start in range(n):
        if not free[start]:
            continue
        free[start] = False
        frontier = [start]
        while frontier:
            x = frontier.pop()
            low, high = np.searchsorted(at[rest], (at[x] - radius, at[x] + radius + 1))
            near = rest[low:high]
            for k in range(t.shape[1]):
                if len(near) < 64:
                    break
                if k != lead:
                    near = near[np.abs(t[near, k] - t[x, k]) <= radius]
            near = near[free[near] & (_apart(f[near], f[x]) <= radius)]
            if len(near):
                free[near] = False
                rest = rest[free[rest]]
                member.append(near)
                roots.append(np.full(len(near), start))
                frontier += near.tolist()
    if not member:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return order[np.concatenate(member)], order[np.concatenate(roots)]


def _forest(a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
    """The links among ids a and b as stars (id, least id of its component), a row for each id but the least ones."""
    ids, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    root = np.arange(len(ids))
    while not np.array_equal(root[x], root[y]):
        low = np.minimum(root[x], root[y])
        np.minimum.at(root, root[x], low)
        np.minimum.at(root, root[y], low)
        while not np.array_equal(root, up := root[root]):
            root = up
    far = np.flatnonzero(root != np.arange(len(ids)))
    return pa.RecordBatch.from_arrays([pa.array(ids[far]), pa.array(ids[root[far]])], ["a", "b"])


def _shrink(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Forests of blocks of links (a, b)."""
    held, n = [], 0
    for batch in batches:
        held.append((batch.column(0).to_numpy(), batch.column(1).to_numpy()))
        n += batch.num_rows
        if n >= _CHUNK:
            yield _forest(*(np.concatenate(x) for x in zip(*held)))
            held, n = [], 0
    if n:
        yield _forest(*(np.concatenate(x) for x in zip(*held)))


def _groups(keys: np.ndarray, ids: np.ndarray, fps: np.ndarray, refs: np.ndarray, radius: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """Links, as ids, among whole groups of a chunk that is sorted by key."""
    cuts = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1], [True])))
    sizes = np.diff(cuts)
    out = []
    small = np.repeat((sizes > 1) & (sizes <= 64), sizes)
    k, f, d = keys[small], fps[small], ids[small]
    if len(f):
        table = pivot_table(f, refs)
        step = 1
        while True:  # partners at distance 1, 2, ... within the group
            same = k[step:] == k[:-step] if step < len(k) else np.zeros(0, bool)
            i = np.flatnonzero(same)
            if not len(i):
                break
            for c in range(table.shape[1]):
                i = i[np.abs(table[i, c] - table[i + step, c]) <= radius]
            i = i[_apart(f[i], f[i + step]) <= radius]
            if len(i):
                out.append((d[i + step], d[i]))
            step += 1
    for g in np.flatnonzero(sizes > 64):
        part, who = fps[cuts[g] : cuts[g + 1]], ids[cuts[g] : cuts[g + 1]]
        who, first = np.unique(who, return_index=True)
        if len(who) > 1:
            a, b = _links_of_group(part[first], refs, radius)
            out.append((who[a], who[b]))
    return out


def _linker(radius: int, n_pivots: int, words: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        refs = pivots(n_pivots, words)
        keys, ids = np.zeros(0, np.int64), np.zeros(0, np.int64)
        fps = np.zeros((0, words), np.uint64)

        def out(found: list) -> Iterator[pa.RecordBatch]:
            if found:
                yield _forest(*(np.concatenate(x) for x in zip(*found)))

        for b in batches:
            keys, ids = (np.concatenate([x, b.column(c).to_numpy()]) for c, x in ((0, keys), (1, ids)))
            fps = np.concatenate([fps, np.stack([b.column(2 + k).to_numpy().view(np.uint64) for k in range(words)], axis=1)])
            if len(keys) >= _CHUNK and keys[0] != keys[-1]:
                whole = int(np.flatnonzero(keys != keys[-1])[-1]) + 1
                yield from out(_groups(keys[:whole], ids[:whole], fps[:whole], refs, radius))
                keys, ids, fps = keys[whole:], ids[whole:], fps[whole:]
        if len(keys):
            yield from out(_groups(keys, ids, fps, refs, radius))

    return run


def cover_parts(n: int, radius: int) -> int:
    """Parts of the 64 bits so that a key has about as many bits as the classes need."""
    need = max(16, n.bit_length() + 1)
    for parts in range(radius + 1, 64):
        if 64 * (parts - radius) // parts >= need:
            return parts
    return 63


def cover_keys(fp: Column, parts: int, radius: int) -> Column:
    """One key for each choice of parts that may agree: the bits there, and the choice's number in a hash."""
    edges = [round(64 * i / parts) for i in range(parts + 1)]
    masks = [((1 << (b - a)) - 1) << a for a, b in zip(edges, edges[1:])]
    keys = []
    for c, chosen in enumerate(combinations(masks, parts - radius)):
        mask = sum(chosen)
        keys.append(F.xxhash64(fp.bitwiseAND(F.lit(mask - (1 << 64) if mask >= 1 << 63 else mask)), F.lit(c)))
    return F.array(*keys)


def drawn_keys(fps: list[Column], n: int, radius: int, miss: float, seed: int = 3) -> Column:
    """Keys of bits drawn at random, as many as bring a pair at the full radius together but for a share ``miss``.

    The number of bits grows with the logarithm of the classes, so that groups stay small.
    """
    total = 64 * len(fps)
    bits = max(16, n.bit_length() - 2)
    agree = math.prod((total - radius - i) / (total - i) for i in range(bits))
    rng = np.random.default_rng(seed)
    keys = []
    for c in range(math.ceil(math.log(miss) / math.log(1 - agree))):
        masks = [0] * len(fps)
        for bit in rng.choice(total, bits, replace=False).tolist():
            masks[bit // 64] |= 1 << bit % 64
        keys.append(F.xxhash64(*(f.bitwiseAND(F.lit(m - (1 << 64) if m >= 1 << 63 else m)) for f, m in zip(fps, masks) if m), F.lit(c)))
    return F.array(*keys)


def links(classes: DataFrame, radius: int = 4, n_pivots: int = 24, hot: int = 100_000, miss: float = 0.01) -> DataFrame:
    """Star links (a, b) of ids between the different fingerprints of ``classes(id, f0..)``."""
    spark = classes.sparkSession
    names = [c for c in classes.columns if c != "id"]
    fps = [F.col(c) for c in names]
    n_classes = classes.count()
    # a cover loses no link, but needs a part more than bits may differ
    keys = cover_keys(fps[0], cover_parts(n_classes, radius), radius) if len(fps) == 1 and radius <= 6 else drawn_keys(fps, n_classes, radius, miss)
    dealt = classes.select("id", *names, F.explode(keys).alias("key"))
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    linker = _linker(radius, n_pivots, len(names))
    crowded = dealt.groupBy("key").agg(F.count(F.lit(1)).alias("size")).filter(F.col("size") > hot)
    crowded = cut(crowded)  # at most classes * choices / hot rows
    if crowded.isEmpty():
        usual, tiles = dealt, None
    else:
        marked = dealt.join(crowded, "key", "left")
        usual = marked.filter(F.col("size").isNull()).select("id", *names, "key")
        tiles = _tiles(marked.filter(F.col("size").isNotNull()), names, radius)
    out = usual.select("key", "id", *names).repartition(n, "key").sortWithinPartitions("key").mapInArrow(linker, "a long, b long")
    if tiles is not None:
        out = out.unionByName(tiles.repartition(n, "key").sortWithinPartitions("key").mapInArrow(linker, "a long, b long"))
    return out


def _tiles(rows: DataFrame, names: list[str], radius: int) -> DataFrame:
    """Cuts crowded groups by pivot coordinates into cells that overlap by the radius.

    In a coordinate two linked rows differ by at most the radius, so with cells of
    width radius + 1 a row joins its own cell and, as a guest, the next one below.
    Rows that lie together in every coordinate are near copies of each other and stay in
    one tile; there nearly all pairs are links, and a forest over them is quickly whole.
    """
    width = radius + 1
    out = rows
    for i, p in enumerate((0x00000000FFFFFFFF, 0x0000FFFF0000FFFF, 0x00FF00FF00FF00FF)):
        cell = F.floor(sum((F.bit_count(F.col(c).bitwiseXOR(F.lit(p))) for c in names), F.lit(0)) / width)
        out = out.withColumn(f"c{i}", F.explode(F.array(cell, cell - 1)))
    return out.select(F.xxhash64("key", "c0", "c1", "c2").alias("key"), "id", *names)


def components(edges: DataFrame, most: int = 60) -> DataFrame:
    """node, root (least node of its component) for the nodes of ``edges(a, b)``, by star contraction."""
    now = cut(edges.select(F.greatest("a", "b").cast("long").alias("a"), F.least("a", "b").cast("long").alias("b")).filter("a <> b").distinct())
    # links that repeat each other go where blocks of them are read, before any join
    now = cut(now.coalesce(blocks_for(now.count(), _CHUNK)).mapInArrow(_shrink, "a long, b long"))
    before = None
    for _ in range(most):
        # every node points its larger neighbours, then its smaller ones, to its least neighbour
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.filter("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        large = large.filter("a <> b").distinct()
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(low.select("a", F.col("m").alias("b")))
        now = cut(small.filter("a <> b").distinct())
        state = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if state == before:
            break
        before = state
    else:
        raise RuntimeError("components did not settle")
    return now.select(F.col("a").alias("node"), F.col("b").alias("root"))


def near_duplicates(docs: DataFrame, row_id: str = "doc_id", text: str = "text", width: int = 4, radius: int = 4, words: int = 1, n_pivots: int = 24, hot: int = 100_000, miss: float = 0.01) -> DataFrame:
    """Per row: doc_id, fingerprint (16 hexadecimal digits for each word), component_id (least id that links reach)."""
    names = [f"f{k}" for k in range(words)]
    prints = cut(fingerprints(docs, row_id, text, width, words=words))
    # a class is known by its least id, so the least id of a component is a node of it
    classes = cut(prints.groupBy(*names).agg(F.min("doc_id").alias("id")))
    stars = components(links(classes.filter("id is not null").select(F.col("id").cast("long").alias("id"), *names), radius, n_pivots, hot, miss))
    linked = classes.join(stars, F.col("id") == F.col("node"), "left").select(*names, F.coalesce("root", "id").cast(docs.schema[row_id].dataType).alias("component_id"))
    hexed = F.concat(*(F.lower(F.lpad(F.hex(c), 16, "0")) for c in reversed(names)))
    return prints.join(linked, names).select("doc_id", hexed.alias("fingerprint"), "component_id")
