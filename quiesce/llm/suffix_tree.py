"""Language-model scores by a probabilistic suffix tree over words.

*Symbols* are the contract's tokens: words in ASCII lower case, and the end of a text.
They are known by the XXH64 of the word and a space (of V different words about V * V / 2**65 pairs collide).

*Tree.* The root is the base: (c + 1) / (N + V + 1). A context of d words is looked at
if its suffix of d - 1 words is in the tree and it occurs at least ``least`` times in
training texts; it enters the tree by a divergence test: the sum over its transitions,
those seen twice or more, of  n log(n / c / P(next | suffix))  has to exceed ``test``
for each of them. So the tree is closed under suffixes, grows with the corpus, and no
context, count or distribution is cut off by size. Transitions are smoothed by absolute
discounting: what is discounted or seen once goes to the suffix's distribution, so each
context's probabilities sum to those of its suffix. A token's probability is that of the
longest context in the tree before it, inside its text.

*How.* Texts become blocks of token numbers, kept by block for all rounds. A round asks
for sums over the corpus: each block sends the different keys that it needs, in buckets
of sorted, delta-coded arrays; a bucket adds up what all blocks say about a key and
answers each block in the order of its question. Level by level, one round counts the
strings that end in a context of the tree, another adds up the terms of the test (each
string by one block that holds it). No model is broadcast or collected. A key costs a
block at most one entry, however often it occurs, so a hot word is no hot key.

Defined results: null text is empty and consists of the end alone; without any training
text all words are unknown and equally likely; rows that repeat an id are scored each,
as are rows of null id (held out by the rule for empty text); ties cannot arise; extra
columns are ignored, whatever their names; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import blocks_for, crc_mod, release, stash

END = b"\n"  # occurs in no word
#: Different keys that a bucket holds, about.
BUCKET = 1 << 20
DISCOUNT = 0.75
_BLOCK = "block long, ids array<{kind}>, held array<boolean>, sizes array<int>, words binary, places binary"


def tokens(text: str | None) -> list[bytes]:
    """The meaning of a text; blocks find the same by arrays (``numbered_tokens``)."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    words.append(END)
    return words


#: Lower case of A-Z, and a space for each blank, so that END stays free to end texts.
_PLAIN = bytes(32 if i == 32 or 9 <= i <= 13 else i + 32 if 65 <= i <= 90 else i for i in range(256))


def numbered_tokens(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Different tokens in order of appearance, words with a space behind them; the number of each token of all texts; tokens for each text."""
    data = np.frombuffer(b"".join(x for t in texts for x in (t.translate(_PLAIN), b" ", END)), np.uint8)
    idle = data == 32
    ends = idle | (data == END[0])  # of tokens: the blank after a word, or an END
    idle[1:] &= ends[:-1]  # only a blank after a blank or at the start of a text, the first one's too
    data, ends = data[~idle], ends[~idle]
    last = np.flatnonzero(ends)
    offsets = np.concatenate(([0], last + 1))
    encoded = pa.Array.from_buffers(pa.large_binary(), len(last), [None, pa.py_buffer(offsets), pa.py_buffer(data)]).dictionary_encode()
    sizes = np.diff(np.flatnonzero(data[last] == END[0]), prepend=-1)
    return encoded.dictionary.to_numpy(zero_copy_only=False), encoded.indices.to_numpy(), sizes


# ---- arrays as bytes

#: One for each process, whose tasks run in one thread.
_COMPRESSOR, _DECOMPRESSOR = zstandard.ZstdCompressor(level=1), zstandard.ZstdDecompressor()


def packed(a: np.ndarray) -> bytes:
    """Bytes of equal weight side by side, which is what makes counts and differences compressible."""
    planes = np.ascontiguousarray(a).view(np.uint8).reshape(len(a), a.dtype.itemsize).T
    return _COMPRESSOR.compress(planes.tobytes())


def unpacked(data: bytes, kind: type) -> np.ndarray:
    planes = np.frombuffer(_DECOMPRESSOR.decompress(data), np.uint8)
    size = np.dtype(kind).itemsize
    return np.ascontiguousarray(planes.reshape(size, len(planes) // size).T).view(kind).ravel()


def packed_keys(sorted_keys: np.ndarray) -> bytes:
    return packed(np.diff(sorted_keys, prepend=np.uint64(0)))


def unpacked_keys(data: bytes) -> np.ndarray:
    return np.cumsum(unpacked(data, np.uint64), dtype=np.uint64)


def extended(contexts: np.ndarray, of: np.ndarray, words: np.ndarray, last: np.ndarray) -> np.ndarray:
    """Keys of strings from the different keys of contexts and words, and the places among them of each string's context and last word."""
    x = (contexts * np.uint64(0x9E3779B97F4A7C15))[of]
    x += (words ^ (words >> np.uint64(29)))[last]
    x ^= x >> np.uint64(32)
    x *= np.uint64(0xD6E8FEB86659FD93)
    x ^= x >> np.uint64(32)
    return x


def distinct(a: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The different values in order, where any one of each is, and each value's place among them.

    Sorts the upper bits with places in the lower ones, which is faster than sorting places;
    where values differ in the lower bits only, this may leave them out of order, and then places are sorted.
    """
    low = np.uint64((1 << max(len(a) - 1, 0).bit_length()) - 1)
    order = a & ~low
    order |= np.arange(len(a), dtype=np.uint64)
    order.sort()
    order &= low
    order = order.view(np.int64)
    ordered = a[order]
    if (ordered[1:] < ordered[:-1]).any():
        order = np.argsort(a)
        ordered = a[order]
    new = np.empty(len(a), bool)
    new[:1] = True
    np.not_equal(ordered[1:], ordered[:-1], out=new[1:])
    place = np.empty(len(a), np.int64)
    place[order] = np.cumsum(new) - 1
    return ordered[new], order[new], place


# ---- blocks


def blocks_of(docs: DataFrame, row_id: str, text: str, held_out: tuple[int, int], block_bytes: int) -> DataFrame:
    kind = docs.schema[row_id].dataType.simpleString()
    modulus, remainder = held_out
    rows = docs.select(F.col(row_id).alias("i"), F.col(text).alias("t"), (crc_mod(row_id, modulus) == remainder).alias("h"), F.spark_partition_id().alias("p"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, held, texts, size, n, part, id_type = [], [], [], 0, 0, 0, pa.int64()

        def close() -> pa.RecordBatch:
            words, numbers, sizes = numbered_tokens(texts)
            hashes = np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))
            order = np.argsort(hashes, kind="stable")
            rank = np.empty(len(order), np.int32)
            rank[order] = np.arange(len(order), dtype=np.int32)
            columns = {"block": pa.array([(part << 24) | n], pa.int64()), "ids": pa.array([ids], pa.list_(id_type)), "held": pa.array([held], pa.list_(pa.bool_())), "sizes": pa.array([sizes], pa.list_(pa.int32()))}
            return pa.RecordBatch.from_pydict(columns | {"words": pa.array([packed_keys(hashes[order])], pa.binary()), "places": pa.array([packed(rank[numbers])], pa.binary())})

        for b in batches:
            id_type = b.column(0).type
            part = b.column(3)[0].as_py() if b.num_rows else part
            for i, t, h in zip(b.column(0).to_pylist(), b.column(1).cast(pa.large_binary()), b.column(2).to_pylist()):
                ids.append(i)
                held.append(h)
                texts.append(t.as_py() or b"")
                size += len(texts[-1]) + 2
                if size >= block_bytes:
                    yield close()
                    ids, held, texts, size, n = [], [], [], 0, n + 1
        if ids:
            yield close()
        release()

    return rows.mapInArrow(run, _BLOCK.format(kind=kind))


class Block:
    """Arrays of a block: keys of different words in order, each token's place among them, whether it is learned from."""

    def __init__(self, words: bytes, places: bytes, sizes: np.ndarray, held: np.ndarray) -> None:
        self.words, self.places = unpacked_keys(words), unpacked(places, np.int32).astype(np.int64)
        self.sizes = sizes.astype(np.int64)
        self.starts = np.cumsum(self.sizes) - self.sizes
        self.train = ~np.repeat(held.astype(bool), self.sizes)


def walk(b: Block, answers: dict[int, list[np.ndarray]], total: float, different: float, depth: int, least: int) -> tuple[list[np.ndarray], np.ndarray | None, np.ndarray]:
    """The next question (sorted keys, then columns to sum) as far as answers go, or probabilities; and counts of different words.

    Step 2 d: counts of strings of d + 1 words, and whether this block speaks for a string.
    Step 2 d + 1, d > 0: of contexts of d words the test's sum, its transitions and their counts;
    what comes back are the counts and transitions of contexts that pass.

    Only tokens whose context is looked at are touched. What depends on a string alone is kept
    by string; contexts are strings of the step before, so their places are known without a sort.
    """
    if 0 not in answers:
        return [b.words, np.bincount(b.places[b.train], minlength=len(b.words)).astype(np.int64)], None, np.zeros(0)
    n = known = answers[0][0].astype(float)
    p = ((known + 1) / (total + different + 1))[b.places]
    keys, place = b.words, b.places  # of the strings of d words that end at each token
    inner = np.ones(len(p), bool)
    inner[b.starts] = False
    kept = np.flatnonzero(inner)  # tokens before which the context of d - 1 words is in the tree
    for d in range(1, depth + 1):
        before = place[kept - 1]
        enough = np.append(n >= least, False)[before]  # place -1: no such string
        live, context = kept[enough], before[enough]
        twice = np.append(n >= 2, False)[place[live]]
        at, of = live[twice], context[twice]
        strings, some, to = distinct(extended(keys, of, b.words, b.places[at]))
        if 2 * d not in answers:
            return [strings, np.bincount(to[b.train[at]], minlength=len(strings)).astype(np.int64)], None, known
        count, speaks = answers[2 * d][0].astype(float), answers[2 * d][1].astype(bool)
        count[count < 2] = 0
        asked = np.zeros(len(keys), bool)
        asked[context] = True
        if 2 * d + 1 not in answers:
            mine = np.flatnonzero(speaks & (count > 0))
            said = of[some[mine]]
            term = count[mine] * (np.log(count[mine] / n[said]) - np.log(p[at[some[mine]]]))
            rank = np.cumsum(asked)[said] - 1
            added = [np.bincount(rank, w, int(asked.sum())) for w in (term, np.ones(len(said)), count[mine])]
            return [keys[asked], *(a.astype(t) for a, t in zip(added, ASKED[1]))], None, known
        mass, kinds = (x.astype(float) for x in answers[2 * d + 1])  # zero where the test failed
        good, rest = np.zeros(len(keys), bool), np.zeros(len(keys))
        good[asked] = kinds > 0
        rest[asked] = n[asked] - mass + DISCOUNT * kinds
        passed = good[context]
        kept, context = live[passed], context[passed]
        place = np.full(len(p), -1)
        place[at] = to
        own = np.append(np.maximum(count - DISCOUNT, 0), 0.0)[place[kept]]
        own += rest[context] * p[kept]
        own /= n[context]
        p[kept] = own
        keys, n = strings, count
    return [], p, known


# ---- questions and answers

#: Columns of a question, and of its answer, by the step's last bit.
ASKED = ((np.int64,), (np.float32, np.int64, np.int64))
TOLD = ((np.int64, np.uint8), (np.int64, np.int64))


def questions(block: int, question: list[np.ndarray], buckets: int) -> dict[str, list]:
    """One row for each bucket that keys fall in; a bucket is a range of keys."""
    keys, values = question[0], question[1:]
    width = -(-(1 << 64) // buckets)
    bounds = np.append(np.searchsorted(keys, np.array([i * width for i in range(1, buckets)], np.uint64)), len(keys))
    out: dict[str, list] = {"bucket": [], "block": [], "keys": [], "values": []}
    low = 0
    for i, high in enumerate(bounds.tolist()):
        if high > low:
            out["bucket"].append(i)
            out["block"].append(block)
            out["keys"].append(packed_keys(keys[low:high]))
            out["values"].append([packed(v[low:high]) for v in values])
            low = high
    return out


def sums(keys: list[np.ndarray], values: list[list[np.ndarray]]) -> tuple[list[list[np.ndarray]], int]:
    """For each question the sums over all questions, and who speaks for a key (one that holds it); keys of a positive first sum."""
    flat = np.concatenate(keys)
    _, some, which = distinct(flat)
    speaks = np.zeros(len(flat), bool)
    speaks[some] = True
    added = [np.bincount(which, np.concatenate([v[c] for v in values])) for c in range(len(values[0]))]
    cuts = np.cumsum([len(k) for k in keys])[:-1]
    columns = [np.split(a[which], cuts) for a in added] + [np.split(speaks, cuts)]
    return [list(x) for x in zip(*columns)], int((added[0] > 0).sum())


def passing(term: np.ndarray, kinds: np.ndarray, mass: np.ndarray, test: float) -> list[np.ndarray]:
    """The divergence test: counts and transitions of contexts that pass it, else zero."""
    good = (kinds > 0) & (term > test * kinds)
    return [np.where(good, mass, 0), np.where(good, kinds, 0)]


def _answer(step: int, test: float):
    def run(table: pa.Table) -> pa.Table:
        blocks = table.column("block").to_numpy()
        order = np.argsort(blocks, kind="stable")
        keys = [unpacked_keys(table.column("keys")[i].as_py()) for i in order.tolist()]
        values = [[unpacked(v, kind) for v, kind in zip(table.column("values")[i].as_py(), ASKED[step % 2])] for i in order.tolist()]
        told, different = sums(keys, values)
        bucket = table.column("bucket")[0].as_py()
        if step % 2:
            data = [[packed(c.astype(np.int64)) for c in passing(*t[:3], test)] for t in told]
        else:
            data = [[packed(t[0].astype(np.int64)), packed(np.packbits(t[1]))] for t in told]
        release()
        n = len(order)
        return pa.Table.from_arrays(
            [pa.array(blocks[order]), pa.array([step] * n, pa.int32()), pa.array([bucket] * n, pa.int32()), pa.array([different] + [0] * (n - 1), pa.int64()), pa.array(data, pa.list_(pa.binary()))], ["block", "step", "bucket", "different", "data"]
        )

    return run


def _told(right: pa.Table) -> dict[int, list[np.ndarray]]:
    """Answers by step, buckets in order."""
    out: dict[int, list[np.ndarray]] = {}
    rows = sorted(zip(right.column("step").to_pylist(), right.column("bucket").to_pylist(), range(right.num_rows)))
    for step in sorted({s for s, _, _ in rows}):
        parts = []
        for s, _, i in rows:
            if s == step:
                data = right.column("data")[i].as_py()
                if step % 2 == 0:
                    n = unpacked(data[0], np.int64)
                    parts.append([n, np.unpackbits(unpacked(data[1], np.uint8))[: len(n)]])
                else:
                    parts.append([unpacked(c, np.int64) for c in data])
        out[step] = [np.concatenate(x) for x in zip(*parts)]
    return out


_NONE = [[np.zeros(0, t) for t in kinds] for kinds in TOLD]
_QUESTION = "bucket int, block long, keys binary, values array<binary>"
_ANSWER = "block long, step int, bucket int, different long, data array<binary>"


def _met(left: pa.Table, right: pa.Table, done: int) -> tuple[Block, dict]:
    """The block and what it was told in the steps before ``done``; a step in which it asked nothing told it nothing."""
    held, sizes = (left.column(c)[0].values.to_numpy(zero_copy_only=False) for c in ("held", "sizes"))
    b = Block(left.column("words")[0].as_py(), left.column("places")[0].as_py(), sizes, held)
    told = _told(right)
    return b, {s: told.get(s, _NONE[s % 2]) for s in (0, *range(2, done))} if done else {}


_NOTHING = pa.table({"step": pa.array([], pa.int32()), "bucket": pa.array([], pa.int32())})


def _asker(step: int, buckets: int, settings: tuple):
    def ask(left: pa.Table, right: pa.Table) -> pa.Table:
        rows: dict[str, list] = {"bucket": [], "block": [], "keys": [], "values": []}
        if left.num_rows:
            b, told = _met(left, right, step)
            rows = questions(left.column("block")[0].as_py(), walk(b, told, *settings)[0], buckets)
            del b, told
            release()
        return pa.table({"bucket": pa.array(rows["bucket"], pa.int32()), "block": pa.array(rows["block"], pa.int64()), "keys": pa.array(rows["keys"], pa.binary()), "values": pa.array(rows["values"], pa.list_(pa.binary()))})

    return ask


def score_texts(
    docs: DataFrame, row_id: str = "doc_id", text: str = "text", held_out: tuple[int, int] = (7, 2), depth: int = 2, least: int = 2, test: float = 1.0, block_bytes: int = 1 << 22
) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score (both log10)."""
    if least < 2:
        raise ValueError("a context has to occur twice at least")
    kind = docs.schema[row_id].dataType.simpleString()
    written = stash(blocks_of(docs, row_id, text, held_out, block_bytes))
    counted = F.transform(F.arrays_zip("held", "sizes"), lambda x: F.when(x["held"], 0).otherwise(x["sizes"]).cast("long"))
    total, every, n_blocks = written.agg(
        F.coalesce(F.sum(F.aggregate(counted, F.lit(0).cast("long"), lambda a, x: a + x)), F.lit(0)), F.coalesce(F.sum(F.aggregate("sizes", F.lit(0).cast("long"), lambda a, x: a + x)), F.lit(0)), F.count(F.lit(1))
    ).first()
    buckets = blocks_for(every, BUCKET)
    parts = blocks_for(n_blocks, 2)
    blocks = written.repartition(parts, "block").persist(StorageLevel.MEMORY_AND_DISK)
    answers: DataFrame | None = None
    different = 0
    steps = (0, *range(2, 2 * depth + 2))
    for step in steps:
        ask = _asker(step, buckets, (total, different, depth, least))
        if answers is None:
            asked = blocks.groupBy("block").applyInArrow(lambda left: ask(left, _NOTHING), _QUESTION)
        else:
            asked = blocks.groupBy("block").cogroup(answers.groupBy("block")).applyInArrow(ask, _QUESTION)
        told = stash(asked.groupBy("bucket").applyInArrow(_answer(step, test), _ANSWER))
        if answers is None:
            different = told.agg(F.coalesce(F.sum("different"), F.lit(0))).first()[0]
        answers = told if answers is None else answers.unionByName(told)

    def score(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows:
            return empty.slice(0, 0)
        b, told = _met(left, right, steps[-1] + 1)
        _, p, known = walk(b, told, total, different, depth, least)
        base = np.log10((known + 1) / (total + different + 1))[b.places]
        ids, held = left.column("ids")[0].values, left.column("held")[0].values
        columns = [ids, held, pa.array(b.sizes), pa.array(np.add.reduceat((known > 0).astype(np.int64)[b.places], b.starts)), pa.array(np.full(len(ids), total, np.int64)), pa.array(np.add.reduceat(base, b.starts)), pa.array(np.add.reduceat(np.log10(p), b.starts))]
        del b, told, p, known, base
        release()
        return pa.Table.from_arrays(columns, ["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"])

    schema = f"doc_id {kind}, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"
    empty = pa.table({c: pa.array([], t) for c, t in (("doc_id", pa.int64()), ("held_out", pa.bool_()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("train_tokens", pa.int64()), ("base_score", pa.float64()), ("score", pa.float64()))})
    return blocks.groupBy("block").cogroup(answers.groupBy("block")).applyInArrow(score, schema)
