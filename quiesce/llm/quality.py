"""Quality scores by a factorisation machine over hashed features.

Features of a text: its hashed words (ASCII lower case), hashed two-ends of words
(the last two characters, which carry punctuation marks), structure statistics
(shares of letters, capitals, digits, blanks, marks and line breaks; mean word
length; share of different words; share of words seen twice in a row), each in
hashed steps of its value, and one metadata feature, the step of the text's length.
Labels, language, source and id never enter a score.

A feature's weight is its tempered frequency, scaled so that a text has length one.
The score is the logistic of  b + sum w_f x_f + sum_{f<g} <v_f, v_g> x_f x_g;  the
pairwise part is  (|sum v_f x_f|^2 - sum |v_f|^2 x_f^2) / 2,  linear in the features.

Training reads at most ``sample`` labelled rows, those with the least hash of their
id, so the fitted machine and what is broadcast have a fixed size; scoring reads
every whole text.

Defined results: null text is empty and scored like any other; labels that are
null or whose text is missing are not learned from; with no label at all every
score is one half; rows that repeat an id are scored each, and one of them, that with
the least hash of its text, is learned from; rows of null id are scored and never
learned from; an empty table gives an empty result; extra columns are ignored by
``score_quality`` and kept by ``accepted``, whatever their names.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import crc_mod, release

BITS = 16
RANK = 8
SAMPLE = 12_000
_STEPS = 12
_WORD: dict[bytes, int] = {}
_MEMO = 400_000
_CAPITALS = bytes(range(65, 91))
_LETTERS = bytes([*range(65, 91), *range(97, 123), *range(128, 256)])
_DIGITS = b"0123456789"
_MARKS = bytes(c for c in range(33, 127) if not chr(c).isalnum())
_RUNS = re.compile(rb"[!-/:-@\[-`{-~]{2,}")


def _word_slot(word: bytes) -> int:
    slot = _WORD.get(word)
    if slot is None:
        if len(_WORD) >= _MEMO:
            _WORD.clear()
        slot = _WORD[word] = crc32(word) & ((1 << BITS) - 1)
    return slot


def _share(raw: bytes, kind: bytes, n: int) -> float:
    return 1 - len(raw.translate(None, kind)) / n if n else 0.0


def structure(raw: bytes, words: list[bytes], different: int) -> list[float]:
    """Statistics between 0 and 1 of a text in UTF-8."""
    n, m = len(raw), max(1, len(words))
    repeated = sum(map(bytes.__eq__, words, words[1:])) / m
    return [
        _share(raw, _LETTERS, n),
        _share(raw, _CAPITALS, n),
        _share(raw, _DIGITS, n),
        _share(raw, b" ", n),
        _share(raw, b"\n", n) * 10,
        _share(raw, _MARKS, n),
        min(1.0, n / m / 40),
        different / m,
        min(1.0, repeated * 4),
        min(1.0, len(_RUNS.findall(raw)) / m),
        min(1.0, raw.count(b"|") / m),
        np.log1p(n) / 24,
    ]


def features(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """Slots and weights of a text; the weights' squares sum to one."""
    raw = (text or "").encode("utf-8", "surrogatepass")
    words = raw.split()
    counts = Counter(raw.lower().split())
    ends = Counter(w[-2:] for w in counts)
    slots = [_word_slot(w) for w in counts]
    weights = list(counts.values())
    slots += [crc32(b"\x01" + e) & ((1 << BITS) - 1) for e in ends]
    weights += ends.values()
    w = np.sqrt(np.array(weights, float))
    if len(w):
        w *= 0.8 / np.sqrt((w * w).sum())
    stats = structure(raw, words, len(counts))
    for i, x in enumerate(stats):
        slots.append(crc32(b"\x02%d:%d" % (i, min(_STEPS - 1, int(x * _STEPS)))) & ((1 << BITS) - 1))
        slots.append(crc32(b"\x03%d:%d" % (i, min(99, int(x * 100)))) & ((1 << BITS) - 1))
    w = np.concatenate((w, np.full(2 * len(stats), 0.6 / np.sqrt(2 * len(stats)))))
    return np.array(slots, np.int64), w


class FactorisationMachine:
    def __init__(self, bits: int = BITS, rank: int = RANK, seed: int = 11) -> None:
        self.b = 0.0
        self.w = np.zeros(1 << bits)
        self.v = np.random.default_rng(seed).normal(0, 0.02, (1 << bits, rank))

    def raw(self, slots: np.ndarray, x: np.ndarray) -> float:
        vx = self.v[slots] * x[:, None]
        s = vx.sum(axis=0)
        return self.b + float(self.w[slots] @ x) + 0.5 * float(s @ s - (vx * vx).sum())

    def score(self, slots: np.ndarray, x: np.ndarray) -> float:
        return float(1 / (1 + np.exp(-np.clip(self.raw(slots, x), -35, 35))))

    def fit(self, rows: list[tuple[np.ndarray, np.ndarray]], labels: np.ndarray, passes: int = 6, rate: float = 0.15, decay: float = 1e-5, seed: int = 5) -> FactorisationMachine:
        """Adaptive gradient steps on the logistic loss, the rows in a fixed random order."""
        if len(labels) == 0:
            self.v[:] = 0  # nothing learned: every score is one half
            return self
        rng = np.random.default_rng(seed)
        share = np.clip(labels.mean(), 1e-3, 1 - 1e-3)
        self.b = float(np.log(share / (1 - share)))
        gw, gv, gb = np.full(self.w.shape, 1e-4), np.full(self.v.shape, 1e-4), 1e-4
        for _ in range(passes):
            for i in rng.permutation(len(rows)):
                f, x = rows[i][0].astype(np.int64), rows[i][1].astype(float)
                vx = self.v[f] * x[:, None]
                s = vx.sum(axis=0)
                z = self.b + float(self.w[f] @ x) + 0.5 * float(s @ s - (vx * vx).sum())
                g = 1 / (1 + np.exp(-np.clip(z, -35, 35))) - labels[i]
                dw = g * x + decay * self.w[f]
                dv = g * (x[:, None] * (s - vx)) + decay * self.v[f]
                gw[f] += dw * dw
                gv[f] += dv * dv
                gb += g * g
                self.w[f] -= rate * dw / np.sqrt(gw[f])
                self.v[f] -= 0.3 * rate * dv / np.sqrt(gv[f])
                self.b -= rate * g / np.sqrt(gb)
        return self


def fit(docs: DataFrame, labels: DataFrame, row_id: str, text: str, label: str, held_out: int, sample: int) -> FactorisationMachine:
    """Features are made on the executors; at most ``sample`` short rows reach the driver."""
    known = labels.filter(F.col(label).isNotNull() & F.col(row_id).isNotNull() & (crc_mod(row_id, held_out) != 0)).select(row_id, F.col(label).alias("_y"))
    order = F.xxhash64(F.col(row_id))
    chosen = known.orderBy(order, row_id, "_y").limit(sample)
    texts = docs.select(F.col(row_id).alias("i"), F.col(text).alias("t"))
    rows = texts.join(F.broadcast(chosen.select(F.col(row_id).alias("i"), F.col("_y").cast("double").alias("y"))), "i")
    # of rows that repeat an id one is learned from, so that no more than the chosen ones reach the driver
    rows = rows.groupBy("i", "y").agg(F.min_by("t", F.xxhash64("t")).alias("t")).select(F.xxhash64("i").alias("o"), "t", "y")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = [features(t.as_py()) for t in b.column(1)]
            yield pa.RecordBatch.from_arrays(
                [b.column(0), b.column(2), pa.array([f.astype("<u2").tobytes() for f, _ in got], pa.binary()), pa.array([x.astype("<f4").tobytes() for _, x in got], pa.binary())], ["o", "y", "f", "x"]
            )

    got = rows.mapInArrow(run, "o long, y double, f binary, x binary").toArrow().sort_by([("o", "ascending"), ("y", "ascending"), ("f", "ascending")])
    # read where they lie, since the driver holds all of them at once
    pairs = [(np.frombuffer(f.as_buffer(), "<u2"), np.frombuffer(x.as_buffer(), "<f4")) for f, x in zip(got.column("f"), got.column("x"))]
    machine = FactorisationMachine().fit(pairs, got.column("y").to_numpy())
    del got, pairs
    release()
    return machine


def _scorer(docs: DataFrame, labels: DataFrame, row_id: str, text: str, label: str, held_out: int, cut: float, sample: int, passed: list) -> DataFrame:
    """The passed columns (named apart from ours) with score and predicted."""
    machine = docs.sparkSession.sparkContext.broadcast(fit(docs, labels, row_id, text, label, held_out, sample))
    rows = docs.select(*passed, F.col(text))
    fields = rows.schema[:-1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = machine.value
        for b in batches:
            score = np.fromiter((m.score(*features(t.as_py())) for t in b.column(b.num_columns - 1)), np.float64, b.num_rows)
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(score), pa.array((score >= cut).astype(np.int32))], [*b.schema.names[:-1], "score", "predicted"])

    return rows.mapInArrow(run, ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in fields] + ["score double", "predicted int"]))


def score_quality(docs: DataFrame, labels: DataFrame, row_id: str = "doc_id", text: str = "text", label: str = "quality", held_out: int = 5, cut: float = 0.3, sample: int = SAMPLE) -> DataFrame:
    """doc_id, held_out, score, predicted."""
    passed = [F.col(row_id).alias("doc_id"), (crc_mod(row_id, held_out) == 0).alias("held_out")]
    return _scorer(docs, labels, row_id, text, label, held_out, cut, sample, passed)


def accepted(docs: DataFrame, labels: DataFrame, row_id: str = "doc_id", text: str = "text", label: str = "quality", held_out: int = 5, cut: float = 0.3, sample: int = SAMPLE) -> DataFrame:
    """The rows of ``docs``, with all their columns, that the machine accepts."""
    rows = _scorer(docs, labels, row_id, text, label, held_out, cut, sample, [F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row")])
    return rows.filter("predicted = 1").select("row.*")
