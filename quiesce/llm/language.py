"""Language of a text by nearest centroids of TF-IDF vectors.

Vectors hold hashed byte n-grams (one to ``ORDER`` bytes, ASCII lower case, runs of
anything but letters as one space), term frequency damped by its logarithm and
weighted by inverse document frequency, at length one. Each language has up to
``clusters`` centroids from spherical k-means over its training texts, since a
language may come in several styles. A text gets the language of the centroid with
the largest cosine. It is marked ``rejected`` where that cosine is below what nearly
all training texts of the centroid reach (``quantile`` of them, less ``slack``);
the nearest language is still named.

The score is the nearest language's share of the similarity, sharpened: 1 for a
text that lies on its centroid and far from other languages.

Training reads about ``sample`` labelled texts, those with the least hash of their id,
so that the centroids, which are broadcast, have a fixed size per language. ``sample``
is drawn over languages in proportion, at least 50 of each where there are as many, and
no language is left out: the model grows with the number of languages alone.

Defined results: ``und`` with score 0 for null text and for text without a letter
(Unicode category L); of equally near centroids the first language by name wins;
without any training text every text is ``und``; null or empty languages are not
learned from; rows that repeat an id, or have none, are predicted each; whole texts
are read, however long; extra columns are ignored, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex as re
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import crc_mod

ORDER = 3
DIMS = 1 << 12
SAMPLE = 6_000
_LETTER = re.compile(r"\p{L}")
#: Letters in ASCII lower case; bytes over 127 stay; everything else is a space.
_FOLD = bytes(c + 32 if 65 <= c <= 90 else c if 97 <= c <= 122 or c >= 128 else 32 for c in range(256))


def has_letter(text: str | None) -> bool:
    return text is not None and _LETTER.search(text) is not None


def frequencies(texts: list[str]) -> np.ndarray:
    """Damped n-gram frequencies, one row for each text."""
    parts = [b" " + b" ".join(t.encode("utf-8", "surrogatepass").translate(_FOLD).split()) + b" " for t in texts]
    buf = np.frombuffer(b"".join(parts), np.uint8).astype(np.uint32)
    sizes = np.fromiter(map(len, parts), np.int64, len(parts))
    out = np.zeros(len(parts) * DIMS)
    row = np.repeat(np.arange(len(parts), dtype=np.uint32) * np.uint32(DIMS), sizes)
    code = np.zeros(len(buf), np.uint32)
    for k in range(ORDER):
        n = len(buf) - k
        if n <= 0:
            break
        code = code[:n] * np.uint32(257) + buf[k:] + np.uint32(1)
        slot = ((code * np.uint32(2654435761)) >> np.uint32(32 - 12)) + row[:n]
        # an n-gram that runs into the next text belongs to none
        out += np.bincount(slot[row[:n] == row[k:]] if k else slot, minlength=len(out))
    out = out.reshape(len(parts), DIMS)
    return np.log1p(out, out=out)


def _unit(x: np.ndarray) -> np.ndarray:
    return x / np.maximum(np.linalg.norm(x, axis=-1, keepdims=True), 1e-12)


def spherical_kmeans(x: np.ndarray, k: int, sweeps: int = 12) -> np.ndarray:
    """At most k unit centroids; starts spread out, each farthest from those before it."""
    centres = [_unit(x.mean(axis=0))]
    while len(centres) < min(k, len(x)):
        centres.append(x[np.argmin(np.max(x @ np.array(centres).T, axis=1))])
    c = np.array(centres)
    for _ in range(sweeps):
        near = np.argmax(x @ c.T, axis=1)
        new = np.array([_unit(x[near == i].mean(axis=0)) if (near == i).any() else c[i] for i in range(len(c))])
        if np.allclose(new, c):
            break
        c = new
    return c


class Centroids:
    def __init__(self, rows: list[tuple[np.ndarray, np.ndarray]], langs: list[str], clusters: int, quantile: float, slack: float) -> None:
        """rows: slots and damped frequencies of the training texts; one language at a time is made dense."""
        self.langs = sorted(set(langs))
        seen = np.zeros(DIMS)
        for f, _ in rows:
            seen[f] += 1
        self.idf = (np.log((1 + len(rows)) / (1 + seen)) + 1).astype(np.float32)
        of: dict[str, list[int]] = {}
        for i, lang in enumerate(langs):
            of.setdefault(lang, []).append(i)

        def dense(lang: str) -> np.ndarray:
            x = np.zeros((len(of[lang]), DIMS), np.float32)
            for r, i in enumerate(of[lang]):
                x[r, rows[i][0]] = rows[i][1]
            return _unit(x * self.idf)

        centres, owner = [], []
        for i, lang in enumerate(self.langs):
            c = spherical_kmeans(dense(lang), clusters).astype(np.float32)
            centres.append(c)
            owner += [i] * len(c)
        self.centres, self.owner = np.concatenate(centres) if centres else np.zeros((0, DIMS)), np.array(owner, int)
        best: list[list[float]] = [[] for _ in owner]
        for lang in self.langs:
            cosine = dense(lang) @ self.centres.T
            for c, x in zip(cosine.argmax(axis=1).tolist(), cosine.max(axis=1).tolist()):
                best[c].append(x)
        self.least = np.array([np.quantile(b, quantile) - slack if b else 0.0 for b in best])

    def predict(self, texts: list[str | None]) -> tuple[list[str], np.ndarray, np.ndarray]:
        """Languages, scores, rejections."""
        lang, score, rejected = ["und"] * len(texts), np.zeros(len(texts)), np.ones(len(texts), bool)
        use = [i for i, t in enumerate(texts) if has_letter(t)] if len(self.owner) else []
        if use:
            cosine = _unit(frequencies([texts[i] for i in use]) * self.idf) @ self.centres.T
            near = cosine.argmax(axis=1)
            by_lang = np.stack([cosine[:, self.owner == i].max(axis=1) for i in range(len(self.langs))], axis=1)
            sharp = np.exp(20 * (by_lang - by_lang.max(axis=1, keepdims=True)))
            best = cosine.max(axis=1)
            score[use] = np.clip(1 / sharp.sum(axis=1), 0, 1)
            rejected[use] = best < self.least[near]
            for i, c in zip(use, near):
                lang[i] = self.langs[self.owner[c]]
        return lang, score, rejected


def _groups(texts: list[str | None], size: int = 1 << 20) -> Iterator[list[str | None]]:
    out, n = [], 0
    for t in texts:
        out.append(t)
        n += len(t or "")
        if n >= size or len(out) >= 256:
            yield out
            out, n = [], 0
    if out:
        yield out


def fit(docs: DataFrame, row_id: str, text: str, lang: str, held_out: tuple[int, int], sample: int, clusters: int, quantile: float, slack: float) -> Centroids:
    modulus, remainder = held_out
    order = F.xxhash64(F.col(row_id), F.col(lang))
    rows = docs.filter(F.col(lang).isNotNull() & (F.col(lang) != "") & F.col(text).isNotNull() & (crc_mod(row_id, modulus) != remainder)).select(order.alias("o"), F.col(lang).alias("l"))
    counts = {r["l"]: r["n"] for r in rows.groupBy("l").agg(F.count(F.lit(1)).alias("n")).collect()}  # one row for each language
    total = sum(counts.values())
    if not total:
        return Centroids([], [], clusters, quantile, slack)
    # A hash below a language's bound draws its share of the sample, over all rows and without a sort.
    span = 1 << 64
    bound = {k: min(span - 1, int(span * min(1.0, max(50.0, sample * n / total) / n))) - (1 << 63) for k, n in counts.items()}
    limit = F.create_map(*[F.lit(x) for kv in bound.items() for x in kv])
    chosen = docs.filter(F.col(lang).isNotNull() & F.col(text).isNotNull() & (crc_mod(row_id, modulus) != remainder)).filter(order <= F.element_at(limit, F.col(lang)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts, langs, orders = b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist()
            use = [i for i, t in enumerate(texts) if has_letter(t)]
            for at in range(0, len(use), 64):
                part = use[at : at + 64]
                rows = frequencies([texts[i] for i in part])
                slots = [np.flatnonzero(r) for r in rows]
                yield pa.RecordBatch.from_arrays(
                    [pa.array([orders[i] for i in part], pa.int64()), pa.array([langs[i] for i in part]), pa.array([f.astype(np.uint16).tobytes() for f in slots], pa.binary()), pa.array([r[f].astype(np.float32).tobytes() for r, f in zip(rows, slots)], pa.binary())], ["o", "l", "f", "x"]
                )

    # at most about ``sample`` sparse rows
    got = chosen.select(F.col(text).alias("t"), F.col(lang).alias("l"), order.alias("o")).mapInArrow(run, "o long, l string, f binary, x binary").toArrow().sort_by([("o", "ascending"), ("l", "ascending"), ("f", "ascending")])
    rows = [(np.frombuffer(f, np.uint16), np.frombuffer(x, np.float32)) for f, x in zip(got.column("f").to_pylist(), got.column("x").to_pylist())]
    return Centroids(rows, got.column("l").to_pylist(), clusters, quantile, slack)


def predict_language(
    docs: DataFrame, row_id: str = "doc_id", text: str = "text", lang: str = "lang", held_out: tuple[int, int] = (4, 2), sample: int = SAMPLE, clusters: int = 3, quantile: float = 0.01, slack: float = 0.05
) -> DataFrame:
    """doc_id, held_out, lang_pred, score, rejected."""
    kind = docs.schema[row_id].dataType.simpleString()
    model = docs.sparkSession.sparkContext.broadcast(fit(docs, row_id, text, lang, held_out, sample, clusters, quantile, slack))
    modulus, remainder = held_out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = model.value
        for b in batches:
            langs, scores, rejected = [], [], []
            for part in _groups(b.column(2).to_pylist()):
                x, y, z = m.predict(part)
                langs += x
                scores.append(y)
                rejected.append(z)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(langs, pa.string()), pa.array(np.concatenate(scores) if scores else [], pa.float64()), pa.array(np.concatenate(rejected) if rejected else [], pa.bool_())], ["doc_id", "held_out", "lang_pred", "score", "rejected"])

    return docs.select(F.col(row_id).alias("doc_id"), (crc_mod(row_id, modulus) == remainder).alias("held_out"), F.col(text).alias("t")).mapInArrow(run, f"doc_id {kind}, held_out boolean, lang_pred string, score double, rejected boolean")
