"""Byte-level BPE by longest matches and backtracking, and its inverse.

Bytes are mapped to Latin-1 characters, so that one character is one byte and
pyahocorasick can find vocabulary entries inside a pre-token. Encoding takes the
longest entry at each position and goes back to the next shorter one whenever the
entry would not stand beside its left neighbour. Two adjacent tokens may stand
beside each other if merging their joined bytes by rank would never cross their
border; that answer depends on the pair alone and is memoised. Each position is
given up at most once, so the work is linear in the bytes, and the result equals
the one of merging pairs by rank.

Pre-tokens are memoised in a bounded table. Defined results: null text is empty
and has no ids; whitespace and invalid surrogates are ordinary bytes.
"""

from __future__ import annotations

import base64
import hashlib
from array import array
from collections.abc import Iterator
from functools import lru_cache

import ahocorasick
import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Bound of the memo tables of one Python worker, in entries.
MEMO = 300_000


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


class Bpe:
    """Encoder and decoder for one table of ranks and one pre-token pattern."""

    def __init__(self, ranks: dict[bytes, int], pattern: str) -> None:
        self.rank = {k.decode("latin-1"): v for k, v in ranks.items()}
        self.text_of = {v: k for k, v in self.rank.items()}
        self.bytes_of = {v: k for k, v in ranks.items()}
        self.find = regex.compile(pattern).finditer
        self.findall = regex.compile(pattern).findall
        self.trie = ahocorasick.Automaton(ahocorasick.STORE_INTS)
        for k, v in self.rank.items():
            self.trie.add_word(k, v)
        self.trie.make_automaton()
        self.split_of: dict[int, tuple[int, int] | None] = {}
        self.shorter: dict[int, int] = {}
        self.pair: dict[int, bool] = {}
        self.words: dict[str, bytes] = {}
        self.width = max(ranks.values()) + 1
        self.longest_word = 512

    def _split(self, token: int) -> tuple[int, int] | None:
        """The two tokens whose merge makes the token; None for a base token."""
        if token in self.split_of:
            return self.split_of[token]
        s, out = self.text_of[token], None
        if len(s) > 1:
            parts = list(s)
            rank = self.rank
            while len(parts) > 2:
                best = min(range(len(parts) - 1), key=lambda i: rank.get(parts[i] + parts[i + 1], 1 << 60))
                low = rank.get(parts[best] + parts[best + 1], 1 << 60)
                if low >= token:
                    parts = []
                    break
                parts[best : best + 2] = [parts[best] + parts[best + 1]]
            if len(parts) == 2 and parts[0] in rank and parts[1] in rank:
                out = rank[parts[0]], rank[parts[1]]
        self.split_of[token] = out
        return out

    def fits(self, a: int, b: int) -> bool:
        """Whether tokens a and b keep their border when their joined bytes are merged."""
        key = a * self.width + b
        known = self.pair.get(key)
        if known is None:
            if len(self.pair) >= MEMO:
                self.pair.clear()
            known = self.pair[key] = self._fits(a, b)
        return known

    def _fits(self, a: int, b: int) -> bool:
        # Undo merges on both sides of the border, the latest first; a merge across
        # the border that comes before the merge undone last would have won.
        rank, text_of = self.rank, self.text_of
        limit = 1 << 60
        while True:
            across = rank.get(text_of[a] + text_of[b])
            if across is not None and across < limit:
                return False
            sa, sb = self._split(a), self._split(b)
            if sa is None and sb is None:
                return True
            # The later merge is undone. Of equal ranks the left merge is the earlier
            # one, so one across the border still beats an equal one on its right.
            if sb is None or (sa is not None and a > b):
                limit, a = a, sa[1]
            else:
                limit, b = b + 1, sb[0]

    def _next(self, token: int) -> int:
        """The longest proper prefix that is a token; -1 if none."""
        out = self.shorter.get(token)
        if out is None:
            s = self.text_of[token]
            out = self.shorter[token] = next((self.rank[s[:i]] for i in range(len(s) - 1, 0, -1) if s[:i] in self.rank), -1)
        return out

    def _longest(self, s: str) -> list[int]:
        """The longest token that starts at each position."""
        out = [-1] * len(s)
        rank, text_of = self.rank, self.text_of
        for end, token in self.trie.iter(s):
            # iter() reports every entry that ends here, the longest first
            start = end - len(text_of[token]) + 1
            out[start] = token  # a later end is a longer entry
        return out

    def encode_piece(self, s: str) -> list[int]:
        """Ids of one pre-token in Latin-1 form."""
        whole = self.rank.get(s)
        if whole is not None:
            return [whole]
        n, longest = len(s), self._longest(s)
        size = self.text_of
        dead = bytearray(n + 1)  # positions from which no compatible rest was found
        out: list[int] = []
        at, token = 0, longest[0]
        while token >= 0:
            last = out[-1] if out else -1
            while True:
                stop = at + len(size[token])
                if not dead[stop] and (last < 0 or self.fits(last, token)):
                    out.append(token)
                    at = stop
                    token = longest[at] if at < n else -1
                    break
                token = self._next(token)
                if token < 0:
                    # give this position up, and shorten the token before it
                    dead[at] = 1
                    token = out.pop()
                    at -= len(size[token])
                    last = out[-1] if out else -1
                    continue
        return out

    def packed(self, piece: str) -> bytes:
        """Ids of a pre-token as little-endian unsigned 32-bit integers."""
        out = self.words.get(piece)
        if out is None:
            out = array("I", self.encode_piece(piece.encode("utf-8", "surrogatepass").decode("latin-1"))).tobytes()
            if len(piece) <= self.longest_word:
                if len(self.words) >= MEMO:
                    self.words.clear()
                self.words[piece] = out
        return out

    def encode(self, text: str) -> bytes:
        known = self.words
        pieces = self.findall(text)
        try:
            return b"".join([known[p] for p in pieces])
        except KeyError:
            return b"".join([known[p] if p in known else self.packed(p) for p in pieces])

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, np.frombuffer(ids, "<u4").tolist()))


@lru_cache(maxsize=4)
def load(path: str, pattern: str) -> Bpe:
    return Bpe(read_ranks(path), pattern)


def encode(docs: DataFrame, path: str, pattern: str, row_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id and ids (array of integers)."""
    kind = docs.schema[row_id].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(path, pattern)
        for b in batches:
            ids = [np.frombuffer(bpe.encode(t.as_py() or ""), "<u4").astype(np.int32) for t in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(ids, pa.list_(pa.int32()))], ["doc_id", "ids"])

    return docs.select(F.col(row_id).alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, f"doc_id {kind}, ids array<int>")


def decode(encoded: DataFrame, path: str, pattern: str, row_id: str = "doc_id", ids: str = "ids") -> DataFrame:
    """doc_id and content (the bytes of the ids)."""
    kind = encoded.schema[row_id].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(path, pattern)
        for b in batches:
            out = [b"".join(map(bpe.bytes_of.__getitem__, x.as_py() or [])) for x in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.binary())], ["doc_id", "content"])

    return encoded.select(F.col(row_id).alias("doc_id"), F.col(ids).alias("ids")).mapInArrow(run, f"doc_id {kind}, content binary")


def digests(docs: DataFrame, path: str, pattern: str, row_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_tokens, ids_sha256 and decoded_sha256 of each text, encoded and decoded in one pass."""
    kind = docs.schema[row_id].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(path, pattern)
        for b in batches:
            n, first, second = [], [], []
            for t in b.column(1):
                ids = bpe.encode(t.as_py() or "")
                n.append(len(ids) // 4)
                first.append(hashlib.sha256(ids).hexdigest())
                second.append(hashlib.sha256(bpe.decode(ids)).hexdigest())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(first), pa.array(second)], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select(F.col(row_id).alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, f"doc_id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")
