"""Byte-level BPE: encoding by a segment tree of pair ranks, and decoding.

A piece of text (one match of the splitting pattern) keeps its live neighbours in a
doubly linked list over byte positions. A segment tree over the positions stores
``rank * size + position`` of the pair that starts there, so its root is the leftmost
pair of least rank; a merge changes three leaves, each in logarithmic time. A piece of n
bytes costs O(n log n), however long and repetitive it is.
"""

from __future__ import annotations

import base64
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column
from pyspark.sql import functions as F

from . import worker

#: Pieces remembered per worker, and the longest piece worth remembering (bytes).
REMEMBERED, LONGEST = 650_000, 64
NONE = 1 << 62


def merge(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    """Token ids of one piece."""
    if (whole := ranks.get(piece)) is not None:
        return [whole]
    n = len(piece)
    shift = max(1, (n - 1).bit_length())
    size = 1 << shift
    tree = [NONE] * (2 * size)
    rank_of = ranks.get
    for i in range(n - 1):
        if (r := rank_of(piece[i : i + 2])) is not None:
            tree[size + i] = r << shift | i
    for at in range(size - 1, 0, -1):
        a, b = tree[2 * at], tree[2 * at + 1]
        tree[at] = a if a < b else b
    after, before = list(range(1, n + 1)), list(range(-1, n))
    mask = size - 1

    def put(i: int, value: int) -> None:
        at = size + i
        tree[at] = value
        at >>= 1
        while at:
            a, b = tree[2 * at], tree[2 * at + 1]
            least = a if a < b else b
            if tree[at] == least:
                return
            tree[at] = least
            at >>= 1

    while (best := tree[1]) != NONE:
        i = best & mask
        j = after[i]
        k = after[j]
        after[i] = k
        put(j, NONE)
        if k < n:
            before[k] = i
            r = rank_of(piece[i : after[k]])
            put(i, NONE if r is None else r << shift | i)
        else:
            put(i, NONE)
        if (p := before[i]) >= 0:
            r = rank_of(piece[p:k])
            put(p, NONE if r is None else r << shift | p)
    out, i = [], 0
    while i < n:
        out.append(ranks[piece[i : after[i]]])
        i = after[i]
    return out


class Codec:
    """Ranks, splitting pattern and a bounded memory of short pieces."""

    def __init__(self, path: str, pattern: str):
        with open(path, "rb") as f:
            self.ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}
        self.split = regex.compile(pattern).findall
        self.seen: dict[str, bytes] = {}
        top = max(self.ranks.values()) + 1
        self.length = np.zeros(top, np.int64)
        for token, i in self.ranks.items():
            self.length[i] = len(token)
        self.start = np.concatenate(([0], np.cumsum(self.length)[:-1]))
        flat = bytearray(int(self.length.sum()))
        for token, i in self.ranks.items():
            flat[self.start[i] : self.start[i] + len(token)] = token
        self.flat = np.frombuffer(bytes(flat), np.uint8)

    def encode(self, text: str) -> bytes:
        """Ids of one whole text as little-endian 32-bit integers."""
        seen = self.seen
        out = []
        for piece in self.split(text):
            if (ids := seen.get(piece)) is None:
                raw = piece.encode("utf-8")
                ids = np.array(merge(raw, self.ranks), "<i4").tobytes()
                if len(raw) <= LONGEST:
                    if len(seen) > REMEMBERED:
                        seen.clear()
                    seen[piece] = ids
            out.append(ids)
        return b"".join(out)

    def decode(self, ids: np.ndarray) -> bytes:
        """The bytes that ids stand for; unknown ids raise IndexError."""
        parts = []
        for at in range(0, len(ids), 1 << 16):  # bounded memory for very long texts
            some = ids[at : at + (1 << 16)].astype(np.int64)
            if len(some) and (some.min() < 0 or some.max() >= len(self.length)):
                raise IndexError("id outside the vocabulary")
            n = self.length[some]
            ends = np.cumsum(n)
            place = np.arange(ends[-1] if len(ends) else 0) + np.repeat(self.start[some] - ends + n, n)
            parts.append(self.flat[place].tobytes())
        return b"".join(parts)


@lru_cache(maxsize=2)
def codec(path: str, pattern: str) -> Codec:
    return Codec(path, pattern)


worker.remembers("bpe", codec.cache_clear)


def encode(text: Column, path: str, pattern: str) -> Column:
    """``array<int>`` of token ids of a text column. Null counts as the empty text, which
    has no ids. Special tokens are never made: their strings are ordinary text. A very long
    text is encoded whole, in n log n time for its longest piece; what is remembered of pieces is
    bounded within a text too. Rows are independent, so ties, repeated rows, empty tables and
    other columns don't matter."""

    def ids_of(texts: pa.Array) -> pa.Array:
        worker.enter("bpe")
        work = codec(path, pattern)
        rows = [work.encode(t.as_py() or "") for t in texts]
        ends = np.cumsum([0] + [len(r) // 4 for r in rows], dtype=np.int64).astype(np.int32)
        return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.frombuffer(b"".join(rows), "<i4"), pa.int32()))

    # Not to be repeated: without this the optimiser would encode again for each use of the ids.
    return F.arrow_udf(ids_of, "array<int>").asNondeterministic()(text)


def decode(ids: Column, path: str, pattern: str) -> Column:
    """``binary`` of the bytes that an ``array<int>`` of ids stands for (null: empty)."""

    def bytes_of(lists: pa.Array) -> pa.Array:
        worker.enter("bpe")
        work = codec(path, pattern)
        return pa.array([work.decode(np.asarray(x.values) if x.is_valid else np.zeros(0, np.int32)) for x in lists], pa.binary())

    return F.arrow_udf(bytes_of, "binary")(ids)
