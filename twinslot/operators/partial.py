"""Partial counts of pairs, packed by a task before they are shuffled and summed bucket by bucket."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

PACKED = "bucket int, pairs binary"
COUNTS = "item_a long, item_b long, support long"

#: Partial counts that a bucket may get, by a bound that no data exceeds by more than repairs; buckets at most.
BUCKET_PAIRS, MAX_BUCKETS = 1_000_000, 1 << 16

#: Pairs that a task packs at once.
PACKED_PAIRS = 2_000_000

#: Neighbouring second items (so many bits of them) share a bucket, so that their differences stay small.
NEAR_BITS = 6

_U = np.uint64


def bucket_count(bound: int) -> int:
    return int(min(MAX_BUCKETS, max(1, -(-int(bound) // BUCKET_PAIRS))))


def _bucket_of(a: np.ndarray, b: np.ndarray, buckets: int) -> np.ndarray:
    mixed = a.view(_U) * _U(0x9E3779B97F4A7C15) ^ (b >> NEAR_BITS).view(_U) * _U(0xC2B2AE3D27D4EB4F)
    return ((mixed ^ mixed >> _U(29)) * _U(0xBF58476D1CE4E5B9) >> _U(33)).astype(np.int64) % buckets


def _planes(values: np.ndarray) -> tuple[int, bytes]:
    """Unsigned numbers in as few bytes each as the largest needs, first bytes first."""
    width = max(1, (int(values.max()).bit_length() + 7) // 8) if len(values) else 1
    return width, values.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width].T.tobytes()


def _numbers(data: memoryview, n: int, width: int) -> np.ndarray:
    out = np.zeros((n, 8), np.uint8)
    out[:, :width] = np.frombuffer(data, np.uint8, n * width).reshape(width, n).T
    return out.reshape(-1).view("<u8")


def encode(a: np.ndarray, b: np.ndarray, n: np.ndarray) -> bytes:
    """Rows in order of (a, b): first items as runs, second ones as differences, counts (any sign) as they are."""
    ua, ub = a.view(_U), b.view(_U)
    new = np.ones(len(a), bool)
    new[1:] = ua[1:] != ua[:-1]
    at = np.flatnonzero(new)
    step = ub.copy()
    step[1:] -= ub[:-1]  # wraps, and back
    base = _U(int(b.min()) % (1 << 64))
    step[at] = ub[at] - base
    first = ua[at]
    first[1:] -= ua[at[:-1]]
    first[0] = 0
    parts = [_planes(c) for c in (first, np.diff(np.append(at, len(a))).view(_U), step, (n << 1 ^ n >> 63).view(_U))]
    head = np.array([len(at), len(a), *(w for w, _ in parts)], "<i8").tobytes() + np.array([ua[0], base], "<u8").tobytes()
    raw = head + b"".join(p for _, p in parts)
    return len(raw).to_bytes(8, "little") + pa.compress(raw, codec="zstd", asbytes=True)


def decode(blob: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    raw = memoryview(pa.decompress(blob[8:], int.from_bytes(blob[:8], "little"), codec="zstd", asbytes=True))
    runs, rows, *widths = np.frombuffer(raw, "<i8", 6).tolist()
    a0, base = np.frombuffer(raw, "<u8", 2, 48)
    at, columns = 64, []
    for count, width in zip((runs, runs, rows, rows), widths):
        columns.append(_numbers(raw[at:], count, width))
        at += count * width
    first, length, step, n = columns
    length = length.astype(np.int64)
    starts = np.cumsum(length) - length
    total = np.cumsum(step)
    b = total - np.repeat(total[starts] - step[starts], length) + base
    a = np.repeat(np.cumsum(first) + a0, length)
    return a.view(np.int64), b.view(np.int64), (n >> _U(1)).view(np.int64) ^ -(n & _U(1)).view(np.int64)


def summed(a: np.ndarray, b: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """One row for each pair, in order of (a, b)."""
    if not len(a):
        return a, b, n
    order = np.lexsort((b, a))
    a, b, n = a[order], b[order], n[order]
    new = np.ones(len(a), bool)
    new[1:] = (a[1:] != a[:-1]) | (b[1:] != b[:-1])
    at = np.flatnonzero(new)
    return a[at], b[at], np.add.reduceat(n, at)


def pack(parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]], buckets: int) -> list[tuple[int, bytes]]:
    """``(bucket, pairs)`` of partial counts."""
    a, b, n = (np.concatenate([np.zeros(0, np.int64), *c]) for c in zip(*parts)) if parts else (np.zeros(0, np.int64),) * 3
    if not len(a):
        return []
    a, b, n = summed(a, b, n)
    bucket = _bucket_of(a, b, buckets)
    order = np.argsort(bucket, kind="stable")
    ends = np.searchsorted(bucket[order], np.arange(buckets + 1))
    return [(k, encode(*(c[order[i:j]] for c in (a, b, n)))) for k, (i, j) in enumerate(zip(ends[:-1].tolist(), ends[1:].tolist())) if i < j]


def packed_rows(rows: list[tuple[int, bytes]]) -> pa.Table:
    buckets, blobs = zip(*rows) if rows else ((), ())
    return pa.Table.from_arrays([pa.array(buckets, pa.int32()), pa.array(blobs, pa.binary())], names=["bucket", "pairs"])


def packed(counts: DataFrame, buckets: int) -> DataFrame:
    """``counts(item_a, item_b, support)``, any number of rows a pair, packed by the tasks that make them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, size = [], 0
        for batch in batches:
            parts.append(tuple(c.to_numpy(zero_copy_only=False).copy() for c in batch.columns))
            size += batch.num_rows
            if size >= PACKED_PAIRS:
                yield from packed_rows(pack(parts, buckets)).to_batches()
                parts, size = [], 0
        yield from packed_rows(pack(parts, buckets)).to_batches()

    return counts.select("item_a", "item_b", "support").mapInArrow(run, PACKED)


def totals(rows: DataFrame, least: int = 1) -> DataFrame:
    """``(item_a, item_b, support)`` of pairs whose counts sum to ``least`` or more. A task
    decodes some of a bucket's rows at a time and holds each pair once."""

    def run(table: pa.Table) -> pa.Table:
        kept, more, size = (np.zeros(0, np.int64),) * 3, [], 0
        for blob in table.column("pairs"):
            more.append(decode(blob.as_py()))
            size += len(more[-1][0])
            if size >= max(PACKED_PAIRS, len(kept[0])):
                kept, more, size = summed(*map(np.concatenate, zip(kept, *more))), [], 0
        a, b, n = summed(*map(np.concatenate, zip(kept, *more)))
        keep = n >= least
        return pa.Table.from_arrays([pa.array(c[keep], pa.int64()) for c in (a, b, n)], names=["item_a", "item_b", "support"])

    return rows.groupBy("bucket").applyInArrow(run, COUNTS)
