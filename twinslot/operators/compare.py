"""Counting common elements slot by slot, without branches on the data."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import Config
from ..functions import layout, perm
from ..sources.incidence import segment_of

_LANES = {bits: np.uint64(sum(1 << k for k in range(bits - 1, 64, bits))) for bits in (8, 16, 32)}


def lane_matches_np(x: np.ndarray, y: np.ndarray, bits: int = 8) -> np.ndarray:
    """Counted lanes of 64-bit words: element bits agree and an indicator is set.

    Adding all-ones element bits to a difference carries into a lane's top bit exactly when
    the difference isn't zero, and never beyond it."""
    top = _LANES[bits]
    low = ~top
    differ = ((x ^ y) & low) + low
    return np.bitwise_count(~differ & (x | y) & top)


def lane_count(x: Column, y: Column) -> Column:
    """The same for 32-bit words that are held in longs (four 8-bit lanes), as a Column."""
    top, low = F.lit(0x80808080).cast("long"), F.lit(0x7F7F7F7F).cast("long")
    differ = x.bitwiseXOR(y).bitwiseAND(low) + low
    return F.bit_count(F.bitwise_not(differ).bitwiseAND(x.bitwiseOR(y)).bitwiseAND(top))


class Matrix:
    """Maps of one width as rows, element bits and indicator bits apart."""

    def __init__(self, words: np.ndarray, bits: int):
        self.top = _LANES[bits]
        self.low, self.high = words & ~self.top, words & self.top


def count_row(row: np.ndarray, matrix: Matrix, slice_bytes: int) -> np.ndarray:
    """Counts of one map (64-bit words) against every row of a matrix. The narrower side is
    compared with every stretch of the wider one, a cache's worth of rows at a time.

    A lane's top bit minus the difference of the element bits keeps that bit exactly where
    they agree, and no lane borrows from another."""
    top, (count, n), w = matrix.top, matrix.low.shape, len(row)
    low, high = row & ~top, row & top
    wide = max(w, n)
    if n >= w:
        shape = (count, n // w, w)
        left = (low, high)
    else:
        shape = (count, 1, n)
        left = (low.reshape(1, w // n, n), high.reshape(1, w // n, n))
    mine = matrix.low.reshape(shape), matrix.high.reshape(shape)
    out = np.zeros(count, np.int64)
    step = max(1, slice_bytes // (8 * wide))
    first = (min(step, count), wide // min(w, n), min(w, n))
    agree, seen, ones = np.empty(first, np.uint64), np.empty(first, np.uint64), np.empty(first, np.uint8)
    for at in range(0, count, step):
        m = min(step, count - at)
        a, s, c = agree[:m], seen[:m], ones[:m]
        np.bitwise_xor(mine[0][at : at + m], left[0], out=a)
        np.subtract(top, a, out=a)
        np.bitwise_or(mine[1][at : at + m], left[1], out=s)
        np.bitwise_and(a, s, out=a)
        np.bitwise_count(a, out=c)
        out[at : at + m] = c.reshape(m, wide).sum(axis=1, dtype=np.int32)
    return out


def count_np(a: bytes, b: bytes, cfg: Config) -> int:
    """Common elements that two maps of one segment hold."""
    x, y = np.frombuffer(a, np.uint64), np.frombuffer(b, np.uint64)
    return int(count_row(x, Matrix(y[None, :], cfg.slot_bits), cfg.slice_bytes)[0])


# Kernels of tiles: counts of every left payload against every right payload.

# A matrix, or rows, columns and counts of those that aren't zero, or None: too many rows at once.
Kernel = Callable[[list[bytes], list[bytes]], np.ndarray | tuple[np.ndarray, np.ndarray, np.ndarray] | None]


def _by_width(payloads: list[bytes]) -> list[tuple[np.ndarray, np.ndarray]]:
    sizes = np.array([len(p) for p in payloads])
    return [
        (np.flatnonzero(sizes == s), np.stack([np.frombuffer(payloads[i], np.uint64) for i in np.flatnonzero(sizes == s)]))
        for s in np.unique(sizes)
    ]


#: Occupied slots are met one by one where that is cheaper than so many bytes of slots for each that meets.
MEETING_BYTES = 20

#: Meeting slots that are listed at once; occupied slots of both sides that are there at once.
MEETINGS, OCCUPIED_SLOTS = 2 << 20, 4 << 20


def _named(codes: np.ndarray, tables: np.ndarray, bits: np.ndarray, cfg: Config) -> np.ndarray:
    """Numbers of occupied slots: table and code (of which position and element bits are the two parts),
    indicator last. Slots that face each other and agree in their element bits have one table and code, whatever the widths."""
    return (tables * cfg.segment + codes) << 1 | bits


def owned(names: list[np.ndarray]) -> np.ndarray:
    """Numbers of the slots of several maps, in order, each with its map's number in the low half."""
    owner = np.repeat(np.arange(len(names), dtype=np.int64), list(map(len, names)))
    out = np.concatenate([np.zeros(0, np.int64), *names]) << 32 | owner
    out.sort()
    return out


def count_occupied(left: list[np.ndarray], right: list[np.ndarray], most: float) -> np.ndarray | None:
    """Counts of all left against all right maps, given the numbers of their occupied slots: those that agree meet, and
    count where either indicator is set. None where more than ``most`` would meet."""
    l, r = owned(left), owned(right)
    mine, theirs = l >> 32, r >> 32
    # Of agreeing slots those with the indicator come last; one without it counts against these only.
    start, end = np.searchsorted(theirs, mine ^ 1), np.searchsorted(theirs, mine | 1, side="right")
    if (end - start).sum() > most:
        return None
    return count_meetings(l, r, start, end, (len(left), len(right)))


def count_meetings(
    l: np.ndarray, r: np.ndarray, start: np.ndarray, end: np.ndarray, shape: tuple[int, int], rule: Callable[[np.ndarray, np.ndarray], np.ndarray] | None = None
) -> np.ndarray:
    """How often maps meet if slot i of ``l`` meets slots ``start[i]`` to ``end[i]`` of ``r``; those
    for which ``rule`` (given numbers of slots on both sides) is false don't count."""
    out = np.zeros(shape[0] * shape[1], np.int64)
    met = np.flatnonzero(end > start)
    row, other, start, n = (l[met] & 0xFFFFFFFF) * shape[1], r & 0xFFFFFFFF, start[met], (end - start)[met]
    ends = np.cumsum(n)
    at = 0
    while at < len(met):
        done = int(ends[at - 1]) if at else 0
        to = max(at + 1, int(np.searchsorted(ends, done + MEETINGS, side="right")))
        k = n[at:to]
        j = np.arange(int(ends[to - 1]) - done) + np.repeat(start[at:to] - (ends[at:to] - k - done), k)
        place = np.repeat(row[at:to], k) + other[j]
        if rule is not None:
            place = place[rule(np.repeat(met[at:to], k), j)]
        out += np.bincount(place, minlength=len(out))
        at = to
    return out.reshape(shape)


def slot_kernel(cfg: Config) -> Kernel:
    def kernel(left: list[bytes], right: list[bytes]) -> np.ndarray:
        out = np.zeros((len(left), len(right)), np.int64)
        classes = [(places, Matrix(words, cfg.slot_bits)) for places, words in _by_width(right)]
        for i, payload in enumerate(left):
            row = np.frombuffer(payload, np.uint64)
            for places, matrix in classes:
                out[i, places] = count_row(row, matrix, cfg.slice_bytes)
        return out

    return kernel


def compacted(slots: np.ndarray, log2_r: int, cfg: Config) -> bytes:
    """A map as its elements and the table of each one's later copy (which names the other), compressed: vacant
    slots and second copies take no room. ``expanded`` gives the same slots. Dense sets are two bits for each id of the
    segment, others differences with two bits an element."""
    codes, tables, bits = layout.decode(slots, log2_r, cfg)
    later = bits == 1
    t = tables[later]
    x = perm.inverses(cfg.segment, cfg.seed)[t, codes[later]]
    order = np.argsort(x)
    x, t = x[order], t[order]
    width = 2 if cfg.segment <= 1 << 16 else 4
    if len(x) * (8 * width + 2) > 2 * cfg.segment:
        state = np.zeros(cfg.segment, np.uint8)
        state[x] = t + 1
        kind, raw = 1, np.packbits(state & 1).tobytes() + np.packbits(state >> 1).tobytes()
    else:
        step = np.diff(x, prepend=0).astype(f"<u{width}")
        kind, raw = 0, step.view(np.uint8).reshape(-1, width).T.tobytes() + np.packbits(t & 1).tobytes() + np.packbits(t >> 1).tobytes()
    return bytes((log2_r, kind)) + len(x).to_bytes(4, "little") + len(raw).to_bytes(4, "little") + pa.compress(raw, codec="zstd", asbytes=True)


def _stored(blob: bytes, cfg: Config) -> tuple[int, np.ndarray, np.ndarray]:
    """``(log2_r, elements, tables of their later copies)`` of a compacted map."""
    log2_r, kind, n = blob[0], blob[1], int.from_bytes(blob[2:6], "little")
    raw = np.frombuffer(pa.decompress(blob[10:], int.from_bytes(blob[6:10], "little"), codec="zstd", asbytes=True), np.uint8)
    if kind:
        half = len(raw) // 2
        low, high = (np.unpackbits(p, count=cfg.segment) for p in (raw[:half], raw[half:]))
        state = low | high << 1
        x = np.flatnonzero(state)
        t = state[x].astype(np.int64) - 1
    else:
        width = 2 if cfg.segment <= 1 << 16 else 4
        x = np.cumsum(np.ascontiguousarray(raw[: n * width].reshape(width, n).T).reshape(-1).view(f"<u{width}"), dtype=np.int64)
        low, high = (np.unpackbits(p, count=n) for p in np.split(raw[n * width :], 2))
        t = (low | high << 1).astype(np.int64)
    return log2_r, x, t


def expanded(blob: bytes, cfg: Config) -> np.ndarray:
    """The slots of a compacted map."""
    log2_r, x, t = _stored(blob, cfg)
    slots = np.zeros(3 << log2_r, layout.KINDS[cfg.slot_bits])
    codes = perm.tables(cfg.segment, cfg.seed)
    for table, bit in ((t, 1), ((t + 2) % 3, 0)):
        code = codes[table, x].astype(np.int64)
        slots[layout.slot_of(code, table, 1 << log2_r, 1 << cfg.r0_bits)] = layout.encode(code, np.full(len(x), bit), cfg)
    return slots


def occupied(blob: bytes, cfg: Config) -> np.ndarray:
    """The numbers of the occupied slots of a compacted map (see ``_named``)."""
    _, x, t = _stored(blob, cfg)
    codes = perm.tables(cfg.segment, cfg.seed)
    tables, bits = np.concatenate([t, (t + 2) % 3]), np.repeat([1, 0], len(x))
    return _named(codes[tables, np.concatenate([x, x])].astype(np.int64), tables, bits, cfg)


def compact_kernel(cfg: Config) -> Kernel:
    """``slot_kernel`` on compacted maps. Of sparse maps the occupied slots meet; else maps are expanded, and a tile's
    bytes of slots are there at once on the right."""
    kernel = slot_kernel(cfg)
    size = lambda p: (3 << p[0]) * cfg.slot_bits // 8

    def dense(left: list[bytes], right: list[bytes]) -> np.ndarray:
        out, at = np.zeros((len(left), len(right)), np.int64), 0
        few = max(1, cfg.tile_bytes // max([1, *map(size, left)]))
        while at < len(right):
            end, room = at, cfg.tile_bytes
            while end < len(right) and (end == at or size(right[end]) <= room):
                room -= size(right[end])
                end += 1
            there = [expanded(p, cfg).tobytes() for p in right[at:end]]
            for i in range(0, len(left), few):
                out[i : i + few, at:end] = kernel([expanded(p, cfg).tobytes() for p in left[i : i + few]], there)
            at = end
        return out

    elements = lambda p: int.from_bytes(p[2:6], "little")

    def run(left: list[bytes], right: list[bytes]) -> np.ndarray:
        mine = np.sort(list(map(size, left)))
        named, held = None, 2 * sum(map(elements, left))
        out, at = np.zeros((len(left), len(right)), np.int64), 0
        while at < len(right):
            end, room = at, OCCUPIED_SLOTS - held
            while end < len(right) and (end == at or 2 * elements(right[end]) <= room):
                room -= 2 * elements(right[end])
                end += 1
            some, found = right[at:end], None
            wide = np.sort(list(map(size, some)))
            sums, below = np.append(0, np.cumsum(wide)), np.searchsorted(wide, mine)
            compared = float((mine * below + sums[-1] - sums[below]).sum())  # the wider of each two
            if room >= 0:
                named = named or [occupied(p, cfg) for p in left]
                found = count_occupied(named, [occupied(p, cfg) for p in some], compared / MEETING_BYTES)
            if found is None:
                end = len(right)
                found = dense(left, right[at:])
            out[:, at:end] = found
            at = end
        return out

    return run


def pack_words(x: np.ndarray) -> bytes:
    """Sorted positions of one segment as bitmap words of 64: those that aren't zero, then their 16-bit places."""
    place, first = np.unique(x >> 6, return_index=True)
    words = np.bitwise_or.reduceat(np.uint64(1) << (x & 63).astype(np.uint64), first) if len(x) else np.zeros(0, np.uint64)
    return words.tobytes() + place.astype(np.uint16).tobytes()


def _words(payloads: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Owner, place and word of all words of packed bitmaps."""
    n = np.array([len(p) // 10 for p in payloads], np.int64)
    words = np.concatenate([np.zeros(0, np.uint64), *(np.frombuffer(p, np.uint64, k) for p, k in zip(payloads, n.tolist()))])
    places = np.concatenate([np.zeros(0, np.uint16), *(np.frombuffer(p, np.uint16, k, 8 * k) for p, k in zip(payloads, n.tolist()))])
    return np.repeat(np.arange(len(payloads)), n), places.astype(np.int64), words


#: Bitmaps are compared whole if over one in so many of the words that any of them has aren't zero.
SPARSE_WORDS = 8


def bitmap_kernel(left: list[bytes], right: list[bytes]) -> np.ndarray:
    """``bitmap_counts`` as a matrix."""
    found = bitmap_counts(left, right, len(left))
    if isinstance(found, np.ndarray):
        return found
    out = np.zeros((len(left), len(right)), np.int64)
    out[found[:2]] = found[2]
    return out


def bitmap_counts(left: list[bytes], right: list[bytes], most: int = 512) -> np.ndarray | tuple[np.ndarray, np.ndarray, np.ndarray] | None:
    """One bit per transaction id: AND, then population count, of the words that either side has. Of sparse bitmaps the
    bytes that aren't zero meet, and only pairs with a count are returned; others make a matrix of ``most`` rows (else None)."""
    (lo, lp, lw), (ro, rp, rw) = _words(left), _words(right)
    used = np.intersect1d(lp, rp)
    (lo, lp, lw), (ro, rp, rw) = (tuple(c[np.isin(p, used)] for c in (o, p, w)) for o, p, w in ((lo, lp, lw), (ro, rp, rw)))
    if SPARSE_WORDS * (len(lw) + len(rw)) > len(used) * (len(left) + len(right)):
        if len(left) > most:
            return None
        out = np.zeros((len(left), len(right)), np.int64)
        rows, matrix = np.zeros((len(left), len(used)), np.uint64), np.zeros((len(right), len(used)), np.uint64)
        rows[lo, np.searchsorted(used, lp)], matrix[ro, np.searchsorted(used, rp)] = lw, rw
        for i, row in enumerate(rows):
            out[i] = np.bitwise_count(row & matrix).sum(axis=1, dtype=np.int64)
        return out
    (lo, lp, lw), (ro, rp, rw) = (_bytes(*side) for side in ((lo, lp, lw), (ro, rp, rw)))
    start, end = np.searchsorted(rp, lp), np.searchsorted(rp, lp, side="right")
    found, size, at, ends = [], 0, 0, np.cumsum(end - start)
    while at < len(lp):
        done = int(ends[at - 1]) if at else 0
        to = max(at + 1, int(np.searchsorted(ends, done + MEETINGS, side="right")))
        k = (end - start)[at:to]
        j = np.arange(int(ends[to - 1]) - done) + np.repeat(start[at:to] - (ends[at:to] - k - done), k)
        both = np.repeat(lw[at:to], k) & rw[j]
        some = np.flatnonzero(both)
        place = np.repeat(lo[at:to], k)[some] * len(right) + ro[j[some]]
        found.append((place, np.bitwise_count(both[some]).astype(np.int64)))
        size += len(some)
        if size > 2 * MEETINGS:
            found = [_added(found)]
            size = len(found[0][0]) // 2  # what is left may be all there is: it is added up again when it has grown
        at = to
    place, n = _added(found)
    return place // max(1, len(right)), place % max(1, len(right)), n


def _bytes(owner: np.ndarray, places: np.ndarray, words: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The bytes of words that aren't zero, in order of place: owners, places, bytes."""
    every = np.ascontiguousarray(words).view(np.uint8)
    at = np.flatnonzero(every)
    place = places[at >> 3] << 3 | at & 7
    order = np.argsort(place, kind="stable")
    return owner[at >> 3][order], place[order], every[at][order]


def _added(found: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """Numbers without repeats, in order, and the sums of their counts."""
    place, n = (np.concatenate([np.zeros(0, np.int64), *c]) for c in zip(*found)) if found else (np.zeros(0, np.int64),) * 2
    order = np.argsort(place)
    place, n = place[order], n[order]
    first = np.flatnonzero(np.diff(place, prepend=-1))
    return place[first], np.add.reduceat(n, first) if len(n) else n


def merge_np(a: np.ndarray, b: np.ndarray) -> int:
    """Common elements of two sorted arrays without repeats, by one merge."""
    both = np.concatenate([a, b])
    both.sort(kind="stable")  # two runs: a merge
    return int((both[1:] == both[:-1]).sum())


def merge_kernel(left: list[bytes], right: list[bytes]) -> np.ndarray:
    """Sorted 32-bit lists."""
    rows = [np.frombuffer(p, np.int32) for p in right]
    return np.array([[merge_np(np.frombuffer(p, np.int32), r) for r in rows] for p in left], np.int64).reshape(len(left), len(right))


def count(a: Column, b: Column, cfg: Config = Config()) -> Column:
    """Common elements of two map columns of one segment (null with a null)."""

    def counts(x: pa.Array, y: pa.Array) -> pa.Array:
        return pa.array([None if p is None or q is None else count_np(p, q, cfg) for p, q in zip(x.to_pylist(), y.to_pylist())], pa.int64())

    return F.arrow_udf(counts, "long")(a, b)


def elements_np(slots: bytes, log2_r: int, cfg: Config) -> np.ndarray:
    """The elements (positions in the segment) that one map holds, sorted."""
    codes, tables, bits = layout.decode(np.frombuffer(slots, layout.KINDS[cfg.slot_bits]), log2_r, cfg)
    once = bits == 1  # the later copy of each element
    return np.sort(perm.inverses(cfg.segment, cfg.seed)[tables[once], codes[once]])


def elements(maps: DataFrame, cfg: Config = Config()) -> DataFrame:
    """``(item, tid)`` of all elements that maps hold (failed ones aren't in them)."""

    def run(batches):
        for batch in batches:
            for row in batch.to_pylist():
                x = elements_np(row["slots"], row["log2_r"], cfg)
                base = np.full(len(x), row["seg"], np.int64) * cfg.segment  # wraps, and back, in the lowest segment of long
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(x), row["item"]), pa.int64()), pa.array(base + x, pa.int64())], ["item", "tid"])

    return maps.select("item", "seg", "log2_r", "slots").mapInArrow(run, "item long, tid long")


def held_np(slots: bytes, log2_r: int, x: np.ndarray, cfg: Config) -> np.ndarray:
    """Does one map hold the positions ``x``? Looks at three slots each."""
    values = np.frombuffer(slots, layout.KINDS[cfg.slot_bits]).astype(np.int64) & ((1 << (cfg.slot_bits - 1)) - 1)
    codes = perm.tables(cfg.segment, cfg.seed)[:, x].astype(np.int64)
    at = np.stack([layout.slot_of(codes[t], t, 1 << log2_r, 1 << cfg.r0_bits) for t in range(3)])
    return (values[at] == (codes >> cfg.shift) + 1).any(axis=0)


def contains(maps: DataFrame, probes: DataFrame, cfg: Config = Config()) -> DataFrame:
    """Distinct ``probes(item, tid)`` with ``found``: do the item's maps hold the id?

    Probes of one item and segment (at most a segment of them) meet their map once and look
    at the three slots of each id together. An item or a segment without a map holds
    nothing; failed elements aren't found here (join the failed log for them). Probes with
    a null are left out, repeated ones give one row."""

    def probe(slots: pa.Array, bits: pa.Array, tids: pa.Array) -> pa.Array:
        out = []
        for data, b, some in zip(slots, bits.to_pylist(), tids):
            x = np.asarray(some.values) % cfg.segment
            out.append(np.zeros(len(x), bool) if not data.is_valid else held_np(data.as_py(), b, x, cfg))
        ends = np.cumsum([0, *map(len, out)]).astype(np.int32)
        return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate([np.zeros(0, bool), *out]), pa.bool_()))

    known = probes.where("item IS NOT NULL AND tid IS NOT NULL")
    placed = known.groupBy("item", segment_of("tid", cfg.segment).alias("seg")).agg(F.collect_set("tid").alias("tids"))
    joined = placed.join(maps.select("item", "seg", "log2_r", "slots"), ["item", "seg"], "left")
    answered = joined.select("item", "tids", F.arrow_udf(probe, "array<boolean>")("slots", "log2_r", "tids").alias("found"))
    return answered.select("item", F.explode(F.arrays_zip("tids", "found")).alias("p")).select("item", F.col("p.tids").alias("tid"), "p.found")
