"""Building twin-slot maps: batch placement of two copies of every element.

Sets are placed many at a time. In each round every homeless copy tries the slot of its next
table; one copy wins a slot and turns out whoever sat there, and all others go on to the
table after. Copies of one element never share a table, because a copy that meets its twin
goes on. After the last round an element with a homeless copy loses both and is logged
as failed; every other element then sits in exactly two of its three slots.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import Config
from ..functions import layout, perm
from ..schema import require
from ..sources.incidence import DISTINCT_SEGMENT, packed, repacked, rows_of_sets, segmented
from ..stages import cut

SLOTS_AT_ONCE = 4 << 20


@dataclass
class Placement:
    """Slot values of several sets in a row, failed elements, and counters (moves of each set)."""

    slots: np.ndarray
    failed: np.ndarray
    moves: np.ndarray
    rounds: int


def place(sets: np.ndarray, x: np.ndarray, starts: np.ndarray, log2_r: np.ndarray, cfg: Config, max_rounds: int | None = None) -> Placement:
    """Place elements ``x`` of sets ``sets`` (numbers from 0); set k has slots from
    ``starts[k]`` and range ``2 ** log2_r[k]``. Deterministic for a given order of elements."""
    r0, domain = 1 << cfg.r0_bits, cfg.segment
    n, total = len(x), int((3 << log2_r.astype(np.int64)).sum()) if len(log2_r) else 0
    codes = np.stack([perm.permute_np(x, t, domain, cfg.seed) for t in range(3)]).astype(np.int64) if n else np.zeros((3, 0), np.int64)
    r = np.int64(1) << log2_r.astype(np.int64)[sets]
    where = np.stack([starts[sets] + layout.slot_of(codes[t], t, r, r0) for t in range(3)]) if n else codes
    holder = np.full(total, -1, np.int64)  # copy number: 2 * element + 0 or 1
    at = np.full(2 * n, -1, np.int8)  # the table a copy sits in
    homeless = np.arange(2 * n)
    target = np.tile(np.array([0, 1], np.int8), n)
    moves, rounds = np.zeros(len(starts), np.int64), 0
    limit = cfg.max_rounds if max_rounds is None else max_rounds
    while len(homeless) and rounds < limit:
        rounds += 1
        goal = target[homeless]
        goal = np.where(at[homeless ^ 1] == goal, (goal + 1) % 3, goal)  # the twin is there
        slot = where[goal, homeless >> 1]
        order = np.argsort(slot, kind="stable")
        first = np.ones(len(order), bool)
        first[1:] = slot[order[1:]] != slot[order[:-1]]
        win, lose = order[first], order[~first]
        out = holder[slot[win]]
        out = out[out >= 0]
        target[out] = (at[out] + 1) % 3
        at[out] = -1
        holder[slot[win]] = homeless[win]
        at[homeless[win]] = goal[win]
        target[homeless[lose]] = (goal[lose] + 1) % 3
        moves += np.bincount(sets[homeless[win] >> 1], minlength=len(starts))
        homeless = np.sort(np.concatenate([homeless[lose], out]))
    bad = np.unique(homeless >> 1)
    if len(bad):
        gone = np.concatenate([2 * bad, 2 * bad + 1])
        gone = gone[at[gone] >= 0]
        holder[where[at[gone], gone >> 1]] = -1
    slots = np.zeros(total, layout.KINDS[cfg.slot_bits])
    full = np.flatnonzero(holder >= 0)
    copies = holder[full]
    t, other = at[copies], at[copies ^ 1]
    slots[full] = layout.encode(codes[t, copies >> 1], layout.indicator(t, other), cfg)
    return Placement(slots, bad, moves, rounds)


def build_arrays(item: np.ndarray, seg: np.ndarray, x: np.ndarray, cfg: Config):
    """Maps of all sets in arrays sorted by (item, seg, x): yields, set by set,
    ``(first row, rows, log2_r, slot values, failed rows, moves)``."""
    if not len(item):
        return
    new = np.ones(len(item), bool)
    new[1:] = (item[1:] != item[:-1]) | (seg[1:] != seg[:-1])
    first = np.flatnonzero(new)
    count = np.diff(np.append(first, len(item)))
    bits = layout.range_bits(count, cfg)
    width = 3 << bits
    at = 0
    while at < len(first):  # as many sets as fit the working memory
        end = at + max(1, int(np.searchsorted(np.cumsum(width[at:]), SLOTS_AT_ONCE, side="right")))
        rows = slice(first[at], first[end] if end < len(first) else len(item))
        starts = np.concatenate(([0], np.cumsum(width[at:end])))
        sets = np.repeat(np.arange(end - at), count[at:end])
        done = place(sets, x[rows], starts[:-1], bits[at:end], cfg)
        failed_of = sets[done.failed] if len(done.failed) else done.failed
        for k in range(end - at):
            mine = done.failed[failed_of == k] + first[at] if len(done.failed) else done.failed
            yield first[at + k], count[at + k], int(bits[at + k]), done.slots[starts[k] : starts[k + 1]], mine, int(done.moves[k])
        at = end


BUILT = "item long, seg long, card int, log2_r int, slots binary, failed long, moves long"


def build(inc: DataFrame, cfg: Config = Config(), sets: DataFrame | None = None, compact: bool = False) -> DataFrame:
    """Maps and failed elements in one relation: a map has ``slots``, a failed element has
    its transaction id in ``failed`` (item and seg in both).

    Many sets share a task's call: sets are hashed to buckets of about
    ``cfg.bucket_elements`` elements. A set of one segment has at most a segment of elements.
    ``sets`` are the packed sets of ``inc`` where the caller has them. ``compact`` puts the short form of
    ``compare.compacted`` in the place of slots.
    """
    from . import compare

    require(inc, "item", "tid")
    rows = repacked(sets, DISTINCT_SEGMENT, cfg.segment) if sets is not None else packed(segmented(inc, cfg.segment))
    total = (sets.agg(F.sum("n")).first()[0] or 0) if sets is not None else inc.count()
    buckets = max(1, -(-total // cfg.bucket_elements))

    def run(table: pa.Table) -> pa.Table:
        item, seg, x = rows_of_sets(table)
        order = np.lexsort((x, seg, item))
        item, seg, x = item[order], seg[order], x[order]
        tid = seg * np.int64(cfg.segment) + x  # wraps, and back, in the lowest segment of long
        out = []
        for lo, n, bits, slots, bad, moves in build_arrays(item, seg, x, cfg):
            stored = compare.compacted(slots, bits, cfg) if compact else slots.tobytes()
            out.append((item[lo], seg[lo], n, bits, stored, None, moves))
            out += [(item[b], seg[b], None, None, None, tid[b], None) for b in bad]
        kinds = (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary(), pa.int64(), pa.int64())
        names = [c.split()[0] for c in BUILT.split(", ")]
        columns = list(zip(*out)) or [()] * len(kinds)
        return pa.Table.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds)], names=names)

    bucket = F.pmod(F.xxhash64("item", "seg"), F.lit(buckets)).cast("int")
    return cut(rows.groupBy(bucket.alias("bucket")).applyInArrow(run, BUILT), "maps", "none" if compact else "zstd")


def maps_of(built: DataFrame) -> DataFrame:
    return built.where("slots IS NOT NULL").select("item", "seg", "card", "log2_r", "slots")


def failed_of(built: DataFrame) -> DataFrame:
    return built.where("failed IS NOT NULL").select("item", F.col("failed").alias("tid"))


def build_maps(inc: DataFrame, cfg: Config = Config()) -> DataFrame:
    """``(item, seg, card, log2_r, slots)``; ``card`` counts failed elements too."""
    return maps_of(build(inc, cfg))


def failed(inc: DataFrame, cfg: Config = Config()) -> DataFrame:
    """``(item, tid)`` of elements that found no two places."""
    return failed_of(build(inc, cfg))
