"""More than two sets: itemsets, d of d+1 tables, anchor counting, general redundancy."""

from __future__ import annotations

from dataclasses import dataclass
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import Config
from ..functions import perm
from ..sources.incidence import places_of, segmented, whole_sets, written
from ..stages import cut
from . import compare, pairs, repair


@dataclass(frozen=True)
class Redundancy:
    """Every element is in ``copies`` of ``tables`` tables: 2 of 3 for pairs, d of 2d - 1 in
    general, d of d + 1 so that up to d sets share a table."""

    copies: int
    tables: int

    @property
    def masks(self) -> list[int]:
        return [sum(1 << t for t in chosen) for chosen in combinations(range(self.tables), self.copies)]


def _places(x: np.ndarray, red: Redundancy, bits: int, cfg: Config) -> np.ndarray:
    return (perm.tables(cfg.segment, cfg.seed, red.tables)[:, x] & ((1 << bits) - 1)).astype(np.int64)


def assign(x: np.ndarray, red: Redundancy, bits: int, cfg: Config, max_rounds: int = 60) -> np.ndarray:
    """The tables of each element of one set, as bits; zero for elements that found too few places."""
    return assign_sets([x], red, [bits], cfg, max_rounds)[0]


#: Elements that are assigned at once.
ASSIGNED = 1 << 16


def assign_each(sets: list[np.ndarray], red: Redundancy, bits_of, cfg: Config, max_rounds: int = 60) -> list[np.ndarray]:
    """``assign`` of many sets, as many at once as have some ten thousand elements."""
    out, at = [], 0
    while at < len(sets):
        end, size = at + 1, len(sets[at])
        while end < len(sets) and size + len(sets[end]) <= ASSIGNED:
            size += len(sets[end])
            end += 1
        out += assign_sets(sets[at:end], red, [bits_of(len(x)) for x in sets[at:end]], cfg, max_rounds)
        at = end
    return out


def assign_sets(sets: list[np.ndarray], red: Redundancy, bits: list[int], cfg: Config, max_rounds: int = 60) -> list[np.ndarray]:
    """``assign`` of several sets, each in tables of its own; one doesn't change what another gets."""
    sizes, ranges = [len(x) for x in sets], [1 << b for b in bits]
    x = np.concatenate([np.zeros(0, np.int64), *sets])
    n, first = len(x), np.repeat(np.cumsum(ranges) - ranges, sizes)
    where = (perm.tables(cfg.segment, cfg.seed, red.tables)[:, x] & (np.repeat(ranges, sizes) - 1)).astype(np.int64) + first
    holder = np.full((red.tables, sum(ranges)), -1, np.int32)
    has, held = np.zeros((red.tables, n), bool), np.zeros(n, np.int8)
    turn = (np.arange(n) - np.repeat(np.cumsum(sizes) - sizes, sizes)) % red.tables
    for _ in range(max_rounds):
        short = np.flatnonzero(held < red.copies)
        if not len(short):
            break
        for t in range(red.tables):  # one table at a time: each short element whose turn it is
            mine = short[(turn[short] == t) & ~has[t, short]]
            slots, at = np.unique(where[t, mine], return_index=True)
            win = mine[at]
            out = holder[t, slots]
            out = out[out >= 0]
            has[t, out] = False
            held[out] -= 1
            turn[out] = (t + 1) % red.tables
            holder[t, slots] = win
            has[t, win] = True
            held[win] += 1
        turn[short] = (turn[short] + 1) % red.tables
    has[:, held != red.copies] = False
    return np.split((has * (1 << np.arange(red.tables))[:, None]).sum(axis=0), np.cumsum(sizes)[:-1])


def spread(x: np.ndarray, mask: np.ndarray, red: Redundancy, bits: int, cfg: Config) -> tuple[np.ndarray, np.ndarray]:
    """Tables ``values[t, slot]`` (element + 1, zero vacant) and ``masks[t, slot]`` (the tables of
    that element) of assigned elements."""
    values, masks = (np.zeros((red.tables, 1 << bits), np.int64) for _ in range(2))
    where = _places(x, red, bits, cfg)
    for t in range(red.tables):
        at = np.flatnonzero(mask >> t & 1)
        values[t, where[t, at]] = x[at] + 1
        masks[t, where[t, at]] = mask[at]
    return values, masks


def place(x: np.ndarray, red: Redundancy, bits: int, cfg: Config, max_rounds: int = 60) -> tuple[np.ndarray, np.ndarray]:
    """Both tables of one set; elements that found too few places are missing from both."""
    return spread(x, assign(x, red, bits, cfg, max_rounds), red, bits, cfg)


def witnesses(sets: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
    """Elements common to all sets, each once: a slot counts where all values agree and its
    table is the lowest that no set leaves out for this element."""
    r = max(v.shape[1] for v, _ in sets)
    wide = [(np.tile(v, r // v.shape[1]), np.tile(m, r // m.shape[1])) for v, m in sets]
    value, mask = wide[0][0].copy(), wide[0][1].copy()
    same = value > 0
    for v, m in wide[1:]:
        same &= v == value
        mask &= m
    t = np.arange(value.shape[0])[:, None]
    lowest = (mask & -mask) == (1 << t)
    return np.unique(value[same & lowest]) - 1


def _bits_of(red: Redundancy):
    """log2 of the range of a set of n elements."""
    return lambda n: max(6, int(2 * n * max(2, red.copies) - 1).bit_length())


def count(inc: DataFrame, itemsets: DataFrame, d: int, redundancy: Redundancy | None = None, cfg: Config = Config()) -> DataFrame:
    """``itemsets(items)`` of up to ``d`` items with their ``support``, from d of d + 1 layouts.

    Each set's elements are assigned to tables once; elements and assignment are written and
    joined to the itemsets that hold the set (half more bytes than its list; the tables themselves, with
    their vacant slots, would be tens of times more), and spread out where they meet. Ranges grow with the
    number of copies. Elements that found too few places are evaluated exactly: the sets that
    hold them are looked at. Supports of zero are reported."""
    red = redundancy or Redundancy(d, d + 1)
    if d * (red.tables - red.copies) >= red.tables:
        raise ValueError(f"{d} sets in {red.copies} of {red.tables} tables may have no table in common")
    if red.tables > 16:
        raise ValueError("an assignment is stored in 16 bits, so there are 16 tables at most")
    wanted = cut(itemsets.select(F.array_sort(F.array_distinct("items")).alias("items")).distinct(), "itemsets")
    members = wanted.select("items", F.explode("items").alias("item"))
    rows = segmented(inc.join(members.select("item").distinct(), "item", "left_semi"), cfg.segment)
    sets = rows.groupBy("item", "seg").agg(F.array_sort(F.collect_set("x")).alias("xs"))  # at most a segment each

    bits_of = _bits_of(red)

    def lay(xs: pa.Array) -> pa.Array:
        out = []
        lists = [np.asarray(one.values).astype(np.int64) for one in xs]
        for x, mask in zip(lists, assign_each(lists, red, bits_of, cfg)):
            out.append((x.astype("<i4").tobytes(), mask.astype("<u2").tobytes()))
        return pa.StructArray.from_arrays([pa.array(c, pa.binary()) for c in (zip(*out) if out else ((), ()))], ["x", "m"])

    layouts = cut(sets.select("item", "seg", F.arrow_udf(lay, "x binary, m binary")("xs").alias("s")), "layouts")

    def common(groups: pa.Array) -> pa.Array:
        out = []
        for group in groups:
            made, lists, lost = [], [], []
            for s in group.as_py():
                x, mask = np.frombuffer(s["x"], "<i4").astype(np.int64), np.frombuffer(s["m"], "<u2").astype(np.int64)
                made.append(spread(x, mask, red, bits_of(len(x)), cfg))
                lists.append(x)
                lost.append(x[mask == 0])
            again = np.unique(np.concatenate(lost))  # failed in some set: look at the sets themselves
            for x in lists if len(again) else ():
                again = np.intersect1d(again, x, assume_unique=True)
            out.append(len(witnesses(made)) + len(again))
        return pa.array(out, pa.int64())

    met = members.join(layouts, "item").groupBy("items", "seg").agg(F.collect_list("s").alias("sets"))  # at most d sets each
    full = met.where(F.size("sets") == F.size("items"))
    counted = full.select("items", F.arrow_udf(common, "long")("sets").alias("n")).groupBy("items").agg(F.sum("n").alias("support"))
    return wanted.join(counted, "items", "left").select("items", F.coalesce("support", F.lit(0)).cast("long").alias("support"))


def _rights(payloads: list[tuple[np.ndarray, np.ndarray]], red: Redundancy, bits: int, cfg: Config) -> tuple[np.ndarray, np.ndarray]:
    """Slot by set: elements + 1 (zero is vacant), and those tables of an element that come before the slot's."""
    value = np.zeros((red.tables << bits, len(payloads)), np.uint16 if cfg.segment < 1 << 16 else np.uint32)
    lower = np.zeros(value.shape, np.uint16)
    for k, (x, mask) in enumerate(payloads):
        where = _places(x, red, bits, cfg)
        for t in range(red.tables):
            at = np.flatnonzero(mask >> t & 1)
            value[(t << bits) + where[t, at], k] = x[at] + 1
            lower[(t << bits) + where[t, at], k] = mask[at] & ((1 << t) - 1)
    return value, lower


#: Slots of a map that are compared at once with a block of others.
SLOTS_AT_ONCE = 512

#: A meeting of two occupied slots costs as much as so many comparisons of facing slots.
SLOTS_A_MEETING = 8


def pair_kernel(red: Redundancy, bits_of, cfg: Config):
    """Counts of all left against all right layouts (places, then tables, of the elements of one set; no tables: none counts).

    The rule of ``witnesses`` for two sets: a place counts where both hold one element and its table is the lowest that both
    use for it. Occupied slots of one table and element meet (they face each other whatever the ranges); where that would be more
    work, each occupied slot of the left map is compared with a row of facing slots, by their own range on the right."""

    def laid(payload: bytes) -> tuple[np.ndarray, np.ndarray]:
        n = len(payload) // 6
        return np.frombuffer(payload, "<i4", n).astype(np.int64), np.frombuffer(payload, "<u2", n, 4 * n).astype(np.int64)

    def dense(left: list[bytes], right: list[bytes]) -> np.ndarray:
        out = np.zeros((len(left), len(right)), np.int64)
        wide = np.array([bits_of(len(p) // 6) for p in right], np.int64)
        lefts = [laid(p) for p in left]
        for bits in np.unique(wide).tolist():
            mine = np.flatnonzero(wide == bits)
            value, lower = _rights([laid(right[j]) for j in mine], red, bits, cfg)
            for i, (x, mask) in enumerate(lefts):
                where = _places(x, red, bits, cfg)
                t, at = np.nonzero(mask >> np.arange(red.tables)[:, None] & 1)
                slot, want, low = (t << bits) + where[t, at], (x[at] + 1).astype(value.dtype)[:, None], (mask[at] & ((1 << t) - 1)).astype(np.uint16)[:, None]
                for k in range(0, len(slot), SLOTS_AT_ONCE):
                    some = slice(k, k + SLOTS_AT_ONCE)
                    hit = (value[slot[some]] == want[some]) & (lower[slot[some]] & low[some] == 0)
                    out[i, mine] += hit.sum(axis=0, dtype=np.int32)
        return out

    def occupied(payload: bytes) -> np.ndarray:
        """Numbers of the occupied slots: table and element, then the tables before it that the element uses."""
        x, mask = laid(payload)
        t, at = np.nonzero(mask >> np.arange(red.tables)[:, None] & 1)
        return (t * cfg.segment + x[at]) << red.tables | mask[at] & ((1 << t) - 1)

    def met(left: list[np.ndarray], right: list[np.ndarray], most: float) -> np.ndarray | None:
        l, r = compare.owned(left), compare.owned(right)
        slots = [n >> 32 + red.tables for n in (l, r)]
        start, end = np.searchsorted(slots[1], slots[0]), np.searchsorted(slots[1], slots[0], side="right")
        if (end - start).sum() > most:
            return None
        lower = lambda n: n >> 32 & ((1 << red.tables) - 1)
        return compare.count_meetings(l, r, start, end, (len(left), len(right)), lambda i, j: lower(l)[i] & lower(r)[j] == 0)

    def kernel(left: list[bytes], right: list[bytes]) -> np.ndarray:
        held = lambda side: red.copies * sum(len(p) // 6 for p in side)
        if red.tables * cfg.segment << red.tables < 1 << 31 and held(left) + held(right) <= compare.OCCUPIED_SLOTS:
            found = met([occupied(p) for p in left], [occupied(p) for p in right], held(left) * len(right) / SLOTS_A_MEETING)
            if found is not None:
                return found
        return dense(left, right)

    return kernel


def pair_support(inc: DataFrame, redundancy: Redundancy, min_support: int = 1, cfg: Config = Config(), max_rounds: int = 60) -> DataFrame:
    """``(item_a, item_b, support)`` of all pairs with ``support >= max(1, min_support)`` from maps of general redundancy.

    Sets travel as elements and assignment (six bytes an element) to the tiles of their segment, where each is spread
    out once and meets all others; no itemset is listed. Pairs with an element that found too few places count it from ``inc``."""
    red = redundancy
    if 2 * (red.tables - red.copies) >= red.tables or red.tables > 16:
        raise ValueError("two sets need a table in common, and there are 16 tables at most")
    bits_of = _bits_of(red)
    rows = written(inc.select("item", "tid") if inc.columns != ["item", "tid"] else inc, "incidence")
    sets = whole_sets(rows, cfg.segment)  # at most a segment each

    def lay(xs: pa.Array, ws: pa.Array) -> pa.Array:
        out = []
        lists = [places_of(*one).astype(np.int64) for one in zip(xs.to_pylist(), ws.to_pylist())]
        for x, mask in zip(lists, assign_each(lists, red, bits_of, cfg, max_rounds)):
            out.append((x.astype("<i4").tobytes() + mask.astype("<u2").tobytes(), x[mask == 0].astype("<i4").tolist()))
        return pa.StructArray.from_arrays([pa.array(c, k) for c, k in zip(zip(*out) if out else ((), ()), (pa.binary(), pa.list_(pa.int32())))], ["payload", "lost"])

    laid = cut(sets.select("item", "seg", F.arrow_udf(lay, "payload binary, lost array<int>")("xs", "ws").alias("s")).select("item", "seg", "s.*"), "layouts", "zstd")
    tid = F.col("seg") * F.lit(cfg.segment).cast("long") + F.col("x")
    lost = laid.where("size(lost) > 0").select("item", "seg", F.explode("lost").alias("x")).select("item", tid.alias("tid"))
    more = repair.side_pairs(cut(lost, "lost"), rows)
    return pairs.tiled_counts(laid.select("item", "seg", "payload"), pair_kernel(red, bits_of, cfg), cfg, more, least=max(1, min_support), inc=rows)


def count_anchor(inc: DataFrame, itemsets: DataFrame, cfg: Config = Config()) -> DataFrame:
    """The same supports from ordinary two-of-three maps: the first set is the anchor, hits
    of its slots in the other maps are added up under the rule of pair counting, and an
    element of which the two copies have one hit per other set is in all of them."""
    from ..functions import layout
    from . import builder

    wanted = cut(itemsets.select(F.array_sort(F.array_distinct("items")).alias("items")).distinct(), "itemsets")
    members = wanted.select("items", F.explode("items").alias("item"))
    needed = cut(inc.join(members.select("item").distinct(), "item", "left_semi"), "needed")
    built = builder.build(needed, cfg)
    top = 1 << (cfg.slot_bits - 1)

    def hit(groups: pa.Array) -> pa.Array:
        out = []
        for group in groups:
            rows = sorted(group.as_py(), key=lambda row: row["item"])
            anchor = np.frombuffer(rows[0]["slots"], layout.KINDS[cfg.slot_bits])
            hits = np.zeros(len(anchor), np.int64)
            for row in rows[1:]:
                other = np.frombuffer(row["slots"], layout.KINDS[cfg.slot_bits])
                a = anchor[None, :] if len(other) >= len(anchor) else anchor.reshape(-1, len(other))
                b = other.reshape(-1, len(anchor)) if len(other) >= len(anchor) else other[None, :]
                rule = ((a ^ b) & (top - 1) == 0) & ((a | b) & top != 0)
                hits += rule.sum(axis=0) if len(other) >= len(anchor) else rule.ravel()
            at = np.flatnonzero(anchor)
            codes, tables, _ = layout.decode(anchor, rows[0]["log2_r"], cfg)
            element = perm.inverses(cfg.segment, cfg.seed)[tables, codes]
            held, back = np.unique(element, return_inverse=True)
            total = np.bincount(back, weights=hits[at], minlength=len(held))
            out.append(int((total == len(rows) - 1).sum()) if len(rows) > 1 else len(held))
        return pa.array(out, pa.int64())

    met = members.join(builder.maps_of(built), "item").groupBy("items", "seg").agg(F.collect_list(F.struct("item", "log2_r", "slots")).alias("maps"))
    full = met.where(F.size("maps") == F.size("items"))  # at most an itemset's maps each
    counted = full.select("items", F.arrow_udf(hit, "long")("maps").alias("support"))
    lost = builder.failed_of(built)
    again = lost.select("tid").distinct().join(needed, "tid").join(members, "item").groupBy("items", "tid").agg(F.count_distinct("item").alias("n"))
    touched = lost.join(members, "item").select("items", "tid").distinct()
    more = again.join(touched, ["items", "tid"], "left_semi").where(F.col("n") == F.size("items")).groupBy("items").agg(F.count("*").alias("support"))
    sums = counted.unionByName(more).groupBy("items").agg(F.sum("support").alias("support"))
    return wanted.join(sums, "items", "left").select("items", F.coalesce("support", F.lit(0)).cast("long").alias("support"))


def itemsets(inc: DataFrame, min_support: int, max_size: int = 3, method: str = "tables", cfg: Config = Config()) -> DataFrame:
    """Frequent itemsets of 2 to ``max_size`` items: frequent pairs from maps, candidates by
    joining sets that share all but their last item, supports by ``method`` (tables: d of
    d + 1; anchor: two-of-three maps)."""
    inc = cut(pairs.prune(inc, min_support), "incidence")
    found = pairs.pair_support(inc, min_support=min_support, cfg=cfg).select(F.array("item_a", "item_b").alias("items"), "support")
    levels = [cut(found, "level")]
    for k in range(3, max_size + 1):
        last = levels[-1].select("items")
        a = last.select(F.slice("items", 1, k - 2).alias("head"), F.element_at("items", -1).alias("x"))
        b = last.select(F.slice("items", 1, k - 2).alias("head"), F.element_at("items", -1).alias("y"))
        made = a.join(b, "head").where("x < y").select(F.concat("head", F.array("x", "y")).alias("items"))
        holes = made.select("items", F.explode(F.sequence(F.lit(1), F.lit(k))).alias("hole"))
        subset = F.expr("filter(items, (v, i) -> i <> hole - 1)")
        good = holes.select("items", subset.alias("sub")).join(last.withColumnRenamed("items", "sub"), "sub", "left_semi")
        made = good.groupBy("items").count().where(F.col("count") == k).select("items")
        counted = count(inc, made, k, cfg=cfg) if method == "tables" else count_anchor(inc, made, cfg)
        levels.append(cut(counted.where(F.col("support") >= min_support), "level"))
    out = levels[0]
    for level in levels[1:]:
        out = out.unionByName(level)
    return out
