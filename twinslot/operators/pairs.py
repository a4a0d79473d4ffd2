"""Supports of item pairs from one payload per item and segment, tile by tile."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..config import Config
from ..schema import require
from ..sources.incidence import dense_ids, of_sets, sets_of
from ..stages import cut, discard
from . import builder, compare, partial, repair

TILE = "item_a long, item_b long, support long"


def prune(inc: DataFrame, min_support: int) -> DataFrame:
    """Rows of items that occur in ``min_support`` transactions or more."""
    if min_support <= 1:
        return inc
    # Written, so that the shuffles that made ``inc`` for it are gone when its rows are made.
    frequent = cut(inc.groupBy("item").agg(F.count("*").alias("n")).where(F.col("n") >= min_support).select("item"), "frequent")
    return inc.join(frequent, "item", "left_semi")


def _kept_sets(inc: DataFrame, min_support: int) -> DataFrame:
    """``prune`` on packed sets, written."""
    sets = cut(sets_of(inc), "incidence", "zstd")
    if min_support <= 1:
        return sets
    frequent = cut(sets.groupBy("item").agg(F.sum("n").alias("n")).where(F.col("n") >= min_support).select("item"), "frequent")
    kept = cut(sets.join(frequent, "item", "left_semi"), "incidence", "zstd")
    discard(sets)
    return kept


def kept(inc: DataFrame, min_support: int) -> DataFrame:
    """``prune`` of an incidence of longs, written as packed sets."""
    return of_sets(_kept_sets(inc, min_support))


def rank_by_width(payloads: DataFrame, sort_by_width: bool = True) -> DataFrame:
    """``(item, id)``: dense rank of items by their widest payload (then by item)."""
    widest = payloads.groupBy("item").agg(F.max(F.length("payload")).alias("width"))
    keys = ("width", "item") if sort_by_width else ("item",)
    return dense_ids(widest, *keys).select("item", "width", "id")


def block_count(items: int, cfg: Config) -> int:
    return max(1, -(-items // cfg.tile_items))


def _blocks(payloads: DataFrame, cfg: Config) -> tuple[DataFrame, int]:
    """``(item, block)`` and the number of blocks, small enough for a tile's memory.

    Items are in order of width, so a block's size follows the widths around it: each power
    of two of widths has its own number of items a block, and neighbouring powers share a block as
    long as they fit one. Without the order all blocks are as small as the widest map needs."""
    ranked = cut(rank_by_width(payloads, cfg.sort_by_width), "ranks")
    power = (F.length(F.bin(F.col("width").cast("long"))) if cfg.sort_by_width else F.lit(0)).alias("power")
    rows = ranked.groupBy(power).agg(F.count("*").alias("n"), F.max("width").alias("w")).orderBy("power").collect()  # 32 at most
    groups: list[list[int]] = []  # items and widest map
    for _, n, w in rows:
        n, w = n, max(1, w)
        if groups and groups[-1][0] + n <= cfg.tile_items and (groups[-1][0] + n) * w <= cfg.tile_bytes:
            groups[-1] = [groups[-1][0] + n, w]
        else:
            groups.append([n, w])
    block, first, blocks = F.lit(0).cast("int"), 0, 0
    for n, w in groups:
        size = max(1, min(cfg.tile_items, cfg.tile_bytes // w))
        here = F.expr(f"cast((id - {first}) div {size} + {blocks} as int)")
        block = F.when(F.col("id") >= first, here).otherwise(block)
        first, blocks = first + n, blocks + -(-n // size)
    return ranked.select("item", block.alias("block")), blocks


#: Maps and bytes of a segment that one task may hold.
SEGMENT_ITEMS, SEGMENT_BYTES = 4096, 128 << 20

#: A side of a tile grows to so many times ``Config.tile_items`` while there are enough tiles for
#: the cores, since each doubling halves what is shuffled; so many tiles for each core are enough.
GROWTH, TILES_A_CORE = 4, 4

#: Where more than so many times the payloads would be shuffled, a tile for each core is enough.
SENT_TIMES = 3

#: A hash is a fraction of this.
FRACTIONS = 1 << 20


def _segment_blocks(payloads: DataFrame, cfg: Config) -> DataFrame:
    """``payloads`` with ``block`` and ``blocks``, the number of them in its segment."""
    return _placed(payloads, cfg)[0]


def _placed(payloads: DataFrame, cfg: Config) -> tuple[DataFrame, int]:
    """``_segment_blocks``, and the number of pairs that meet.

    Only maps of one segment meet, so each segment has its own blocks, as many as its own maps
    need: items that share no segment cost each other nothing. Within a segment blocks go by width: each power of two of
    widths has a stretch of them as long as its maps and bytes ask for, and hashes spread its items over it.
    The driver sees one row; there is a row for each segment and power."""
    power = (F.length(F.bin(F.length("payload").cast("long"))) if cfg.sort_by_width else F.lit(0)).cast("int")
    sized = payloads.withColumn("power", power)
    per = cut(sized.groupBy("seg", "power").agg(F.count("*").alias("n"), F.sum(F.length("payload")).alias("bytes")), "segments")
    whole = per.groupBy("seg").agg(F.sum("n").alias("n"), F.sum("bytes").alias("bytes"))
    met = whole.agg(F.sum(F.col("n").cast("decimal(38,0)") * (F.col("n") - 1) / 2)).first()[0] or 0
    one = cfg.distribution == "segments"
    if one:
        n, widest = whole.agg(F.max("n"), F.max("bytes")).first()
        if n is not None and (n > SEGMENT_ITEMS or widest > SEGMENT_BYTES):
            raise ValueError(f"a segment of {n} maps and {widest} bytes is too much for a task; use tiles")
    room = lambda k: F.greatest(F.col("n") / (cfg.tile_items * k), F.col("bytes") / (cfg.tile_bytes * min(k, 2)))
    grown = 1
    if cfg.distribution == "auto":
        tried = [1 << i for i in range(GROWTH.bit_length())]
        tiles_of = lambda k: F.sum(F.ceil(room(k)) * (F.ceil(room(k)) + 1) / 2).alias(f"k{k}")
        sent_of = lambda k: (F.sum(F.col("bytes") * F.ceil(room(k))) / F.sum("bytes")).alias(f"s{k}")
        made = whole.agg(*map(tiles_of, tried), *map(sent_of, tried)).first()
        cores = payloads.sparkSession.sparkContext.defaultParallelism
        grown = max((k for k in tried if (made[f"k{k}"] or 0) >= TILES_A_CORE * cores), default=1)
        if (made[f"s{grown}"] or 0) > SENT_TIMES:
            grown = max((k for k in tried if k >= grown and made[f"k{k}"] >= cores), default=grown)
    before = Window.partitionBy("seg").orderBy("power").rowsBetween(Window.unboundedPreceding, -1)
    needs = per.select("seg", "power", room(grown).alias("need"))
    placed = needs.withColumn("first", F.coalesce(F.sum("need").over(before), F.lit(0.0))).withColumn("all", F.sum("need").over(Window.partitionBy("seg")))
    blocks = F.lit(1) if one else F.greatest(F.ceil("all"), F.lit(1)).cast("int")
    known = cut(placed.select("seg", "power", "need", "first", "all", blocks.alias("blocks")), "segment-blocks")
    at = (F.col("first") + F.col("need") * F.pmod(F.xxhash64("item"), F.lit(FRACTIONS)) / FRACTIONS) / F.col("all") * F.col("blocks")
    block = F.least(F.floor(at).cast("int"), F.col("blocks") - 1)
    return sized.join(known, ["seg", "power"]).select("item", "seg", "payload", block.alias("block"), "blocks"), int(met)


def _tile(kernel: compare.Kernel, same_family: bool, cfg: Config, buckets: int = 0, at_once: int = 0):
    """Counts of a tile's pairs, as rows or packed for ``buckets``. A kernel sees ``at_once`` rows if it takes more than the tile plan's."""

    def run(table: pa.Table) -> pa.Table:
        side = table.column("side").to_numpy()
        items, payloads = table.column("item").to_numpy(), table.column("payload").to_pylist()
        p, q = table.column("p")[0].as_py(), table.column("q")[0].as_py()
        left = sorted(np.flatnonzero(side == 0), key=lambda i: items[i])
        right = left if same_family and p == q else sorted(np.flatnonzero(side == 1), key=lambda i: items[i])
        found, size, done = [(np.zeros(0, np.int64),) * 3], 0, []
        at, most = 0 if len(right) else len(left), max(cfg.tile_items, at_once)
        while at < len(left):  # counts of some rows at a time
            some = left[at : at + most]
            facing = right[at:] if same_family and p == q and cfg.triangle else right
            counts = kernel([payloads[i] for i in some], [payloads[i] for i in facing])
            if counts is None:
                most = cfg.tile_items
                continue
            at += len(some)
            a, b = items[some], items[facing]
            i, j = np.nonzero(counts) if isinstance(counts, np.ndarray) else counts[:2]
            n = counts[i, j] if isinstance(counts, np.ndarray) else counts[2]
            lo, hi = a[i], b[j]
            if same_family and (p == q or not cfg.triangle):
                keep = lo < hi
                lo, hi, n = lo[keep], hi[keep], n[keep]
            if same_family and cfg.triangle:
                lo, hi = np.minimum(lo, hi), np.maximum(lo, hi)
            found.append((lo, hi, n))
            size += len(lo)
            if buckets and size >= partial.PACKED_PAIRS:
                done += partial.pack(found, buckets)
                found, size = [], 0
        if buckets:
            return partial.packed_rows(done + partial.pack(found, buckets))
        return pa.Table.from_arrays([pa.array(np.concatenate(c), pa.int64()) for c in zip(*found)], names=["item_a", "item_b", "support"])

    return run


def tiles(left: DataFrame, n_left: int, right: DataFrame | None = None, n_right: int = 0, triangle: bool = True) -> DataFrame:
    """Payload rows replicated to the tiles of their block: ``(p, q, seg, side, item, payload)``.

    In one family tile (p, q) is made for p <= q only (or for all p, q without
    ``triangle``); in two families for all. A row goes to one row or column of tiles per
    segment, so what is shuffled is the payloads times the number of blocks."""
    block = F.col("block")
    if right is not None:
        l = left.withColumn("q", F.explode(F.sequence(F.lit(0), F.lit(max(0, n_right - 1))))).select(block.alias("p"), "q", "seg", F.lit(0).alias("side"), "item", "payload")
        r = right.withColumn("p", F.explode(F.sequence(F.lit(0), F.lit(max(0, n_left - 1))))).select("p", block.alias("q"), "seg", F.lit(1).alias("side"), "item", "payload")
        return l.unionByName(r)
    low = block if triangle else F.lit(0)
    rows = left.withColumn("q", F.explode(F.sequence(low, F.lit(n_left - 1)))).select(block.alias("p"), "q", "seg", F.lit(0).alias("side"), "item", "payload")
    high = block if triangle else F.lit(n_left - 1)
    columns = left.withColumn("p", F.explode(F.sequence(F.lit(0), high))).where("p <> block").select("p", block.alias("q"), "seg", F.lit(1).alias("side"), "item", "payload")
    return rows.unionByName(columns)


def _segment_tiles(placed: DataFrame, triangle: bool) -> DataFrame:
    """The tiles of one family whose blocks are those of each row's segment (see ``tiles``)."""
    block, last = F.col("block"), F.col("blocks") - 1
    low, high = (block, block) if triangle else (F.lit(0), last)
    rows = placed.withColumn("q", F.explode(F.sequence(low, last))).select(block.alias("p"), "q", "seg", F.lit(0).alias("side"), "item", "payload")
    columns = placed.withColumn("p", F.explode(F.sequence(F.lit(0), high))).where("p <> block").select("p", block.alias("q"), "seg", F.lit(1).alias("side"), "item", "payload")
    return rows.unionByName(columns)


#: If more pairs of maps meet, buckets of counts follow the pairs in transactions, which takes a pass over the incidence.
MANY_PAIRS = 1_000_000_000


def emissions(inc: DataFrame) -> int:
    """Pairs of items in transactions, with repeats: no fewer than pairs and segments with a count."""
    t = F.col("count").cast("decimal(38,0)")
    return int(inc.groupBy("tid").count().agg(F.sum(t * (t - 1) / 2)).first()[0] or 0)


def tiled_counts(
    payloads: DataFrame, kernel: compare.Kernel, cfg: Config = Config(), more: DataFrame | None = None, block_items: int = 0, least: int = 1, inc: DataFrame | None = None
) -> DataFrame:
    """Summed counts of all pairs of ``payloads(item, seg, payload)`` and of ``more(item_a, item_b,
    support)``, in one aggregation; sums below ``least`` are dropped. Tiles pack their counts, so a pair and segment is a
    byte or two of shuffle, not a row. Blocks hold ``block_items`` payloads where that is
    more than the tile plan's; a kernel that can't takes ``cfg.tile_items`` of them at a time. Where many pairs
    meet, the counts that aren't zero are bounded by the pairs in the transactions of ``inc``."""
    placed, met = _placed(payloads, replace(cfg, tile_items=max(cfg.tile_items, block_items)))
    if inc is not None and met > MANY_PAIRS:
        met = min(met, emissions(inc))
    buckets = partial.bucket_count(met)
    parts = _segment_tiles(placed, cfg.triangle).groupBy("p", "q", "seg").applyInArrow(_tile(kernel, True, cfg, buckets, block_items), partial.PACKED)
    if more is not None:
        parts = parts.unionByName(partial.packed(more, buckets))
    return partial.totals(parts, least)


def every_pair(items: DataFrame, cfg: Config = Config()) -> DataFrame:
    """``(item_a, item_b)`` of all pairs of distinct items: n^2 / 2 rows, made tile by tile from
    two equi-joined copies of the items, so no side is broadcast or met by a nested loop."""
    known = cut(items.select("item").distinct(), "items")
    n = block_count(known.count(), cfg)
    placed = known.withColumn("block", F.pmod(F.xxhash64("item"), F.lit(n)).cast("int"))
    a = placed.select(F.col("item").alias("x"), F.col("block").alias("p"), F.explode(F.sequence("block", F.lit(n - 1))).alias("q"))
    b = placed.select(F.col("item").alias("y"), F.col("block").alias("q"), F.explode(F.sequence(F.lit(0), F.col("block"))).alias("p"))
    met = a.join(b, ["p", "q"]).where("p < q OR x < y")
    return met.select(F.least("x", "y").alias("item_a"), F.greatest("x", "y").alias("item_b"))


def pair_support(
    inc: DataFrame, method: str = "twinslot", min_support: int = 1, cfg: Config | None = None, include_zero: bool = False
) -> DataFrame:
    """``(item_a, item_b, support)`` of all pairs with ``support >= max(1, min_support)``.

    ``method`` is twinslot or one of the baselines. ``inc`` has distinct (item, tid) of longs.
    Without ``cfg`` slot width and segment length follow the instance's size and density.
    ``include_zero`` lists every pair of items, also those that never meet: n^2 / 2 rows.
    """
    require(inc, "item", "tid")
    if include_zero:
        found, every = pair_support(inc, method, 1, cfg), every_pair(inc, cfg or Config())
        return every.join(found, ["item_a", "item_b"], "left").select("item_a", "item_b", F.coalesce("support", F.lit(0)).cast("long").alias("support"))
    if method != "twinslot":
        from . import baselines

        return baselines.pair_support(inc, method, min_support, cfg or Config())
    inc = kept(inc, min_support)
    sets = sets_of(inc)
    if cfg is None:
        from ..plans import planner

        cfg = planner.tune_segments(inc)
    built = builder.build(inc, cfg, sets, compact=True)
    delta = repair.side_pairs(builder.failed_of(built), inc)
    return tiled_counts(builder.maps_of(built).select("item", "seg", F.col("slots").alias("payload")), compare.compact_kernel(cfg), cfg, delta, least=max(1, min_support), inc=inc)


def cross_support(left: DataFrame, right: DataFrame, min_support: int = 1, cfg: Config = Config()) -> DataFrame:
    """``(item_a, item_b, support)`` of all pairs of a left and a right set over the same ids."""
    built = [builder.build(cut(x, "incidence"), cfg) for x in (left, right)]
    families = [builder.maps_of(b).select("item", "seg", F.col("slots").alias("payload")) for b in built]
    (lb, nl), (rb, nr) = (_blocks(f, cfg) for f in families)
    if not nl or not nr:
        return left.sparkSession.createDataFrame([], TILE)
    grid = tiles(families[0].join(lb, "item"), nl, families[1].join(rb, "item"), nr)
    parts = grid.groupBy("p", "q", "seg").applyInArrow(_tile(compare.slot_kernel(cfg), False, cfg), TILE)
    lost_l, lost_r = (builder.failed_of(b) for b in built)
    hits = [
        lost_l.withColumnRenamed("item", "item_a").join(right.withColumnRenamed("item", "item_b"), "tid"),
        lost_r.withColumnRenamed("item", "item_b").join(left.withColumnRenamed("item", "item_a"), "tid"),
    ]
    delta = hits[0].select("tid", "item_a", "item_b").unionByName(hits[1].select("tid", "item_a", "item_b")).distinct()
    delta = delta.groupBy("item_a", "item_b").agg(F.count("*").alias("support"))
    return repair.merge(parts, delta).where(F.col("support") >= max(1, min_support))


def pair_support_slots(inc: DataFrame, cfg: Config = Config(), range_bits: int | None = None) -> DataFrame:
    """The counting rule as relations: slots of one common range joined on their place.

    Every map is built with one range (``range_bits``, at least what the largest set
    needs), its slots become rows (seg, slot, value, bit, item), and a pair counts a place where
    values agree and either bit is set. The checkable definition, not the fast way."""
    built = builder.build(inc, cfg)
    maps = builder.maps_of(built)
    bits = range_bits or maps.agg(F.max("log2_r")).first()[0] or cfg.r0_bits
    from ..functions import layout

    def rows(batches):
        for batch in batches:
            for m in batch.to_pylist():
                values = np.frombuffer(m["slots"], layout.KINDS[cfg.slot_bits]).astype(np.int64)
                ratio = (3 << bits) // len(values)
                at = np.flatnonzero(values)
                codes, tables, bit = layout.decode(np.frombuffer(m["slots"], layout.KINDS[cfg.slot_bits]), m["log2_r"], cfg)
                n = len(at)
                # A narrow map faces every stretch of a wide one: repeat it along the common range.
                place = (at[None, :] + len(values) * np.arange(ratio)[:, None]).ravel()
                rep = lambda v: np.tile(v, ratio)
                low = (1 << (cfg.slot_bits - 1)) - 1
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.full(n * ratio, m["item"]), pa.int64()), pa.array(np.full(n * ratio, m["seg"]), pa.int64()), pa.array(place, pa.int64()),
                     pa.array(rep(values[at] & low), pa.int64()), pa.array(rep(bit), pa.int64()), pa.array(np.full(n * ratio, m["log2_r"]), pa.int32())],
                    ["item", "seg", "slot", "value", "bit", "log2_r"],
                )

    slots = cut(maps.mapInArrow(rows, "item long, seg long, slot long, value long, bit long, log2_r int"), "slots")
    a, b = slots.alias("a"), slots.alias("b")
    width = F.call_function("shiftleft", F.lit(3).cast("long"), F.greatest("a.log2_r", "b.log2_r"))
    met = a.join(b, ["seg", "slot", "value"]).where((F.col("a.item") < F.col("b.item")) & (F.col("a.bit").bitwiseOR(F.col("b.bit")) == 1) & (F.col("slot") < width))
    counted = met.groupBy(F.col("a.item").alias("item_a"), F.col("b.item").alias("item_b")).agg(F.count("*").alias("support"))
    return repair.merge(counted, repair.side_pairs(builder.failed_of(built), inc))


def pair_support_lanes(inc: DataFrame, cfg: Config = Config()) -> DataFrame:
    """Packed counting in built-in functions: the four slots of a 32-bit word are compared at once.

    Words of one place join; a narrow map's words are repeated along the widest range, and a pair
    counts the places of the wider of its two. Words without an element can't count and are left out."""
    if cfg.slot_bits != 8:
        raise ValueError("a word has four slots of 8 bits")
    built = builder.build(inc, cfg)
    maps = builder.maps_of(built)
    bits = maps.agg(F.max("log2_r")).first()[0] or cfg.r0_bits
    shift = lambda x, n: F.call_function("shiftleft", F.lit(x).cast("long"), n)
    wide = maps.select("item", "seg", "slots", (shift(3, F.col("log2_r")) / 4).cast("long").alias("n"), shift(1, F.lit(bits) - F.col("log2_r")).alias("ratio"))
    word = F.conv(F.hex(F.substr("slots", (4 * F.col("i") + 1).cast("int"), F.lit(4))), 16, 10).cast("long")
    words = wide.withColumn("i", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 1))).select("item", "seg", "n", "ratio", "i", word.alias("word"))
    words = words.where("word <> 0").withColumn("k", F.explode(F.sequence(F.lit(0).cast("long"), F.col("ratio") - 1)))
    words = cut(words.select("item", "seg", "n", (F.col("i") + F.col("k") * F.col("n")).alias("place"), "word"), "words")
    a, b = words.alias("a"), words.alias("b")
    met = a.join(b, ["seg", "place"]).where((F.col("a.item") < F.col("b.item")) & (F.col("place") < F.greatest("a.n", "b.n")))
    n = F.sum(compare.lane_count(F.col("a.word"), F.col("b.word")).cast("long"))
    counted = met.groupBy(F.col("a.item").alias("item_a"), F.col("b.item").alias("item_b")).agg(n.alias("support"))
    return repair.merge(counted, repair.side_pairs(builder.failed_of(built), inc)).where(F.col("support") > 0)
