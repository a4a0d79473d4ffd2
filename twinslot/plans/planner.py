"""Cost-based choices that Catalyst can't make: which method, which container, which segments."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import Config
from ..functions import layout
from ..sources.incidence import DISTINCT_SEGMENT, repacked, segmented, sets_of
from ..stages import cut


@dataclass(frozen=True)
class Statistics:
    """What one pass over an incidence tells: n items, m transactions, N rows, pair emissions."""

    items: int
    transactions: int
    rows: int
    emissions: int

    @property
    def density(self) -> float:
        return self.rows / (self.items * self.transactions) if self.rows else 0.0


def statistics(inc: DataFrame) -> Statistics:
    """Two aggregations, each to one row; nothing per item or transaction reaches the driver."""
    by_tid = inc.groupBy("tid").agg(F.count("*").alias("t"))
    t = F.col("t").cast("decimal(38,0)")
    m, rows, emissions = by_tid.agg(F.count("*"), F.coalesce(F.sum("t"), F.lit(0)), F.coalesce(F.sum(t * (t - 1) / 2), F.lit(0))).first()
    return Statistics(inc.select("item").distinct().count(), m, int(rows), int(emissions))


#: Relative costs of one pair emission (shuffled counter) and of one byte of slot comparison.
EMISSION_COST, BYTE_COST = 60.0, 1.0


def choose(inc: DataFrame, cfg: Config | None = None, stats: Statistics | None = None) -> str:
    """``horizontal``, ``bitmap`` or ``twinslot`` for all pairs of an incidence.

    Horizontal counting pays for each emitted pair; vertical methods for n^2 / 2 comparisons
    of a width that is the segment's bits for bitmaps and follows the set size for maps."""
    s = stats or statistics(inc)
    if not s.rows:
        return "horizontal"
    cfg = cfg or tune(s)
    segments = -(-s.transactions // cfg.segment)
    card = max(1, s.rows // (s.items * segments))
    bits = int(layout.range_bits(card, cfg))
    span = min(cfg.segment, s.transactions)
    comparisons = s.items * (s.items - 1) / 2 * segments * BYTE_COST
    costs = {
        "horizontal": s.emissions * EMISSION_COST,
        "bitmap": comparisons * span / 8,
        "twinslot": comparisons * (3 << bits) * cfg.slot_bits / 8,
    }
    return min(costs, key=costs.get)


#: Bytes that a further segment costs a pair of maps besides its slots (calls, partial counts).
SEGMENT_COST = 64


def tune(s: Statistics, base: Config = Config()) -> Config:
    """Slot width and segment length of least bytes for sets of average size: byte slots
    in short segments for dense sets, wider slots in long segments for sparse ones, whose
    ranges would otherwise be stuck at the floor that packing sets."""
    if not s.rows:
        return base

    def cost(cfg: Config) -> float:
        segments = -(-s.transactions // cfg.segment)
        card = max(1, -(-s.rows // (s.items * segments)))
        return segments * ((3 << int(layout.range_bits(card, cfg))) * cfg.slot_bits // 8 + SEGMENT_COST)

    tried = [replace(base, segment_j=j, slot_bits=b) for b in (8, 16, 32) for j in range(7, 14)]
    return min(tried, key=cost)


#: Bytes of slot comparison that a partial count costs (made, shuffled, summed), and a map (placed, stored, read); size of the sketches of items.
PARTIAL_COST, MAP_COST, SKETCH = 2000, 100_000, 10


def tune_segments(inc: DataFrame, base: Config = Config()) -> Config:
    """Slot width and segment length of least work, by what meets in segments: only maps of one segment
    are compared, so sets that lie in different stretches of ids don't count for each other as
    they do in averages over the whole (``tune``), and sparse maps cost their meeting slots. One pass sketches the items of the shortest
    segments; longer ones unite sketches, and the driver sees one row for each length."""
    from ..operators import compare

    short = 127 << 7
    sets = repacked(sets_of(inc), DISTINCT_SEGMENT, short)
    sketched = sets.groupBy("seg").agg(F.sum("n").alias("n"), F.hll_sketch_agg("item", SKETCH).alias("s"))
    sketched = cut(sketched, "sketches")
    costs = {}
    for j in range(7, 14):
        per = sketched.groupBy(F.shiftright("seg", j - 7).alias("seg")).agg(F.sum("n").alias("rows"), F.hll_sketch_estimate(F.hll_union_agg("s")).alias("items"))
        items = F.greatest("items", F.lit(1))
        card = F.ceil(F.col("rows") / items)
        pairs = items.cast("double") * items / 2
        met = card * card / (127 << j)
        rest = pairs * F.least(F.lit(1.0), met) * PARTIAL_COST + pairs * SEGMENT_COST + items * MAP_COST
        tried = {b: replace(base, segment_j=j, slot_bits=b) for b in (8, 16, 32)}
        width = lambda b, c: F.call_function("shiftleft", F.lit(3).cast("long"), layout.range_bits_column(card, c)) * (b // 8)
        found = per.agg(*(F.sum(pairs * F.least(width(b, c), met * compare.MEETING_BYTES) + rest).alias(str(b)) for b, c in tried.items())).first()
        costs |= {c: found[str(b)] for b, c in tried.items() if found[str(b)] is not None}
    return min(costs, key=costs.get) if costs else base


def container_bytes(card: Column, span: Column | int, cfg: Config = Config()) -> dict[str, Column]:
    """Bytes of one (item, segment) set in each container."""
    bits = {b: layout.range_bits_column(card, replace(cfg, slot_bits=b)) for b in (8, 16, 32)}
    maps = {f"slot{b}": (F.call_function("shiftleft", F.lit(3).cast("long"), x) * (b // 8)).cast("long") for b, x in bits.items()}
    span = span if isinstance(span, Column) else F.lit(span)
    return {"list": (card * 4).cast("long"), **maps, "bitmap": F.ceil(span / 8).cast("long")}


def containers(inc: DataFrame, cfg: Config = Config()) -> DataFrame:
    """``(item, seg, card, container, bytes)``: the smallest container of each set, the
    first of list, slot8, slot16, slot32, bitmap on ties."""
    cards = segmented(inc, cfg.segment).groupBy("item", "seg").agg(F.count("*").alias("card"))
    sizes = container_bytes(F.col("card"), cfg.segment, cfg)
    ranked = F.array_min(F.array(*(F.struct(v.alias("bytes"), F.lit(i).alias("k"), F.lit(name).alias("name")) for i, (name, v) in enumerate(sizes.items()))))
    return cards.select("item", "seg", "card", ranked["name"].alias("container"), ranked["bytes"].alias("bytes"))


def pair_support(inc: DataFrame, min_support: int = 1, cfg: Config | None = None) -> DataFrame:
    """All frequent pairs by whatever method is cheapest."""
    from ..operators import pairs

    kept = cut(pairs.prune(inc, min_support), "planned")
    stats = statistics(kept)
    cfg = cfg or tune(stats)
    return pairs.pair_support(kept, choose(kept, cfg, stats), min_support, cfg)
