"""Cost and accuracy measures."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import Config
from ..functions import layout


from . import builder


def instance(inc: DataFrame) -> DataFrame:
    """One row: n items, m transactions, N rows, average set size, density N / (n m)."""
    one = inc.agg(F.count_distinct("item").alias("n"), F.count_distinct("tid").alias("m"), F.count("*").alias("total"))
    return one.select("n", "m", "total", F.round(F.col("total") / F.col("n"), 6).alias("avg_size"), F.round(F.col("total") / (F.col("n") * F.col("m")), 9).alias("density"))


def density(inc: DataFrame) -> DataFrame:
    """Per set: ``(item, card, density)`` = card / m."""
    m = inc.agg(F.count_distinct("tid").alias("m"))
    return inc.groupBy("item").agg(F.count("*").alias("card")).join(F.broadcast(m)).select("item", "card", F.round(F.col("card") / F.col("m"), 9).alias("density"))


def _next_power(card):
    """2 ^ ceil(log2 card) in integers."""
    bits = F.when(card <= 1, F.lit(0)).otherwise(F.length(F.bin((card - 1).cast("long"))))
    return F.call_function("shiftleft", F.lit(1).cast("long"), bits)


def map_bytes(inc: DataFrame) -> DataFrame:
    """Per set: ``(item, card, bytes)`` with bytes = 3 * 2 ^ ceil(log2(2 card)), one byte a slot."""
    return inc.groupBy("item").agg(F.count("*").alias("card")).select("item", "card", (6 * _next_power(F.col("card"))).alias("bytes"))


def bytes_by_layout(inc: DataFrame) -> DataFrame:
    """One row: bytes of sorted lists (4 a tid), bitmaps (m bits a set), plain maps, and the
    n (n - 1) / 2 pair counters of the candidate method."""
    sizes = map_bytes(inc).agg(F.count("*").alias("n"), F.sum("card").alias("total"), F.sum("bytes").alias("map_bytes"))
    m = inc.agg(F.count_distinct("tid").alias("m"))
    return sizes.join(F.broadcast(m)).select(
        "n", "m", "total", (4 * F.col("total")).alias("list_bytes"), (F.col("n") * F.expr("(m + 7) div 8")).alias("bitmap_bytes"), "map_bytes",
        F.expr("4 * (n * (n - 1) div 2)").alias("counter_bytes"),
    )


def space_ratio(inc: DataFrame) -> DataFrame:
    """Per set: map bits over the information minimum log2 C(m, card), by Stirling's series."""
    m = inc.agg(F.count_distinct("tid").cast("double").alias("m"))

    def log2_factorial(x):
        series = x * F.log(x) - x + 0.5 * F.log(2 * math.pi * x) + 1 / (12 * x) - 1 / (360 * F.pow(x, F.lit(3)))
        return F.when(x < 1, F.lit(0.0)).otherwise(series / math.log(2))

    k = F.col("card").cast("double")
    least = log2_factorial(F.col("m")) - log2_factorial(k) - log2_factorial(F.col("m") - k)
    sized = map_bytes(inc).join(F.broadcast(m)).withColumn("min_bits", least)
    return sized.select("item", "card", "min_bits", (8 * F.col("bytes") / F.when(F.col("min_bits") > 0, F.col("min_bits"))).alias("ratio"))


def compression_gain(inc: DataFrame) -> DataFrame:
    """Per set: does packing to a byte save space, card >= (m + 1) / 256? And the shift."""
    m = inc.agg(F.count_distinct("tid").alias("m"))
    shift = F.when(F.col("m") + 1 <= 128, 0).otherwise(F.length(F.bin(F.expr("(m + 1 + 127) div 128 - 1"))))
    return inc.groupBy("item").agg(F.count("*").alias("card")).join(F.broadcast(m)).select("item", "card", (256 * F.col("card") >= F.col("m") + 1).alias("gain"), shift.cast("int").alias("shift"))


def build_stats(inc: DataFrame, cfg: Config = Config()) -> DataFrame:
    """One row: sets, elements, failed elements, moves a copy (mean, and the largest mean of a set),
    and the largest load card / r of batch placement. ``sequential.transcripts`` sets single
    insertions against the bounds."""
    built = builder.build(inc, cfg)
    maps = builder.maps_of(built).select("card", "log2_r")
    lost = built.where("failed IS NOT NULL").agg(F.count("*").alias("failed"))
    per_copy = F.col("moves") / (2 * F.col("card"))
    moves = built.where("slots IS NOT NULL").agg(F.round(F.sum("moves") / F.sum(2 * F.col("card")), 4).alias("moves_per_copy"), F.round(F.max(per_copy), 4).alias("most_per_copy"))
    load = F.max(F.col("card") / F.pow(F.lit(2.0), F.col("log2_r")))
    one = maps.agg(F.count("*").alias("sets"), F.coalesce(F.sum("card"), F.lit(0)).alias("elements"), F.round(load, 6).alias("max_load"))
    return one.join(lost).join(moves).select(
        "sets", "elements", "failed", "moves_per_copy", "most_per_copy", "max_load", F.round(F.col("failed") / F.greatest("elements", F.lit(1)), 9).alias("failed_per_element")
    )


def failure_bound(n: int, r: int) -> float:
    """Order of the chance that one insertion fails: 1 / (eps^3 n r) with r = (2 + eps) n."""
    eps = r / n - 2
    return math.inf if eps <= 0 else 1 / (eps**3 * n * r)


def transcript_bound(n: int, r: int, steps: int) -> float:
    """Bound on the chance that a successful insertion takes ``steps`` moves or more."""
    return min(1.0, 2 * (2 * n / r) ** (steps / 3 - 2))


def copies_per_element(inc: DataFrame, cfg: Config = Config()) -> DataFrame:
    """Per item: occupied slots plus twice the failed elements, which must be twice its size."""
    def occupied(slots: pa.Array) -> pa.Array:
        return pa.array([int(np.count_nonzero(np.frombuffer(s, layout.KINDS[cfg.slot_bits]))) for s in slots.to_pylist()], pa.int64())

    built = builder.build(inc, cfg)
    held = builder.maps_of(built).select("item", F.arrow_udf(occupied, "long")("slots").alias("copies"))
    lost = builder.failed_of(built).select("item", F.lit(2).cast("long").alias("copies"))
    return held.unionByName(lost).groupBy("item").agg(F.sum("copies").alias("copies"))


def diagonal(inc: DataFrame, cfg: Config = Config()) -> DataFrame:
    """Per item: its maps compared with themselves plus its failed elements, which must be its size."""
    from . import compare

    built = builder.build(inc, cfg)
    own = builder.maps_of(built).select("item", compare.count(F.col("slots"), F.col("slots"), cfg).alias("n"))
    lost = builder.failed_of(built).select("item", F.lit(1).cast("long").alias("n"))
    return own.unionByName(lost).groupBy("item").agg(F.sum("n").alias("n"))


def tile_cost(inc: DataFrame, k: int, sort_by_width: bool = True) -> DataFrame:
    """One row: slot tests of all pairs p <= q when every tile costs as its widest map, with
    items in rank order by width or by id; and without tiles."""
    from ..sources.incidence import dense_ids

    widths = map_bytes(inc).select("item", F.col("bytes").alias("width"))
    keys = ("width", "item") if sort_by_width else ("item",)
    ranked = dense_ids(widths, *keys).select("width", F.floor(F.col("id") / k).alias("block"))
    blocks = ranked.groupBy("block").agg(F.count("*").alias("n"), F.max("width").alias("w"))
    a, b = blocks.alias("a"), F.broadcast(blocks).alias("b")  # n / k rows
    cost = F.col("a.n") * F.col("b.n") * F.greatest("a.w", "b.w")
    return a.join(b, F.col("a.block") <= F.col("b.block")).agg(F.sum(cost).alias("slot_tests"), F.count("*").alias("tiles"))


def pair_diff(got: DataFrame, want: DataFrame) -> DataFrame:
    """One row: pairs that differ, and the sum of absolute differences of support."""
    w = want.select("item_a", "item_b", F.col("support").alias("wanted"))
    both = got.join(w, ["item_a", "item_b"], "full").select((F.coalesce("support", F.lit(0)) - F.coalesce("wanted", F.lit(0))).alias("d"))
    return both.agg(F.count_if(F.col("d") != 0).alias("pairs"), F.coalesce(F.sum(F.abs("d")), F.lit(0)).cast("long").alias("total"))


def byte_throughput(n: int, width: float, seconds: float, peak: float | None = None) -> dict[str, float]:
    """Bytes read a second by n^2 comparisons of maps of ``width`` bytes; share of the peak."""
    rate = n * n * width / seconds
    return {"bytes_per_s": rate} | ({"share_of_peak": rate / peak} if peak else {})


def element_throughput(n: int, size: float, seconds: float) -> dict[str, float]:
    """Elements handled a second, with the band that rounding of ranges allows: the best
    case fills a map of the same bytes, the worst has just crossed a power of two."""
    rate = n * n * size / seconds
    full = 2 ** math.ceil(math.log2(size)) / size
    return {"elements_per_s": rate, "best": rate * full, "worst": rate * full / 2}


def association(pairs: DataFrame, inc: DataFrame) -> DataFrame:
    """Support, confidence both ways, lift, Jaccard, cosine, overlap and containment of pairs."""
    sizes = inc.groupBy("item").agg(F.count("*").alias("size"))
    m = inc.agg(F.count_distinct("tid").alias("m"))
    joined = (
        pairs.join(sizes.withColumnRenamed("item", "item_a").withColumnRenamed("size", "a"), "item_a")
        .join(sizes.withColumnRenamed("item", "item_b").withColumnRenamed("size", "b"), "item_b")
        .join(F.broadcast(m))
    )
    s, a, b = F.col("support"), F.col("a"), F.col("b")
    return joined.select(
        "item_a", "item_b", "support", F.round(s / F.col("m"), 9).alias("support_share"), F.round(s / a, 9).alias("confidence_ab"), F.round(s / b, 9).alias("confidence_ba"),
        F.round(s * F.col("m") / (a * b), 9).alias("lift"), F.round(s / (a + b - s), 9).alias("jaccard"), F.round(s / F.sqrt((a * b).cast("double")), 9).alias("cosine"),
        F.round(s / F.least(a, b), 9).alias("overlap"),
    )
