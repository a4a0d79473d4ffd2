"""Problems that reduce to set intersection."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import Config
from ..stages import cut
from . import builder, compare, pairs


def bool_matmul(left: DataFrame, right: DataFrame, counts: bool = False, method: str = "join", cfg: Config = Config()) -> DataFrame:
    """Product of boolean matrices ``left(row, k)`` and ``right(k, col)``: ``(row, col[, n])``.

    ``join`` is the sparse plan: distinct inputs, equi-join on k, distinct or count with
    partial aggregation. ``twinslot`` compares the maps of rows with those of columns."""
    if method == "twinslot":
        a = left.select(F.col("row").alias("item"), F.col("k").alias("tid")).distinct()
        b = right.select(F.col("col").alias("item"), F.col("k").alias("tid")).distinct()
        out = pairs.cross_support(a, b, 1, cfg).select(F.col("item_a").alias("row"), F.col("item_b").alias("col"), F.col("support").alias("n"))
        return out if counts else out.select("row", "col")
    joined = left.select("row", "k").distinct().join(right.select("k", "col").distinct(), "k")
    if counts:
        return joined.groupBy("row", "col").agg(F.count("*").alias("n"))
    return joined.select("row", "col").distinct()


def join_project(left: DataFrame, right: DataFrame, on: str, keep: tuple[str, ...]) -> DataFrame:
    """Join, drop the join attribute, remove duplicates.

    Both sides are cut to the needed columns and made distinct before the join; if only
    one side is kept the join is a semi-join."""
    mine = [c for c in keep if c in left.columns]
    theirs = [c for c in keep if c not in left.columns]
    l = left.select(on, *mine).distinct()
    r = right.select(on, *theirs).distinct()
    if not theirs:
        return l.join(r, on, "left_semi").select(*mine).distinct()
    if not mine:
        return r.join(l, on, "left_semi").select(*theirs).distinct()
    return l.join(r, on).select(*keep).distinct()


def conjunctive(df: DataFrame, key: str, predicates: list[Column], mode: str = "ids") -> DataFrame:
    """Keys of rows that satisfy all predicates: one filter that reaches the scan."""
    hits = df.where(reduce(lambda a, b: a & b, predicates)).select(key)
    return hits if mode == "ids" else hits.agg(F.count("*").alias("n"))


def conjunctive_sets(df: DataFrame, key: str, predicates: list[Column], cfg: Config = Config()) -> DataFrame:
    """The number of keys under each pair of pre-evaluated predicates: ``(item_a, item_b,
    support)``, predicates numbered from 0; for predicates that are asked for many times."""
    flags = F.array(*(F.when(p, F.lit(i).cast("long")) for i, p in enumerate(predicates)))
    inc = df.select(F.explode(F.filter(flags, lambda x: x.isNotNull())).alias("item"), F.col(key).alias("tid")).where("tid IS NOT NULL").distinct()
    return pairs.pair_support(inc, cfg=cfg)


def intersection(inc: DataFrame, a: int, b: int, cfg: Config = Config()) -> DataFrame:
    """``(tid)``: the common elements of two sets, read back from their maps; failed
    elements are taken from the log."""
    two = cut(inc.where(F.col("item").isin(a, b)), "two")
    built = builder.build(two, cfg)
    held = compare.elements(builder.maps_of(built), cfg).unionByName(builder.failed_of(built))
    return held.groupBy("tid").agg(F.count_distinct("item").alias("n")).where("n = 2").select("tid")


def intersection_size(inc: DataFrame, a: int, b: int, cfg: Config = Config()) -> DataFrame:
    """One row ``(n)``: the size of the intersection, by comparing maps segment by segment."""
    two = cut(inc.where(F.col("item").isin(a, b)), "two")
    built = builder.build(two, cfg)
    maps = builder.maps_of(built)
    x = maps.where(F.col("item") == a).select("seg", F.col("slots").alias("x"))
    y = maps.where(F.col("item") == b).select("seg", F.col("slots").alias("y"))
    counted = x.join(y, "seg").select(compare.count(F.col("x"), F.col("y"), cfg).alias("n"))
    lost = builder.failed_of(built).select("tid").distinct().join(two, "tid").groupBy("tid").agg(F.count_distinct("item").alias("c"))
    more = lost.where("c = 2").select(F.lit(1).cast("long").alias("n"))
    return counted.unionByName(more).agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n"))


def combine_maps(*_: object) -> None:
    """Refused: the result of combining two maps isn't a map (two of three places no longer
    hold for what is left). Ask for counts or for elements."""
    raise TypeError("combining two maps gives no map; use compare.count, apps.intersection or kway")
