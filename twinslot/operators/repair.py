"""Pairs that failed insertions hide from the maps, recovered relationally."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Failed elements are broadcast up to so many.
BROADCAST_FAILED = 100_000


def side_pairs(failed: DataFrame, inc: DataFrame) -> DataFrame:
    """``(item_a, item_b, support)``: one for each transaction in which either member failed.

    A transaction's pair counts once even if both members failed, and pairs of different
    transactions add up, so duplicates are removed per (transaction, pair)."""
    n = failed.count()
    small = F.broadcast(failed) if n <= BROADCAST_FAILED else failed
    hit = inc.join(small.withColumnRenamed("item", "lost"), "tid").where("item <> lost")
    pairs = hit.select("tid", F.least("item", "lost").alias("item_a"), F.greatest("item", "lost").alias("item_b")).distinct()
    return pairs.groupBy("item_a", "item_b").agg(F.count("*").alias("support"))


def merge(counted: DataFrame, delta: DataFrame) -> DataFrame:
    """Counts plus side pairs, summed per pair (thresholds come after this)."""
    return counted.unionByName(delta).groupBy("item_a", "item_b").agg(F.sum("support").alias("support"))
