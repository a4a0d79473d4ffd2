"""The relational surface around the methods: thin compositions that stay in Catalyst."""

from __future__ import annotations

from functools import reduce

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Largest row count of a side that a nested loop may broadcast.
NESTED_LOOP_ROWS = 100_000
#: Largest row count of a side that an equi-join broadcasts; larger ones are hashed in parts.
BROADCAST_ROWS = 1_000_000
#: Rows of a chunk of a range join: the longest run of bit-packed values in Parquet, so that repeats of a chunk look alike.
CHUNK = 504
#: Points that a bucket of a range join holds on average at most, and the most buckets that a range covers.
BUCKET_POINTS, BUCKETS = 100 * CHUNK, 1_000
#: Pairs of points and ranges a task of a range join, and its most tasks.
TASK_PAIRS, TASKS = 100_000_000, 10_000


def project(df: DataFrame, **exprs: Column | str) -> DataFrame:
    return df.select(*((F.expr(e) if isinstance(e, str) else e).alias(n) for n, e in exprs.items()))


def where(df: DataFrame, *predicates: Column, mode: str = "and") -> DataFrame:
    join_with = (lambda a, b: a & b) if mode == "and" else (lambda a, b: a | b)
    return df.where(reduce(join_with, predicates))


def join(left: DataFrame, right: DataFrame, on: list[str], how: str = "inner", strategy: str = "auto") -> DataFrame:
    """Equi-join; strategy is auto, broadcast, hash or merge. A side that is broadcast passes the driver
    whole, so beyond ``BROADCAST_ROWS`` (counted no further) the hash tables are made of its shuffled parts instead."""
    if strategy == "broadcast" and right.limit(BROADCAST_ROWS + 1).count() > BROADCAST_ROWS:
        strategy = "hash"
    hint = {"broadcast": "broadcast", "hash": "shuffle_hash", "merge": "merge"}.get(strategy)
    return left.join(right.hint(hint) if hint else right, on, how)


def semi(left: DataFrame, right: DataFrame, on: list[str]) -> DataFrame:
    return left.join(right.select(*on), on, "left_semi")


def anti(left: DataFrame, right: DataFrame, on: list[str]) -> DataFrame:
    return left.join(right.select(*on), on, "left_anti")


def theta(left: DataFrame, right: DataFrame, condition: Column, limit: int = NESTED_LOOP_ROWS) -> DataFrame:
    """Join on any condition by broadcasting ``right``, refused beyond ``limit`` rows."""
    if right.limit(limit + 1).count() > limit:
        raise ValueError(f"the right side of a nested loop has more than {limit} rows; use range_join or interval_join")
    return left.join(F.broadcast(right), condition)


def _chunks(df: DataFrame, tasks: int, *order: Column) -> DataFrame:
    """Rows in an order, up to ``CHUNK`` neighbours an array ``_rows``."""
    dealt = df.repartitionByRange(tasks, *order, F.xxhash64(*df.columns)).sortWithinPartitions(*order)

    def gather(batches):
        for batch in batches:
            starts = [*range(0, batch.num_rows, CHUNK), batch.num_rows]
            rows = pa.StructArray.from_arrays(batch.columns, fields=list(batch.schema))
            yield pa.record_batch([pa.ListArray.from_arrays(pa.array(starts, pa.int32()), rows)], ["_rows"])

    return dealt.mapInArrow(gather, T.StructType([T.StructField("_rows", T.ArrayType(df.schema, False))]))


def range_join(points: DataFrame, ranges: DataFrame, x: str, lo: str, hi: str, width: float, broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """Points in closed ranges. Neighbouring points are packed in chunks, and so are ranges; chunks that
    overlap meet, the bounds decide. Both are dealt to buckets of at most ``width`` and meet in the first one they
    share; up to ``broadcast_rows`` points are broadcast, or else as many ranges, which need no buckets.

    Matches become rows as the last step: what is shuffled or broadcast follows the inputs. A range repeats
    the points of a chunk in one order, which columnar files store as runs and copies."""
    ranges = ranges.where(F.col(lo) <= F.col(hi))
    least, greatest, n_ranges = ranges.agg(F.min(lo), F.max(hi), F.count(F.lit(1))).first()
    points = points.where(F.col(x).between(F.lit(least), F.lit(greatest)))
    number = F.col(x).cast("double")
    finite = F.when(~F.isnan(number) & (F.abs(number) < float("inf")), number)
    low, high, n_points = points.agg(F.min(finite), F.max(finite), F.count(F.lit(1))).first()
    low, high = (0.0, 0.0) if low is None else (low, high)
    width = max(min(width, (high - low) * BUCKET_POINTS / max(n_points, 1)), (high - low) / BUCKETS) or width

    def bucket(c):
        # What lies beyond the points' finite values, NaN too, goes to the bucket at that end.
        return F.floor((F.least(F.greatest(c.cast("double"), F.lit(low)), F.lit(high)) - low) / width).cast("long")

    def sided(chunks, start, end):
        return chunks.select("_rows", F.array_min(f"_rows.{start}").alias("_lo"), F.array_max(f"_rows.{end}").alias("_hi"))

    def dealt(side):
        return side.withColumn("_first", bucket(F.col("_lo"))).withColumn("_b", F.explode(F.sequence("_first", bucket(F.col("_hi")))))

    tasks = min(max(1, round(n_points * n_ranges / TASK_PAIRS)), TASKS)
    whole_points = n_points <= broadcast_rows
    p = sided(_chunks(points, 1 if whole_points else max(1, min(tasks, n_points // (8 * CHUNK))), F.col(x)), x, x)
    # Ranges of like widths are neighbours: a wide one would stretch the chunk of narrow ones over its buckets.
    like = F.floor(F.log2(bucket(F.col(hi)) - bucket(F.col(lo)) + 1))
    r = sided(_chunks(ranges, max(1, min(tasks, n_ranges // CHUNK)), like, F.col(lo)), lo, hi)
    overlap = (F.col("p._lo") <= F.col("r._hi")) & (F.col("r._lo") <= F.col("p._hi"))
    if not whole_points and n_ranges <= broadcast_rows:
        met = p.alias("p").join(F.broadcast(r).alias("r"), overlap)
    else:
        once = (F.col("p._b") == F.col("r._b")) & (F.col("r._b") == F.greatest("p._first", "r._first"))
        p = F.broadcast(dealt(p)) if whole_points else dealt(p)
        met = dealt(r).alias("r").join(p.alias("p"), once & overlap)
    one = met.select(
        F.col("p._rows").alias("_points"), F.col("p._lo").alias("_lo"), F.col("p._hi").alias("_hi"),
        F.explode(F.filter("r._rows", lambda r: (r[lo] <= F.col("p._hi")) & (r[hi] >= F.col("p._lo")))).alias("_range"),
    )

    # A chunk is in order, so a range's points there are a slice: its ends by binary search.
    def before(inside):
        at = lambda n, step: F.when(inside(F.get("_points", n + step - 1)[x]), n + step).otherwise(n)
        return F.aggregate(F.array(*(F.lit(1 << k) for k in reversed(range(CHUNK.bit_length())))), F.lit(0), at)

    start, end = F.col(f"_range.{lo}"), F.col(f"_range.{hi}")
    skipped = before(lambda v: v < start)
    some = F.slice("_points", skipped + 1, before(lambda v: v <= end) - skipped)
    whole = (start <= F.col("_lo")) & (F.col("_hi") <= end)
    found = one.select("_range.*", F.when(whole, F.col("_points")).otherwise(some).alias("_found"))
    return found.select(*ranges.columns, F.explode("_found").alias("_point")).select("_point.*", *ranges.columns)


def interval_join(left: DataFrame, right: DataFrame, key: str, tl: str, tr: str, lo: str, hi: str) -> DataFrame:
    """Rows of one key with ``tl + lo <= tr <= tl + hi`` (interval strings)."""
    r = right.withColumnRenamed(key, "_key")
    a, b = F.expr(f"{tl} + interval {lo}"), F.expr(f"{tl} + interval {hi}")
    return left.join(r, (left[key] == r["_key"]) & (r[tr] >= a) & (r[tr] <= b)).drop("_key")


def asof_join(left: DataFrame, right: DataFrame, key: str, tl: str, tr: str, value: str) -> DataFrame:
    """Each left row with the latest right ``value`` of its key at or before its time: one
    shuffle of the union, last non-null in time order (the right row first on ties)."""
    l = left.select("*", F.col(tl).alias("_t"), F.lit(1).alias("_side"), F.lit(None).cast(right.schema[value].dataType).alias("_value"))
    r = right.select(F.col(key), F.col(tr).alias("_t"), F.lit(0).alias("_side"), F.col(value).alias("_value"))
    w = Window.partitionBy(key).orderBy("_t", "_side", "_value").rowsBetween(Window.unboundedPreceding, 0)
    both = l.unionByName(r, allowMissingColumns=True)
    return both.withColumn(f"asof_{value}", F.last("_value", ignorenulls=True).over(w)).where("_side = 1").select(*left.columns, f"asof_{value}")


def aggregate(df: DataFrame, keys: list[str], having: Column | None = None, **aggs: Column) -> DataFrame:
    out = df.groupBy(*keys).agg(*(a.alias(n) for n, a in aggs.items()))
    return out if having is None else out.where(having)


def distinct_counts(df: DataFrame, keys: list[str], column: str, approximate: bool = False, rsd: float = 0.02) -> DataFrame:
    count = F.approx_count_distinct(column, rsd) if approximate else F.count_distinct(column)
    return df.groupBy(*keys).agg(count.alias("n"))


def cube(df: DataFrame, keys: list[str], **aggs: Column) -> DataFrame:
    return df.cube(*keys).agg(F.grouping_id().cast("long").alias("gid"), *(a.alias(n) for n, a in aggs.items()))


def rollup(df: DataFrame, keys: list[str], **aggs: Column) -> DataFrame:
    return df.rollup(*keys).agg(F.grouping_id().cast("long").alias("gid"), *(a.alias(n) for n, a in aggs.items()))


def grouping_sets(df: DataFrame, sets: list[list[str]], keys: list[str], **aggs: Column) -> DataFrame:
    return df.groupingSets([[F.col(c) for c in s] for s in sets], *keys).agg(F.grouping_id().cast("long").alias("gid"), *(a.alias(n) for n, a in aggs.items()))


def pivot_counts(df: DataFrame, key: str, column: str, values: list[str]) -> DataFrame:
    return df.groupBy(key).pivot(column, values).agg(F.count(F.lit(1))).na.fill(0)


def rank_items(df: DataFrame, part: list[str], order: list[Column], kind: str, buckets: int = 4) -> DataFrame:
    """row_number, rank, dense_rank or ntile within ``part`` (at least one column: an unpartitioned
    window is one task; use sources.incidence.dense_ids for a global order)."""
    if not part:
        raise ValueError("a window needs a partition; use dense_ids for a global order")
    w = Window.partitionBy(*part).orderBy(*order)
    function = F.ntile(buckets) if kind == "ntile" else {"row_number": F.row_number, "rank": F.rank, "dense_rank": F.dense_rank}[kind]()
    return df.withColumn(kind, function.over(w))


def lag_lead(df: DataFrame, part: list[str], order: list[str], column: str, n: int = 1) -> DataFrame:
    w = Window.partitionBy(*part).orderBy(*order)
    return df.withColumn(f"lag_{column}", F.lag(column, n).over(w)).withColumn(f"lead_{column}", F.lead(column, n).over(w))


def running(df: DataFrame, part: list[str], order: list[str], column: str, frame: str = "rows", size: int | None = None) -> DataFrame:
    w = Window.partitionBy(*part).orderBy(*order)
    start = Window.unboundedPreceding if size is None else -size
    w = w.rowsBetween(start, 0) if frame == "rows" else w.rangeBetween(start, 0)
    return df.withColumn(f"running_{column}", F.sum(column).over(w))


def top_k(df: DataFrame, order: list[Column], k: int) -> DataFrame:
    """The first k rows of a total order: a heap a task, then one merge."""
    return df.orderBy(*order).limit(k)


def top_k_per(df: DataFrame, part: list[str], order: list[Column], k: int) -> DataFrame:
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(*part).orderBy(*order))).where(F.col("rank") <= k)


def partners(pairs: DataFrame, k: int) -> DataFrame:
    """Each item's k most frequent partners, ties to the smaller partner."""
    both = pairs.select(F.col("item_a").alias("item"), F.col("item_b").alias("partner"), "support").unionByName(
        pairs.select(F.col("item_b").alias("item"), F.col("item_a").alias("partner"), "support")
    )
    return top_k_per(both, ["item"], [F.desc("support"), F.asc("partner")], k)


def set_op(left: DataFrame, right: DataFrame, op: str, all: bool = False) -> DataFrame:
    if op == "union":
        both = left.unionByName(right)
        return both if all else both.distinct()
    if op == "intersect":
        return left.intersectAll(right) if all else left.intersect(right)
    if op == "except":
        return left.exceptAll(right) if all else left.subtract(right)
    raise ValueError(f"unknown set operation {op!r}")


def array_set_op(df: DataFrame, a: str, b: str, op: str) -> DataFrame:
    function = {"intersect": F.array_intersect, "union": F.array_union, "except": F.array_except, "overlap": F.arrays_overlap}[op]
    return df.withColumn(op, function(a, b))
