"""Timings: phases of the method, methods against each other, kernels against the machine."""

from __future__ import annotations

import resource
import time
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .config import Config
from .operators import builder, compare, pairs, repair
from .sources import incidence
from .stages import cut

#: A run that takes longer counts as exceeded (seconds).
LIMIT = 1800.0


def timed(make: Callable[[], DataFrame]) -> float:
    """Seconds to compute all rows, without writing them."""
    began = time.perf_counter()
    make().write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def within(make: Callable[[], DataFrame], limit: float = LIMIT) -> tuple[float, bool]:
    """Seconds, and whether the limit was exceeded; a run beyond it is cancelled."""
    import threading

    from pyspark import InheritableThread

    out: dict = {}
    spark = SparkSession.getActiveSession()

    def run() -> None:
        spark.sparkContext.setJobGroup("twinslot-bench", "limited run", interruptOnCancel=True)
        try:
            out["s"] = timed(make)
        except Exception as error:
            out["error"] = error

    began = time.perf_counter()
    thread: threading.Thread = InheritableThread(target=run)
    thread.start()
    thread.join(limit)
    if thread.is_alive():
        spark.sparkContext.cancelJobGroup("twinslot-bench")
        thread.join()
        return time.perf_counter() - began, True
    if "error" in out:
        raise out["error"]
    return out["s"], False


def phase_times(inc: DataFrame, cfg: Config = Config(), min_support: int = 1) -> dict[str, float]:
    """Seconds of preprocessing, build, pair phase and repair, and their sum."""
    out, began = {}, time.perf_counter()

    def lap(name: str) -> None:
        nonlocal began
        now = time.perf_counter()
        out[name], began = now - began, now

    rows = cut(pairs.prune(inc, min_support), "bench")
    lap("prepare")
    built = builder.build(rows, cfg)
    lap("build")
    payloads = builder.maps_of(built).select("item", "seg", F.col("slots").alias("payload"))
    counted = cut(pairs.tiled_counts(payloads, compare.slot_kernel(cfg), cfg), "bench")
    lap("pairs")
    repair.merge(counted, repair.side_pairs(builder.failed_of(built), rows)).write.format("noop").mode("overwrite").save()
    lap("repair")
    return out | {"total": sum(out.values())}


def instance(spark: SparkSession, sf_dir: str, items: int, total: int, p: int) -> DataFrame:
    """The deterministic instance of density 1/p with parts as ``items`` items, orders as
    transactions and about ``total`` rows (written)."""
    parts = spark.read.parquet(f"{sf_dir}/part.parquet").select(F.col("p_partkey").alias("s_suppkey")).where(F.col("s_suppkey") < items)
    orders = spark.read.parquet(f"{sf_dir}/orders.parquet").select(F.col("o_orderkey").alias("p_partkey")).where(F.col("p_partkey") < total * p // items)
    return cut(incidence.grid(orders, parts, p), "bench")


def series(name: str, rows: DataFrame, methods: tuple[str, ...], limit: float = LIMIT, min_support: int = 1) -> dict[str, dict]:
    """Seconds of every method on one instance, and whether it went over the limit."""
    out = {}
    for method in methods:
        seconds, over = within(lambda m=method: pairs.pair_support(rows, m, min_support), limit)
        out[f"{name}_{method}"] = {"s": round(seconds, 3), "over_limit": over}
    return out


def prefix(words: DataFrame, docs: int) -> tuple[DataFrame, int]:
    """The words of the ``docs`` documents of smallest id as dense item ids (written), and a support of 2 %."""
    least = max(2, docs // 50)
    last = words.select("tid").distinct().orderBy("tid").limit(docs).agg(F.max("tid")).first()[0]
    ids, _ = incidence.encoded(cut(pairs.prune(words.where(F.col("tid") <= last), least), "bench"))
    return cut(ids, "bench"), least


def stored_bytes(inc: DataFrame, cfg: Config | None = None) -> dict[str, int]:
    """Bytes that each layout really stores for an instance: maps with their floor, slack and slot
    width, 32-bit lists, and bitmaps a segment long."""
    from .operators import baselines
    from .plans import planner

    cfg = cfg or planner.tune(planner.statistics(inc))
    size = lambda df, c: df.agg(F.coalesce(F.sum(F.length(c)), F.lit(0))).first()[0]
    return {
        "map_bytes": size(builder.maps_of(builder.build(inc, cfg)), "slots"), "list_bytes": size(baselines.packed_lists(inc, cfg), "payload"),
        "bitmap_bytes": size(baselines.packed_bitmaps(inc, cfg), "payload"),
    }


def peak_worker_mb(spark: SparkSession) -> float:
    """The most resident memory that any of the Python workers at hand has had, in MB: a
    high-water mark since the worker started."""

    def go(batches):
        for _ in batches:
            time.sleep(0.05)  # so that every worker gets one
            yield pa.RecordBatch.from_arrays([pa.array([resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1024], pa.float64())], ["mb"])

    n = 4 * spark.sparkContext.defaultParallelism
    return round(max(r["mb"] for r in spark.range(0, n, 1, n).mapInArrow(go, "mb double").collect()), 1)


def split_scaling(inc: DataFrame, method: str, parts: int, min_support: int = 1, cfg: Config = Config()) -> float:
    """Seconds of the slowest of ``parts`` equal parts of the transactions, run one at a time."""
    rows = cut(inc, "bench")
    return max(timed(lambda k=k: pairs.pair_support(rows.where(F.col("tid") % parts == k), method, min_support, cfg)) for k in range(parts))


def _workers(spark: SparkSession, workers: int, run: Callable[[], float]) -> float:
    """The longest time that one of ``workers`` simultaneous runs took."""

    def go(batches):
        for _ in batches:
            yield pa.RecordBatch.from_arrays([pa.array([run()], pa.float64())], ["s"])

    return max(r["s"] for r in spark.range(0, workers, 1, workers).mapInArrow(go, "s double").collect())


def kernel_throughput(spark: SparkSession, words: int = 5_000_000, reps: int = 300, workers: int = 1, cfg: Config = Config()) -> float:
    """Bytes a second, over all workers, of the lane counting on two arrays of 32-bit words."""

    def run() -> float:
        rng = np.random.default_rng(1)
        x, y = (rng.integers(0, 1 << 63, words // 2, dtype=np.int64).view(np.uint64) for _ in range(2))
        step = cfg.slice_bytes // 8
        began = time.perf_counter()
        for _ in range(reps):
            sum(int(compare.lane_matches_np(x[at : at + step], y[at : at + step]).sum()) for at in range(0, len(x), step))
        return time.perf_counter() - began

    return workers * reps * 2 * 4 * words / _workers(spark, workers, run)


def tile_throughput(n: int = 512, width: int = 3 << 13, cfg: Config = Config()) -> float:
    """Bytes a second of one tile of n x n maps, as the pair phase counts them (n^2 times a map's bytes)."""
    rng = np.random.default_rng(2)
    payloads = [rng.integers(0, 256, width, dtype=np.uint8).tobytes() for _ in range(n)]
    began = time.perf_counter()
    compare.slot_kernel(cfg)(payloads, payloads)
    return n * n * width / (time.perf_counter() - began)


def merge_throughput(spark: SparkSession, log2_n: int = 24, reps: int = 100, workers: int = 1) -> float:
    """Elements a second, over all workers, of counting common elements of two sorted arrays by one
    merge (the sort finds two runs and merges them)."""

    def run() -> float:
        rng = np.random.default_rng(3)
        x, y = (np.unique(rng.integers(0, 1 << 31, 1 << log2_n, dtype=np.int64)).astype(np.int32) for _ in range(2))
        began = time.perf_counter()
        for _ in range(reps):
            compare.merge_np(x, y)
        return time.perf_counter() - began

    return workers * reps * 2 * (1 << log2_n) / _workers(spark, workers, run)
