"""Incidences, windows and pair supports over streams."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from ..config import Config
from ..functions import sqlfun
from ..sources.incidence import place_of, segment_of
from ..stages import new_path

EVENTS = "event_id long, user_id long, ts timestamp, event_type string, value double, props string"


def source(spark: SparkSession, path: str, schema: str = EVENTS, files_per_batch: int | None = None) -> DataFrame:
    """Files that appear in a directory, with a declared schema."""
    reader = spark.readStream.schema(schema)
    return (reader.option("maxFilesPerTrigger", files_per_batch) if files_per_batch else reader).parquet(path)


def incidence(src: DataFrame, item: str, tid: str, time: str = "ts", watermark: str = "10 minutes") -> DataFrame:
    """Distinct ``(item, tid)`` of a stream, duplicates removed within the watermark."""
    rows = src.select(F.col(item).alias("item"), F.col(tid).alias("tid"), F.col(time).alias("time"))
    return rows.where("item IS NOT NULL AND tid IS NOT NULL").withWatermark("time", watermark).dropDuplicatesWithinWatermark(["item", "tid"])


def windowed_sets(src: DataFrame, kind: str, key: str = "event_type", member: str = "user_id", time: str = "ts", watermark: str = "10 minutes",
                  size: str = "1 hour", slide: str = "30 minutes") -> DataFrame:
    """Rows and distinct members (approximate, a bounded sketch a window) of tumbling, sliding or session windows."""
    window = {"tumbling": F.window(time, size), "sliding": F.window(time, size, slide), "session": F.session_window(time, size)}[kind]
    grouped = src.withWatermark(time, watermark).groupBy(window.alias("w"), key)
    return grouped.agg(F.count("*").alias("n"), F.approx_count_distinct(member).alias("members")).select(
        F.col("w.start").alias("start"), F.col("w.end").alias("end"), key, "n", "members"
    )


def with_static(src: DataFrame, static: DataFrame, on: str) -> DataFrame:
    """Stream-static join; the static side is read anew by each batch."""
    return src.join(static, on)


def followed_by(src: DataFrame, other: DataFrame, key: str = "user_id", time: str = "ts", within: str = "1 hour", watermark: str = "10 minutes") -> DataFrame:
    """Stream-stream interval join: rows of ``other`` after a row of ``src`` of the same key."""
    a = src.select(F.col(key).alias("key_a"), F.col(time).alias("t_a"), F.col("event_id").alias("id_a")).withWatermark("t_a", watermark)
    b = other.select(F.col(key).alias("key_b"), F.col(time).alias("t_b"), F.col("event_id").alias("id_b")).withWatermark("t_b", watermark)
    return a.join(b, (F.col("key_a") == F.col("key_b")) & (F.col("t_b") > F.col("t_a")) & (F.col("t_b") <= F.col("t_a") + F.expr(f"interval {within}")))


class PairStore:
    """Pair supports that micro-batches keep up to date.

    A batch's new incidences meet each other and what is stored; the counts of the batch are
    one immutable part named by the batch's number, so replaying a batch replaces its part
    and never counts twice. ``supports`` sums the parts."""

    def __init__(self, spark: SparkSession, path: str | None = None):
        self.spark, self.path = spark, path or new_path(spark, "pairs")

    def _parts(self, kind: str, schema: str) -> DataFrame:
        try:
            return self.spark.read.parquet(f"{self.path}/{kind}")
        except Exception as error:  # nothing stored yet
            if "PATH_NOT_FOUND" not in str(error):
                raise
            return self.spark.createDataFrame([], schema + ", batch long")

    def add(self, batch: DataFrame, number: int) -> None:
        old = self._parts("incidence", "item string, tid long").where(F.col("batch") < number).select("item", "tid")
        rows = batch.select(F.col("item").cast("string").alias("item"), F.col("tid").cast("long").alias("tid")).distinct()
        new = rows.join(old, ["item", "tid"], "left_anti")
        new.write.mode("overwrite").parquet(f"{self.path}/incidence/batch={number}")
        new = self.spark.read.schema("item string, tid long").parquet(f"{self.path}/incidence/batch={number}")
        a, b, o = new.alias("a"), new.alias("b"), old.alias("o")
        lo, hi = F.least("x", "y").alias("item_a"), F.greatest("x", "y").alias("item_b")
        inner = a.join(b, "tid").where("a.item < b.item").select(F.col("a.item").alias("x"), F.col("b.item").alias("y"))
        outer = a.join(o, "tid").select(F.col("a.item").alias("x"), F.col("o.item").alias("y"))
        counts = inner.unionByName(outer).groupBy(lo, hi).agg(F.count("*").alias("support"))
        counts.write.mode("overwrite").parquet(f"{self.path}/counts/batch={number}")

    def supports(self) -> DataFrame:
        parts = self._parts("counts", "item_a string, item_b string, support long")
        return parts.groupBy("item_a", "item_b").agg(F.sum("support").alias("support"))


def pair_support(src: DataFrame, item: str, tid: str, store: PairStore, checkpoint: str):
    """A started query that keeps ``store`` up to date, one batch at a time until the source is read."""
    rows = src.select(F.col(item).alias("item"), F.col(tid).alias("tid")).where("item IS NOT NULL AND tid IS NOT NULL")
    return rows.writeStream.foreachBatch(store.add).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def growing_sets(src: DataFrame, item: str, tid: str, cfg: Config = sqlfun.CONFIG) -> DataFrame:
    """``(item, seg, size, log2_range, map)`` each time a set's map has changed, in append mode.

    The state of an item and segment is its map (as ``twinslot_build`` makes it), so it is bounded by
    a segment; a batch reads the elements back, adds new ones and places them again, in a range that
    doubles when it is outgrown. The row of the largest size is the current map."""
    schema = "item string, seg long, size long, log2_range int, map binary"

    def update(key, batches, group):
        held = sqlfun.elements_one(bytes(group.get[0]), cfg) if group.exists else np.zeros(0, np.int64)
        seen = [pdf["x"].to_numpy(np.int64) for pdf in batches]
        members = np.union1d(held, np.concatenate([held, *seen]))
        if len(members) > len(held):
            data = sqlfun.build_one(members, cfg)
            group.update((data,))
            yield pd.DataFrame([(key[0], key[1], len(members), data[0], data)], columns=["item", "seg", "size", "log2_range", "map"])

    at = F.col(tid).cast("long")
    rows = src.select(F.col(item).cast("string").alias("item"), segment_of(at, cfg.segment).alias("seg"), place_of(at, cfg.segment).alias("x"))
    return rows.where("item IS NOT NULL AND x IS NOT NULL").groupBy("item", "seg").applyInPandasWithState(update, schema, "map binary", "append", GroupStateTimeout.NoTimeout)


def run_once(streaming: DataFrame, path: str, checkpoint: str, mode: str = "append") -> None:
    """Process what the source has, to Parquet, and stop (restarts go on from the checkpoint)."""
    streaming.writeStream.format("parquet").outputMode(mode).option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
