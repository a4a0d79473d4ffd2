"""Shared helpers: tables, free column names, connected components."""

from __future__ import annotations

from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..stages import cut, discard, new_path, scratch, shared_dir

__all__ = ["components", "cut", "discard", "free_name", "new_path", "scratch", "shared_dir", "small_batches", "table"]


@contextmanager
def small_batches(spark: SparkSession, rows: int = 512):
    """While tables are written inside, Arrow batches of texts hold at most ``rows`` rows."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    was = spark.conf.get(key)
    spark.conf.set(key, str(min(rows, int(was)) if int(was) > 0 else rows))
    try:
        yield
    finally:
        spark.conf.set(key, was)


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def free_name(df: DataFrame, wanted: str) -> str:
    """A column name that ``df`` doesn't have yet (names compare without case)."""
    have = {c.lower() for c in df.columns}
    while wanted.lower() in have:
        wanted += "_"
    return wanted


def components(links: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Connected components of ``links(a long, b long)`` -> ``(node, component)``.

    Alternating star contraction: each round points every node at the smallest
    node of its neighbourhood (large step, then small step) until the links
    are a forest of stars. A round is two partial aggregations and two joins whose
    sides are read from written tables, so Spark can split a hub's rows; no
    neighbourhood is ever gathered. Nodes that occur in no link don't appear.
    Links with a null end or equal ends are ignored; no links give no rows.
    """
    edges = cut(
        links.where("a IS NOT NULL AND b IS NOT NULL AND a <> b")
        .select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"))
        .distinct(),
        "links",
    )
    for _ in range(max_rounds):
        # Large step: both directions; larger neighbours move to the node's minimum.
        both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = cut(both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")), "least")
        large = cut(
            both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct(), "large"
        )
        discard(least)
        # Small step: a node and its smaller neighbours all move to their minimum.
        least = cut(large.groupBy("u").agg(F.min("v").alias("m")), "least")
        joined = large.join(least, "u")
        small = cut(
            joined.select(F.col("v").alias("u"), F.col("m").alias("v"))
            .union(least.select("u", F.col("m").alias("v")))
            .where("u <> v")
            .distinct(),
            "small",
        )
        discard(least)
        discard(large)
        discard(edges)
        edges = small
        # Links lead from larger to smaller nodes, so a forest of stars (no node with
        # two parents, no parent with a parent) is final: its centres are the minima.
        chained = edges.join(edges.select(F.col("v").alias("u")).distinct(), "u", "left_semi")
        if chained.isEmpty() and edges.groupBy("u").count().where("count > 1").isEmpty():
            break
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).union(
        edges.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    )
