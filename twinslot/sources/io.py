"""Sources and sinks: tables, basket files, maps, pairs, buckets."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..schema import MAPS, require


def read_table(spark: SparkSession, directory: str, name: str, columns: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{directory}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_baskets(spark: SparkSession, path: str, sep: str = " ", tid: str | None = None) -> DataFrame:
    """``(tid, token)`` of a text file with one transaction a line.

    Lines have no number in a distributed file, so a transaction is named by the file and its
    place there, unless the first token is its id (``tid="first"``). Blank tokens are left out."""
    tokens = F.split(F.trim("value"), sep)
    lines = spark.read.text(path).select(tokens.alias("tokens"), F.monotonically_increasing_id().alias("line"))
    if tid == "first":
        rows = lines.select(F.element_at("tokens", 1).try_cast("long").alias("tid"), F.explode(F.slice("tokens", 2, 1 << 30)).alias("token"))
    else:
        rows = lines.select(F.col("line").alias("tid"), F.explode("tokens").alias("token"))
    return rows.where("token <> ''")


def read_delimited(spark: SparkSession, path: str, schema: T.StructType | str, header: bool = True) -> DataFrame:
    return spark.read.schema(schema).option("header", header).csv(path)


def read_json(spark: SparkSession, path: str, schema: T.StructType | str) -> DataFrame:
    return spark.read.schema(schema).json(path)


def write_maps(maps: DataFrame, path: str, mode: str = "errorifexists") -> None:
    """Maps partitioned by segment, so that ranges of transactions prune files."""
    require(maps, *MAPS.fieldNames())
    maps.select(*MAPS.fieldNames()).repartition("seg").write.mode(mode).partitionBy("seg").parquet(path)


def read_maps(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(MAPS).parquet(path).select(*MAPS.fieldNames())


def write_pairs(pairs: DataFrame, path: str, fmt: str = "parquet", mode: str = "errorifexists") -> None:
    """parquet, csv, json, baskets (text lines ``a b support``) or noop (timing only)."""
    if fmt == "noop":
        pairs.write.format("noop").mode("overwrite").save()
    elif fmt == "baskets":
        pairs.select(F.concat_ws(" ", "item_a", "item_b", "support").alias("value")).write.mode(mode).text(path)
    elif fmt in ("parquet", "csv", "json"):
        writer = pairs.write.mode(mode)
        (writer.option("header", True) if fmt == "csv" else writer).format(fmt).save(path)
    else:
        raise ValueError(f"unknown format {fmt!r}")


def bucketed(df: DataFrame, name: str, columns: list[str], n: int) -> DataFrame:
    """A bucketed table: later joins and groupings on the columns need no exchange."""
    df.write.mode("overwrite").bucketBy(n, *columns).sortBy(*columns).saveAsTable(name)
    return df.sparkSession.table(name)
