"""Canonical relations, and checks of inputs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import types as T

INCIDENCE = T.StructType([T.StructField("item", T.LongType()), T.StructField("tid", T.LongType())])
PAIRS = T.StructType([T.StructField("item_a", T.LongType()), T.StructField("item_b", T.LongType()), T.StructField("support", T.LongType())])
MAPS = T.StructType(
    [
        T.StructField("item", T.LongType()), T.StructField("seg", T.LongType()), T.StructField("card", T.IntegerType()),
        T.StructField("log2_r", T.IntegerType()), T.StructField("slots", T.BinaryType()),
    ]
)
FAILED = INCIDENCE


def require(df: DataFrame, *columns: str) -> DataFrame:
    """``df``, or ``ValueError`` if it lacks a column."""
    missing = [c for c in columns if c not in df.columns]
    if missing:
        raise ValueError(f"columns {missing} are missing; there are {df.columns}")
    return df
