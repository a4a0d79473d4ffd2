"""SQL functions: counts and membership on maps, an aggregate that builds one, table functions.

After ``register(spark)``: ``twinslot_count(a, b)``, ``twinslot_contains(map, log2_r, x)``,
``twinslot_card(map)``, ``twinslot_build(x)`` (grouped aggregate over positions of one segment),
``twinslot_elements(map)`` and ``basket_pairs(items)`` (table functions for LATERAL)."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..config import Config
from . import layout

CONFIG = Config(slack=0.6)


def build_one(x: np.ndarray, cfg: Config) -> bytes:
    """One map of positions within a segment: one byte log2 of the range, the slots, and the
    elements that found no place as 32-bit integers behind them."""
    from ..operators import builder

    x = np.unique(x.astype(np.int64))
    bits = layout.range_bits(np.array([max(1, len(x))]), cfg)
    done = builder.place(np.zeros(len(x), np.int64), x, np.zeros(1, np.int64), bits, cfg)
    return bytes([int(bits[0])]) + done.slots.tobytes() + x[done.failed].astype("<i4").tobytes()


def parts(data: bytes, cfg: Config) -> tuple[int, bytes, np.ndarray]:
    bits = data[0]
    end = 1 + (3 << bits) * cfg.slot_bits // 8
    return bits, data[1:end], np.frombuffer(data[end:], "<i4").astype(np.int64)


def elements_one(data: bytes, cfg: Config) -> np.ndarray:
    from ..operators import compare

    bits, slots, lost = parts(data, cfg)
    return np.sort(np.concatenate([compare.elements_np(slots, bits, cfg), lost]))


def count_one(a: bytes, b: bytes, cfg: Config) -> int:
    from ..operators import compare

    (_, x, lost_x), (_, y, lost_y) = parts(a, cfg), parts(b, cfg)
    n = compare.count_np(x, y, cfg)
    if len(lost_x) or len(lost_y):  # repair: failed elements are looked up
        ex, ey = elements_one(a, cfg), elements_one(b, cfg)
        n += len(np.intersect1d(np.union1d(lost_x, lost_y), np.intersect1d(ex, ey)))
    return n


class Elements:
    """Table function: the elements of a map."""

    def eval(self, data: bytes):
        if data is not None:
            for x in elements_one(bytes(data), CONFIG).tolist():
                yield (x,)


class BasketPairs:
    """Table function: all pairs of a basket's distinct items, smaller first."""

    def eval(self, items: list[int]):
        some = sorted({i for i in items or [] if i is not None})
        for i, a in enumerate(some):
            for b in some[i + 1 :]:
                yield a, b


def build_agg(cfg: Config = CONFIG):
    """Grouped aggregate: positions of one segment to a map."""

    def build(x: pd.Series) -> bytes:
        return build_one(x.to_numpy(), cfg)

    return F.pandas_udf(build, "binary")


def register(spark: SparkSession, cfg: Config = CONFIG) -> None:
    def counts(pairs: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for a, b in pairs:
            yield pd.Series([None if x is None or y is None else count_one(bytes(x), bytes(y), cfg) for x, y in zip(a, b)], dtype="Int64")

    def cards(a: pd.Series) -> pd.Series:
        return pd.Series([None if x is None else len(elements_one(bytes(x), cfg)) for x in a], dtype="Int64")

    def holds(a: pd.Series, x: pd.Series) -> pd.Series:
        """Rows of one map are looked up together; a null gives a null."""
        from ..operators import compare

        out = pd.Series([None] * len(a), dtype="boolean", index=a.index)
        known = a.notna() & x.notna()
        for data, rows in x[known].groupby(a[known].map(bytes), sort=False):
            bits, slots, lost = parts(data, cfg)
            places = rows.to_numpy(np.int64)
            out[rows.index] = compare.held_np(slots, bits, places, cfg) | np.isin(places, lost)
        return out

    spark.udf.register("twinslot_count", F.pandas_udf(counts, "long"))
    spark.udf.register("twinslot_card", F.pandas_udf(cards, "long"))
    spark.udf.register("twinslot_contains", F.pandas_udf(holds, "boolean"))
    spark.udf.register("twinslot_build", build_agg(cfg))
    spark.udtf.register("twinslot_elements", F.udtf(Elements, returnType="x long"))
    spark.udtf.register("basket_pairs", F.udtf(BasketPairs, returnType="item_a long, item_b long"))
