"""Chat logs: collapse cumulative snapshots, then render what is left.

A log often holds a conversation many times, once after each turn. Every turn gets the
rolling hash of the turns up to it; a conversation whose full hash is the hash of a
proper prefix of another one is a snapshot of that one, and an anti-join drops it. Of
equal conversations the smallest conv_id stays. All of it is DataFrame operations.

The rolling hash is a sum of 32-bit lanes of hashes of (position, role, text), so it can be
built in two levels: within blocks of ``BLOCK`` turns, and over blocks. One conversation
that holds a third of all turns is therefore dealt to many tasks.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cut

BLOCK = 64
LANES = ("l0", "l1", "l2", "l3")


def _hash(*columns: Column) -> list[Column]:
    """Two 64-bit hashes in which null and the empty string differ."""
    parts = [x for c in columns for x in (c.isNull(), c)]
    return [F.xxhash64(*parts), F.xxhash64(F.lit("second"), *reversed(parts))]


def turns(df: DataFrame, conv_id: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """Distinct turns without their texts: ``(conv_id, block, turn, h1, h2)``."""
    h1, h2 = _hash(F.col(role), F.col(text))
    at = F.col(turn).cast("long")
    return (
        df.select(F.col(conv_id).cast("long").alias("conv_id"), F.floor(at / BLOCK).alias("block"), at.alias("turn"), h1.alias("h1"), h2.alias("h2"))
        .where("conv_id IS NOT NULL")
        .distinct()
    )


def prefixes(rows: DataFrame) -> DataFrame:
    """``rows`` with ``pos`` (from 1), the four lanes of the prefix that ends there, and
    ``has_next``. Order: turn (null first), then the hashes, so ties have one order too."""
    inner = Window.partitionBy("conv_id", "block").orderBy(F.col("turn").asc_nulls_first(), "h1", "h2")
    outer = Window.partitionBy("conv_id").orderBy(F.col("block").asc_nulls_first())
    so_far = outer.rowsBetween(Window.unboundedPreceding, -1)
    key = lambda left, right: (left["conv_id"] == right["conv_id"]) & left["block"].eqNullSafe(right["block"])
    blocks = rows.groupBy("conv_id", "block").agg(F.count("*").alias("n"))
    blocks = cut(
        blocks.withColumn("base", F.coalesce(F.sum("n").over(so_far), F.lit(0))).withColumn("more", F.lead("n").over(outer).isNotNull()), "blocks"
    )
    placed = rows.withColumn("rn", F.row_number().over(inner)).withColumn("last", F.lead("h1").over(inner).isNull())
    b = blocks.select(F.col("conv_id").alias("bc"), F.col("block").alias("bb"), "base", "more")
    placed = placed.join(b, (F.col("conv_id") == F.col("bc")) & F.col("block").eqNullSafe(F.col("bb"))).drop("bc", "bb")
    pos = (F.col("base") + F.col("rn")).cast("long")
    e1, e2 = F.xxhash64(pos, "h1", "h2"), F.xxhash64("h2", "h1", pos)
    low = F.lit(0xFFFFFFFF).cast("long")
    lanes = [e1.bitwiseAND(low), F.shiftrightunsigned(e1, 32), e2.bitwiseAND(low), F.shiftrightunsigned(e2, 32)]
    placed = placed.select(
        "conv_id", "block", "turn", "h1", "h2", pos.alias("pos"), (F.col("more") | ~F.col("last")).alias("has_next"),
        *(x.alias(n) for x, n in zip(lanes, LANES)),
    )
    placed = cut(placed, "placed")
    sums = placed.groupBy("conv_id", "block").agg(*(F.sum(n).alias(n) for n in LANES))
    sums = cut(sums.select("conv_id", "block", *(F.coalesce(F.sum(n).over(so_far), F.lit(0)).alias(f"b{n}") for n in LANES)), "sums")
    s = sums.withColumnRenamed("conv_id", "sc").withColumnRenamed("block", "sb")
    run = inner.rowsBetween(Window.unboundedPreceding, 0)
    return (
        placed.select("conv_id", "block", "turn", "h1", "h2", "pos", "has_next", *(F.sum(n).over(run).alias(n) for n in LANES))
        .join(s, (F.col("conv_id") == F.col("sc")) & F.col("block").eqNullSafe(F.col("sb")))
        .select("conv_id", "block", "turn", "h1", "h2", "pos", "has_next", *((F.col(n) + F.col(f"b{n}")).alias(n) for n in LANES))
    )


def maximal(df: DataFrame, conv_id: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> tuple[DataFrame, DataFrame]:
    """``(kept, positions)``: kept has ``(conv_id, n_turns, copies)``, one row for each
    maximal conversation; positions has each turn's place in its conversation.

    Rows with a null conv_id belong to no conversation. A row repeated exactly counts
    once. Null roles and texts are values of their own. Turns of one number are ordered by
    their hashes. Further columns don't matter; an empty table gives none.
    """
    marked = cut(prefixes(turns(df, conv_id, turn, role, text)), "prefixes")
    same = ["pos", *LANES]
    whole = marked.where("NOT has_next").groupBy(*same).agg(F.min("conv_id").alias("conv_id"), F.count("*").alias("copies"))
    longer = marked.where("has_next").select(*same).distinct()
    kept = whole.join(longer, same, "left_anti").select("conv_id", F.col("pos").alias("n_turns"), "copies")
    return cut(kept, "kept"), marked


def render(df: DataFrame, conv_id: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """``(conv_id, segment, n_turns, copies, rendered)`` of the maximal conversations.

    A turn is ``<|role|>``, a line break, its text, ``<|end|>`` and a line break (null role:
    ``unknown``; null text: empty). A segment holds at most ``BLOCK`` turns, numbered from 0,
    and segments of a conversation in order are its whole text: no row grows with a
    conversation's length. A turn's text is never cut, so a segment is as long as its texts.
    Turns without a number are one block of their conversation, ordered by their hashes.
    """
    kept, marked = maximal(df, conv_id, turn, role, text)
    h1, h2 = _hash(F.col(role), F.col(text))
    line = F.concat(F.lit("<|"), F.coalesce(F.col(role), F.lit("unknown")), F.lit("|>\n"), F.coalesce(F.col(text), F.lit("")), F.lit("<|end|>\n"))
    at = F.col(turn).cast("long")
    lines = df.select(F.col(conv_id).cast("long").alias("conv_id"), at.alias("turn"), h1.alias("h1"), h2.alias("h2"), line.alias("line"))
    places = marked.join(kept, "conv_id").select(
        F.col("conv_id").alias("pc"), F.col("turn").alias("pt"), F.col("h1").alias("p1"), F.col("h2").alias("p2"), "pos", "n_turns", "copies"
    )
    joined = lines.join(
        cut(places, "places"), (F.col("conv_id") == F.col("pc")) & F.col("turn").eqNullSafe(F.col("pt")) & (F.col("h1") == F.col("p1")) & (F.col("h2") == F.col("p2"))
    )
    segment = F.floor((F.col("pos") - 1) / BLOCK).alias("segment")
    return (
        joined.groupBy("conv_id", segment, "n_turns", "copies")
        .agg(F.array_sort(F.collect_set(F.struct("pos", "line"))).alias("lines"))
        .select("conv_id", "segment", "n_turns", "copies", F.array_join(F.col("lines.line"), "").alias("rendered"))
    )
