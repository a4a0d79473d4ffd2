"""Ranges, addresses, indicator bits and packed slots."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from ..config import Config

KINDS = {8: "<u1", 16: "<u2", 32: "<u4"}


def range_bits(card: np.ndarray | int, cfg: Config) -> np.ndarray:
    """log2 of the range of a set of ``card`` elements: twice the next power of two, at
    least what the packing needs, doubled near the critical load, at most a segment."""
    n = np.maximum(np.asarray(card, np.int64), 1)
    up = np.zeros_like(n)
    for b in range(1, 40):
        up += (n - 1) >> (b - 1) > 0  # integer bit length
    bits = up + 1
    bits = bits + ((1 << bits) < 2 * (1 + cfg.slack) * n) * (cfg.slack > 0)
    return np.minimum(np.maximum(bits, cfg.r0_bits), max(cfg.cap_bits, cfg.r0_bits))


def range_bits_column(card: Column, cfg: Config) -> Column:
    """The same in Column arithmetic (card >= 1)."""
    bits = F.when(card <= 1, F.lit(1)).otherwise(F.length(F.bin((card - 1).cast("long"))) + 1)
    r = F.call_function("shiftleft", F.lit(1).cast("long"), bits)
    if cfg.slack > 0:
        bits = bits + F.when(r < card * F.lit(2 * (1 + cfg.slack)), 1).otherwise(0)
    return F.least(F.greatest(bits, F.lit(cfg.r0_bits)), F.lit(max(cfg.cap_bits, cfg.r0_bits))).cast("int")


def slot_of(code: np.ndarray, t: int | np.ndarray, r: np.ndarray | int, r0: int, tables: int = 3) -> np.ndarray:
    """Place of a code in table ``t``: tables alternate in units of ``r0`` slots, so slot q
    of a wide map always faces slot q mod width of a narrow one."""
    low = code & (r - 1)
    return (low // r0) * (tables * r0) + (low % r0) + t * r0


def indicator(t: np.ndarray, other: np.ndarray) -> np.ndarray:
    """1 on the copy that comes later in the cyclic order of its two tables."""
    return ((np.asarray(t) - np.asarray(other)) % 3 == 1).astype(np.uint8)


def encode(code: np.ndarray, bit: np.ndarray, cfg: Config) -> np.ndarray:
    """Slot values: the code's high bits plus one (zero is vacant), indicator on top."""
    return (((np.asarray(code, np.int64) >> cfg.shift) + 1) | (np.asarray(bit, np.int64) << (cfg.slot_bits - 1))).astype(KINDS[cfg.slot_bits])


def decode(slots: np.ndarray, log2_r: int, cfg: Config) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``(codes, tables, bits)`` of the occupied slots of one map: high bits from the slot,
    low bits from its position."""
    at = np.flatnonzero(slots)
    r0 = 1 << cfg.r0_bits
    value = slots[at].astype(np.int64)
    bit = value >> (cfg.slot_bits - 1)
    high = (value & ((1 << (cfg.slot_bits - 1)) - 1)) - 1
    block, inner = at // (3 * r0), at % (3 * r0)
    position = block * r0 + inner % r0
    return high << cfg.shift | position & ((1 << cfg.shift) - 1), inner // r0, bit
