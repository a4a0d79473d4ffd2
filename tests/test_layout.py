"""Slots, ranges, indicator bits and lane counting."""

import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

from twinslot.config import Config
from twinslot.functions import layout
from twinslot.operators import builder, compare


@pytest.mark.parametrize("bits", (8, 16, 32))
def test_codes_survive_packing(bits):
    cfg = Config(segment_j=5, slot_bits=bits)
    codes = np.arange(cfg.segment)
    r_bits = cfg.cap_bits
    r0 = 1 << cfg.r0_bits
    for t in range(3):
        slots = np.zeros(3 << max(r_bits, cfg.r0_bits), layout.KINDS[bits])
        where = layout.slot_of(codes, t, 1 << max(r_bits, cfg.r0_bits), r0)
        assert len(set(where.tolist())) == len(codes)
        slots[where] = layout.encode(codes, codes % 2, cfg)
        got, tables, bit = layout.decode(slots, max(r_bits, cfg.r0_bits), cfg)
        order = np.argsort(got)
        assert (got[order] == codes).all() and (tables == t).all() and (bit[order] == codes % 2).all()
        assert (slots[where] != 0).all()  # zero is kept for vacancy


def test_wide_slots_face_narrow_ones():
    cfg = Config(segment_j=4)
    codes = np.arange(cfg.segment)
    r0 = 1 << cfg.r0_bits
    for small, large in itertools.combinations(range(cfg.r0_bits, cfg.r0_bits + 5), 2):
        for t in range(3):
            wide, narrow = (layout.slot_of(codes, t, 1 << b, r0) for b in (large, small))
            assert (wide % (3 << small) == narrow).all()


def test_range_rule():
    plain = Config(slack=0.0, segment_j=0)
    for n in (1, 2, 31, 32, 33):
        assert 1 << int(layout.range_bits(n, plain)) >= min(2 * n, 1 << plain.cap_bits)
    assert int(layout.range_bits(1024, Config(slack=0.0))) == 11
    assert int(layout.range_bits(1024, Config())) == 12  # at the critical load
    assert int(layout.range_bits(65_000, Config())) == Config().cap_bits


def test_range_rule_as_column(spark):
    cfg = Config()
    ns = [1, 2, 3, 255, 256, 257, 1000, 1024, 1025, 1781, 1782, 40_000, 65_024]
    df = spark.createDataFrame([(n,) for n in ns], "n long").select("n", layout.range_bits_column(F.col("n"), cfg).alias("b"))
    assert {r["n"]: r["b"] for r in df.collect()} == {n: int(layout.range_bits(n, cfg)) for n in ns}


def test_indicator_counts_every_case_once(spark):
    """One element in two sets: nine combinations of tables, each counted once; vacancy never."""
    choices = [(0, 1), (1, 2), (2, 0)]

    def word(pair):
        first, last = pair
        lanes = [0, 0, 0, 0]
        lanes[first] = 5 | 0x80 * int(layout.indicator(np.array(first), np.array(last)))
        lanes[last] = 5 | 0x80 * int(layout.indicator(np.array(last), np.array(first)))
        return sum(v << 8 * i for i, v in enumerate(lanes))

    words = [word(c) for c in choices] + [0]
    assert [int(layout.indicator(np.array(b), np.array(a))) for a, b in choices] == [1, 1, 1]
    df = spark.createDataFrame([(a, b) for a in words for b in words], "a long, b long")
    got = {(r[0], r[1]): r[2] for r in df.select("a", "b", compare.lane_count(F.col("a"), F.col("b"))).collect()}
    for a in words:
        for b in words:
            want = int(a != 0 and b != 0)
            assert got[a, b] == want
            assert int(compare.lane_matches_np(np.array([a], np.uint64), np.array([b], np.uint64)).sum()) == want


@pytest.mark.parametrize("bits", (8, 16, 32))
def test_lanes_against_a_loop(bits):
    rng = np.random.default_rng(3)
    n = 400
    kind = layout.KINDS[bits]
    x, y = (rng.integers(0, 1 << bits, 8 * n).astype(kind) for _ in range(2))
    y[::3] = x[::3]
    y[1::3] = x[1::3] ^ np.array(1 << (bits - 1), kind)
    top = 1 << (bits - 1)
    want = sum((int(a) ^ int(b)) & (top - 1) == 0 and (int(a) | int(b)) & top != 0 for a, b in zip(x, y))
    assert int(compare.lane_matches_np(x.view(np.uint64), y.view(np.uint64), bits).sum()) == want


def test_all_byte_pairs():
    a, b = (v.ravel().astype(np.uint8) for v in np.meshgrid(np.arange(256), np.arange(256)))
    want = ((a ^ b) & 127 == 0) & ((a | b) & 128 != 0)
    got = compare.lane_matches_np(a.view(np.uint64), b.view(np.uint64))
    assert (got == want.reshape(-1, 8).sum(axis=1)).all()


def test_worked_placement():
    """Three elements of which two share places: each ends in exactly two of its three."""
    cfg = Config(segment_j=0)
    x = np.array([3, 40, 77])
    done = builder.place(np.zeros(3, np.int64), x, np.zeros(1, np.int64), layout.range_bits(np.array([3]), cfg), cfg)
    assert not len(done.failed) and np.count_nonzero(done.slots) == 6
    assert compare.elements_np(done.slots.tobytes(), int(layout.range_bits(3, cfg)), cfg).tolist() == x.tolist()


@pytest.mark.parametrize("n,rounds", [(1, 30), (30, 30), (1000, 30), (1024, 30), (500, 1), (900, 3)])
def test_two_copies_or_none(n, rounds):
    cfg = Config(segment_j=3, slack=0.0, max_rounds=rounds)
    rng = np.random.default_rng(n + rounds)
    xs = [np.sort(rng.choice(cfg.segment, min(n, cfg.segment), replace=False)) for _ in range(4)]
    bits = np.array([int(layout.range_bits(len(x), cfg)) for x in xs])
    starts = np.concatenate(([0], np.cumsum(3 << bits)[:-1]))
    flat = np.concatenate(xs)
    done = builder.place(np.repeat(np.arange(4), [len(x) for x in xs]), flat, starts, bits, cfg)
    assert np.count_nonzero(done.slots) + 2 * len(done.failed) == 2 * len(flat)
    failed = np.zeros(len(flat), bool)
    failed[done.failed] = True
    at = 0
    for k, x in enumerate(xs):
        held = compare.elements_np(done.slots[starts[k] : starts[k] + (3 << bits[k])].tobytes(), int(bits[k]), cfg)
        assert held.tolist() == x[~failed[at : at + len(x)]].tolist()
        at += len(x)


def test_counts_of_unequal_widths():
    cfg = Config(segment_j=6)
    rng = np.random.default_rng(5)
    sets = [np.sort(rng.choice(cfg.segment, n, replace=False)) for n in (1, 7, 300, 2000, cfg.segment)]
    maps = []
    for x in sets:
        bits = layout.range_bits(np.array([len(x)]), cfg)
        done = builder.place(np.zeros(len(x), np.int64), x, np.zeros(1, np.int64), bits, cfg)
        assert not len(done.failed)
        maps.append((done.slots.tobytes(), int(bits[0])))
    for (x, (a, _)), (y, (b, _)) in itertools.product(zip(sets, maps), repeat=2):
        assert compare.count_np(a, b, cfg) == len(np.intersect1d(x, y))


def test_failure_grows_at_the_critical_load():
    """Loads below a half place nearly all elements, loads above lose some; moves stay small."""
    cfg = Config(segment_j=9, slack=0.0)
    rng = np.random.default_rng(1)

    def run(n, bits):
        x = np.sort(rng.choice(cfg.segment, n, replace=False))
        return builder.place(np.zeros(n, np.int64), x, np.zeros(1, np.int64), np.array([bits]), cfg)

    easy, hard = run(1024, 12), run(1400, 11)
    assert not len(easy.failed) and len(hard.failed) > 0
    assert 1 <= easy.moves.sum() / 2048 < hard.moves.sum() / 2800
