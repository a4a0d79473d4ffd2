"""Plans that must not grow with the tables: broadcasts have a bound, groups follow what they are sent."""

from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from twinslot.operators import baselines, builder, compare, kway, pairs, partial
from twinslot.operators import relational as rel
from twinslot.sources import incidence as inc

from .test_pairs import brute, frame, got, instance


def test_large_sides_are_not_broadcast(spark, monkeypatch):
    monkeypatch.setattr(rel, "BROADCAST_ROWS", 10)
    left = spark.range(40).select((F.col("id") % 20).alias("k"), "id")
    for n, broadcast in ((10, True), (11, False)):
        right = spark.range(n).select(F.col("id").alias("k"), (F.col("id") * 2).alias("v"))
        made = rel.join(left, right, ["k"], "inner", "broadcast")
        assert ("BroadcastHashJoin" in made._jdf.queryExecution().executedPlan().toString()) == broadcast
        assert made.count() == 2 * n


def test_groups_follow_stretches(spark, monkeypatch):
    """Long transactions send the square of their length, so they get more groups than their rows ask for."""
    rows = instance(5)
    monkeypatch.setattr(baselines, "FP_GROUPS", 1)
    monkeypatch.setattr(baselines, "FP_STRETCH", 200)
    total = sum(t * (t + 1) // 2 for t in Counter(tid for _, tid in set(rows)).values())
    assert baselines.fp_groups(frame(spark, rows)) == -(-total // 200) > 2
    assert got(baselines.fp_growth(frame(spark, rows))) == brute(rows)


def test_stretches_are_shuffled_once(spark):
    """Ids of 32 bits and longer ones give the same pairs; stretches meet one exchange by group."""
    rows = instance(6)
    assert got(baselines.fp_growth(frame(spark, rows))) == brute(rows)
    far = [(i + (1 << 40), t) for i, t in rows]
    plan = baselines.fp_growth(frame(spark, far))
    text = plan._jdf.queryExecution().executedPlan().toString()
    assert got(plan) == brute(far) and text.count("Exchange hashpartitioning(g#") == 1 and "path#" not in "".join(x for x in text.splitlines() if "Exchange" in x)


@pytest.mark.parametrize("low, high", ((0, 60), (1 << 62, (1 << 62) + 900), (-(1 << 63), (1 << 63) - 1)))
def test_partial_counts_are_packed(low, high):
    """Packed counts are those that went in, summed for each pair, at any ids and of either sign; near ids take under four bytes."""
    r = np.random.default_rng(7)
    a, b, n = r.integers(low, high, 4000), r.integers(low, high, 4000), r.integers(-2, 9, 4000)
    want = Counter()
    for x, y, k in zip(a.tolist(), b.tolist(), n.tolist()):
        want[x, y] += k
    rows = partial.pack([(a[:1000], b[:1000], n[:1000]), (a[1000:], b[1000:], n[1000:])], 5)
    found = [pair for _, blob in rows for pair in zip(*(c.tolist() for c in partial.decode(blob)))]
    assert len(found) == len(want) and {(x, y): k for x, y, k in found} == dict(want)
    assert high - low > 1000 or sum(len(blob) for _, blob in rows) < 4 * len(found)


def test_tiles_ship_packed_counts(spark, monkeypatch):
    """No exchange has a row for each pair and segment, and small steps and many buckets change nothing."""
    rows = instance(8)
    plan = pairs.pair_support(frame(spark, rows), cfg=pairs.Config(segment_j=0, max_rounds=2))
    text = plan._jdf.queryExecution().executedPlan().toString()
    assert "Exchange hashpartitioning(bucket#" in text
    assert got(plan) == brute(rows)
    monkeypatch.setattr(partial, "BUCKET_PAIRS", 3)
    assert got(pairs.pair_support(frame(spark, rows), min_support=2, cfg=pairs.Config(segment_j=0, max_rounds=2))) == {k: v for k, v in brute(rows).items() if v > 1}


@pytest.mark.parametrize("red, rounds", ((kway.Redundancy(3, 5), 60), (kway.Redundancy(3, 5), 1), (kway.Redundancy(2, 3), 1)))
def test_general_pairs_meet_in_tiles(spark, monkeypatch, red, rounds):
    """Pairs of general redundancy list no itemsets, count alike for sets of different ranges, and lose no element without places."""
    monkeypatch.setattr(pairs, "every_pair", None)
    rows = instance(9, n=8, m=500, p=0.3) + [(20, t) for t in range(0, 500, 3)] + [(21, t) for t in range(500)] + [(22, 7)]
    cfg = pairs.Config(segment_j=2, tile_items=3)
    assert got(kway.pair_support(frame(spark, rows), red, 2, cfg, rounds)) == brute(rows, 2)
    few = kway.assign(np.arange(500) % 508, red, kway._bits_of(red)(500), cfg, rounds)
    assert (few == 0).any() == (rounds < 60)


@pytest.mark.parametrize("cfg", (pairs.Config(), pairs.Config(segment_j=0), pairs.Config(slot_bits=16, segment_j=10), pairs.Config(slack=0.0, max_rounds=2)))
@pytest.mark.parametrize("share", (0.0, 0.004, 0.25, 0.9))
def test_compacted_maps_are_the_maps(cfg, share):
    """Elements and the table of the later copy are the whole map, in a few bits an element at any density."""
    x = np.flatnonzero(np.random.default_rng(3).random(cfg.segment) < share) if share else np.array([cfg.segment - 1])
    for _, n, bits, slots, _, _ in builder.build_arrays(np.zeros(len(x), np.int64), np.zeros(len(x), np.int64), x, cfg):
        small = compare.compacted(slots, bits, cfg)
        assert (compare.expanded(small, cfg) == slots).all() and len(small) < 3 * n + 40
        assert share < 0.2 or 10 * len(small) < len(slots.tobytes()) + 400
        assert compare.compact_kernel(cfg)([small], [small, small]).tolist() == [[len(compare.elements_np(slots.tobytes(), bits, cfg))] * 2]


def test_dense_sets_are_packed_as_words():
    r = np.random.default_rng(4)
    rows = {(i, s, x) for i, share in ((1, 0.3), (2, 0.001)) for s in (-1, 5) for x in np.flatnonzero(r.random(1 << 16) < share).tolist()}
    item, seg, x = (np.array(c) for c in zip(*rows, *list(rows)[:50]))  # repeats
    batches = list(inc._sets([(item, seg, x)]))
    back = [tuple(row) for b in batches for row in zip(*(c.tolist() for c in inc.rows_of_sets(b)))]
    assert len(back) == len(rows) and set(back) == rows and sum(sum(b.column("n").to_pylist()) for b in batches) == len(rows)
    assert sum(len(w or b"") for b in batches for w in b.column("ws").to_pylist()) < len(rows)
