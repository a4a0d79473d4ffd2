"""Prefix trees and one-at-a-time insertion against brute force and the analysis."""

import itertools
import random
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from twinslot.config import Config
from twinslot.functions import layout
from twinslot.operators import baselines, builder, compare, fptree, measure, pairs, sequential

from .test_pairs import brute, frame, got, instance


@pytest.mark.parametrize("max_size", (2, 3, 5))
@pytest.mark.parametrize("seed", range(4))
def test_trees_hold_all_itemsets(seed, max_size):
    rng = random.Random(seed)
    baskets = [tuple(i for i in range(9) if rng.random() < 0.5) for _ in range(60)]
    merged = Counter(baskets)
    tree = fptree.build([np.array(b, np.int64) for b in merged], list(merged.values()))
    assert len(tree.item) == len({b[: k + 1] for b in baskets for k in range(len(b))})  # a node for each prefix
    assert tree.count[tree.parent < 0].sum() == sum(1 for b in baskets if b)
    want = Counter(c for b in baskets for k in range(2, max_size + 1) for c in itertools.combinations(b, k))
    for least in (1, 8):
        found = []
        fptree.mine(tree, np.ones(9, bool), (), least, max_size, found)
        assert len(found) == len(dict(found)) and dict(found) == {c: n for c, n in want.items() if n >= least}
    some, found = np.arange(9) % 2 == 0, []
    fptree.mine(tree, some, (), 3, max_size, found)
    assert dict(found) == {c: n for c, n in want.items() if n >= 3 and some[c[-1]]}


def test_sums_are_reduced_on_the_way(monkeypatch):
    monkeypatch.setattr(fptree, "PENDING", 3)
    test_trees_hold_all_itemsets(1, 3)


def test_fp_growth_of_sizes(spark, monkeypatch):
    monkeypatch.setattr(baselines, "FP_GROUPS", 3)
    rows = instance(11, n=10, m=120, p=0.4)
    by_tid = {}
    for item, tid in rows:
        by_tid.setdefault(tid, []).append(item)
    want = Counter(c for items in by_tid.values() for k in (1, 2, 3, 4) for c in itertools.combinations(sorted(items), k))
    for make in (baselines.fp_growth_sets, baselines.library_fp_growth_sets):
        found = {tuple(r["items"]): r["support"] for r in make(frame(spark, rows), 9, 4).collect()}
        assert found == {c: n for c, n in want.items() if n >= 9}
    eclat = {tuple(r["items"]): r["support"] for r in baselines.eclat_sets(frame(spark, rows), 9, 4).collect()}
    assert eclat == {c: n for c, n in want.items() if n >= 9 and len(c) > 1}
    assert baselines.fp_growth_sets(frame(spark, []), 1, 3).count() == 0


def _one(x, cfg, **how):
    return sequential.place(np.array(sorted(x), np.int64), int(layout.range_bits(len(x), cfg)), cfg, **how)


@pytest.mark.parametrize("cfg", (Config(segment_j=3), Config(segment_j=3, slack=0.0), Config(segment_j=3, slot_bits=16, slack=0.0)))
def test_one_at_a_time_and_in_batches_count_alike(cfg):
    rng = random.Random(2)
    for n, m in ((1, 1), (5, 400), (256, 257), (700, 300)):
        a, b = (set(rng.sample(range(cfg.segment), k)) for k in (n, m))
        made, lost = {}, {}
        for name, x in (("a", a), ("b", b)):
            slots, gone, moves = _one(x, cfg)
            bits = int(layout.range_bits(len(x), cfg))
            held = compare.elements_np(slots.tobytes(), bits, cfg)
            assert set(held.tolist()) | set(gone.tolist()) == x and not set(held.tolist()) & set(gone.tolist())
            assert np.count_nonzero(slots) == 2 * len(held) and len(moves) >= 2 * len(held)
            made[name], lost[name] = slots.tobytes(), set(gone.tolist())
        common = (a - lost["a"]) & (b - lost["b"])
        assert compare.count_np(made["a"], made["b"], cfg) == len(common)


def test_a_full_table_gives_elements_up():
    cfg = Config(segment_j=0, slot_bits=32)
    homes = np.zeros((3, 4), np.int64) + np.arange(3)[:, None]  # four elements, three slots
    nest = sequential.Nest(homes, 3, 5)
    for e in range(4):
        nest.insert(e)
    inside = Counter(nest.holder.values())
    assert set(inside) | nest.failed == set(range(4)) and not set(inside) & nest.failed
    assert all(n == 2 for n in inside.values()) and max(nest.moves) <= 15
    assert len(_one([3], cfg)[2]) == 2


def test_transcripts_stay_under_the_bounds(spark):
    """Lengths of insertions and failures of a few hundred sets near and below the critical load."""
    rows = [(i, t) for i in range(60) for t in random.Random(i).sample(range(8128), 100 + 13 * i)]
    found = sequential.transcripts(frame(spark, rows), Config(segment_j=6, slot_bits=16, slack=0.0)).collect()
    by_step = {r["steps"]: r for r in found}
    assert by_step[1]["insertions"] >= 2 * len(rows)
    assert all(r["insertions"] <= r["bound"] for k, r in by_step.items() if k is not None)
    assert [by_step[k]["insertions"] for k in sorted(k for k in by_step if k)] == sorted((by_step[k]["insertions"] for k in by_step if k), reverse=True)
    total, n = sum(by_step[k]["insertions"] for k in by_step if k), by_step[1]["insertions"]
    assert total / n < 4  # constant expected moves
    roomy = sequential.transcripts(frame(spark, rows), Config(segment_j=6, slot_bits=16, slack=0.6)).where("steps IS NULL").first()
    assert roomy["insertions"] == 0


def test_batches_report_moves_of_each_set(spark):
    df = frame(spark, [(1, t) for t in range(1000)] + [(2, 5)])
    moves = {r["item"]: r["moves"] for r in builder.build(df).where("slots IS NOT NULL").collect()}
    assert moves[1] >= 2000 and moves[2] == 2
    row = measure.build_stats(df).first()
    assert row["elements"] == 1001 and row["moves_per_copy"] == round((moves[1] + 2) / 2002, 4) and row["most_per_copy"] == round(moves[1] / 2000, 4)


def test_blocks_follow_widths(spark):
    """Ten wide maps and many narrow ones: narrow blocks aren't cut as small as wide ones need."""
    wide, narrow = [(i, t) for i in range(10) for t in range(3000)], [(i, t) for i in range(10, 200) for t in (i, i + 1)]
    df, cfg = frame(spark, wide + narrow), Config(tile_items=100, tile_bytes=100_000, distribution="tiles")
    maps = builder.build_maps(df, cfg).select("item", F.col("slots").alias("payload"))
    blocks, n = pairs._blocks(maps, cfg)
    sizes = Counter(r["block"] for r in blocks.collect())
    assert set(sizes) == set(range(n)) and max(sizes.values()) == 100_000 // (3 << 9) and n == 6
    widths = {r["item"]: len(r["payload"]) for r in maps.collect()}
    held = Counter()
    for r in blocks.collect():
        held[r["block"]] += widths[r["item"]]
    assert max(held.values()) <= 100_000
    assert got(pairs.pair_support(df, cfg=cfg)) == brute(wide + narrow)


def test_segments_as_tasks(spark):
    rows = instance(12, n=14, m=600)
    for how in ("segments", "tiles", "auto"):
        assert got(pairs.pair_support(frame(spark, rows), cfg=Config(segment_j=0, tile_items=3, distribution=how))) == brute(rows)
    with pytest.raises(ValueError):
        Config(distribution="other")


def test_too_large_segments_are_refused(spark, monkeypatch):
    monkeypatch.setattr(pairs, "SEGMENT_ITEMS", 2)
    with pytest.raises(ValueError, match="too much for a task"):
        pairs.pair_support(frame(spark, instance(1)), cfg=Config(distribution="segments"))


def test_every_pair(spark):
    items = spark.range(23).select(F.col("id").alias("item"))
    found = sorted(map(tuple, pairs.every_pair(items, Config(tile_items=4)).collect()))
    assert found == sorted(itertools.combinations(range(23), 2))
    zero = got(pairs.pair_support(frame(spark, [(1, 1), (2, 1), (3, 2)]), include_zero=True))
    assert zero == {(1, 2): 1, (1, 3): 0, (2, 3): 0}


def test_each_segment_has_its_own_blocks(spark):
    """Items that share no segment don't cost each other tiles: five copies of an instance with keys of their own are cut as one is."""
    rows = instance(7, n=8, m=127)
    copies = [(i + 8 * k, t + 127 * k) for k in range(5) for i, t in rows]
    cfg = Config(segment_j=0, tile_items=8, distribution="tiles")
    maps = builder.build_maps(frame(spark, copies), cfg).select("item", "seg", F.col("slots").alias("payload"))
    sent = pairs._segment_tiles(pairs._segment_blocks(maps, cfg), True)
    assert sent.count() == maps.count() and sent.where("p <> 0 OR q <> 0").isEmpty()
    assert got(pairs.pair_support(frame(spark, copies), cfg=cfg)) == brute(copies)
    assert got(pairs.pair_support(frame(spark, copies))) == brute(copies)
