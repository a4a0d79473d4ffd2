"""Maps and sets are handled by their elements where these are few: work follows matches, not slots."""

from collections import Counter

import numpy as np
import pytest

from twinslot.config import Config
from twinslot.operators import builder, compare, kway, pairs, partial
from twinslot.sources import incidence


def _maps(sets, cfg):
    made, held = [], []
    for x in sets:
        zero = np.zeros(len(x), np.int64)
        for _, _, bits, slots, bad, _ in builder.build_arrays(zero, zero, x, cfg):
            made.append(compare.compacted(slots, bits, cfg))
            held.append(np.delete(x, bad))
    return made, held


@pytest.mark.parametrize("cfg", [Config(), Config(slot_bits=16), Config(slot_bits=32), Config(segment_j=2), Config(max_rounds=1)])
def test_sparse_maps_meet_by_their_occupied_slots(cfg, monkeypatch):
    rng = np.random.default_rng(5)
    sizes = rng.integers(1, cfg.segment // 60 + 3, 60)
    maps, held = _maps([np.sort(rng.choice(cfg.segment, n, replace=False)).astype(np.int64) for n in sizes], cfg)
    want = [[len(np.intersect1d(a, b)) for b in held] for a in held[:25]]

    def refused(*_):
        raise AssertionError("vacant slots of sparse maps are compared")

    monkeypatch.setattr(compare, "count_row", refused)
    assert compare.compact_kernel(cfg)(maps[:25], maps).tolist() == want
    for name, few in (("OCCUPIED_SLOTS", 2 * int(sizes[:25].sum() + sizes.max())), ("MEETINGS", 3)):  # some maps, and some meetings, at a time
        monkeypatch.setattr(compare, name, few)
        assert compare.compact_kernel(cfg)(maps[:25], maps).tolist() == want


def test_dense_maps_are_compared_slot_by_slot(monkeypatch):
    cfg, rng = Config(), np.random.default_rng(6)
    maps, held = _maps([np.sort(rng.choice(cfg.segment, 30_000, replace=False)).astype(np.int64) for _ in range(3)], cfg)
    monkeypatch.setattr(compare, "MEETING_BYTES", 1000)
    assert compare.compact_kernel(cfg)(maps, maps).tolist() == [[len(np.intersect1d(a, b)) for b in held] for a in held]


def test_sets_are_whole_after_one_shuffle(spark, monkeypatch):
    low, high = -(2**63), 2**63 - 1
    rows = [(k % 7, (k * 37) % 90_000) for k in range(3000)] * 2 + [(1, low), (1, low), (2, high), (2, -1), (2, None), (None, 5)]
    made = incidence.from_columns(spark.createDataFrame(rows, "i long, t long").repartition(5), "i", "t")
    want = sorted({r for r in rows if None not in r})
    assert sorted(map(tuple, made.collect())) == want
    for segment in (incidence.DISTINCT_SEGMENT, Config().segment, 127):
        sets = incidence.whole_sets(made, segment).collect()
        assert len({(r["item"], r["seg"]) for r in sets}) == len(sets)
        assert sorted((r["item"], r["seg"] * segment + int(x)) for r in sets for x in incidence.places_of(r["xs"], r["ws"])) == want
    assert sorted(map(tuple, incidence.written(made, "sets").collect())) == want
    frequent = {i for i in range(7) if sum(a == i for a, _ in want) >= 429}
    assert 0 < len(frequent) < 7
    kept = pairs._kept_sets(made, 429).collect()
    assert {r["item"] for r in kept} == frequent and sum(r["n"] for r in kept) == sum(a in frequent for a, _ in want)


def test_sets_go_on_over_flushes(spark, monkeypatch):
    monkeypatch.setattr(incidence, "PACKED_ROWS", 50)  # this process's functions; those of tasks are pickled with it
    rows = [(k % 3, (k * 31) % 4000) for k in range(2000)]
    made = incidence.whole_sets(spark.createDataFrame(rows, "item long, tid long").distinct(), 1000).collect()
    assert len(made) == len({(r["item"], r["seg"]) for r in made})
    assert sorted((r["item"], r["seg"] * 1000 + int(x)) for r in made for x in incidence.places_of(r["xs"], r["ws"])) == sorted(set(rows))


def test_layouts_of_general_redundancy_meet_by_their_occupied_slots(monkeypatch):
    cfg, red, rng = Config(segment_j=5), kway.Redundancy(3, 5), np.random.default_rng(7)
    bits_of = kway._bits_of(red)
    sets = [np.sort(rng.choice(cfg.segment, n, replace=False)).astype(np.int64) for n in rng.integers(1, 200, 50)]
    masks = [kway.assign(x, red, bits_of(len(x)), cfg) for x in sets]
    masks[3][:2] = 0  # no tables: these don't count
    made = [x.astype("<i4").tobytes() + m.astype("<u2").tobytes() for x, m in zip(sets, masks)]
    held = [x[m > 0] for x, m in zip(sets, masks)]
    kernel = kway.pair_kernel(red, bits_of, cfg)
    want = [[len(np.intersect1d(a, b)) for b in held] for a in held[:20]]
    with monkeypatch.context() as m:
        m.setattr(kway, "_rights", lambda *_: pytest.fail("vacant slots of sparse layouts are compared"))
        assert kernel(made[:20], made).tolist() == want
    monkeypatch.setattr(kway, "SLOTS_A_MEETING", 1e9)
    assert kernel(made[:20], made).tolist() == want


def test_bitmaps_of_few_bits_give_pairs_not_a_matrix():
    rng = np.random.default_rng(8)
    sets = [np.unique(rng.integers(0, 65_024, n)) for n in rng.integers(1, 20, 700)]
    packed = [compare.pack_words(x) for x in sets]
    i, j, n = compare.bitmap_counts(packed, packed[10:])
    got = {(a, b): c for a, b, c in zip(i.tolist(), j.tolist(), n.tolist())}
    assert len(got) == len(n) and min(got.values()) > 0
    held = [set(x.tolist()) for x in sets]
    assert got == {(a, b): len(x & y) for a, x in enumerate(held) for b, y in enumerate(held[10:]) if x & y}
    dense = [compare.pack_words(np.arange(0, 640, 2)) for _ in range(700)]
    assert compare.bitmap_counts(dense, dense) is None and (compare.bitmap_counts(dense[:500], dense) == 320).all()


@pytest.mark.parametrize("method", ["bitmap", "twinslot", "merge"])
def test_buckets_follow_the_pairs_of_transactions(spark, monkeypatch, method):
    seen = []
    of = partial.bucket_count
    monkeypatch.setattr(partial, "bucket_count", lambda bound: seen.append(bound) or of(bound))
    monkeypatch.setattr(pairs, "MANY_PAIRS", 10)
    rows = [(i, t) for t in range(40) for i in range(t * 3, t * 3 + 4)]
    inc = spark.createDataFrame(rows, "item long, tid long")
    got = {(r["item_a"], r["item_b"]): r["support"] for r in pairs.pair_support(inc, method).collect()}
    want = Counter((a, b) for t in range(40) for a in range(t * 3, t * 3 + 4) for b in range(a + 1, t * 3 + 4))
    assert got == want and seen == [40 * 6]
