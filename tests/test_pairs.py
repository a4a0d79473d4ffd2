"""Every method against one brute force, with the edge cases of instances."""

import itertools
import random
from collections import Counter

import pytest
from pyspark.sql import functions as F

from twinslot.config import Config
from twinslot.operators import apps, baselines, builder, compare, kway, measure, pairs, repair
from twinslot.plans import planner
from twinslot.sources import incidence as inc


def frame(spark, rows):
    return spark.createDataFrame(rows, "item long, tid long")


def brute(rows, min_support=1):
    by_tid = {}
    for item, tid in set(rows):
        by_tid.setdefault(tid, set()).add(item)
    counts = Counter(p for items in by_tid.values() for p in itertools.combinations(sorted(items), 2))
    return {p: n for p, n in counts.items() if n >= min_support}


def got(df):
    return {(r["item_a"], r["item_b"]): r["support"] for r in df.collect()}


def instance(seed, n=12, m=300, p=0.2):
    rng = random.Random(seed)
    return [(i, t) for i in range(n) for t in range(m) if rng.random() < p]


INSTANCES = {
    "random": instance(1),
    "one_item": [(1, t) for t in range(5)],
    "one_tid": [(i, 7) for i in range(5)],
    "disjoint": [(1, 1), (2, 2), (3, 3)],
    "identical": [(i, t) for i in range(3) for t in range(40)],
    "large_keys": [(1 << 40, (1 << 33) + t) for t in range(9)] + [(5, (1 << 33) + t) for t in range(4, 12)],
    "negative_tids": [(1, t) for t in range(-200, 3)] + [(2, t) for t in range(-100, 9)],
    "segment_edges": [(i, t) for i in range(3) for t in (126, 127, 128, 253, 254, 255)],
    "powers": [(k, t) for k, n in enumerate((1, 2, 3, 4, 7, 8, 9, 63, 64, 65)) for t in range(n)],
}


@pytest.mark.parametrize("name", INSTANCES)
def test_twinslot(spark, name):
    rows = INSTANCES[name]
    for cfg in (Config(), Config(segment_j=0), Config(segment_j=0, max_rounds=1, slack=0.0)):
        assert got(pairs.pair_support(frame(spark, rows), cfg=cfg)) == brute(rows)


def test_empty(spark):
    nothing = frame(spark, [])
    for method in ("twinslot", *baselines.METHODS):
        assert pairs.pair_support(nothing, method).collect() == []


@pytest.mark.parametrize("method", ["twinslot", *baselines.METHODS])
def test_methods(spark, method):
    rows = instance(2)
    for min_support in (1, 12):
        assert got(pairs.pair_support(frame(spark, rows), method, min_support)) == brute(rows, min_support)


@pytest.mark.parametrize(
    "cfg",
    [Config(tile_items=1), Config(tile_items=2), Config(tile_items=5), Config(tile_items=5, triangle=False), Config(sort_by_width=False), Config(tile_bytes=1), Config(slot_bits=16, segment_j=1), Config(slot_bits=32, segment_j=1), Config(slice_bytes=8), Config(bucket_elements=10)],
)
def test_plan_parameters_change_nothing(spark, cfg):
    rows = instance(3)
    assert got(pairs.pair_support(frame(spark, rows), cfg=cfg)) == brute(rows)


def test_partitions_change_nothing(spark):
    rows = instance(4)
    one, many = frame(spark, rows).repartition(1), frame(spark, rows).repartition(13)
    assert got(pairs.pair_support(one)) == got(pairs.pair_support(many)) == brute(rows)


def test_slot_relation(spark):
    rows = instance(5, n=6)
    for cfg in (Config(segment_j=1), Config(segment_j=1, max_rounds=1)):
        assert got(pairs.pair_support_slots(frame(spark, rows), cfg)) == brute(rows)


def test_words_of_four_slots(spark):
    rows = instance(13, n=6) + [(9, t) for t in range(0, 300, 50)] + [(9, 5000)]
    for cfg in (Config(segment_j=1), Config(segment_j=1, max_rounds=1)):
        assert got(pairs.pair_support_lanes(frame(spark, rows), cfg)) == brute(rows)


def test_threshold_comes_after_repair(spark):
    rows = instance(6)
    assert got(pairs.pair_support(frame(spark, rows), min_support=14, cfg=Config(segment_j=0, max_rounds=1))) == brute(rows, 14)


def test_side_pairs_count_a_transaction_once(spark):
    rows = frame(spark, [(1, 10), (2, 10), (3, 10), (1, 11), (2, 11)])
    lost = frame(spark, [(1, 10), (2, 10), (1, 11)])
    assert got(repair.side_pairs(lost, rows)) == {(1, 2): 2, (1, 3): 1, (2, 3): 1}


def test_cross_support(spark):
    left, right = instance(7, n=5), instance(8, n=7)
    want = Counter((a, b) for a, t in left for b, u in right if t == u)
    for cfg in (Config(tile_items=3), Config(segment_j=0, max_rounds=1)):
        assert got(pairs.cross_support(frame(spark, left), frame(spark, right), cfg=cfg)) == dict(want)


def test_builders_drop_nulls_and_repeats(spark):
    df = spark.createDataFrame([(1, 2), (1, 2), (None, 2), (1, None), (3, 2)], "a long, b long")
    assert sorted(inc.from_columns(df, "a", "b").collect()) == [(1, 2), (3, 2)]
    with pytest.raises(ValueError):
        inc.from_columns(df, "a", "missing")


def test_words_with_accents_as_items(spark):
    df = spark.createDataFrame([(1, "Élan élan mot"), (2, "élan autre"), (3, None)], "tid long, text string")
    words = inc.from_text(df, "tid", "text", r"\p{L}+")
    ids, dictionary = inc.encoded(words)
    names = {r["id"]: r["key"] for r in dictionary.collect()}
    assert sorted(names) == list(range(len(names)))
    assert {tuple(sorted((names[a], names[b]))): n for (a, b), n in got(pairs.pair_support(ids)).items()} == {("mot", "élan"): 1, ("autre", "élan"): 1}


def test_dense_ids_are_an_order(spark):
    df = spark.createDataFrame([(x,) for x in random.Random(9).sample(range(10_000), 3000)], "x long").repartition(7)
    rows = sorted(inc.dense_ids(df, "x", partitions=5).collect())
    assert [r["id"] for r in rows] == list(range(3000))


def test_membership_and_listing(spark):
    rows = instance(10, n=4)
    df = frame(spark, rows)
    built = builder.build(df, Config(segment_j=1))
    probes = frame(spark, [(i, t) for i in range(5) for t in range(0, 400, 3)])
    hold = {(r["item"], r["tid"]) for r in compare.contains(builder.maps_of(built), probes, Config(segment_j=1)).collect() if r["found"]}
    lost = {tuple(r) for r in builder.failed_of(built).collect()}
    assert hold | lost & {tuple(r) for r in probes.collect()} == set(rows) & {tuple(r) for r in probes.collect()}
    common = {t for i, t in rows if i == 0} & {t for i, t in rows if i == 1}
    for cfg in (Config(), Config(segment_j=0, max_rounds=1)):
        assert {r["tid"] for r in apps.intersection(df, 0, 1, cfg).collect()} == common
        assert apps.intersection_size(df, 0, 1, cfg).first()["n"] == len(common)


def test_no_map_of_two_maps():
    with pytest.raises(TypeError):
        apps.combine_maps(b"", b"")


def brute_sets(rows, min_support, max_size):
    by_item = {}
    for i, t in rows:
        by_item.setdefault(i, set()).add(t)
    out = {}
    for k in range(2, max_size + 1):
        for items in itertools.combinations(sorted(by_item), k):
            n = len(set.intersection(*(by_item[i] for i in items)))
            if n >= min_support:
                out[items] = n
    return out


def test_itemsets(spark):
    rows = instance(11, n=7, m=200, p=0.5)
    df = frame(spark, rows)
    want = brute_sets(rows, 22, 4)
    assert any(len(k) == 4 for k in want) or any(len(k) == 3 for k in want)
    sets = lambda d: {tuple(r["items"]): r["support"] for r in d.collect() if len(r["items"]) > 1}
    assert sets(kway.itemsets(df, 22, 4)) == want
    assert sets(kway.itemsets(df, 22, 4, "anchor")) == want
    assert sets(kway.itemsets(df, 22, 4, "anchor", Config(max_rounds=1))) == want
    assert sets(baselines.eclat_sets(df, 22, 4)) == want
    assert sets(baselines.fp_growth_sets(df, 22, 4)) == want
    levels = baselines.apriori_levels(df, 22, 4)
    assert {k: v for level in levels for k, v in sets(level).items()} == want


def test_redundancy_must_leave_a_common_table(spark):
    rows = instance(12, n=4)
    trip = spark.createDataFrame([([0, 1, 2],)], "items array<bigint>")
    with pytest.raises(ValueError):
        kway.count(frame(spark, rows), trip, 3, kway.Redundancy(3, 5))
    for a, b in itertools.combinations(kway.Redundancy(3, 5).masks, 2):
        assert a & b
    for some in itertools.combinations(kway.Redundancy(3, 4).masks, 3):
        assert some[0] & some[1] & some[2]
    pair = spark.createDataFrame([([0, 1],)], "items array<bigint>")
    assert kway.count(frame(spark, rows), pair, 2, kway.Redundancy(3, 5)).first()["support"] == brute(rows).get((0, 1), 0)


def test_planner(spark):
    sparse = frame(spark, [(t % 997, t // 2) for t in range(2000)])
    dense = frame(spark, instance(13, n=40, m=400, p=0.5))
    assert planner.choose(sparse) == "horizontal"
    assert planner.choose(dense) in ("bitmap", "twinslot")
    assert got(planner.pair_support(dense)) == brute([tuple(r) for r in dense.collect()])
    kinds = {r["container"] for r in planner.containers(frame(spark, [(1, 5)] + [(2, t) for t in range(60_000)])).collect()}
    assert kinds == {"list", "bitmap"}


def test_tuning(spark):
    """Dense sets get byte slots, sparse ones wider slots in longer segments; counts don't change."""
    dense = planner.Statistics(1000, 147_000, 600_000, 0)
    sparse = planner.Statistics(20_000, 147_000, 600_000, 0)
    assert planner.tune(dense).slot_bits == 8 and planner.tune(sparse).slot_bits == 16
    assert planner.tune(sparse).segment > planner.tune(dense).segment
    rows = [(i, t) for i in range(60) for t in range(i, 4000, 131)]
    assert got(pairs.pair_support(frame(spark, rows))) == got(pairs.pair_support(frame(spark, rows), "horizontal"))


def test_measures():
    rate = measure.byte_throughput(4000, 3 * 2**13, 10.87, 159e9)
    assert round(rate["bytes_per_s"] / 1e9, 1) == 36.2 and 4 < 1 / rate["share_of_peak"] < 4.5
    e = measure.element_throughput(4000, 2500, 10.87)
    assert round(e["elements_per_s"] / 1e9, 2) == 3.68 and round(e["best"] / e["elements_per_s"], 2) == 1.64
    assert measure.failure_bound(100, 200) == float("inf") and measure.failure_bound(1000, 4096) < 1e-6
    assert measure.transcript_bound(1000, 4096, 60) < measure.transcript_bound(1000, 4096, 30)


def test_plans(spark):
    """No Cartesian product, and only the key columns reach the scan."""
    lines = spark.read.parquet("/root/testdata/sf0.001/lineitem.parquet")
    plan = pairs.prune(inc.from_columns(lines, "l_suppkey", "l_orderkey"), 5)._jdf.queryExecution().executedPlan().toString()
    assert "ReadSchema: struct<l_orderkey:bigint,l_suppkey:bigint>" in plan and "CartesianProduct" not in plan
    hits = apps.conjunctive(lines, "l_orderkey", [F.col("l_quantity") > 40, F.col("l_returnflag") == "R"])
    assert "PushedFilters: [IsNotNull(l_quantity), IsNotNull(l_returnflag), GreaterThan(l_quantity" in hits._jdf.queryExecution().executedPlan().toString()


def test_sparse_bitmaps_leave_out_empty_words():
    """A set of few ids costs its words, not its segment; sparse and dense bitmaps count the same."""
    import numpy as np

    from twinslot.operators import compare

    rng = np.random.default_rng(3)
    for most in (6, 4000):
        sets = [np.sort(rng.choice(65_024, rng.integers(1, most), replace=False)) for _ in range(40)]
        packed = [compare.pack_words(x.astype(np.int32)) for x in sets]
        assert all(len(p) <= 10 * len(x) for p, x in zip(packed, sets))
        want = [[len(np.intersect1d(a, b)) for b in sets[10:]] for a in sets]
        assert compare.bitmap_kernel(packed, packed[10:]).tolist() == want
