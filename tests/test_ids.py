"""Transaction ids over the whole range of long: segments are exact integers."""

import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from twinslot.config import Config
from twinslot.operators import apps, baselines, builder, compare, kway, pairs
from twinslot.sources import incidence as inc

from .test_pairs import brute, frame, got

LOW, HIGH = -(1 << 63), (1 << 63) - 1
PLACES = {"-2^53": -(1 << 53) - 450, "2^62": 1 << 62, "lowest": LOW, "highest": HIGH - 900}


def instance(base, step=1):
    """Three sets of ids near ``base``; some ids lie whole segments apart."""
    rng = random.Random(7)
    return [(i, base + step * t) for i in range(3) for t in range(900 // step) if rng.random() < 0.5]


@pytest.mark.parametrize("place", PLACES)
@pytest.mark.parametrize("method", ["twinslot", "merge", "bitmap", "bitmap_sql"])
def test_methods_count_exactly(spark, method, place):
    rows = instance(PLACES[place])
    assert got(pairs.pair_support(frame(spark, rows), method, cfg=Config(segment_j=1))) == brute(rows)


def test_ids_a_segment_apart(spark):
    """The case that floating division gets wrong: neighbours of one position in different segments."""
    base, n = 1 << 62, Config().segment
    rows = [(i, base + n * t) for i, some in enumerate((range(1500), range(500, 2500), range(0, 3000))) for t in some]
    for method in ("twinslot", "merge", "bitmap", "bitmap_sql"):
        assert got(pairs.pair_support(frame(spark, rows), method, cfg=Config())) == {(0, 1): 1000, (0, 2): 1500, (1, 2): 2000}


@pytest.mark.parametrize("place", PLACES)
def test_listing_size_and_membership(spark, place):
    rows = instance(PLACES[place])
    df, sets = frame(spark, rows), [{t for i, t in rows if i == k} for k in range(3)]
    for cfg in (Config(segment_j=0, max_rounds=1),):
        assert {r["tid"] for r in apps.intersection(df, 0, 1, cfg).collect()} == sets[0] & sets[1]
        assert apps.intersection_size(df, 0, 1, cfg).first()["n"] == len(sets[0] & sets[1])
    maps = builder.maps_of(builder.build(df, Config(slack=0.6)))
    around = sorted({t + d for t in set().union(*sets) for d in (-1, 0, 1) if LOW <= t + d <= HIGH})
    probes = [(i, t) for i in range(4) for t in around] + [(0, None), (None, 5), (0, around[0])]
    found = compare.contains(maps, frame(spark, probes), Config(slack=0.6)).collect()
    lost = {(r["item"], r["tid"]) for r in builder.failed(df, Config(slack=0.6)).collect()}
    assert len(found) == 4 * len(around)
    assert all(r["found"] == (r["item"] < 3 and r["tid"] in sets[r["item"]]) for r in found if (r["item"], r["tid"]) not in lost)


@pytest.mark.parametrize("place", ["2^62", "lowest"])
def test_more_than_two_sets(spark, place):
    rows = instance(PLACES[place])
    df, wanted = frame(spark, rows), spark.createDataFrame([([0, 1, 2],), ([0, 2],)], "items array<long>")
    sets = [{t for i, t in rows if i == k} for k in range(3)]
    want = {(0, 1, 2): len(sets[0] & sets[1] & sets[2]), (0, 2): len(sets[0] & sets[2])}
    for cfg in (Config(segment_j=0),):
        assert {tuple(r["items"]): r["support"] for r in kway.count(df, wanted, 3, cfg=cfg).collect()} == want
        assert {tuple(r["items"]): r["support"] for r in kway.count_anchor(df, wanted, cfg).collect()} == want


@settings(deadline=None, max_examples=8)
@given(st.lists(st.integers(LOW, HIGH), min_size=1, max_size=50), st.sampled_from([127, 65024, 127 << 13]))
def test_segments_of_any_long(tids, segment):
    from pyspark.sql import SparkSession

    df = SparkSession.getActiveSession().createDataFrame([(1, t) for t in tids], "item long, tid long")
    assert sorted((r["seg"], r["x"]) for r in inc.segmented(df, segment).collect()) == sorted(divmod(t, segment) for t in tids)
    words = baselines.bitmap_words(df.distinct()).select("word", F.bit_count("bits").alias("n")).collect()
    assert {r["word"]: r["n"] for r in words} == {w: len({t for t in tids if t >> 6 == w}) for w in {t >> 6 for t in tids}}


def test_repeated_rows_are_packed_before_they_are_shuffled(spark):
    """Distinct rows over the whole range of long, with repeats and nulls; what is shuffled is a row for each set of a task."""
    from twinslot.sources import incidence

    low, high = -(1 << 63), (1 << 63) - 1
    want = {(i, t) for i in (low, -1, 0, 7, high) for t in (low, low + 1, -65_537, -65_536, -1, 0, 65_535, 65_536, high)}
    rows = [*want, *want, (None, 1), (1, None)]
    made = incidence.from_columns(spark.createDataFrame(rows, "i long, t long"), "i", "t")
    found = [tuple(r) for r in made.select("item", "tid").collect()]
    assert len(found) == len(want) and set(found) == want
    many = spark.range(200_000).selectExpr("id % 3 AS item", "0L AS seg", "cast(id % 5000 AS int) AS x").coalesce(1)
    assert incidence.packed(many).count() == 3
