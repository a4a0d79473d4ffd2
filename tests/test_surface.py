"""Sources, sinks, SQL functions, streams and a choice of registered queries."""

import pytest
from pyspark.sql import functions as F

from twinslot.config import Config
from twinslot.functions import sqlfun
from twinslot.operators import builder, pairs
from twinslot.operators import relational as rel
from twinslot.sources import incidence as inc
from twinslot.sources import io
from twinslot.streaming import stream

from .conftest import DATA

NAMES = [
    "flagship", "fp_order_part_twinslot", "fp_order_supplier_merge", "fp_part_supplier_bitmap", "fp_customer_part_apriori", "fp_order_part_fpgrowth", "twinslot_forced_failures",
    "slots_sql", "lanes_sql", "planned_pairs", "w4_density_16", "w5_split_2", "w1_memory_order_supplier", "bmm_counts_twinslot", "join_project_nations", "conj_brand_size", "conj_sets",
    "intersection_listing", "far_ids_bitmap_sql", "far_ids_listing", "vertical", "horizontal_format", "dense_ids_words", "map_width", "tile_cost_sorted", "assoc_supplier", "op_pred_between", "twinslot_whole_segments",
    "fp_doc_word_fpgrowth", "fp_customer_part_merge_join", "fp_customer_part_merge_sql", "udtf_basket_pairs", "stream_incidence", "stream_pairs", "stream_tumbling", "stream_session", "op_interval_join", "op_asof", "op_cube", "op_pivot",
    "op_running_range", "op_intersect_all", "op_except_all", "fn_string", "fn_date", "fn_bits", "fn_map", "fn_json", "exactness",
]


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_its_sql(same_as_sql, name):
    same_as_sql(name)


def test_entry(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_basket_files(spark, tmp_path):
    rows = spark.createDataFrame([("1 4 5",), ("2 4",), ("",), ("3 5 4 5",)], "value string")
    rows.coalesce(1).write.text(str(tmp_path / "baskets"))
    found = io.read_baskets(spark, str(tmp_path / "baskets"), tid="first")
    made = inc.from_columns(found.withColumn("token", F.col("token").cast("long")), "token", "tid")
    assert {(r[0], r[1]): r[2] for r in pairs.pair_support(made).collect()} == {(4, 5): 2}
    assert io.read_baskets(spark, str(tmp_path / "baskets")).select("tid").distinct().count() == 3


def test_sinks(spark, tmp_path):
    rows = spark.createDataFrame([(1, 1), (2, 1), (1, 2), (2, 2), (3, 2)], "item long, tid long")
    found = pairs.pair_support(rows)
    for fmt in ("parquet", "csv", "json", "baskets", "noop"):
        io.write_pairs(found, str(tmp_path / fmt), fmt)
    schema = "item_a long, item_b long, support long"
    want = sorted(map(tuple, found.collect()))
    assert sorted(map(tuple, spark.read.parquet(str(tmp_path / "parquet")).collect())) == want
    assert sorted(map(tuple, io.read_delimited(spark, str(tmp_path / "csv"), schema).collect())) == want
    assert sorted(map(tuple, io.read_json(spark, str(tmp_path / "json"), schema).select("item_a", "item_b", "support").collect())) == want
    with pytest.raises(ValueError):
        io.write_pairs(found, str(tmp_path / "x"), "xml")
    maps = builder.build_maps(rows, Config())
    io.write_maps(maps, str(tmp_path / "maps"))
    assert sorted(map(tuple, io.read_maps(spark, str(tmp_path / "maps")).collect())) == sorted(map(tuple, maps.collect()))


def test_buckets_need_no_exchange(spark):
    df = spark.range(200).select((F.col("id") % 10).alias("k"), "id")
    a, b = io.bucketed(df, "twinslot_bucket_a", ["k"], 4), io.bucketed(df, "twinslot_bucket_b", ["k"], 4)
    plan = a.hint("merge").join(b, "k")._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan


def test_sql_functions_repair_their_failures(spark):
    import numpy as np

    cfg = Config(segment_j=2, slack=0.0, max_rounds=1)
    rng = np.random.default_rng(2)
    x, y = (np.sort(rng.choice(cfg.segment, 120, replace=False)) for _ in range(2))
    a, b = sqlfun.build_one(x, cfg), sqlfun.build_one(y, cfg)
    assert len(sqlfun.parts(a, cfg)[2]) > 0
    assert sqlfun.elements_one(a, cfg).tolist() == x.tolist()
    assert sqlfun.count_one(a, b, cfg) == len(np.intersect1d(x, y))


def test_nested_loop_is_refused_beyond_its_limit(spark):
    with pytest.raises(ValueError):
        rel.theta(spark.range(3), spark.range(11).withColumnRenamed("id", "b"), F.lit(True), limit=10)
    with pytest.raises(ValueError):
        rel.rank_items(spark.range(3), [], [F.col("id")], "rank")


def _events(spark, path, rows):
    spark.createDataFrame(rows, "event_id long, user_id long, ts timestamp, event_type string, value double, props string").coalesce(1).write.mode("append").parquet(path)


def test_stream_restart_and_replay(spark, tmp_path):
    from datetime import datetime, timedelta

    start, path = datetime(2024, 1, 1), str(tmp_path / "in")
    row = lambda i, u, e: (i, u, start + timedelta(minutes=i), e, 1.0, "{}")
    store = stream.PairStore(spark, str(tmp_path / "store"))
    go = lambda: stream.pair_support(stream.source(spark, path), "event_type", "user_id", store, str(tmp_path / "ck")).awaitTermination()
    _events(spark, path, [row(0, 1, "a"), row(1, 1, "b"), row(2, 2, "a")])
    go()
    _events(spark, path, [row(3, 2, "b"), row(4, 1, "a"), row(5, 1, "c")])
    go()
    found = lambda: {(r[0], r[1]): r[2] for r in store.supports().collect()}
    assert found() == {("a", "b"): 2, ("a", "c"): 1, ("b", "c"): 1}
    store.add(spark.createDataFrame([("b", 2), ("a", 1), ("c", 1)], "item string, tid long"), 1)  # the last batch again
    assert found() == {("a", "b"): 2, ("a", "c"): 1, ("b", "c"): 1}


def test_growing_sets_double(spark, tmp_path):
    from datetime import datetime

    path = str(tmp_path / "in")
    _events(spark, path, [(i, i % 9, datetime(2024, 1, 1), "a", 1.0, "{}") for i in range(40)])
    grown = stream.growing_sets(stream.source(spark, path), "event_type", "user_id")
    query = grown.writeStream.format("memory").queryName("grown").outputMode("append").option("checkpointLocation", str(tmp_path / "ck")).trigger(availableNow=True).start()
    query.awaitTermination()
    assert [tuple(r)[:3] for r in spark.table("grown").collect()] == [("a", 0, 9)]
    more = [(100 + i, 70_000 * (i % 7), datetime(2024, 1, 2), "a", 1.0, "{}") for i in range(21)] + [(130, 8, datetime(2024, 1, 2), "a", 1.0, "{}"), (131, 4000, datetime(2024, 1, 2), "a", 1.0, "{}")]
    _events(spark, path, more)
    query = grown.writeStream.format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "ck2")).trigger(availableNow=True).start()
    query.awaitTermination()
    current = {}
    for r in spark.read.parquet(str(tmp_path / "out")).orderBy("size").collect():
        current[r["seg"]] = (r["size"], r["log2_range"], sqlfun.elements_one(bytes(r["map"]), sqlfun.CONFIG).tolist())
    n = sqlfun.CONFIG.segment
    want = {t for t in range(9)} | {4000} | {70_000 * i for i in range(7)}
    assert {s * n + x for s, (_, _, some) in current.items() for x in some} == want
    assert all(size == len(some) and 1 << bits >= 2 * size for size, bits, some in current.values())


def test_followed_by(spark, tmp_path):
    from datetime import datetime, timedelta

    path, start = str(tmp_path / "in"), datetime(2024, 1, 1)
    _events(spark, path, [(i, 1, start + timedelta(minutes=25 * i), "a" if i % 2 else "b", 1.0, "{}") for i in range(5)])
    src = stream.source(spark, path)
    rows = stream.followed_by(src.where("event_type = 'a'"), src.where("event_type = 'b'"), within="1 hour").select("id_a", "id_b")
    stream.run_once(rows, str(tmp_path / "out"), str(tmp_path / "ck"))
    assert sorted(tuple(r) for r in spark.read.parquet(str(tmp_path / "out")).collect()) == [(1, 2), (3, 4)]
