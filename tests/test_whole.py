"""The whole-table workloads: equal to their SQL, and to brute force past the old id bounds."""

import itertools
from collections import Counter, defaultdict

import pytest
from pyspark.sql import functions as F

NAMES = [
    "w2_items_over_2_twinslot", "w1_memory_items_over_4", "membership", "pairs_3_of_5", "pairs_with_zero", "sql_udf_count", "udtf_elements",
    "udaf_card", "sql_udf_contains", "op_join_full", "op_join_broadcast", "op_range_join", "op_bitmap_words", "fn_explode", "word_triples_tables", "word_triples_anchor", "word_triples_fpgrowth", "join_project_docs", "containers",
]


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_its_sql(same_as_sql, name):
    same_as_sql(name)


@pytest.fixture(scope="module")
def small(spark, tmp_path_factory):
    """Lines of 24 suppliers in which only suppliers from 16 on make frequent triples, and 40 documents."""
    path = str(tmp_path_factory.mktemp("small"))
    lines = [(part, sup) for part in range(60) for sup in {part % 16, (part * 7) % 16, *range(16 + part % 3, 24)}]
    spark.createDataFrame([(n, p, s) for n, (p, s) in enumerate(lines)], "l_orderkey long, l_partkey long, l_suppkey long").write.parquet(f"{path}/lineitem.parquet")
    texts = [(i * 100, " ".join(w for w, every in (("every", 1), ("second", 2), ("third", 3)) if i % every == 0)) for i in range(40)]
    spark.createDataFrame(texts, "doc_id long, text string").write.parquet(f"{path}/documents.parquet")
    return path, lines, texts


@pytest.mark.parametrize("method", ("d_of_d1", "anchor", "anchor_forced_failures", "apriori", "eclat", "fpgrowth", "library_fpgrowth"))
def test_triples_see_every_supplier(spark, small, method):
    import __spark_entry__ as entry

    path, lines, _ = small
    sets = defaultdict(set)
    for part, sup in lines:
        sets[part].add(sup)
    counts = Counter(c for s in sets.values() for c in itertools.combinations(sorted(s), 3))
    want = sorted((*c, n) for c, n in counts.items() if n >= 20)
    assert any(c[0] >= 16 for c in want)
    assert sorted(map(tuple, entry.queries()[f"triples_{method}"](spark, path).select("a", "b", "c", "support").collect())) == want


@pytest.mark.parametrize("k", (4, 1))
def test_shares_grow_with_the_documents(spark, small, k):
    import __spark_entry__ as entry

    path, _, texts = small
    n = len(texts) // k
    counts = Counter(p for _, text in texts[:n] for p in itertools.combinations(sorted(text.split()), 2))
    want = sorted((*p, c) for p, c in counts.items() if c >= max(10, n // 10))
    found = entry.queries()[f"w6_share_{k}"](spark, path)
    assert sorted((*sorted((r["item_a"], r["item_b"])), r["support"]) for r in found.collect()) == want


@pytest.mark.parametrize("broadcast_rows", (1_000_000, 1_100, 0))
def test_range_join_of_odd_numbers(spark, broadcast_rows):
    """Points or ranges are broadcast, or neither is; chunks meet once, ends may be anything."""
    from twinslot.operators import relational as rel

    odd = [None, float("nan"), float("inf"), float("-inf"), -0.0, 1e300, -1e17]
    points = [(i, v) for i, v in enumerate(odd + [float(i % 700) for i in range(1_200)])]
    ends = [(a, b) for a in odd + [5.0, 650.5] for b in odd + [5.0, 650.5]] + [(float(i), i + 9.5) for i in range(600)]
    ranges = [(i, a, b) for i, (a, b) in enumerate(ends)]
    key = lambda v: (v != v, 0.0 if v != v else v)  # noqa: E731  NaN is the greatest, as in SQL
    want = sorted((p, r) for p, v in points for r, a, b in ranges if None not in (v, a, b) and key(a) <= key(v) <= key(b))
    p = spark.createDataFrame(points, "p long not null, x double").repartition(3)
    found = rel.range_join(p, spark.createDataFrame(ranges, "r int, lo double, hi double"), "x", "lo", "hi", 50.0, broadcast_rows)
    assert found.columns == ["p", "x", "r", "lo", "hi"]
    assert sorted(map(tuple, found.select("p", "r").collect())) == want
    none = rel.range_join(p.where("false"), spark.createDataFrame(ranges, "r int, lo double, hi double"), "x", "lo", "hi", 50.0, broadcast_rows)
    assert none.count() == 0


def test_range_join_writes_runs_and_copies(spark, tmp_path):
    """Points in no order, each in about half of 400 ranges in no order."""
    from twinslot.operators import relational as rel

    points = spark.range(20_000).select(F.col("id").alias("p"), (F.col("id") * 7_919 % 20_000 / 4).alias("x"))
    ranges = spark.range(400).select(F.col("id").alias("r"), (F.col("id") * 149 % 400 * 6.25).alias("lo"), (F.col("id") * 149 % 400 * 6.25 + 2_500).alias("hi"))
    rel.range_join(points, ranges, "x", "lo", "hi", 500.0).select("p", "r").write.parquet(f"{tmp_path}/out")
    rows = spark.read.parquet(f"{tmp_path}/out").count()
    assert rows == 400 * 10_001
    assert sum(f.stat().st_size for f in tmp_path.rglob("*.parquet")) < 0.6 * rows
