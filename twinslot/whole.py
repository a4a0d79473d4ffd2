"""Workloads whose work follows from the tables: triples pruned by support, growing prefixes of the
documents, probes from all lines, SQL functions and joins over whole tables.

Where no SQL is given, ``tests/test_whole.py`` compares with brute force."""

from __future__ import annotations

from pyspark.sql import functions as F

from .config import Config
from .functions import sqlfun
from .operators import baselines, builder, compare, kway, measure, pairs
from .operators import relational as rel
from .sources import incidence as inc
from .stages import cut

SEGMENT = sqlfun.CONFIG.segment


def table(t, incidences, inc_sql, pair_sql, by_method) -> dict:
    q: dict = {}

    def add(name, run, sql=None):
        q[name] = (run, sql)

    order_supplier, part_supplier = incidences["order_supplier"], incidences["part_supplier"]
    def share(k):
        def run(s, d):
            docs = t(s, d, "documents", "doc_id", "text")
            n = docs.count() // k
            at = docs.select("doc_id").distinct().where("doc_id IS NOT NULL")
            # The n smallest ids: the bound is found by a distributed sort.
            last = at.orderBy("doc_id").limit(n).agg(F.max("doc_id")).first()[0]
            some = docs.where(F.col("doc_id") <= last) if k > 1 else docs
            rows = inc.from_text(some, "doc_id", "text")
            return by_method(lambda *_: rows, "twinslot", max(10, n // 10), words=True)(s, d)

        return run

    for k in (8, 4, 2, 1):
        add(f"w6_share_{k}", share(k))

    def membership(s, d):
        """All lines' own pairs, and each order with the next supplier: all orders and suppliers are probed."""
        rows = cut(order_supplier(s, d), "rows")
        built = builder.build(rows)
        probes = rows.select("item", "tid").union(rows.select((F.col("item") + 1).alias("item"), "tid")).distinct()
        lost = builder.failed_of(built).withColumn("lost", F.lit(1))
        found = compare.contains(builder.maps_of(built), probes).join(lost, ["item", "tid"], "left")
        return found.select("item", "tid", F.when(F.col("found") | F.col("lost").isNotNull(), 1).otherwise(0).alias("found"))

    add(
        "membership", membership,
        f"WITH i AS ({inc_sql['order_supplier']}), p AS (SELECT item, tid FROM i UNION SELECT item + 1, tid FROM i) SELECT p.item, p.tid, (i.item IS "
        f"NOT NULL)::INTEGER AS found FROM p LEFT JOIN i USING (item, tid)",
    )

    def triples(how):
        return lambda s, d: how(part_supplier(s, d)).where(F.size("items") == 3).select(*(F.element_at("items", i + 1).alias(c) for i, c in enumerate("abc")), "support")

    for name, how in {
        "d_of_d1": lambda rows: kway.itemsets(rows, 20, 3, "tables", Config()),
        "anchor": lambda rows: kway.itemsets(rows, 20, 3, "anchor", Config()),
        "anchor_forced_failures": lambda rows: kway.itemsets(rows, 20, 3, "anchor", Config(max_rounds=1)),
        "apriori": lambda rows: baselines.apriori_levels(rows, 20, 3)[-1],
        "eclat": lambda rows: baselines.eclat_sets(rows, 20, 3),
        "fpgrowth": lambda rows: baselines.fp_growth_sets(rows, 20, 3),
        "library_fpgrowth": lambda rows: baselines.library_fp_growth_sets(rows, 20, 3),
    }.items():
        add(
            f"triples_{name}", triples(how),
            f"WITH i AS ({inc_sql['part_supplier']}) SELECT a.item AS a, b.item AS b, c.item AS c, count(*) AS support FROM i a JOIN i b ON a.tid = b.tid AND a.item < b.item "
            "JOIN i c ON b.tid = c.tid AND b.item < c.item GROUP BY a.item, b.item, c.item HAVING count(*) >= 20",
        )

    def pairs_3_of_5(s, d):
        return kway.pair_support(part_supplier(s, d), kway.Redundancy(3, 5))

    def word_triples(method):
        """Triples of words that a third of the documents share."""

        def run(s, d):
            docs = t(s, d, "documents", "doc_id", "text")
            least = docs.count() // 3 + 1
            words = pairs.prune(inc.from_text(docs, "doc_id", "text"), least)
            ids, dictionary = inc.encoded(cut(words, "words"))
            ids = cut(ids, "word-ids")
            if method == "fpgrowth":
                found = baselines.fp_growth_sets(ids, least, 3)
            else:
                found = kway.itemsets(ids, least, 3, method, Config())
            found = found.where(F.size("items") == 3).select(*(F.element_at("items", i + 1).alias(c) for i, c in enumerate("abc")), "support")
            for c in "abc":
                found = found.join(dictionary.select(F.col("id").alias(c), F.col("key").alias(f"word_{c}")), c).drop(c)
            return found.select("word_a", "word_b", "word_c", "support")

        return run

    for method in ("tables", "anchor", "fpgrowth"):
        add(
            f"word_triples_{method}", word_triples(method),
            f"WITH w AS ({inc_sql['doc_word']}), l AS (SELECT count(*) // 3 + 1 AS least FROM documents), f AS (SELECT item FROM w, l GROUP BY item, "
            f"least HAVING count(*) >= least), "
            "i AS (SELECT item, tid FROM w WHERE item IN (SELECT item FROM f)) SELECT a.item AS word_a, b.item AS word_b, c.item AS word_c, count(*) "
            "AS support FROM i a JOIN i b ON a.tid = b.tid AND a.item < b.item "
            "JOIN i c ON b.tid = c.tid AND b.item < c.item, l GROUP BY a.item, b.item, c.item, least HAVING count(*) >= least",
        )

    add("pairs_3_of_5", pairs_3_of_5, pair_sql(inc_sql["part_supplier"], 1))
    add(
        "pairs_with_zero", lambda s, d: pairs.pair_support(order_supplier(s, d), include_zero=True),
        f"WITH i AS ({inc_sql['order_supplier']}), n AS (SELECT DISTINCT item FROM i), p AS ({pair_sql(inc_sql['order_supplier'], 1)}) "
        "SELECT a.item AS item_a, b.item AS item_b, coalesce(support, 0)::BIGINT AS support FROM n a JOIN n b ON a.item < b.item LEFT JOIN p ON "
        "item_a = a.item AND item_b = b.item",
    )

    def maps(s, d):
        sqlfun.register(s)
        order_supplier(s, d).withColumn("x", F.pmod("tid", F.lit(SEGMENT))).createOrReplaceTempView("twinslot_incidence_whole")
        cut(s.sql(f"SELECT item, (tid - x) div {SEGMENT} AS seg, twinslot_build(x) AS map FROM twinslot_incidence_whole GROUP BY item, (tid - x) div {SEGMENT}"), "sql").createOrReplaceTempView(
            "twinslot_maps_whole",
        )

    def in_sql(text):
        return lambda s, d: (maps(s, d), s.sql(text))[1]

    whole = inc_sql["order_supplier"]
    add(
        "sql_udf_count",
        in_sql("SELECT item_a, item_b, sum(n) AS support FROM (SELECT a.item AS item_a, b.item AS item_b, twinslot_count(a.map, b.map) AS n FROM twinslot_maps_whole a JOIN twinslot_maps_whole b ON a.seg = b.seg AND a.item < b.item) GROUP BY item_a, item_b HAVING sum(n) > 0"),
        pair_sql(whole, 1),
    )
    add(
        "udtf_elements",
        in_sql(f"SELECT m.item, m.seg * {SEGMENT} + e.x AS tid FROM twinslot_maps_whole m, LATERAL twinslot_elements(m.map) e"),
        whole,
    )
    add(
        "udaf_card",
        in_sql("SELECT item, sum(twinslot_card(map)) AS card FROM twinslot_maps_whole GROUP BY item"),
        f"SELECT item, count(*)::BIGINT AS card FROM ({whole}) GROUP BY item",
    )
    add(
        "sql_udf_contains",
        in_sql(f"SELECT count_if(twinslot_contains(m.map, i.x)) AS held FROM twinslot_incidence_whole i JOIN twinslot_maps_whole m ON m.item = i.item AND m.seg = (i.tid - i.x) div {SEGMENT}"),
        f"SELECT count(*)::BIGINT AS held FROM ({whole})",
    )

    # Relational surface.
    lines = lambda s, d: t(s, d, "lineitem", "l_orderkey", "l_partkey").withColumnRenamed("l_orderkey", "k")
    orders = lambda s, d: t(s, d, "orders", "o_orderkey", "o_custkey").withColumnRenamed("o_orderkey", "k")
    sides = "SELECT k, o_custkey, l_partkey FROM (SELECT o_orderkey AS k, o_custkey FROM orders) o {} JOIN (SELECT l_orderkey AS k, l_partkey FROM lineitem) l USING (k)"
    for how in ("inner", "left", "right", "full"):
        add(
            f"op_join_{how}",
            (lambda h: lambda s, d: rel.join(orders(s, d), lines(s, d), ["k"], h).select("k", "o_custkey", "l_partkey"))(how),
            sides.format(how.upper()),
        )
    for strategy in ("broadcast", "hash", "merge"):
        add(
            f"op_join_{strategy}",
            (lambda x: lambda s, d: rel.join(lines(s, d), orders(s, d), ["k"], "inner", x).select("k", "o_custkey", "l_partkey"))(strategy),
            sides.format("INNER"),
        )
    add(
        "op_range_join",
        lambda s, d: rel.range_join(t(s, d, "orders", "o_orderkey", "o_totalprice"), t(s, d, "part", "p_partkey", "p_retailprice").select("p_partkey", (F.col("p_retailprice") * 100).alias("lo"), (F.col("p_retailprice") * 101).alias("hi")), "o_totalprice", "lo", "hi", 5000.0).select("o_orderkey", "p_partkey"),
        "SELECT o_orderkey, p_partkey FROM orders JOIN part ON o_totalprice BETWEEN p_retailprice * 100 AND p_retailprice * 101",
    )
    add(
        "op_bitmap_words",
        lambda s, d: baselines.bitmap_words(order_supplier(s, d)).select("item", "word", F.bit_count("bits").cast("long").alias("n")),
        f"SELECT item, tid // 64 AS word, count(*) AS n FROM ({whole}) GROUP BY ALL",
    )
    baskets = lambda s, d: t(s, d, "lineitem", "l_orderkey", "l_partkey").groupBy("l_orderkey").agg(F.array_sort(F.collect_set("l_partkey")).alias("x"))
    add(
        "fn_explode", lambda s, d: baskets(s, d).select("l_orderkey", F.posexplode("x").alias("pos", "v")).select("l_orderkey", F.col("pos").cast("long").alias("pos"), "v"),
        "WITH b AS (SELECT l_orderkey, list_sort(list(DISTINCT l_partkey)) AS x FROM lineitem GROUP BY l_orderkey) SELECT l_orderkey, "
        "unnest(range(0, len(x))) AS pos, unnest(x) AS v FROM b",
    )
    return q
