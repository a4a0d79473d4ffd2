"""Queries of the relational surface around the methods."""

from __future__ import annotations

from pyspark.sql import functions as F

from .operators import pairs
from .operators import relational as rel


def table(t, incidences, inc_sql, pair_sql) -> dict:
    q: dict = {}

    def add(name, run, sql=None):
        q[name] = (run, sql)

    lines = lambda s, d, *c: t(s, d, "lineitem", *c)
    add("scan_lineitem", lambda s, d: lines(s, d, "l_orderkey", "l_partkey"), "SELECT l_orderkey, l_partkey FROM lineitem")
    add(
        "op_project", lambda s, d: rel.project(t(s, d, "part"), key="p_partkey", big="p_size > 25", price=F.round(F.col("p_retailprice") * 2, 2)),
        "SELECT p_partkey AS key, p_size > 25 AS big, round(p_retailprice * 2, 2) AS price FROM part",
    )
    add(
        "op_filter_and",
        lambda s, d: rel.where(lines(s, d, "l_orderkey", "l_linenumber", "l_quantity"), F.col("l_quantity") > 40, F.col("l_linenumber") == 1).select("l_orderkey"),
        "SELECT l_orderkey FROM lineitem WHERE l_quantity > 40 AND l_linenumber = 1",
    )
    add(
        "op_filter_or",
        lambda s, d: rel.where(lines(s, d, "l_orderkey", "l_linenumber", "l_quantity"), F.col("l_quantity") > 49, F.col("l_linenumber") == 7, mode="or").select("l_orderkey", "l_linenumber"),
        "SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_quantity > 49 OR l_linenumber = 7",
    )
    predicates = {
        "in": (lambda: F.col("p_size").isin(1, 5, 9), "p_size IN (1, 5, 9)"),
        "like": (lambda: F.col("p_name").like("%a%"), "p_name LIKE '%a%'"),
        "rlike": (lambda: F.col("p_brand").rlike("[13]$"), "regexp_matches(p_brand, '[13]$')"),
        "between": (lambda: F.col("p_size").between(10, 20), "p_size BETWEEN 10 AND 20"),
        "nullsafe": (lambda: F.nullif(F.col("p_size"), F.lit(7)).eqNullSafe(F.lit(None)), "nullif(p_size, 7) IS NOT DISTINCT FROM NULL"),
        "not": (lambda: ~(F.col("p_type") == "ECONOMY"), "NOT p_type = 'ECONOMY'"),
    }
    for name, (make, sql) in predicates.items():
        add(
            f"op_pred_{name}",
            (lambda m: lambda s, d: t(s, d, "part").where(m()).select("p_partkey"))(make),
            f"SELECT p_partkey FROM part WHERE {sql}",
        )

    few = lambda s, d: lines(s, d, "l_partkey", "l_quantity").where("l_quantity > 48").select(F.col("l_partkey").alias("p_partkey"))
    for how, word in (("semi", ""), ("anti", "NOT ")):
        add(
            f"op_{how}",
            (lambda h: lambda s, d: getattr(rel, h)(t(s, d, "part", "p_partkey"), few(s, d), ["p_partkey"]))(how),
            f"SELECT p_partkey FROM part WHERE p_partkey {word}IN (SELECT l_partkey FROM lineitem WHERE l_quantity > 48)",
        )
    add(
        "op_theta",
        lambda s, d: rel.theta(t(s, d, "nation", "n_nationkey", "n_regionkey"), t(s, d, "region", "r_regionkey"), F.col("n_regionkey") < F.col("r_regionkey")).select("n_nationkey", "r_regionkey"),
        "SELECT n_nationkey, r_regionkey FROM nation JOIN region ON n_regionkey < r_regionkey",
    )
    events = lambda s, d: t(s, d, "events", "event_id", "user_id", "ts", "event_type", "value", "props")
    add(
        "op_interval_join",
        lambda s, d: rel.interval_join(events(s, d).select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("ta")), events(s, d).where("event_type = 'purchase'").select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("tb")), "user_id", "ta", "tb", "0 hours", "2 hours").select("a", "b"),
        "SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON x.user_id = y.user_id AND y.event_type = 'purchase' AND y.ts BETWEEN "
        "x.ts AND x.ts + INTERVAL 2 HOUR",
    )
    add(
        "op_asof",
        lambda s, d: rel.asof_join(events(s, d).where("event_type = 'purchase'").select("event_id", "user_id", "ts"), events(s, d).where("event_type = 'view'").select("user_id", F.col("ts").alias("t2"), F.col("event_id").alias("seen")), "user_id", "ts", "t2", "seen").select("event_id", "asof_seen"),
        "SELECT event_id, (SELECT arg_max(v.event_id, (v.ts, v.event_id)) FROM events v WHERE v.event_type = 'view' AND v.user_id = e.user_id AND "
        "v.ts <= e.ts) AS asof_seen FROM events e WHERE event_type = 'purchase'",
    )
    add(
        "op_group_sum",
        lambda s, d: rel.aggregate(lines(s, d, "l_returnflag", "l_linestatus", "l_quantity"), ["l_returnflag", "l_linestatus"], n=F.count("*"), q=F.round(F.sum("l_quantity"), 2), top=F.max("l_quantity"), mean=F.round(F.avg("l_quantity"), 4)),
        "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS q, max(l_quantity) AS top, round(avg(l_quantity), 4) AS mean "
        "FROM lineitem GROUP BY ALL",
    )
    add(
        "op_having",
        lambda s, d: rel.aggregate(lines(s, d, "l_partkey"), ["l_partkey"], F.col("n") >= 40, n=F.count("*")),
        "SELECT l_partkey, count(*) AS n FROM lineitem GROUP BY l_partkey HAVING count(*) >= 40",
    )
    add(
        "op_count_if",
        lambda s, d: rel.aggregate(lines(s, d, "l_suppkey", "l_quantity"), ["l_suppkey"], n=F.count_if(F.col("l_quantity") > 25)),
        "SELECT l_suppkey, count_if(l_quantity > 25)::BIGINT AS n FROM lineitem GROUP BY l_suppkey",
    )
    add(
        "op_count_distinct",
        lambda s, d: rel.distinct_counts(t(s, d, "orders", "o_orderpriority", "o_custkey"), ["o_orderpriority"], "o_custkey"),
        "SELECT o_orderpriority, count(DISTINCT o_custkey) AS n FROM orders GROUP BY ALL",
    )
    add(
        "op_count_approx",
        lambda s, d: rel.distinct_counts(t(s, d, "orders", "o_orderpriority", "o_custkey"), ["o_orderpriority"], "o_custkey", approximate=True),
    )
    add(
        "op_percentile_approx",
        lambda s, d: rel.aggregate(lines(s, d, "l_suppkey", "l_quantity"), ["l_suppkey"], p=F.percentile_approx("l_quantity", 0.5, 1000)),
    )
    ord2 = lambda s, d: t(s, d, "orders", "o_orderstatus", "o_orderpriority")
    keys, group = ["o_orderstatus", "o_orderpriority"], "SELECT o_orderstatus, o_orderpriority, grouping(o_orderstatus, o_orderpriority)::BIGINT AS gid, count(*) AS n FROM orders GROUP BY "
    add("op_cube", lambda s, d: rel.cube(ord2(s, d), keys, n=F.count("*")), group + "CUBE (o_orderstatus, o_orderpriority)")
    add("op_rollup", lambda s, d: rel.rollup(ord2(s, d), keys, n=F.count("*")), group + "ROLLUP (o_orderstatus, o_orderpriority)")
    add(
        "op_gsets",
        lambda s, d: rel.grouping_sets(ord2(s, d), [["o_orderstatus"], ["o_orderpriority"]], keys, n=F.count("*")),
        group + "GROUPING SETS ((o_orderstatus), (o_orderpriority))",
    )
    add(
        "op_pivot",
        lambda s, d: rel.pivot_counts(events(s, d), "user_id", "event_type", ["view", "click"]),
        "SELECT user_id, count(*) FILTER (event_type = 'view') AS view, count(*) FILTER (event_type = 'click') AS click FROM events GROUP BY user_id",
    )
    for kind, sql in (("row_number", "row_number()"), ("rank", "rank()"), ("dense_rank", "dense_rank()"), ("ntile", "ntile(4)")):
        tie = ", p_partkey" if kind in ("row_number", "ntile") else ""
        order = lambda k: [F.desc("p_size"), *([F.asc("p_partkey")] if k in ("row_number", "ntile") else [])]
        add(
            f"op_rank_{kind}",
            (lambda k: lambda s, d: rel.rank_items(t(s, d, "part", "p_partkey", "p_brand", "p_size"), ["p_brand"], order(k), k))(kind),
            f"SELECT p_partkey, p_brand, p_size, ({sql} OVER (PARTITION BY p_brand ORDER BY p_size DESC{tie}))::INTEGER AS {kind} FROM part",
        )
    per_user = "OVER (PARTITION BY user_id ORDER BY event_id"
    add(
        "op_lag",
        lambda s, d: rel.lag_lead(events(s, d).select("event_id", "user_id", "event_type"), ["user_id"], ["event_id"], "event_type"),
        f"SELECT event_id, user_id, event_type, lag(event_type) {per_user}) AS lag_event_type, lead(event_type) {per_user}) AS lead_event_type FROM "
        f"events",
    )
    add(
        "op_running_rows",
        lambda s, d: rel.running(events(s, d).select("event_id", "user_id"), ["user_id"], ["event_id"], "event_id", "rows", 3),
        f"SELECT event_id, user_id, (sum(event_id) {per_user} ROWS BETWEEN 3 PRECEDING AND CURRENT ROW))::BIGINT AS running_event_id FROM events",
    )
    add(
        "op_running_range",
        lambda s, d: rel.running(events(s, d).select("event_id", "user_id"), ["user_id"], ["event_id"], "event_id", "range", 500),
        f"SELECT event_id, user_id, (sum(event_id) {per_user} RANGE BETWEEN 500 PRECEDING AND CURRENT ROW))::BIGINT AS running_event_id FROM events",
    )
    top_sql = pair_sql(inc_sql["order_supplier"], 1)
    add(
        "op_topk_pairs",
        lambda s, d: rel.top_k(pairs.pair_support(incidences["order_supplier"](s, d)), [F.desc("support"), F.asc("item_a"), F.asc("item_b")], 25),
        f"{top_sql} ORDER BY support DESC, item_a, item_b LIMIT 25",
    )
    add(
        "op_topk_partners", lambda s, d: rel.partners(pairs.pair_support(incidences["order_supplier"](s, d)), 3),
        f"WITH p AS ({top_sql}), b AS (SELECT item_a AS item, item_b AS partner, support FROM p UNION ALL SELECT item_b, item_a, support FROM p) "
        f"SELECT *, (row_number() OVER (PARTITION BY item ORDER BY support DESC, partner))::INTEGER AS rank FROM b QUALIFY rank <= 3",
    )
    add(
        "op_sort_limit",
        lambda s, d: rel.top_k(t(s, d, "part", "p_partkey", "p_retailprice"), [F.desc("p_retailprice"), F.asc("p_partkey")], 50),
        "SELECT p_partkey, p_retailprice FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 50",
    )
    left = lambda s, d: lines(s, d, "l_orderkey", "l_quantity").where("l_quantity > 35").select("l_orderkey")
    right = lambda s, d: lines(s, d, "l_orderkey", "l_discount").where("l_discount > 0.05").select("l_orderkey")
    for op in ("union", "intersect", "except"):
        for every in (False, True):
            add(
                f"op_{op}{'_all' if every else ''}",
                (lambda o, e: lambda s, d: rel.set_op(left(s, d), right(s, d), o, e))(op, every),
                f"SELECT l_orderkey FROM lineitem WHERE l_quantity > 35 {op.upper()}{' ALL' if every else ''} SELECT l_orderkey FROM lineitem WHERE "
                f"l_discount > 0.05",
            )
    baskets = lambda s, d: lines(s, d, "l_orderkey", "l_partkey").groupBy("l_orderkey").agg(F.array_sort(F.collect_set("l_partkey")).alias("x")).withColumn("y", F.transform("x", lambda v: v - v % 2))
    basket_sql = "WITH b AS (SELECT l_orderkey, list_sort(list(DISTINCT l_partkey)) AS x FROM lineitem GROUP BY l_orderkey), c AS (SELECT *, list_transform(x, lambda v: v - v % 2) AS y FROM b) "
    arrays = {"intersect": "len(list_intersect(list_distinct(x), y))", "union": "len(list_distinct(list_concat(x, y)))", "except": "len(list_filter(x, lambda v: NOT list_contains(y, v)))"}
    for op, sql in arrays.items():
        add(
            f"op_array_{op}",
            (lambda o: lambda s, d: rel.array_set_op(baskets(s, d), "x", "y", o).select("l_orderkey", F.size(o).cast("long").alias("n")))(op),
            basket_sql + f"SELECT l_orderkey, {sql}::BIGINT AS n FROM c",
        )
    add(
        "op_array_overlap",
        lambda s, d: rel.array_set_op(baskets(s, d), "x", "y", "overlap").select("l_orderkey", "overlap"),
        basket_sql + "SELECT l_orderkey, list_has_any(x, y) AS overlap FROM c",
    )
    add(
        "fn_string", lambda s, d: t(s, d, "part", "p_partkey", "p_name", "p_brand").select("p_partkey", F.lower(F.trim("p_name")).alias("low"), F.substring("p_name", 2, 3).alias("sub"), F.regexp_replace("p_brand", "[0-9]+", "#").alias("rep"), F.element_at(F.split("p_brand", "#"), -1).alias("last"), F.concat_ws("-", "p_name", "p_brand").alias("both"), F.length("p_name").cast("long").alias("len"), F.levenshtein("p_name", "p_brand").cast("long").alias("dist")),
        "SELECT p_partkey, lower(trim(p_name)) AS low, substring(p_name, 2, 3) AS sub, regexp_replace(p_brand, '[0-9]+', '#', 'g') AS rep, "
        "string_split(p_brand, '#')[-1] AS last, concat_ws('-', p_name, p_brand) AS both, length(p_name) AS len, levenshtein(p_name, p_brand) AS "
        "dist FROM part",
    )
    date = "o_orderdate"
    stamp = lambda c: F.date_format(c, "yyyy-MM-dd")
    add(
        "fn_date", lambda s, d: t(s, d, "orders", "o_orderkey", "o_orderdate").select("o_orderkey", stamp(F.date_trunc("month", date)).alias("month"), F.year(date).cast("long").alias("y"), F.month(date).cast("long").alias("m"), F.datediff(date, F.lit("1992-01-01").cast("date")).cast("long").alias("days"), stamp(F.add_months(date, 2)).alias("later"), stamp(F.col(date) + F.expr("interval 10 days")).alias("plus")),
        "SELECT o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, year(o_orderdate) AS y, month(o_orderdate) AS m, "
        "date_diff('day', DATE '1992-01-01', o_orderdate::DATE) AS days, strftime(o_orderdate::DATE + INTERVAL 2 MONTH, '%Y-%m-%d') AS later, "
        "strftime(o_orderdate + INTERVAL 10 DAY, '%Y-%m-%d') AS plus FROM orders",
    )
    k = lambda: F.col("l_orderkey")
    add(
        "fn_bits", lambda s, d: lines(s, d, "l_orderkey", "l_linenumber").select("l_orderkey", "l_linenumber", F.shiftleft(k(), 3).alias("sl"), F.shiftright(k(), 2).alias("sr"), k().bitwiseAND(F.lit(255)).alias("a"), k().bitwiseOR(F.lit(1)).alias("o"), k().bitwiseXOR(F.lit(21845)).alias("x"), F.bit_count(k()).cast("long").alias("c"), F.pmod(k(), F.lit(7)).alias("p")),
        "SELECT l_orderkey, l_linenumber, l_orderkey << 3 AS sl, l_orderkey >> 2 AS sr, l_orderkey & 255 AS a, l_orderkey | 1 AS o, xor(l_orderkey, "
        "21845) AS x, bit_count(l_orderkey)::BIGINT AS c, l_orderkey % 7 AS p FROM lineitem",
    )
    add(
        "fn_math",
        lambda s, d: t(s, d, "part", "p_partkey", "p_size").select("p_partkey", F.ceil(F.log2("p_size")).alias("l"), F.lower(F.hex("p_partkey")).alias("h"), F.round(F.sqrt("p_size"), 6).alias("r")),
        "SELECT p_partkey, ceil(log2(p_size))::BIGINT AS l, lower(to_hex(p_partkey)) AS h, round(sqrt(p_size), 6) AS r FROM part",
    )
    add(
        "fn_array", lambda s, d: baskets(s, d).select("l_orderkey", F.aggregate("x", F.lit(0).cast("long"), lambda a, v: a + v).alias("total"), F.size(F.filter("x", lambda v: v % 2 == 0)).cast("long").alias("even"), F.aggregate(F.zip_with("x", "y", lambda a, b: a - b), F.lit(0).cast("long"), lambda a, v: a + v).alias("odd"), F.size(F.flatten(F.array("x", "y"))).cast("long").alias("flat"), F.size(F.sequence(F.lit(1), F.size("x"))).cast("long").alias("seq")),
        basket_sql + "SELECT l_orderkey, list_sum(x)::BIGINT AS total, len(list_filter(x, lambda v: v % 2 = 0)) AS even, list_sum(list_transform(x, lambda v: v % 2))::BIGINT AS odd, 2 * len(x) AS flat, len(x) AS seq FROM c",
    )
    add(
        "fn_map",
        lambda s, d: events(s, d).groupBy("user_id").agg(F.map_from_entries(F.collect_set(F.struct("event_type", F.lit(1)))).alias("m")).select("user_id", F.array_join(F.array_sort(F.map_keys("m")), ",").alias("keys"), F.coalesce(F.try_element_at("m", F.lit("view")), F.lit(0)).cast("long").alias("view")),
        "SELECT user_id, string_agg(DISTINCT event_type, ',' ORDER BY event_type) AS keys, max(CASE WHEN event_type = 'view' THEN 1 ELSE 0 "
        "END)::BIGINT AS view FROM events GROUP BY user_id",
    )
    add(
        "fn_json",
        lambda s, d: events(s, d).select("event_id", F.from_json("props", "k int")["k"].cast("long").alias("k"), F.get_json_object("props", "$.k").alias("text"), F.to_json(F.struct("event_id")).alias("back")),
        "SELECT event_id, (props->>'$.k')::BIGINT AS k, props->>'$.k' AS text, '{\"event_id\":' || event_id || '}' AS back FROM events",
    )
    return q
