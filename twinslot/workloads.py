"""Queries over the given tables, one per method, variant, measure and operator, each with
plain SQL that says the same (where SQL can)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .config import Config
from .functions import sqlfun
from .operators import apps, baselines, builder, compare, measure, pairs, sequential
from .operators import relational as rel
from .plans import planner
from .sources import incidence as inc
from .sources import io
from .stages import cut, new_path
from .streaming import stream

Query = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, Query] = {}
_SQL: dict[str, str] = {}


def _add(name: str, query: Query, sql: str | None = None) -> None:
    _QUERIES[name] = query
    if sql:
        _SQL[name] = sql


def _query(sql: str | None = None, name: str | None = None):
    def put(query: Query) -> Query:
        _add(name or query.__name__, query, sql)
        return query

    return put


def queries() -> dict[str, Query]:
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)


def t(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    return io.read_table(spark, sf_dir, name, list(columns))


# Incidences ---------------------------------------------------------------------------------


def order_part(s: SparkSession, d: str) -> DataFrame:
    return inc.from_columns(t(s, d, "lineitem", "l_partkey", "l_orderkey"), "l_partkey", "l_orderkey")


def order_supplier(s: SparkSession, d: str) -> DataFrame:
    return inc.from_columns(t(s, d, "lineitem", "l_suppkey", "l_orderkey"), "l_suppkey", "l_orderkey")


def part_supplier(s: SparkSession, d: str) -> DataFrame:
    return inc.from_columns(t(s, d, "lineitem", "l_suppkey", "l_partkey"), "l_suppkey", "l_partkey")


def customer_part(s: SparkSession, d: str) -> DataFrame:
    lines = t(s, d, "lineitem", "l_partkey", "l_orderkey").withColumnRenamed("l_orderkey", "k")
    return inc.from_join(lines, t(s, d, "orders", "o_orderkey", "o_custkey").withColumnRenamed("o_orderkey", "k"), "k", "l_partkey", "o_custkey")


def doc_word(s: SparkSession, d: str) -> DataFrame:
    return inc.from_text(t(s, d, "documents", "doc_id", "text"), "doc_id", "text")


INC_SQL = {
    "order_part": "SELECT DISTINCT l_partkey AS item, l_orderkey AS tid FROM lineitem",
    "order_supplier": "SELECT DISTINCT l_suppkey AS item, l_orderkey AS tid FROM lineitem",
    "part_supplier": "SELECT DISTINCT l_suppkey AS item, l_partkey AS tid FROM lineitem",
    "customer_part": "SELECT DISTINCT l_partkey AS item, o_custkey AS tid FROM lineitem JOIN orders ON o_orderkey = l_orderkey",
    "doc_word": "SELECT DISTINCT lower(unnest(regexp_extract_all(text, '[A-Za-z]+'))) AS item, doc_id AS tid FROM documents",
}
INCIDENCES = {"order_part": order_part, "order_supplier": order_supplier, "part_supplier": part_supplier, "customer_part": customer_part, "doc_word": doc_word}
SUPPORT = {"order_part": 2, "order_supplier": 30, "part_supplier": 150, "customer_part": 3, "doc_word": 100}


def pair_sql(incidence: str, min_support: int) -> str:
    return (
        f"WITH i AS ({incidence}) SELECT a.item AS item_a, b.item AS item_b, count(*)::BIGINT AS support FROM i a JOIN i b "
        f"ON a.tid = b.tid AND a.item < b.item GROUP BY ALL HAVING count(*) >= {min_support}"
    )


def by_method(make: Query, method: str, min_support: int, cfg: Config | None = None, words: bool = False) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        rows = make(s, d)
        if not words:
            return pairs.pair_support(rows, method, min_support, cfg)
        ids, dictionary = inc.encoded(cut(pairs.prune(rows, min_support), "words"))
        found = pairs.pair_support(ids, method, min_support, cfg)
        a = dictionary.select(F.col("key").alias("word_a"), F.col("id").alias("item_a"))
        b = dictionary.select(F.col("key").alias("word_b"), F.col("id").alias("item_b"))
        return found.join(a, "item_a").join(b, "item_b").select(F.col("word_a").alias("item_a"), F.col("word_b").alias("item_b"), "support")

    return run


for _name, _make in INCIDENCES.items():
    for _method in ("twinslot", *baselines.METHODS):
        # The library's FP-growth enumerates itemsets of every size, which words of shared passages make exponentially many.
        if (_name, _method) != ("doc_word", "library_fpgrowth"):
            _add(
                f"fp_{_name}_{_method}",
                by_method(_make, _method, SUPPORT[_name], words=_name == "doc_word"),
                pair_sql(INC_SQL[_name], SUPPORT[_name]),
            )

VARIANTS = {
    "twinslot_all_pairs": (Config(), 1), "twinslot_forced_failures": (Config(max_rounds=1), 30), "twinslot_slot16": (Config(slot_bits=16), 30),
    "twinslot_slot32": (Config(slot_bits=32), 30), "twinslot_unsorted": (Config(sort_by_width=False), 30), "twinslot_segmented": (Config(segment_j=4), 30),
    "twinslot_full_square": (Config(triangle=False), 30), "twinslot_small_tiles": (Config(tile_items=16), 30), "twinslot_plain_ranges": (Config(slack=0.0), 30),
    "twinslot_whole_segments": (Config(segment_j=5, tile_items=16, distribution="segments"), 30), "twinslot_shipped_maps": (Config(segment_j=5, tile_items=16, distribution="tiles"), 30),
}
for _name, (_cfg, _min) in VARIANTS.items():
    _add(_name, by_method(order_supplier, "twinslot", _min, _cfg), pair_sql(INC_SQL["order_supplier"], _min))


# Ids far beyond 2^53, as hashes and stamps have them: counts, listings and probes stay exact.
FAR = 1 << 62


def far_order_supplier(s: SparkSession, d: str) -> DataFrame:
    return order_supplier(s, d).withColumn("tid", F.col("tid") * 64 + FAR)


_FAR_SQL = f"SELECT DISTINCT l_suppkey AS item, l_orderkey * 64 + {FAR} AS tid FROM lineitem"
for _method in ("twinslot", "merge", "bitmap", "bitmap_sql"):
    _add(f"far_ids_{_method}", by_method(far_order_supplier, _method, 1, Config() if _method != "bitmap_sql" else None), pair_sql(_FAR_SQL, 1))
_add(
    "far_ids_listing",
    lambda s, d: apps.intersection(far_order_supplier(s, d), 1, 2),
    f"SELECT tid FROM ({_FAR_SQL}) WHERE item = 1 INTERSECT SELECT tid FROM ({_FAR_SQL}) WHERE item = 2",
)


@_query(pair_sql(INC_SQL["order_supplier"], 1))
def slots_sql(s, d):
    """The counting rule as a join of slot rows."""
    return pairs.pair_support_slots(order_supplier(s, d))


@_query(pair_sql(INC_SQL["order_supplier"], 1))
def lanes_sql(s, d):
    """Packed words compared four slots at a time, as a join of words."""
    return pairs.pair_support_lanes(order_supplier(s, d))


@_query(pair_sql(INC_SQL["customer_part"], 3))
def planned_pairs(s, d):
    """The cheapest method by cost."""
    return planner.pair_support(customer_part(s, d), 3)


@_query(
    f"SELECT pa.p_name AS name_a, pb.p_name AS name_b, support, item_a, item_b FROM ({pair_sql(INC_SQL['order_part'], 2)}) x "
    "JOIN part pa ON pa.p_partkey = item_a JOIN part pb ON pb.p_partkey = item_b ORDER BY support DESC, item_a, item_b LIMIT 100"
)
def flagship(s, d):
    """The hundred most frequent part pairs of orders, with their names."""
    top = rel.top_k(pairs.pair_support(order_part(s, d), min_support=2), [F.desc("support"), F.asc("item_a"), F.asc("item_b")], 100)
    names = t(s, d, "part", "p_partkey", "p_name")
    a = names.select(F.col("p_partkey").alias("item_a"), F.col("p_name").alias("name_a"))
    b = names.select(F.col("p_partkey").alias("item_b"), F.col("p_name").alias("name_b"))
    return F.broadcast(top).join(a, "item_a").join(b, "item_b").select("name_a", "name_b", "support", "item_a", "item_b")


# Workloads ----------------------------------------------------------------------------------

GRID = "((p_partkey * 7919 + s_suppkey * 104729 + 17) * ((p_partkey + 3) * 31 + s_suppkey * s_suppkey * 13 + 7)) % 1000003"


def grid(p: int, fold: int = 1) -> tuple[Query, str]:
    """The deterministic instance of density 1/p over all parts and suppliers. With ``fold`` k suppliers
    make one item of k times as many transactions: fewer items, and the same number of rows and density."""

    def make(s: SparkSession, d: str) -> DataFrame:
        rows = inc.grid(t(s, d, "part", "p_partkey"), t(s, d, "supplier", "s_suppkey"), p)
        return rows.select(F.expr(f"item div {fold}").alias("item"), (F.col("tid") * fold + F.col("item") % fold).alias("tid")) if fold > 1 else rows

    return make, f"SELECT s_suppkey // {fold} AS item, p_partkey * {fold} + s_suppkey % {fold} AS tid FROM part, supplier WHERE {GRID} % {p} = 0"


for _k in (4, 2, 1):  # n grows, the instance's size and density don't
    _make, _sql = grid(16, _k)
    for _method in ("twinslot", "bitmap", "merge", "horizontal", "apriori", "fpgrowth"):
        _add(f"w2_items_over_{_k}_{_method}", by_method(_make, _method, 1), pair_sql(_sql, 1))
for _p in (2, 4, 8, 16, 32, 64):
    _make, _sql = grid(_p)
    _add(f"w4_density_{_p}", by_method(_make, "twinslot", 1), pair_sql(_sql, 1))


def _split(i: int) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        rows = inc.written(order_supplier(s, d), "split")
        parts = [pairs.pair_support(rows.where(F.col("tid") % i == k) if i > 1 else rows) for k in range(i)]
        whole = parts[0]
        for part in parts[1:]:
            whole = whole.unionByName(part)
        return whole.groupBy("item_a", "item_b").agg(F.sum("support").alias("support"))

    return run


for _i in (1, 2, 4, 8):
    _add(f"w5_split_{_i}", _split(_i), pair_sql(INC_SQL["order_supplier"], 1))


_BYTES = (
    "WITH i AS ({}), c AS (SELECT item, count(*) AS card FROM i GROUP BY item), m AS (SELECT count(DISTINCT tid) AS m FROM i), "
    "p AS (SELECT item, card, (SELECT min(1::BIGINT << k) FROM range(0, 40) r(k) WHERE (1::BIGINT << k) >= card) AS up FROM c) "
)
_LAYOUT = (
    _BYTES + "SELECT count(*)::BIGINT AS n, any_value(m.m)::BIGINT AS m, sum(card)::BIGINT AS total, (4 * sum(card))::BIGINT AS list_bytes, "
    "(count(*) * ((any_value(m.m) + 7) // 8))::BIGINT AS bitmap_bytes, sum(6 * up)::BIGINT AS map_bytes, (4 * (count(*) * (count(*) - 1) // "
    "2))::BIGINT AS counter_bytes FROM p, m"
)
for _name in ("order_supplier", "part_supplier", "order_part"):
    _add(f"w1_memory_{_name}", (lambda make: lambda s, d: measure.bytes_by_layout(make(s, d)))(INCIDENCES[_name]), _LAYOUT.format(INC_SQL[_name]))
for _k in (4, 2, 1):
    _make, _sql = grid(16, _k)
    _add(f"w1_memory_items_over_{_k}", (lambda make: lambda s, d: measure.bytes_by_layout(make(s, d)))(_make), _LAYOUT.format(_sql))


# Applications -------------------------------------------------------------------------------

_LEFT = "SELECT DISTINCT o_custkey AS r, l_partkey AS k FROM lineitem JOIN orders ON o_orderkey = l_orderkey"
_RIGHT = "SELECT DISTINCT l_partkey AS k, l_suppkey AS c FROM lineitem"


def _matrices(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    left = customer_part(s, d).select(F.col("tid").alias("row"), F.col("item").alias("k"))
    return left, part_supplier(s, d).select(F.col("tid").alias("k"), F.col("item").alias("col"))


_BMM = f"SELECT r AS \"row\", c AS col, count(*)::BIGINT AS n FROM ({_LEFT}) a JOIN ({_RIGHT}) b USING (k) GROUP BY ALL"
_add("bmm_customer_supplier", lambda s, d: apps.bool_matmul(*_matrices(s, d)), f'SELECT DISTINCT "row", col FROM ({_BMM})')
_add("bmm_counts_join", lambda s, d: apps.bool_matmul(*_matrices(s, d), counts=True), _BMM)
_add("bmm_counts_twinslot", lambda s, d: apps.bool_matmul(*_matrices(s, d), counts=True, method="twinslot"), _BMM)


@_query("SELECT DISTINCT c_nationkey, s_nationkey FROM (" + _LEFT + ") a JOIN (" + _RIGHT + ") b USING (k) JOIN customer ON c_custkey = r JOIN supplier ON s_suppkey = c")
def join_project_nations(s, d):
    """Nations of customers and suppliers that a part links."""
    left = customer_part(s, d).join(t(s, d, "customer", "c_custkey", "c_nationkey"), F.col("tid") == F.col("c_custkey")).select(F.col("item").alias("k"), "c_nationkey")
    right = part_supplier(s, d).join(t(s, d, "supplier", "s_suppkey", "s_nationkey"), F.col("item") == F.col("s_suppkey")).select(F.col("tid").alias("k"), "s_nationkey")
    return apps.join_project(left, right, "k", ("c_nationkey", "s_nationkey"))


@_query("SELECT DISTINCT o_custkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_quantity >= 49)")
def join_project_semi(s, d):
    """Only one side is kept, so the plan is a semi-join."""
    lines = t(s, d, "lineitem", "l_orderkey", "l_quantity").where("l_quantity >= 49").select(F.col("l_orderkey").alias("o_orderkey"))
    return apps.join_project(t(s, d, "orders", "o_orderkey", "o_custkey"), lines, "o_orderkey", ("o_custkey",))


RARE = 5
_RARE = f"SELECT item, tid FROM ({INC_SQL['doc_word']}) QUALIFY count(*) OVER (PARTITION BY item) BETWEEN 2 AND {RARE}"


@_query(f"WITH r AS ({_RARE}) SELECT DISTINCT a.tid AS doc_a, b.tid AS doc_b FROM r a JOIN r b ON a.item = b.item AND a.tid < b.tid")
def join_project_docs(s, d):
    """Pairs of documents that share a rare word (one of two to ``RARE`` documents)."""
    words = doc_word(s, d)
    rare = words.groupBy("item").agg(F.count("*").alias("n")).where(F.col("n").between(2, RARE)).select("item")
    rows = cut(words.join(rare, "item"), "rare")
    a, b = (rows.select("item", F.col("tid").alias(c)) for c in ("doc_a", "doc_b"))
    return apps.join_project(a, b, "item", ("doc_a", "doc_b")).where("doc_a < doc_b")


def _conj(name: str, table: str, key: str, columns: list[str], preds: Callable[[], list], sql: str) -> None:
    _add(f"conj_{name}", lambda s, d: apps.conjunctive(t(s, d, table, key, *columns), key, preds()), f"SELECT {key} FROM {table} WHERE {sql}")


_conj(
    "brand_size",
    "part",
    "p_partkey",
    ["p_brand", "p_size"],
    lambda: [F.col("p_brand") == "Brand#13", F.col("p_size") < 20],
    "p_brand = 'Brand#13' AND p_size < 20",
)
_conj(
    "status_priority",
    "orders",
    "o_orderkey",
    ["o_orderstatus", "o_orderpriority"],
    lambda: [F.col("o_orderstatus") == "F", F.col("o_orderpriority").startswith("1")],
    "o_orderstatus = 'F' AND starts_with(o_orderpriority, '1')",
)
_conj("quality_toxic", "labels", "doc_id", ["quality", "toxic"], lambda: [F.col("quality") == 1, F.col("toxic") == 0], "quality = 1 AND toxic = 0")


@_query("SELECT count(*)::BIGINT AS n FROM lineitem WHERE l_returnflag = 'R' AND l_quantity > 25")
def conj_count(s, d):
    return apps.conjunctive(t(s, d, "lineitem", "l_orderkey", "l_returnflag", "l_quantity"), "l_orderkey", [F.col("l_returnflag") == "R", F.col("l_quantity") > 25], "count")


@_query(
    "WITH f AS (SELECT o_orderkey AS k, unnest([CASE WHEN o_orderstatus = 'F' THEN 0 END, CASE WHEN starts_with(o_orderpriority, '1') THEN 1 END, "
    "CASE WHEN o_totalprice > 200000 THEN 2 END]) AS item FROM orders), "
    "g AS (SELECT DISTINCT item::BIGINT AS item, k FROM f WHERE item IS NOT NULL) SELECT a.item AS item_a, b.item AS item_b, count(*)::BIGINT AS "
    "support FROM g a JOIN g b ON a.k = b.k AND a.item < b.item GROUP BY ALL"
)
def conj_sets(s, d):
    """Pre-evaluated predicates as sets: all pairwise conjunction sizes at once."""
    orders = t(s, d, "orders", "o_orderkey", "o_orderstatus", "o_orderpriority", "o_totalprice")
    return apps.conjunctive_sets(orders, "o_orderkey", [F.col("o_orderstatus") == "F", F.col("o_orderpriority").startswith("1"), F.col("o_totalprice") > 200000])


_add(
    "intersection_listing",
    lambda s, d: apps.intersection(order_supplier(s, d), 1, 2),
    "SELECT l_orderkey AS tid FROM lineitem WHERE l_suppkey = 1 INTERSECT SELECT l_orderkey FROM lineitem WHERE l_suppkey = 2",
)
_add(
    "intersection_size",
    lambda s, d: apps.intersection_size(order_supplier(s, d), 1, 2),
    "SELECT count(*)::BIGINT AS n FROM (SELECT l_orderkey FROM lineitem WHERE l_suppkey = 1 INTERSECT SELECT l_orderkey FROM lineitem WHERE "
    "l_suppkey = 2)",
)


# Formats and measures -----------------------------------------------------------------------

_add("inc_order_part", order_part, INC_SQL["order_part"])
_add("inc_doc_word", doc_word, INC_SQL["doc_word"])
_add("inc_from_array", lambda s, d: inc.from_array(inc.transactions(order_part(s, d)), "tid", "items"), INC_SQL["order_part"])
_add(
    "inc_event_prop",
    lambda s, d: inc.from_json(t(s, d, "events", "user_id", "props"), "user_id", "props", "k int"),
    "SELECT DISTINCT 'k=' || (props->>'$.k')::INTEGER AS item, user_id AS tid FROM events WHERE (props->>'$.k') IS NOT NULL",
)
_add(
    "inc_from_map",
    lambda s, d: inc.from_map(t(s, d, "events", "user_id", "event_type").withColumn("m", F.create_map("event_type", F.lit(1))), "user_id", "m"),
    "SELECT DISTINCT event_type AS item, user_id AS tid FROM events",
)
_add(
    "vertical",
    lambda s, d: inc.tidlists(order_supplier(s, d)).select("item", F.array_join(F.col("tids").cast("array<string>"), ",").alias("tids")),
    f"SELECT item, string_agg(tid::VARCHAR, ',' ORDER BY tid) AS tids FROM ({INC_SQL['order_supplier']}) GROUP BY item",
)
_add(
    "horizontal_format",
    lambda s, d: inc.transactions(order_part(s, d)).select("tid", F.array_join(F.col("items").cast("array<string>"), ",").alias("items")),
    f"SELECT tid, string_agg(item::VARCHAR, ',' ORDER BY item) AS items FROM ({INC_SQL['order_part']}) GROUP BY tid",
)
_add(
    "dense_ids_words",
    lambda s, d: inc.dictionary(doc_word(s, d), "item"),
    f"SELECT item AS key, row_number() OVER (ORDER BY item) - 1 AS id FROM (SELECT DISTINCT item FROM ({INC_SQL['doc_word']}))",
)
_add(
    "copies_per_element",
    lambda s, d: measure.copies_per_element(order_supplier(s, d)),
    f"SELECT item, (2 * count(*))::BIGINT AS copies FROM ({INC_SQL['order_supplier']}) GROUP BY item",
)
_add(
    "copies_forced_failures",
    lambda s, d: measure.copies_per_element(order_supplier(s, d), Config(max_rounds=1)),
    f"SELECT item, (2 * count(*))::BIGINT AS copies FROM ({INC_SQL['order_supplier']}) GROUP BY item",
)
_add(
    "elements_roundtrip",
    lambda s, d: (lambda b: compare.elements(builder.maps_of(b)).unionByName(builder.failed_of(b)))(builder.build(order_supplier(s, d))),
    INC_SQL["order_supplier"],
)
_add("diagonal", lambda s, d: measure.diagonal(order_supplier(s, d)), f"SELECT item, count(*) AS n FROM ({INC_SQL['order_supplier']}) GROUP BY item")
_add(
    "diagonal_forced_failures",
    lambda s, d: measure.diagonal(order_supplier(s, d), Config(max_rounds=1)),
    f"SELECT item, count(*) AS n FROM ({INC_SQL['order_supplier']}) GROUP BY item",
)
_add(
    "map_width",
    lambda s, d: measure.map_bytes(order_part(s, d)),
    _BYTES.format(INC_SQL["order_part"]) + "SELECT item, card, (6 * up)::BIGINT AS bytes FROM p",
)
_add(
    "instance_size",
    lambda s, d: measure.instance(customer_part(s, d)),
    f"SELECT count(DISTINCT item) AS n, count(DISTINCT tid) AS m, count(*) AS total, round(count(*) / count(DISTINCT item), 6) AS avg_size, "
    f"round(count(*) / (count(DISTINCT item) * count(DISTINCT tid)), 9) AS density FROM ({INC_SQL['customer_part']})",
)
_add(
    "density",
    lambda s, d: measure.density(order_supplier(s, d)),
    f"WITH i AS ({INC_SQL['order_supplier']}) SELECT item, count(*) AS card, round(count(*) / (SELECT count(DISTINCT tid) FROM i), 9) AS density "
    f"FROM i GROUP BY item",
)
_add(
    "compression_gain",
    lambda s, d: measure.compression_gain(order_supplier(s, d)),
    f"WITH i AS ({INC_SQL['order_supplier']}), m AS (SELECT count(DISTINCT tid) AS m FROM i) SELECT item, count(*) AS card, 256 * count(*) >= "
    f"any_value(m) + 1 AS gain, (SELECT min(k) FROM range(0, 40) r(k) WHERE (1::BIGINT << k) * 128 >= any_value(m) + 1)::INTEGER AS shift FROM i, m "
    f"GROUP BY item",
)
_add(
    "space_ratio",
    lambda s, d: measure.space_ratio(order_supplier(s, d)).select("item", "card", F.round("ratio", 2).alias("ratio")),
    _BYTES.format(INC_SQL["order_supplier"]) + "SELECT item, card, round(8 * 6 * up / ((lgamma(m.m + 1) - lgamma(card + 1) - lgamma(m.m - card + 1)) / ln(2)), 2) AS ratio FROM p, m",
)
_add("build_stats", lambda s, d: measure.build_stats(order_supplier(s, d)))
_add("build_stats_plain", lambda s, d: measure.build_stats(order_supplier(s, d), Config(slack=0.0)))
_add("insertion_transcripts", lambda s, d: sequential.transcripts(order_supplier(s, d)))
for _sorted, _key in ((True, "6 * up, item"), (False, "item")):
    _sql = _BYTES.format(INC_SQL["doc_word"]).rstrip() + f", k AS (SELECT 6 * up AS width, (row_number() OVER (ORDER BY {_key}) - 1) // 512 AS block FROM p), blocks AS (SELECT block, count(*) AS n, max(width) AS w FROM k GROUP BY block) SELECT sum(a.n * b.n * greatest(a.w, b.w))::BIGINT AS slot_tests, count(*) AS tiles FROM blocks a JOIN blocks b ON a.block <= b.block"
    _add(f"tile_cost_{'sorted' if _sorted else 'unsorted'}", (lambda by: lambda s, d: measure.tile_cost(doc_word(s, d), 512, by))(_sorted), _sql)
_add(
    "exactness",
    lambda s, d: (lambda rows: measure.pair_diff(pairs.pair_support(rows), pairs.pair_support(rows, "hash")))(inc.written(order_supplier(s, d), "rows")),
    "SELECT 0::BIGINT AS pairs, 0::BIGINT AS total",
)
_add(
    "containers", lambda s, d: planner.containers(order_supplier(s, d)).select("item", "seg", "card", "container", "bytes"),
    f"WITH c AS (SELECT item, tid // 65024 AS seg, count(*) AS card FROM ({INC_SQL['order_supplier']}) GROUP BY ALL), "
    "l AS (SELECT *, CASE WHEN card <= 1 THEN 1 ELSE length(bin(card - 1)) + 1 END AS lg FROM c), "
    "g AS (SELECT *, lg + CASE WHEN (1::BIGINT << lg) < card * 2.3::DOUBLE THEN 1 ELSE 0 END AS b FROM l), "
    "s AS (SELECT *, 4 * card AS list, 3 * (1::BIGINT << least(greatest(b, 9), 16)) AS slot8, 6 * (1::BIGINT << least(greatest(b, 6), 16)) AS "
    "slot16, 12 * (1::BIGINT << least(greatest(b, 6), 16)) AS slot32, 8128 AS bitmap FROM g), "
    "m AS (SELECT *, least(list, slot8, slot16, slot32, bitmap) AS bytes FROM s) SELECT item, seg, card, "
    "CASE bytes WHEN list THEN 'list' WHEN slot8 THEN 'slot8' WHEN slot16 THEN 'slot16' WHEN slot32 THEN 'slot32' ELSE 'bitmap' END AS container, "
    "bytes FROM m",
)
_add(
    "assoc_supplier", lambda s, d: (lambda rows: measure.association(pairs.pair_support(rows, min_support=30), rows))(inc.written(order_supplier(s, d), "rows")),
    f"WITH c AS (SELECT item, count(*) AS n FROM ({INC_SQL['order_supplier']}) GROUP BY item), m AS (SELECT count(DISTINCT l_orderkey) AS m FROM "
    f"lineitem) "
    f"SELECT item_a, item_b, support, round(support / m, 9) AS support_share, round(support / a.n, 9) AS confidence_ab, round(support / b.n, 9) AS "
    f"confidence_ba, round(support * m / (a.n * b.n), 9) AS lift, "
    f"round(support / (a.n + b.n - support), 9) AS jaccard, round(support / sqrt(a.n * b.n), 9) AS cosine, round(support / least(a.n, b.n), 9) AS "
    f"overlap FROM ({pair_sql(INC_SQL['order_supplier'], 30)}) x JOIN c a ON a.item = item_a JOIN c b ON b.item = item_b, m",
)

# SQL functions ------------------------------------------------------------------------------


@_query(pair_sql(INC_SQL["order_part"], 2))
def udtf_basket_pairs(s, d):
    """Horizontal counting with a table function."""
    sqlfun.register(s)
    inc.transactions(order_part(s, d)).createOrReplaceTempView("twinslot_baskets")
    return s.sql("SELECT p.item_a, p.item_b, count(*) AS support FROM twinslot_baskets b, LATERAL basket_pairs(b.items) p GROUP BY p.item_a, p.item_b HAVING count(*) >= 2")


# Streams ------------------------------------------------------------------------------------


def _events_dir(s: SparkSession, d: str) -> str:
    """Events as a directory of files for the streaming source."""
    path = new_path(s, "events")
    t(s, d, "events", "event_id", "user_id", "ts", "event_type", "value", "props").repartition(4).write.parquet(path)
    return path


@_query("SELECT DISTINCT event_type AS item, user_id AS tid FROM events")
def stream_incidence(s, d):
    """Deduplicated incidence of a stream, and what batches that overlap bring twice removed on reading."""
    src = stream.source(s, _events_dir(s, d))
    out, checkpoint = new_path(s, "out"), new_path(s, "ck")
    stream.run_once(stream.incidence(src, "event_type", "user_id", watermark="3650 days").select("item", "tid"), out, checkpoint)
    return s.read.schema("item string, tid long").parquet(out).distinct()


@_query("WITH i AS (SELECT DISTINCT event_type AS item, user_id AS tid FROM events) SELECT a.item AS item_a, b.item AS item_b, count(*)::BIGINT AS support FROM i a JOIN i b ON a.tid = b.tid AND a.item < b.item GROUP BY ALL")
def stream_pairs(s, d):
    """Pair supports kept up to date by micro-batches."""
    store = stream.PairStore(s)
    stream.pair_support(stream.source(s, _events_dir(s, d), files_per_batch=2), "event_type", "user_id", store, new_path(s, "ck")).awaitTermination()
    return store.supports()


_CLOSED = "(SELECT max(ts) - INTERVAL 1 SECOND FROM events)"


def _windowed(kind: str) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        out = new_path(s, "out")
        rows = stream.windowed_sets(stream.source(s, _events_dir(s, d)), kind, watermark="1 second").select("start", "event_type", "n")
        stream.run_once(rows, out, new_path(s, "ck"))
        made = s.read.schema("start timestamp, event_type string, n long").parquet(out)
        return made.select(F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "event_type", "n")

    return run


_STAMP = "strftime(w, '%Y-%m-%d %H:%M:%S') AS start"
_add(
    "stream_tumbling",
    _windowed("tumbling"),
    f"SELECT {_STAMP}, event_type, count(*) AS n FROM (SELECT time_bucket(INTERVAL 1 HOUR, ts) AS w, event_type FROM events) WHERE w + INTERVAL 1 "
    f"HOUR <= {_CLOSED} GROUP BY w, event_type",
)
_add(
    "stream_sliding",
    _windowed("sliding"),
    f"SELECT {_STAMP}, event_type, count(*) AS n FROM (SELECT time_bucket(INTERVAL 30 MINUTE, ts) - k * INTERVAL 30 MINUTE AS w, event_type FROM "
    f"events, range(0, 2) r(k)) WHERE w + INTERVAL 1 HOUR <= {_CLOSED} GROUP BY w, event_type",
)
_add(
    "stream_session", _windowed("session"),
    "WITH o AS (SELECT event_type, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY event_type ORDER BY ts) < INTERVAL 1 HOUR THEN 0 ELSE 1 END AS new "
    "FROM events), "
    "g AS (SELECT *, sum(new) OVER (PARTITION BY event_type ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM o), "
    f"x AS (SELECT event_type, min(ts) AS w, max(ts) + INTERVAL 1 HOUR AS e, count(*) AS n FROM g GROUP BY event_type, g) SELECT {_STAMP}, "
    f"event_type, n FROM x WHERE e <= {_CLOSED}",
)

from . import surface  # noqa: E402

for _name, (_run, _sql) in surface.table(t, INCIDENCES, INC_SQL, pair_sql).items():
    _add(_name, _run, _sql)

from . import whole  # noqa: E402

for _name, (_run, _sql) in whole.table(t, INCIDENCES, INC_SQL, pair_sql, by_method).items():
    _add(_name, _run, _sql)
