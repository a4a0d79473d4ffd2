"""The classical competitors, all answering ``(item_a, item_b, support)``."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.ml.fpm import FPGrowth
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import Config
from ..sources.incidence import places_of, segmented, transactions, whole_sets
from ..stages import cut
from . import compare, fptree, pairs

PAIR = ("item_a", "item_b")

#: Bitmaps in a block: sparse ones are small, and fewer blocks ship less.
BITMAP_ITEMS = 4096


def _packed(inc: DataFrame, cfg: Config, make: Callable[[np.ndarray], bytes]) -> DataFrame:
    """``(item, seg, payload)``: the sorted segment positions of each set, made to bytes."""
    def pack(xs: pa.Array, ws: pa.Array) -> pa.Array:
        return pa.array([make(places_of(*one)) for one in zip(xs.to_pylist(), ws.to_pylist())], pa.binary())

    return whole_sets(inc, cfg.segment).select("item", "seg", F.arrow_udf(pack, "binary")("xs", "ws").alias("payload"))  # at most a segment each


def packed_lists(inc: DataFrame, cfg: Config = Config()) -> DataFrame:
    """``(item, seg, payload)``: sorted 32-bit positions."""
    return _packed(inc, cfg, lambda x: x.tobytes())


def packed_bitmaps(inc: DataFrame, cfg: Config = Config()) -> DataFrame:
    """``(item, seg, payload)``: one bit per transaction of the segment, in words of which those without a bit are left out."""
    return _packed(inc, cfg, compare.pack_words)


def merge(inc: DataFrame, min_support: int = 1, cfg: Config = Config()) -> DataFrame:
    """Merging sorted lists, over the same tiles as the maps."""
    kept = pairs.kept(inc, min_support)
    lists = cut(packed_lists(kept, cfg), "lists")
    return pairs.tiled_counts(lists, compare.merge_kernel, cfg, least=max(1, min_support), inc=kept)


def merge_sql(inc: DataFrame, min_support: int = 1, cfg: Config = Config()) -> DataFrame:
    """Merging in built-in functions: lists of one segment meet in tiles, and the sizes of their
    intersections add up. Quadratic in items like all list merging, but no list is longer
    than a segment and every join is on keys."""
    lists = segmented(pairs.prune(inc, min_support), cfg.segment).groupBy("item", "seg").agg(F.array_sort(F.collect_set("x")).alias("payload"))
    lists = cut(lists, "lists")
    items = cut(lists.select("item").distinct(), "items")
    blocks = items.select("item", F.pmod(F.xxhash64("item"), F.lit(n := pairs.block_count(items.count(), cfg))).cast("int").alias("block"))
    met = cut(pairs.tiles(lists.join(blocks, "item"), n), "tiles")
    a, b = met.where("side = 0").alias("a"), met.alias("b")
    both = a.join(b, ["p", "q", "seg"]).where("(p = q AND a.item < b.item) OR (p <> q AND b.side = 1)")
    size = F.size(F.array_intersect("a.payload", "b.payload")).cast("long")
    lo, hi = F.least("a.item", "b.item").alias("item_a"), F.greatest("a.item", "b.item").alias("item_b")
    return both.select(lo, hi, size.alias("n")).groupBy("item_a", "item_b").agg(F.sum("n").alias("support")).where(F.col("support") >= max(1, min_support))


def merge_join(inc: DataFrame, min_support: int = 1) -> DataFrame:
    """Two cursors over sorted lists: a sort-merge join on the transaction id."""
    kept = pairs.prune(inc, min_support)
    a, b = kept.alias("a"), kept.alias("b").hint("merge")
    joined = a.join(b, "tid").where(F.col("a.item") < F.col("b.item"))
    counted = joined.groupBy(F.col("a.item").alias("item_a"), F.col("b.item").alias("item_b")).agg(F.count("*").alias("support"))
    return counted.where(F.col("support") >= min_support)


def bitmap(inc: DataFrame, min_support: int = 1, cfg: Config = Config()) -> DataFrame:
    """One bit per transaction: AND and population count, over the same tiles."""
    kept = pairs.kept(inc, min_support)
    maps = cut(packed_bitmaps(kept, cfg), "bitmaps", "zstd")
    return pairs.tiled_counts(maps, compare.bitmap_counts, cfg, block_items=BITMAP_ITEMS, least=max(1, min_support), inc=kept)


def bitmap_words(inc: DataFrame) -> DataFrame:
    """``(item, word, bits)``: 64-transaction words by grouped OR, no Python."""
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), F.pmod("tid", F.lit(64)).cast("int"))
    return inc.groupBy("item", F.shiftright("tid", 6).alias("word")).agg(F.bit_or(bit).alias("bits"))


def bitmap_sql(inc: DataFrame, min_support: int = 1) -> DataFrame:
    """Bitmaps relationally: words joined on their number, AND, bit count, sum."""
    words = bitmap_words(pairs.prune(inc, min_support))
    a, b = words.alias("a"), words.alias("b")
    both = F.bit_count(F.col("a.bits").bitwiseAND(F.col("b.bits"))).cast("long")
    joined = a.join(b, "word").where(F.col("a.item") < F.col("b.item"))
    counted = joined.groupBy(F.col("a.item").alias("item_a"), F.col("b.item").alias("item_b")).agg(F.sum(both).alias("support"))
    return counted.where(F.col("support") >= max(1, min_support))


def hash_probe(inc: DataFrame, min_support: int = 1) -> DataFrame:
    """Probing one set's hash table with the elements of the others: a hash join on tid."""
    kept = pairs.prune(inc, min_support)
    a, b = kept.alias("a"), kept.alias("b").hint("shuffle_hash")
    joined = a.join(b, "tid").where(F.col("a.item") < F.col("b.item"))
    counted = joined.groupBy(F.col("a.item").alias("item_a"), F.col("b.item").alias("item_b")).agg(F.count("*").alias("support"))
    return counted.where(F.col("support") >= min_support)


def horizontal(inc: DataFrame, min_support: int = 1) -> DataFrame:
    """A counter for each pair, filled transaction by transaction.

    A transaction's pairs are made from its sorted items; partial sums before the
    shuffle keep one counter per pair and task."""
    baskets = transactions(pairs.prune(inc, min_support)).where(F.size("items") > 1)
    first = baskets.select("items", F.posexplode("items").alias("pos", "item_a"))
    later = F.slice("items", F.col("pos") + 2, F.size("items"))
    made = first.select("item_a", F.explode(later).alias("item_b"))
    return made.groupBy(*PAIR).agg(F.count("*").alias("support")).where(F.col("support") >= min_support)


def apriori_levels(inc: DataFrame, min_support: int, max_size: int = 2) -> list[DataFrame]:
    """Frequent itemsets level by level: ``(items array, support)`` for sizes 1 to ``max_size``.

    Candidates of size k + 1 join two frequent sets that share all but the last item and
    have all their subsets of size k frequent; their support is counted against the
    transactions of the frequent sets. Levels are written, so lineage doesn't grow."""
    one = cut(inc.groupBy("item").agg(F.count("*").alias("support")).where(F.col("support") >= min_support), "level")
    levels = [one.select(F.array("item").alias("items"), "support")]
    live = cut(inc.join(one.select("item"), "item", "left_semi").select(F.array("item").alias("items"), "tid"), "live")
    singles = inc.join(one.select("item"), "item", "left_semi")
    for k in range(2, max_size + 1):
        frequent = levels[-1].select("items")
        head = lambda c: F.slice(c, 1, k - 2) if k > 2 else F.array().cast("array<bigint>")
        a = frequent.select(head("items").alias("head"), F.element_at("items", -1).alias("x"))
        b = frequent.select(head("items").alias("head"), F.element_at("items", -1).alias("y"))
        if k > 2:
            made = a.join(b, "head").where("x < y").select(F.concat("head", F.array("x", "y")).alias("items"))
            holes = made.select("items", F.explode(F.sequence(F.lit(1), F.lit(k))).alias("hole"))
            subset = F.expr("filter(items, (v, i) -> i <> hole - 1)")
            good = holes.select("items", subset.alias("sub")).join(frequent.withColumnRenamed("items", "sub"), "sub", "left_semi")
            made = cut(good.groupBy("items").count().where(F.col("count") == k).select("items"), "candidates")
            # A transaction holds a candidate iff it holds its prefix and its last item.
            prefix = made.select(F.slice("items", 1, k - 1).alias("prefix"), F.element_at("items", -1).alias("item"), "items")
            held = live.withColumnRenamed("items", "prefix").join(prefix, "prefix").join(singles, ["tid", "item"], "left_semi").select("items", "tid")
        else:
            # Every pair of frequent items is a candidate: counters for those that occur.
            one_of = singles.alias("s")
            held = live.join(one_of, "tid").where(F.element_at("items", 1) < F.col("s.item"))
            held = held.select(F.concat("items", F.array("s.item")).alias("items"), "tid")
        counted = cut(held.groupBy("items").agg(F.count("*").alias("support")).where(F.col("support") >= min_support), "level")
        levels.append(counted)
        if counted.isEmpty():
            break
        if k < max_size:
            live = cut(held.join(counted.select("items"), "items", "left_semi"), "live")
    return levels


def apriori(inc: DataFrame, min_support: int = 1) -> DataFrame:
    return _pairs_of(apriori_levels(inc, min_support, 2)[-1])


def library_fp_growth_sets(inc: DataFrame, min_support: int, max_size: int = 2) -> DataFrame:
    """``(items, support)`` by the library's parallel FP-growth, items sorted.

    It enumerates frequent itemsets of every size before ``max_size`` is applied, so it is for
    instances that have few. Its threshold is relative; half a transaction below the absolute
    one guards rounding."""
    m = inc.select("tid").distinct().count()
    if not m:
        return inc.sparkSession.createDataFrame([], "items array<bigint>, support bigint")
    model = FPGrowth(itemsCol="items", minSupport=max(0.0, (min_support - 0.5) / m)).fit(transactions(inc).select("items"))
    found = model.freqItemsets.where((F.size("items") <= max_size) & (F.col("freq") >= min_support))
    return found.select(F.array_sort("items").alias("items"), F.col("freq").alias("support"))


#: Items of the stretches that a group of FP-growth's suffix items gets, at most on average, and the least number of groups.
FP_STRETCH, FP_GROUPS = 1_500_000, 32


def fp_groups(rows: DataFrame) -> int:
    """Groups of suffix items for ``rows(tid, ...)``, by the length of all stretches if each item had its own."""
    t = F.col("count").cast("double")
    stretches = rows.groupBy("tid").count().agg(F.sum(t * (t + 1) / 2)).first()[0] or 0
    return max(FP_GROUPS, int(-(-stretches // FP_STRETCH)))


def fp_growth_sets(inc: DataFrame, min_support: int, max_size: int = 2) -> DataFrame:
    """``(items, support)`` of itemsets up to ``max_size`` by parallel FP-growth, items sorted.

    Transactions are sorted by falling item frequency. Suffix items are dealt to groups; a
    transaction gives each of its groups the stretch up to the group's last item, equal
    stretches of a group are counted, and it builds its prefix tree and mines it for
    its own suffixes, no deeper than ``max_size``. A frequent item's stretches are short, since it
    comes early; a group's distinct stretches must fit a task, and groups follow the length of all
    stretches (the square of a transaction's length, not its length), so none grows with the table."""
    counts = inc.groupBy("item").agg(F.count("*").alias("n")).where(F.col("n") >= min_support)
    counts = cut(counts, "fp-counts")
    one = counts.select(F.array("item").alias("items"), F.col("n").alias("support"))
    if max_size < 2:
        return one
    low, high = counts.agg(F.min("item"), F.max("item")).first()
    small = low is not None and -(1 << 31) <= low and high < 1 << 31  # stretches are most of what is shuffled: half the bytes
    item = F.col("item").cast("int") if small else F.col("item")
    kept = cut(inc.join(counts, "item").select("tid", F.struct((-F.col("n")).alias("o"), item.alias("item")).alias("s")), "fp-rows", "zstd")
    groups = fp_groups(kept)
    baskets = kept.groupBy("tid").agg(F.sort_array(F.collect_set("s")).alias("s")).select(F.col("s.item").alias("items")).where(F.size("items") > 1)
    dealt = baskets.withColumn("of", F.transform("items", lambda x: F.pmod(F.xxhash64(x), F.lit(groups)).cast("int")))
    emitted = dealt.select("items", "of", F.explode(F.array_distinct("of")).alias("g"))
    last = F.size("of") - F.array_position(F.reverse("of"), F.col("g")).cast("int") + 1
    # Dealt by group once: counting equal stretches and mining then shuffle nothing more.
    paths = emitted.select("g", F.slice("items", F.lit(1), last).alias("path")).repartition("g").groupBy("g", "path").agg(F.count("*").alias("n"))
    own = F.transform("path", lambda x: F.pmod(F.xxhash64(x), F.lit(groups)).cast("int") == F.col("g"))

    def mine(table: pa.Table) -> pa.Table:
        lists = table.column("path").combine_chunks()
        names, codes = np.unique(np.asarray(lists.flatten()), return_inverse=True)
        mine_too = np.zeros(len(names), bool)
        mine_too[codes[np.asarray(table.column("own").combine_chunks().flatten())]] = True
        ends = np.cumsum(np.asarray(lists.value_lengths()))
        found: list[tuple[tuple[int, ...], int]] = []
        fptree.mine(fptree.build(np.split(codes, ends[:-1]), table.column("n").to_pylist()), mine_too, (), min_support, max_size, found)
        sets = [sorted(names[list(items)].tolist()) for items, _ in found]
        return pa.Table.from_arrays([pa.array(sets, pa.list_(pa.int64())), pa.array([n for _, n in found], pa.int64())], names=["items", "support"])

    more = paths.select("g", "path", "n", own.alias("own")).groupBy("g").applyInArrow(mine, "items array<bigint>, support bigint")
    return one.unionByName(more)


def _pairs_of(sets: DataFrame) -> DataFrame:
    pair = sets.where(F.size("items") == 2)
    return pair.select(F.element_at("items", 1).alias("item_a"), F.element_at("items", 2).alias("item_b"), "support")


def fp_growth(inc: DataFrame, min_support: int = 1) -> DataFrame:
    return _pairs_of(fp_growth_sets(inc, min_support))


def library_fp_growth(inc: DataFrame, min_support: int = 1) -> DataFrame:
    return _pairs_of(library_fp_growth_sets(pairs.prune(inc, min_support), min_support))


def eclat_sets(inc: DataFrame, min_support: int, max_size: int = 2) -> DataFrame:
    """``(items, support)`` of itemsets of 2 to ``max_size`` items by depth-first search over tidlists.

    Pairs are counted where their lists meet, with partial sums, so no item's lists are
    gathered. Deeper sets come from the classes of frequent pairs: the class of (a, b) holds the
    tidlists of larger items restricted to the pair's transactions, and its search intersects
    lists and never leaves the task. A class must fit a task: it has the rows of the pair's
    transactions, not those of an item."""
    kept = cut(pairs.prune(inc, min_support), "eclat")
    a, b = kept.alias("a"), kept.alias("b")
    met = a.join(b, "tid").where(F.col("a.item") < F.col("b.item")).select(F.col("a.item").alias("x"), F.col("b.item").alias("y"), "tid")
    pair = met.groupBy("x", "y").agg(F.count("*").alias("support")).where(F.col("support") >= min_support)
    two = pair.select(F.array("x", "y").alias("items"), "support")
    if max_size < 3:
        return two
    pair = cut(pair, "eclat-pairs")
    held = met.join(pair.select("x", "y"), ["x", "y"])
    classes = held.join(kept, "tid").where(F.col("item") > F.col("y")).select("x", "y", "item", "tid")

    def search(table: pa.Table) -> pa.Table:
        prefix = [table.column(c)[0].as_py() for c in "xy"]
        items, tids = table.column("item").to_numpy(), table.column("tid").to_numpy()
        order = np.lexsort((tids, items))
        items, tids = items[order], tids[order]
        names, first = np.unique(items, return_index=True)
        lists = [(int(n), t) for n, t in zip(names, np.split(tids, first[1:])) if len(t) >= min_support]
        out: list[tuple[list[int], int]] = []
        stack = [(prefix, lists)]
        while stack:
            head, members = stack.pop()
            for i, (name, mine) in enumerate(members):
                out.append(([*head, name], len(mine)))
                if len(head) + 1 < max_size:
                    deeper = [(n, np.intersect1d(mine, t, assume_unique=True)) for n, t in members[i + 1 :]]
                    stack.append(([*head, name], [(n, t) for n, t in deeper if len(t) >= min_support]))
        return pa.Table.from_arrays(
            [pa.array([o[0] for o in out], pa.list_(pa.int64())), pa.array([o[1] for o in out], pa.int64())], names=["items", "support"]
        )

    return pair.select(F.array("x", "y").alias("items"), "support").unionByName(classes.groupBy("x", "y").applyInArrow(search, "items array<bigint>, support bigint"))


def eclat(inc: DataFrame, min_support: int = 1) -> DataFrame:
    return _pairs_of(eclat_sets(inc, min_support))


METHODS: dict[str, Callable[..., DataFrame]] = {
    "merge": merge, "merge_sql": merge_sql, "merge_join": merge_join, "bitmap": bitmap, "bitmap_sql": bitmap_sql, "hash": hash_probe,
    "horizontal": horizontal, "apriori": apriori, "fpgrowth": fp_growth, "library_fpgrowth": library_fp_growth, "eclat": eclat,
}


def pair_support(inc: DataFrame, method: str, min_support: int = 1, cfg: Config = Config()) -> DataFrame:
    if method not in METHODS:
        raise ValueError(f"method {method!r} is none of {['twinslot', *METHODS]}")
    more = {"cfg": cfg} if method in ("merge", "bitmap") else {}
    return METHODS[method](inc, max(1, min_support), **more)
