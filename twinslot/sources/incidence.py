"""Incidence relations ``(item, tid)``: builders, dense ids, both set formats."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..schema import require
from ..stages import cut


def _made(df: DataFrame) -> DataFrame:
    return df.where(F.col("item").isNotNull() & F.col("tid").isNotNull()).distinct()


#: Rows that a task packs at once.
PACKED_ROWS = 1_000_000


SETS = "item long, seg long, xs binary, ws binary, n int"


def _sets(parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]]):
    """Batches of ``SETS``: the distinct places of each set as 32-bit numbers in order (``xs``) or, where that is
    shorter, as bitmap words of 64 places: those that aren't zero, then their 16-bit numbers (``ws``)."""
    item, seg, x = (np.concatenate(c) for c in zip(*parts))
    order = np.lexsort((x, seg, item))
    item, seg, x = item[order], seg[order], x[order].astype("<i4")
    new = np.ones(len(x), bool)
    new[1:] = (item[1:] != item[:-1]) | (seg[1:] != seg[:-1])
    once = new.copy()
    once[1:] |= x[1:] != x[:-1]
    item, seg, x, new = item[once], seg[once], x[once], new[once]
    at = np.flatnonzero(new)
    n = np.diff(np.append(at, len(x)))
    word = new.copy()
    word[1:] |= x[1:] >> 6 != x[:-1] >> 6
    words = np.add.reduceat(word, at, dtype=np.int64)
    dense = (10 * words < 4 * n) & (np.maximum.reduceat(x, at) < 1 << 22)
    for kind in (False, True):
        some = dense == kind
        if not some.any():
            continue
        rows = np.repeat(some, n)
        if kind:
            starts = np.flatnonzero(word & rows)
            first = np.flatnonzero(word[rows])
            values = np.bitwise_or.reduceat(np.uint64(1) << (x[rows] & 63).astype(np.uint64), first)
            places = (x[starts] >> 6).astype("<u2")
            ends = np.append(0, np.cumsum(words[some])).tolist()
            lists = pa.array([values[i:j].tobytes() + places[i:j].tobytes() for i, j in zip(ends[:-1], ends[1:])], pa.binary())
            columns = [pa.nulls(len(lists), pa.binary()), lists]
        else:
            ends = np.append(0, np.cumsum(n[some])).astype(np.int32) * 4
            lists = pa.Array.from_buffers(pa.binary(), len(ends) - 1, [None, pa.py_buffer(ends), pa.py_buffer(np.ascontiguousarray(x[rows]))])
            columns = [lists, pa.nulls(len(lists), pa.binary())]
        yield pa.RecordBatch.from_arrays([pa.array(item[at][some]), pa.array(seg[at][some]), *columns, pa.array(n[some].astype(np.int32))], [c.split()[0] for c in SETS.split(", ")])


def places_of(xs: bytes | None, ws: bytes | None) -> np.ndarray:
    """The places of one packed set, in order."""
    if xs is not None:
        return np.frombuffer(xs, "<i4")
    k = len(ws) // 10
    at = np.flatnonzero(np.unpackbits(np.frombuffer(ws, np.uint8, 8 * k), bitorder="little")).astype(np.int32)
    return np.frombuffer(ws, "<u2", k, 8 * k).astype(np.int32)[at >> 6] << 6 | at & 63


def rows_of_sets(batch: pa.RecordBatch | pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``(item, seg, x)`` of packed sets."""
    found = [places_of(x, w) for x, w in zip(batch.column("xs").to_pylist(), batch.column("ws").to_pylist())]
    sizes = np.array(list(map(len, found)), np.int64)
    return *(np.repeat(batch.column(c).to_numpy(), sizes) for c in ("item", "seg")), np.concatenate([np.zeros(0, np.int32), *found])


def _flushed(rows):
    parts, size = [], 0
    for row in rows:
        parts.append(row)
        size += len(row[0])
        if size >= PACKED_ROWS:
            yield from _sets(parts)
            parts, size = [], 0
    if size:
        yield from _sets(parts)


def packed(rows: DataFrame) -> DataFrame:
    """``(item, seg, xs, ws, n)`` of ``rows(item, seg, x)``: a million rows of a task become one row for each of their sets
    (see ``_sets``). Sets are not complete: other rows may have more of them."""

    def run(batches):
        yield from _flushed([c.to_numpy(zero_copy_only=False).copy() for c in batch.columns] for batch in batches)

    return rows.select("item", "seg", "x").mapInArrow(run, SETS)


def repacked(sets: DataFrame, was: int, segment: int) -> DataFrame:
    """Packed sets of segments of ``was`` ids as packed sets of segments of ``segment`` ids."""

    def cut_anew(batch):
        item, seg, x = rows_of_sets(batch)
        tid = seg * np.int64(was) + x
        new = tid // segment
        return item, new, tid - new * np.int64(segment)  # wraps, and back, in the lowest segment of long

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 500):  # a segment each at most
                yield from _flushed([cut_anew(batch.slice(at, 500))])

    return sets.select(*(c.split()[0] for c in SETS.split(", "))).mapInArrow(run, SETS)


def unpacked(sets: DataFrame, segment: int) -> DataFrame:
    """``(item, tid)`` of packed sets."""

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                item, seg, x = rows_of_sets(batch.slice(at, 500))
                tid = seg * np.int64(segment) + x
                for i in range(0, len(tid), 1 << 16):
                    yield pa.RecordBatch.from_arrays([pa.array(item[i : i + (1 << 16)], pa.int64()), pa.array(tid[i : i + (1 << 16)], pa.int64())], ["item", "tid"])

    return sets.mapInArrow(run, "item long, tid long")


#: Transaction ids of a segment while repeated rows are dropped.
DISTINCT_SEGMENT = 1 << 16


def united(sets: DataFrame) -> DataFrame:
    """Packed sets, any number of rows a set, as one row a set. Rows come in order of their sets, so a task holds some
    million places and the set that goes on."""

    def run(batches):
        parts, size = [], 0
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                parts.append(rows_of_sets(batch.slice(at, 500)))
                size += len(parts[-1][0])
                if size >= PACKED_ROWS:
                    item, seg, x = (np.concatenate(c) for c in zip(*parts))
                    others = np.flatnonzero((item != item[-1]) | (seg != seg[-1]))
                    k = int(others[-1]) + 1 if len(others) else 0
                    if k:
                        yield from _sets([(item[:k], seg[:k], x[:k])])
                    x = np.unique(x[k:])
                    parts, size = [(item[k : k + len(x)], seg[k : k + len(x)], x)], len(x)
        if size:
            yield from _sets(parts)

    return sets.repartition("item", "seg").sortWithinPartitions("item", "seg").mapInArrow(run, SETS)


def _distinct(rows: DataFrame) -> DataFrame:
    """Distinct ``(item, tid)`` of longs: sets are packed before they are shuffled, a few bytes for each row."""

    def run(batches):
        def cut_up(batch):
            item, tid = (c.to_numpy(zero_copy_only=False).copy() for c in batch.columns)
            seg = tid // DISTINCT_SEGMENT
            return item, seg, tid - seg * np.int64(DISTINCT_SEGMENT)  # wraps, and back, in the lowest segment of long

        yield from _flushed(map(cut_up, batches))

    return of_sets(united(rows.select("item", "tid").mapInArrow(run, SETS)))


def of_sets(sets: DataFrame) -> DataFrame:
    """The incidence of packed sets by segments of ``DISTINCT_SEGMENT`` ids, which it keeps beside its rows."""
    out = unpacked(sets, DISTINCT_SEGMENT)
    out._twinslot_sets = sets
    return out


def sets_of(inc: DataFrame) -> DataFrame:
    """The packed sets of an incidence, by segments of ``DISTINCT_SEGMENT`` ids: those it was made from, or packed anew."""
    sets = getattr(inc, "_twinslot_sets", None)
    return packed(segmented(inc, DISTINCT_SEGMENT)) if sets is None else sets


def whole_sets(inc: DataFrame, segment: int) -> DataFrame:
    """Packed sets of segments of ``segment`` ids, one row a set."""
    return united(repacked(sets_of(inc), DISTINCT_SEGMENT, segment))


def written(inc: DataFrame, label: str) -> DataFrame:
    """``cut`` of an incidence of longs: its packed sets are written, a few bytes for each row."""
    sets = cut(sets_of(inc), label, "zstd")
    out = of_sets(sets)
    out._twinslot_path = sets._twinslot_path
    return out


def from_columns(df: DataFrame, item: str, tid: str) -> DataFrame:
    """Distinct ``(item, tid)``; rows with a null key are dropped."""
    require(df, item, tid)
    rows = df.select(F.col(item).alias("item"), F.col(tid).alias("tid"))
    if any(f.dataType != T.LongType() for f in rows.schema.fields):
        return _made(rows)
    return _distinct(rows.where("item IS NOT NULL AND tid IS NOT NULL"))


def from_array(df: DataFrame, tid: str, items: str) -> DataFrame:
    """One transaction a row, its items in an array."""
    require(df, tid, items)
    return _made(df.select(F.explode(items).alias("item"), F.col(tid).alias("tid")))


def from_map(df: DataFrame, tid: str, items: str) -> DataFrame:
    """Items are the keys of a map column."""
    require(df, tid, items)
    return _made(df.select(F.explode(F.map_keys(items)).alias("item"), F.col(tid).alias("tid")))


def from_json(df: DataFrame, tid: str, document: str, schema: str) -> DataFrame:
    """Items are ``key=value`` of the top-level fields of a JSON string (null values left out)."""
    require(df, tid, document)
    fields = T._parse_datatype_string(schema).fieldNames()
    parsed = df.select(F.from_json(document, schema).alias("j"), F.col(tid).alias("tid"))
    entries = F.array(*(F.concat(F.lit(f"{f}="), F.col(f"j.`{f}`").cast("string")) for f in fields))
    return _made(parsed.select(F.explode(entries).alias("item"), "tid"))


def from_text(df: DataFrame, tid: str, text: str, pattern: str = "[A-Za-z]+") -> DataFrame:
    """Items are the lower-cased matches of ``pattern``."""
    require(df, tid, text)
    words = F.transform(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), F.lower)
    return _made(df.select(F.explode(F.array_distinct(words)).alias("item"), F.col(tid).alias("tid")))


def from_join(left: DataFrame, right: DataFrame, on: str, item: str, tid: str) -> DataFrame:
    """Incidence of two columns that a join attribute links."""
    return _made(left.join(right, on).select(F.col(item).alias("item"), F.col(tid).alias("tid")))


def grid(parts: DataFrame, suppliers: DataFrame, p: int) -> DataFrame:
    """Deterministic instance of density 1/p: item = supplier, tid = part, thinned by a congruence.

    Suppliers are joined as the small side of a generator: both sides are key columns
    only, and the pairing is the instance's definition."""
    pk, sk = F.col("p_partkey"), F.col("s_suppkey")
    mix = (pk * 7919 + sk * 104729 + 17) * ((pk + 3) * 31 + sk * sk * 13 + 7) % 1000003
    # Parts are a small file, each of them a row for every supplier: all cores get a stretch of neighbouring parts.
    dealt = parts.select("p_partkey").repartitionByRange(parts.sparkSession.sparkContext.defaultParallelism, "p_partkey")
    return (
        dealt.crossJoin(suppliers.select("s_suppkey")).where(mix % p == 0).select(sk.alias("item"), pk.alias("tid"))
    )


def tidlists(inc: DataFrame, sort: bool = True) -> DataFrame:
    """Vertical format: ``(item, tids)``."""
    require(inc, "item", "tid")
    tids = F.collect_set("tid")
    return inc.groupBy("item").agg((F.array_sort(tids) if sort else tids).alias("tids"))


def transactions(inc: DataFrame) -> DataFrame:
    """Horizontal format: ``(tid, items)``."""
    require(inc, "item", "tid")
    return inc.groupBy("tid").agg(F.array_sort(F.collect_set("item")).alias("items"))


def dense_ids(df: DataFrame, *order: str | Column, partitions: int | None = None) -> DataFrame:
    """Rows of ``df`` with a dense ``id`` from 0 in the order of ``order``.

    Range-partitioned sort, a running number in each partition, and the counts of the
    partitions before it; the driver sees one count a partition, never a row."""
    keys = [F.col(o) if isinstance(o, str) else o for o in order]
    ranged = df.repartitionByRange(partitions, *keys) if partitions else df.repartitionByRange(*keys)
    placed = ranged.sortWithinPartitions(*keys)
    schema = T.StructType([*df.schema.fields, T.StructField("_part", T.IntegerType()), T.StructField("_row", T.LongType())])

    def number(batches):
        part, row = TaskContext.get().partitionId(), 0
        for batch in batches:
            n = batch.num_rows
            columns = [*batch.columns, pa.array([part] * n, pa.int32()), pa.array(range(row, row + n), pa.int64())]
            row += n
            yield pa.RecordBatch.from_arrays(columns, [*batch.schema.names, "_part", "_row"])

    numbered = cut(placed.mapInArrow(number, schema), "dense")
    counts = sorted((r["_part"], r["n"]) for r in numbered.groupBy("_part").agg(F.count("*").alias("n")).collect())
    before, base = 0, []
    for part, n in counts:
        base.append((part, before))
        before += n
    offsets = df.sparkSession.createDataFrame(base, "_part int, _base long")
    return numbered.join(F.broadcast(offsets), "_part").withColumn("id", F.col("_row") + F.col("_base")).drop("_part", "_row", "_base")


def dictionary(df: DataFrame, key: str) -> DataFrame:
    """``(key, id)``: dense ids of the distinct non-null keys, in key order."""
    return dense_ids(df.select(F.col(key).alias("key")).where("key IS NOT NULL").distinct(), "key")


def encoded(inc: DataFrame) -> tuple[DataFrame, DataFrame]:
    """An incidence with items of any type, in dense item ids, and its dictionary."""
    words = cut(dictionary(inc, "item"), "dictionary")
    return inc.join(words, inc["item"] == words["key"]).select(F.col("id").alias("item"), "tid"), words


def segment_of(tid: Column | str, segment: int) -> Column:
    """The segment of a transaction id: floor division in 64-bit integers, exact over the whole range of long."""
    t, n = F.col(tid) if isinstance(tid, str) else tid, F.lit(segment).cast("long")
    return F.call_function("div", t, n) - F.when(t % n < 0, 1).otherwise(0)


def place_of(tid: Column | str, segment: int) -> Column:
    """The position of a transaction id in its segment, from 0."""
    return F.pmod(F.col(tid) if isinstance(tid, str) else tid, F.lit(segment).cast("long")).cast("int")


def segmented(inc: DataFrame, segment: int) -> DataFrame:
    """``(item, seg, x, tid)``: transaction ids cut into segments of one size."""
    return inc.select("item", segment_of("tid", segment).alias("seg"), place_of("tid", segment).alias("x"), "tid")
