"""Exact top-k by inner product with a three-phase uniform threshold.

A vector's components are cut into slices; a slice gives every candidate a partial score
for a query, and the score is the sum over slices. Phase one takes the head of each slice's
list, adds up the scores of those entries alone, and the k-th best of any block is a cutoff that
the true k-th can't be below. Phase two gives every block that cutoff and collects all entries of
which some slice reaches its equal share: what reaches it in no slice can't reach it in
sum. Phase three adds up exactly what was collected, and merges.

Rows are packed into blocks of matrices where they are read; every query block meets
every row block once, so work is dealt evenly however vectors repeat.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, discard

K, SLICES, SCALE = 20, 4, 64
ROWS, QUERIES = 4096, 2048
#: Query blocks are broadcast up to this many bytes of packed vectors, else dealt to a grid.
BROADCAST_BYTES = 32 << 20
#: So many query blocks and so many row blocks meet under one key of the grid.
GRID_QUERIES, GRID_ROWS = 16, 8
#: Integers of up to 31 bits are stored as such; vectors beyond go to blocks of doubles, each of
#: which stands for one exact integer.
NARROW = float(1 << 31)
PACKED = "ids binary, dim int, wide boolean, matrix binary"
LEAST, MOST = -(1 << 63), (1 << 63) - 1


def vectors(df: DataFrame, vec_id: str = "vec_id", embedding: str = "embedding") -> DataFrame:
    """``(vec_id, x array<double>)`` of vectors with an id and without null or non-finite components."""
    x = F.transform(F.col(embedding), lambda c: c.cast("double"))
    fine = F.forall("x", lambda c: c.isNotNull() & (F.abs(c) < F.lit(math.inf)))  # NaN and infinities fail the comparison
    return df.select(F.col(vec_id).cast("long").alias("vec_id"), x.alias("x")).where(F.col("vec_id").isNotNull() & F.col("x").isNotNull() & fine)


def _pack(rows: int, scale: int):
    """Blocks of up to ``rows`` vectors as matrices of floor(scale x); shorter vectors have zeros behind."""

    def block(ids: np.ndarray, x: np.ndarray, wide: bool) -> pa.RecordBatch:
        matrix = x if wide else np.floor(x * scale).astype(np.int32)
        columns = ([ids.tobytes()], [x.shape[1]], [wide], [matrix.tobytes()])
        kinds = (pa.binary(), pa.int32(), pa.bool_(), pa.binary())
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds)], ["ids", "dim", "wide", "matrix"])

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, rows):
                some = batch.slice(at, rows)
                ids, lists = np.asarray(some.column(0)), some.column(1)
                lengths = np.asarray(lists.value_lengths(), np.int64)
                dim = int(lengths.max()) if len(lengths) else 0
                x = np.zeros((len(ids), dim))
                x[np.arange(dim) < lengths[:, None]] = np.asarray(lists.flatten())
                wide = np.abs(x).max(axis=1, initial=0) >= NARROW / scale
                for kind in (False, True):
                    if (wide == kind).any():
                        yield block(ids[wide == kind], x[wide == kind], kind)

    return run


def _matrix(row: dict, prefix: str, scale: int) -> tuple[np.ndarray, np.ndarray]:
    """Ids and exact integers of a packed block: 32-bit numbers, or Python's for wide vectors."""
    keys = np.frombuffer(row[f"{prefix}ids"], np.int64)
    shape = (len(keys), row[f"{prefix}dim"])
    if not row[f"{prefix}wide"]:
        return keys, np.frombuffer(row[f"{prefix}matrix"], np.int32).reshape(shape)
    # From 2^53 on a double is an integer, so scaling comes after; below, scaling by a power of two is exact.
    exact = [int(v) * scale if abs(v) >= 1 << 53 else math.floor(v * scale) for v in np.frombuffer(row[f"{prefix}matrix"]).tolist()]
    out = np.empty(len(exact), object)
    out[:] = exact
    return keys, out.reshape(shape)


def _partials(q: np.ndarray, r: np.ndarray, slices: int) -> list[np.ndarray]:
    """Partial scores of each slice, exact integers in the cheapest type that holds their sum."""
    dim = min(q.shape[1], r.shape[1])
    top = int(np.abs(q).max(initial=0)) * int(np.abs(r).max(initial=0)) * max(dim, 1)
    kind = np.float32 if top < 1 << 24 else np.float64 if top < 1 << 53 else np.int64 if top < 1 << 63 else object
    cuts = np.linspace(0, dim, slices + 1).astype(int)
    out = [q[:, a:b].astype(kind) @ r[:, a:b].astype(kind).T for a, b in zip(cuts[:-1], cuts[1:])]
    return [p if b > a else np.zeros((len(q), len(r)), kind) for p, a, b in zip(out, cuts[:-1], cuts[1:])]


def _float(values: np.ndarray) -> np.ndarray:
    """Nearest doubles (monotone), infinities for integers beyond them."""
    if values.dtype != object:
        return values.astype(np.float64)
    near = [float(v) if abs(v) < 1 << 1000 else (math.inf if v > 0 else -math.inf) for v in values.ravel().tolist()]
    return np.array(near, np.float64).reshape(values.shape)


def _sum(parts: list[np.ndarray], i, at) -> np.ndarray:
    """Exact scores of some entries: integers of 64 bits, or Python's."""
    kind = object if parts[0].dtype == object else np.int64
    return sum((p[i, at].astype(kind) for p in parts[1:]), parts[0][i, at].astype(kind))


def _cutoffs(k: int, slices: int, scale: int):
    """Phase one: a block's k-th best score among the heads of its slices' lists."""

    def run(batches):
        for batch in batches:
            for row in batch.to_pylist():
                (qk, q), (rk, r) = _matrix(row, "q_", scale), _matrix(row, "", scale)
                if len(rk) <= k:
                    continue
                parts = _partials(q, r, slices)
                heads = [np.argpartition(_float(p), len(rk) - k - 1, axis=1)[:, len(rk) - k - 1 :] for p in parts]
                picks = np.sort(np.concatenate(heads, axis=1), axis=1)
                scores = _float(_sum(parts, np.arange(len(qk))[:, None], picks))  # of the heads alone
                scores[rk[picks] == qk[:, None]] = -np.inf
                scores[:, 1:][picks[:, 1:] == picks[:, :-1]] = -np.inf  # an entry that heads two lists
                kth = np.partition(scores, scores.shape[1] - k, axis=1)[:, scores.shape[1] - k]
                kth = np.where(np.abs(kth) < 1 << 53, kth, np.nextafter(kth, -np.inf))  # a rounded score is no bound
                fine = np.isfinite(kth)
                yield pa.RecordBatch.from_arrays([pa.array(qk[fine], pa.int64()), pa.array(kth[fine], pa.float64())], ["query_id", "kth"])

    return run


def _best(ids: np.ndarray, scores: np.ndarray, k: int) -> np.ndarray:
    """Places of the k best: higher score first, then smaller id."""
    if scores.dtype == object:
        return np.array(sorted(range(len(ids)), key=lambda j: (-scores[j], ids[j]))[:k], int)
    if len(ids) > 4 * k:
        least = np.partition(scores, len(scores) - k)[len(scores) - k]
        keep = np.flatnonzero(scores >= least)
        return keep[np.lexsort((ids[keep], -scores[keep]))[:k]]
    return np.lexsort((ids, -scores))[:k]


def _entries(k: int, slices: int, scale: int):
    """Phases two and three in one block: collect by the shared cutoff, add up what was collected.

    A score above long is the best of its query, so it is an error at once; one below
    is marked (``under``) and an error only if it is among the k best."""

    def run(batches):
        for batch in batches:
            for row in batch.to_pylist():
                (qk, q), (rk, r) = _matrix(row, "q_", scale), _matrix(row, "", scale)
                limit = np.frombuffer(row["cutoffs"], np.float64)
                parts = _partials(q, r, slices)
                collected = np.zeros((len(qk), len(rk)), bool)
                for p in parts:
                    collected |= _float(p) >= (limit / slices)[:, None]
                out = []
                for i in range(len(qk)):
                    at = np.flatnonzero(collected[i])
                    at = at[rk[at] != qk[i]]
                    scores = _sum(parts, i, at)
                    reach = _float(scores) >= limit[i]
                    at, scores = at[reach], scores[reach]
                    best = _best(rk[at], scores, k)
                    top = scores[best].tolist()
                    if top and top[0] > MOST:
                        raise OverflowError(f"the score of vectors {qk[i]} and {rk[at][best[0]]} doesn't fit a long")
                    under = [v < LEAST for v in top]
                    out.append((np.full(len(best), qk[i]), rk[at][best], np.array([max(v, LEAST) for v in top], np.int64), np.array(under, bool)))
                kinds = (pa.int64(), pa.int64(), pa.int64(), pa.bool_())
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c), t) for c, t in zip(zip(*out), kinds)], ["query_id", "vec_id", "score", "under"])

    return run


def _with_cutoffs(batches):
    """Query blocks with the cutoff of each query behind (minus infinity where no block has one)."""
    for batch in batches:
        for row in batch.to_pylist():
            ids = np.frombuffer(row["q_ids"], np.int64)
            known = dict(zip(row["limit_ids"] or [], row["limits"] or []))
            row["cutoffs"] = np.array([known.get(i, -np.inf) for i in ids.tolist()], np.float64).tobytes()
            columns = ("qb", "q_ids", "q_dim", "q_wide", "q_matrix", "cutoffs")
            kinds = (pa.int64(), pa.binary(), pa.int32(), pa.bool_(), pa.binary(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array([row[c]], t) for c, t in zip(columns, kinds)], list(columns))


def _members(batches):
    for batch in batches:
        for row in batch.to_pylist():
            ids = np.frombuffer(row["q_ids"], np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(ids), row["qb"]), pa.int64()), pa.array(ids, pa.int64())], ["qb", "query_id"])


def _numbered(packed: DataFrame, name: str, label: str) -> DataFrame:
    """Blocks with a number ``name``: task, then place in the task (written, so it doesn't change)."""

    def run(batches):
        part, n = TaskContext.get().partitionId(), 0
        for batch in batches:
            numbers = pa.array(np.arange(n, n + batch.num_rows) + (part << 32), pa.int64())
            n += batch.num_rows
            yield pa.RecordBatch.from_arrays([numbers, *batch.columns], [name, *batch.schema.names])

    return cut(packed.mapInArrow(run, f"{name} long, " + ", ".join(f"{c} {t}" for c, t in packed.dtypes)), label)


def top_k(
    df: DataFrame, k: int = K, every: int = 20, slices: int = SLICES, vec_id: str = "vec_id", embedding: str = "embedding",
    broadcast_bytes: int = BROADCAST_BYTES, scale: int = SCALE,
) -> DataFrame:
    """``(query_id, rank, vec_id, score)``: the k best rows for each row whose id is
    divisible by ``every``, never the query's own id.

    Components become floor(``scale`` x), ``scale`` a power of two. Ties go to the smaller vec_id. Null ids or
    vectors and vectors with null or non-finite components take no part; vectors of different
    lengths compare as if the shorter had zeros behind. Components of any finite size are
    scored in exact integers; a result that doesn't fit a long is an error, never a wrong
    number. Rows that repeat a vec_id are candidates each; a repeated query is one query
    (its first vector in value order). Fewer than k candidates give fewer rows; an empty table none.
    """
    spark = df.sparkSession
    read = vectors(df, vec_id, embedding)
    rows = _numbered(read.mapInArrow(_pack(ROWS, scale), PACKED), "rb", "rows")
    asked = cut(read.where(F.col("vec_id") % every == 0).groupBy("vec_id").agg(F.min("x").alias("x")), "asked")
    n = asked.count()
    if not n:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    packed = asked.repartition(max(1, -(-n // QUERIES))).mapInArrow(_pack(QUERIES, scale), PACKED)
    packed = _numbered(packed.select(*(F.col(c).alias(f"q_{c}") for c in packed.columns)), "qb", "queries")
    size, n_queries = packed.agg(F.sum(F.length("q_matrix") + F.length("q_ids")), F.count("*")).first()
    grid = (-(-n_queries // GRID_QUERIES), -(-rows.count() // GRID_ROWS))

    def cells(queries: DataFrame) -> DataFrame:
        """Every query block beside every row block. The queries are broadcast if small; else both
        sides are dealt to a grid of which each key holds a few blocks of each."""
        if size <= broadcast_bytes:
            return rows.join(F.broadcast(queries))
        spread = lambda number, own, other, name: (
            F.pmod(F.xxhash64(number), F.lit(grid[own])).cast("int"), F.explode(F.sequence(F.lit(0), F.lit(grid[other] - 1))).alias(name)
        )
        mine, theirs = spread("rb", 1, 0, "qg"), spread("qb", 0, 1, "rg")
        left = rows.select("*", mine[0].alias("rg"), mine[1])
        right = queries.select("*", theirs[0].alias("qg"), theirs[1])
        return left.join(right, ["qg", "rg"])

    found = cells(packed).mapInArrow(_cutoffs(k, slices, scale), "query_id long, kth double")
    limits = cut(found.groupBy("query_id").agg(F.max("kth").alias("kth")), "cutoffs")
    block_of = packed.select("qb", "q_ids").mapInArrow(_members, "qb long, query_id long")
    by_block = block_of.join(limits, "query_id").groupBy("qb").agg(F.collect_list("query_id").alias("limit_ids"), F.collect_list("kth").alias("limits"))  # a block's
    ready = packed.join(by_block, "qb", "left").mapInArrow(_with_cutoffs, "qb long, q_ids binary, q_dim int, q_wide boolean, q_matrix binary, cutoffs binary")
    ready = cut(ready, "ready")
    for done in (asked, packed, limits):
        discard(done)
    entries = cells(ready).mapInArrow(_entries(k, slices, scale), "query_id long, vec_id long, score long, under boolean")
    order = Window.partitionBy("query_id").orderBy("under", F.desc("score"), "vec_id")
    best = entries.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
    fits = F.when(F.col("under"), F.raise_error(F.lit("a score doesn't fit a long")).cast("long")).otherwise(F.col("score"))
    return best.select("query_id", "rank", "vec_id", fits.alias("score"))
