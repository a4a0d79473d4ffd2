"""Best-fit packing of documents into fixed-length sequences by linear grouping.

Pieces longer than a quarter of a sequence are large. Large lengths are rounded up
within groups of equal cardinality, so few sizes remain; configurations of those
sizes are chosen by exact knapsacks, each around the largest size that is left; actual
documents then take the places (their true lengths leave more room, never less); small ones
go best-fit into what is left.

Everything is planned on the histogram of lengths, which has at most ``capacity`` rows
however many documents there are. A plan is a list of runs: documents of one length and
consecutive ranks fill consecutive sequences. A document finds its place from its length
and its rank among documents of that length, so nothing else about documents reaches
the driver.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections import deque
from functools import lru_cache
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import worker
from .common import cut

CAPACITY, GROUPS, SMALL_PART = 2048, (400, 800), 4
#: The running counts (a row for each task and length) are broadcast up to so many rows, else shuffled.
BROADCAST_COUNTS = 500_000
END = 0
REMEMBERED, LONGEST = 1_200_000, 48

PIECE_SCHEMA = "doc_id long, piece int, start long, length long, ids_crc32 long, chunk int, local long"


def _chunks(text: str) -> list[str]:
    """Stretches without blanks. The tokenizer lower-cases, so ASCII texts are lower-cased
    here, where it makes fewer different chunks (not if they spell a special token, and not
    beyond ASCII, where lower case and normal form don't commute). The four separators that
    Python takes for blanks and the tokenizer doesn't keep a text from the short way."""
    if text.isascii() and "<|" not in text:
        text = text.lower()
    if "\x1c" in text or "\x1d" in text or "\x1e" in text or "\x1f" in text:
        return [c for c in text.replace("\n", " ").replace("\t", " ").split(" ") if c]
    return text.split()


class Words:
    """Ids of texts through a bounded memory of the ids of blank-separated chunks.

    The tokenizer neither merges nor normalises across blanks, so a text's ids are
    its chunks' ids in a row.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.between = "<|startoftext|>"
        self.mark = self.tokenizer.token_to_id(self.between)
        self.seen: dict[str, bytes] = {}

    def _learn(self, chunks: list[str]) -> None:
        """Many chunks in one call, with a special token between them as the boundary."""
        mark, batch = self.mark, self.tokenizer.encode_batch_fast
        plain = [c for c in chunks if "<|" not in c] if mark is not None else []
        for at in range(0, len(plain), 512):
            some = plain[at : at + 512]
            ids = np.array(batch([self.between.join(some)], add_special_tokens=False)[0].ids, "<u4")
            raw, lo = ids.tobytes(), 0
            for chunk, hi in zip(some, [*np.flatnonzero(ids == mark).tolist(), len(ids)], strict=True):
                self.seen[chunk] = raw[4 * lo : 4 * hi]
                lo = hi + 1
        for chunk in set(chunks).difference(plain):
            self.seen[chunk] = np.array(batch([chunk], add_special_tokens=False)[0].ids, "<u4").tobytes()

    def encode(self, texts: list[str]) -> list[bytes]:
        split = [_chunks(t) for t in texts]
        seen = self.seen
        if len(seen) > REMEMBERED:
            seen.clear()
        fresh = set(chain.from_iterable(split)).difference(seen)
        # A word with one mark behind it is two pieces to the tokenizer: their ids in a row.
        marked = [c for c in fresh if c[-1] in ".,!?" and c[:-1].lower().isalpha()]
        fresh.difference_update(marked)
        for c in marked:
            fresh.update(x for x in (c[:-1], c[-1]) if x not in seen)
        self._learn(list(fresh))
        for c in marked:
            seen[c] = seen[c[:-1]] + seen[c[-1]]
        get = seen.__getitem__
        out = [b"".join(map(get, chunks)) for chunks in split]
        for chunk in fresh:
            if len(chunk) > LONGEST:
                del seen[chunk]
        for chunk in marked:
            if len(chunk) > LONGEST:
                del seen[chunk]
        return out


@lru_cache(maxsize=2)
def _words(path: str) -> Words:
    return Words(path)


worker.remembers("packing", _words.cache_clear)


def pieces(docs: DataFrame, path: str, capacity: int = CAPACITY, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per piece: the document's ids and a final 0, cut only where longer than
    ``capacity``. ``chunk`` and ``local`` number the pieces of one length within a task."""

    def run(batches):
        worker.enter("packing")
        work = _words(path)
        chunk = TaskContext.get().partitionId()
        count = np.zeros(capacity + 1, np.int64)
        end = np.array([END], "<u4").tobytes()
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                some = batch.slice(at, 256)
                keys = some.column(0).to_pylist()
                rows = []
                for key, ids in zip(keys, work.encode([t or "" for t in some.column(1).to_pylist()])):
                    ids += end
                    for k, lo in enumerate(range(0, len(ids), 4 * capacity)):
                        part = ids[lo : lo + 4 * capacity]
                        n = len(part) // 4
                        rows.append((key, k, lo // 4, n, zlib.crc32(part), chunk, int(count[n])))
                        count[n] += 1
                names = ("doc_id", "piece", "start", "length", "ids_crc32", "chunk", "local")
                kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], list(names))

    return docs.select(F.col(doc_id).cast("long"), F.col(text)).mapInArrow(run, PIECE_SCHEMA)


def _configuration(sizes: list[int], left: list[int], capacity: int) -> list[int]:
    """How many of each size (at most ``left``) fill ``capacity`` best: an exact bounded knapsack."""
    reach = np.zeros(capacity + 1, bool)
    reach[0] = True
    layers = []
    for size, n in zip(sizes, left):
        layers.append(reach.copy())
        now = reach.copy()
        for _ in range(min(n, capacity // size)):
            more = np.zeros_like(now)
            more[size:] = now[:-size]
            if not (more & ~now).any():
                break
            now |= more
        reach = now
    room = int(np.flatnonzero(reach)[-1])
    use = [0] * len(sizes)
    for k in range(len(sizes) - 1, -1, -1):
        while not layers[k][room]:
            room -= sizes[k]
            use[k] += 1
    return use


Run = tuple[int, int, int, int, int, int]


def sequences(runs: list[Run]) -> int:
    """How many sequences a plan fills."""
    return max((first + -(-n // each) for _, _, n, each, first, _ in runs), default=0)


def plan(histogram: dict[int, int], capacity: int = CAPACITY, groups: tuple[int, ...] = GROUPS) -> list[Run]:
    """Runs ``(length, first rank, count, per sequence, first sequence, offset)`` for a
    histogram of lengths. Their number depends on ``capacity`` and ``groups`` alone.

    Each number of groups gives a plan by linear grouping (more groups round less); the one
    with the fewest sequences wins, the first on ties."""
    return min((grouping(histogram, capacity, g) for g in groups), key=sequences)


def grouping(histogram: dict[int, int], capacity: int, groups: int, small_part: int = SMALL_PART) -> list[Run]:
    """One plan by linear grouping; pieces of up to ``capacity // small_part`` are small."""
    runs: list[Run] = []
    rank = dict.fromkeys(histogram, 0)
    bins = 0
    rooms: list[tuple[int, int, int]] = []  # (room left, first sequence, sequences), ascending

    def take(length: int, n: int, each: int, first: int, offset: int) -> None:
        runs.append((length, rank[length], n, each, first, offset))
        rank[length] += n

    if full := histogram.get(capacity, 0):  # alone in their sequence
        take(capacity, full, 1, bins, 0)
        bins += full
    large = [x for x in sorted(histogram, reverse=True) if capacity // small_part < x < capacity]
    total = sum(histogram[x] for x in large)
    # Groups of equal cardinality by falling length; a group counts at its largest length.
    queues: list[deque[list[int]]] = []
    share, filled = max(1, -(-total // groups)), 0
    for x in large:
        n = histogram[x]
        while n:
            if not queues or filled == share:
                queues.append(deque())
                filled = 0
            part = min(n, share - filled)
            queues[-1].append([x, part])
            n -= part
            filled += part
    sizes = [q[0][0] for q in queues]
    left = [sum(n for _, n in q) for q in queues]
    while any(left):
        live = [k for k, n in enumerate(left) if n]
        # The largest size left is in the configuration; the rest of it is an exact knapsack.
        use = _configuration([sizes[k] for k in live], [left[k] - (k == live[0]) for k in live], capacity - sizes[live[0]])
        use[0] += 1
        slots = [k for k, u in zip(live, use) for _ in range(u)]
        times = min(left[k] // u for k, u in zip(live, use) if u)
        for k, u in zip(live, use):
            left[k] -= u * times
        while times:  # substitute actual lengths: split where any slot's length changes
            heads: dict[int, int] = {}
            lengths, m = [], times
            for k in slots:  # slots of one group take turns from its queue
                heads[k] = heads.get(k, 0) + 1
            for k, u in heads.items():
                queue, got = queues[k], []
                for length, n in queue:
                    got += [length] * min(u - len(got), n)
                    if len(got) == u:
                        break
                if len(set(got)) == 1:
                    m = min(m, queue[0][1] // u)
                else:
                    m = 1
                lengths += [(k, x) for x in got]
            offset = 0
            for k, x in lengths:
                queue = queues[k]
                need = m
                take(x, need, 1, bins, offset)
                while need:
                    entry = next(e for e in queue if e[0] == x)
                    part = min(need, entry[1])
                    entry[1] -= part
                    need -= part
                    if not entry[1]:
                        queue.remove(entry)
                offset += x
            if offset < capacity:
                insort(rooms, (capacity - offset, bins, m))
            bins += m
            times -= m
    for length in sorted((x for x in histogram if x <= capacity // small_part and x < capacity), reverse=True):
        n = histogram[length]
        while n:
            at = bisect_left(rooms, (length, -1, -1))  # the fullest sequences that still take it
            if at < len(rooms):
                room, first, m = rooms.pop(at)
            else:
                room, first, m = capacity, bins, -(-n // (capacity // length))
                bins += m
            each = room // length
            whole = min(m, n // each)
            if whole:
                take(length, whole * each, each, first, capacity - room)
                n -= whole * each
                if room - each * length:
                    insort(rooms, (room - each * length, first, whole))
            if whole < m and n:  # the last few share one more sequence
                take(length, n, n, first + whole, capacity - room)
                insort(rooms, (room - n * length, first + whole, 1)) if room > n * length else None
                whole, n = whole + 1, 0
            if whole < m:
                insort(rooms, (room, first + whole, m - whole))
    return runs


def _place(runs: list[Run]) -> Column:
    table = np.array(sorted(runs), np.int64).reshape(-1, 6)
    key = (table[:, 0] << 48) + table[:, 1]

    def places(lengths: pa.Array, ranks: pa.Array) -> pa.Array:
        n, r = np.asarray(lengths), np.asarray(ranks)
        row = table[np.searchsorted(key, (n << 48) + r, side="right") - 1] if len(n) else np.zeros((0, 6), np.int64)
        nth = r - row[:, 1]
        each = np.maximum(row[:, 3], 1)
        return pa.StructArray.from_arrays(
            [pa.array(row[:, 4] + nth // each, pa.int64()), pa.array(row[:, 5] + nth % each * n, pa.int64())], ["sequence_id", "offset"]
        )

    return F.arrow_udf(places, "sequence_id long, offset long")(F.col("length"), F.col("rank"))


def pack(docs: DataFrame, path: str, capacity: int = CAPACITY, groups: tuple[int, ...] = GROUPS, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``(doc_id, piece, start, length, ids_crc32, sequence_id, offset)``, one row per piece.

    Null and empty texts become one piece that holds only the final id. A null doc_id is
    kept as null; repeated rows are packed as often as they occur; only ``doc_id`` and
    ``text`` are read, so columns of other names don't matter. A very long text is encoded whole, in the
    memory of its task, and cut into pieces. No documents give no rows. Ranks are local ranks within a task plus
    offsets of the task, so a length that a third of all documents share is never in
    one place.
    """
    found = cut(pieces(docs, path, capacity, doc_id, text), "pieces")
    counts = found.groupBy("chunk", "length").agg((F.max("local") + 1).alias("n"))
    before = Window.partitionBy("length").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    counts = cut(counts.withColumn("base", F.coalesce(F.sum("n").over(before), F.lit(0).cast("long"))), "counts")
    histogram = {r["length"]: r["n"] for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # <= capacity rows
    bases = counts.select("chunk", "length", "base")
    bases = F.broadcast(bases) if counts.count() <= BROADCAST_COUNTS else bases.hint("merge")  # a key has one task's pieces at most
    ranked = found.join(bases, ["chunk", "length"]).withColumn("rank", F.col("base") + F.col("local"))
    return ranked.withColumn("place", _place(plan(histogram, capacity, groups))).select(
        "doc_id", "piece", "start", "length", "ids_crc32", "place.sequence_id", "place.offset"
    )
