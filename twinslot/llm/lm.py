"""Stupid-backoff scores of documents against n-gram counts of the whole corpus.

The relations are those of the textbook plan - count tables partitioned by n-gram hash,
joined to the documents' n-grams, summed per document - but their rows are blocks:

* ``blocks``: documents of a few million characters together, as indices into the
  block's distinct words (written once);
* ``requests``: for each block, order and hash partition the distinct n-gram hashes of
  the block with their counts. A frequent n-gram is one entry per block, whatever
  number of rows it has, so no hash partition is hot;
* ``answers``: the corpus-wide counts for each request, made in the hash partition.

Blocks then meet their answers and sum scores. N-grams are compared by 64-bit hashes.
Tables keep n-grams that occur ``min_count`` times or more, and a trigram can't occur
more often than its bigrams; so trigrams are asked for after the bigrams have been
answered, and only those of which both bigrams are frequent enough.
"""

from __future__ import annotations

import math
from math import log

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut

ORDER, BACKOFF, MIN_COUNT = 3, 0.4, 2
BLOCK_CHARS, PART_ENTRIES, LEAST_PARTS = 6_000_000, 1_500_000, 64
MICRO = 1_000_000

BLOCK_SCHEMA = "block long, n_words long, doc_ids array<long>, lengths array<int>, words binary, indices binary"
REQUEST_SCHEMA = "part int, block long, n int, hashes binary, counts binary"
ANSWER_SCHEMA = "part int, block long, n int, counts binary"
SCORE_SCHEMA = "doc_id long, n_words long, score_micro long, n_order3 long, n_order2 long, n_order1 long"


def _squeeze(values: np.ndarray) -> bytes:
    """Integers as byte planes, so that equal high bytes compress away."""
    planes = np.ascontiguousarray(values.view(np.uint8).reshape(len(values), -1).T) if len(values) else np.zeros(0, np.uint8)
    return zstandard.ZstdCompressor(level=1).compress(planes.tobytes())


def _expand(data: bytes, kind: str) -> np.ndarray:
    raw = zstandard.ZstdDecompressor().decompress(data)
    width = np.dtype(kind).itemsize
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8).reshape(width, -1).T).view(kind).ravel()


def _sorted_out(hashes: np.ndarray) -> bytes:
    return _squeeze(np.diff(hashes, prepend=np.uint64(0)))


def _sorted_in(data: bytes) -> np.ndarray:
    return np.cumsum(_expand(data, "<u8"), dtype=np.uint64)


def words_of(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").lower().split()


def _blocks(block_chars: int):
    def run(batches):
        seq = 0
        ids, lengths, codes, parts, size = [], [], {}, [], 0

        def flush():
            nonlocal seq, ids, lengths, codes, parts, size
            vocabulary = np.fromiter((xxhash.xxh64_intdigest(w) for w in codes), np.uint64, len(codes))
            flat = np.concatenate(parts) if parts else np.zeros(0, np.int32)
            common = np.argsort(-np.bincount(flat, minlength=len(codes)), kind="stable")  # small numbers for frequent words
            number = np.empty(len(codes), np.int32)
            number[common] = np.arange(len(codes), dtype=np.int32)
            vocabulary, flat = vocabulary[common], number[flat]
            block = TaskContext.get().partitionId() << 32 | seq
            out = [[block], [len(flat)], [ids], [lengths], [vocabulary.tobytes()], [_squeeze(flat)]]
            kinds = [pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int32()), pa.binary(), pa.binary()]
            seq, ids, lengths, codes, parts, size = seq + 1, [], [], {}, [], 0
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, kinds)], ["block", "n_words", "doc_ids", "lengths", "words", "indices"])

        for batch in batches:
            keys = batch.column(0).to_pylist()
            for key, text in zip(keys, batch.column(1)):
                words = words_of(text.as_py())
                code = codes.setdefault
                parts.append(np.fromiter([code(w, len(codes)) for w in words], np.int32, len(words)))
                ids.append(key)
                lengths.append(len(words))
                size += 1 + sum(map(len, words))
                if size >= block_chars:
                    yield flush()
        if ids:
            yield flush()

    return run


def _ngrams(words: np.ndarray, lengths: np.ndarray, order: int) -> list[np.ndarray]:
    """Hashes of all n-grams by order; entry i of order n is the n-gram that ends at word
    i, zero where the document has fewer words before it."""
    at = np.arange(len(words)) - np.repeat(np.cumsum(lengths) - lengths, lengths)
    out = [words]
    with np.errstate(over="ignore"):
        for n in range(2, order + 1):
            h = np.zeros_like(words)
            h[n - 1 :] = words[n - 1 :]
            mixed = (out[-1][:-1] ^ (out[-1][:-1] >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9) if len(words) else words
            h[1:] = (mixed + words[1:] * np.uint64(0x9E3779B97F4A7C15)) if len(words) else h
            h ^= h >> np.uint64(29)
            h = (h * np.uint64(0x94D049BB133111EB)) | np.uint64(1)
            h[at < n - 1] = 0
            out.append(h)
    return out


def _load(block: dict) -> tuple[np.ndarray, np.ndarray]:
    """Word hashes of a block in order, and the lengths of its documents."""
    vocabulary = np.frombuffer(block["words"], "<u8")
    lengths = np.array(block["lengths"], np.int64)
    indices = _expand(block["indices"], "<i4") if block["n_words"] else np.zeros(0, np.int32)
    return vocabulary[indices] if len(indices) else np.zeros(0, np.uint64), lengths


REQUEST_KINDS = (pa.int32(), pa.int64(), pa.int32(), pa.binary(), pa.binary())
REQUEST_NAMES = ["part", "block", "n", "hashes", "counts"]


def _asked(block: int, n: int, distinct: np.ndarray, counts: np.ndarray, parts: int) -> list[tuple]:
    """Request rows of one block and order: sorted hashes cut by equal shares of their range."""
    shares = np.uint64((1 << 64) // parts + 1)
    edges = np.searchsorted((distinct // shares).astype(np.int64), np.arange(parts + 1))
    return [
        (p, block, n, _sorted_out(distinct[lo:hi]), _squeeze(counts[lo:hi].astype("<u4")))
        for p, (lo, hi) in enumerate(zip(edges[:-1], edges[1:]))
        if hi > lo
    ]


def _requests(parts: int, order: int):
    def run(batches):
        for batch in batches:
            for block in batch.to_pylist():
                words, lengths = _load(block)
                for n, grams in enumerate(_ngrams(words, lengths, order), 1):
                    rows = _asked(block["block"], n, *np.unique(_present(grams, n), return_counts=True), parts)
                    if rows:
                        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), REQUEST_KINDS)], REQUEST_NAMES)

    return run


def _present(grams: np.ndarray, n: int) -> np.ndarray:
    return grams[grams != 0] if n > 1 else grams


def _by_order(answers: pa.Table) -> dict[int, np.ndarray]:
    """Answered counts of one block by order, in the order of its sorted distinct hashes."""
    out: dict[int, list] = {}
    for a in answers.sort_by([("n", "ascending"), ("part", "ascending")]).to_pylist():
        out.setdefault(a["n"], []).append(_expand(a["counts"], "<i8"))
    return {n: np.concatenate(c) for n, c in out.items()}


def _order(values: np.ndarray) -> np.ndarray:
    """Places that sort 64-bit ``values``: numbers are sorted with their places in their
    low bits, which is much faster than sorting places; only if high bits tie, places are."""
    bits = max(1, (len(values) - 1).bit_length())
    mask = np.uint64((1 << bits) - 1)
    packed = np.sort((values & ~mask) | np.arange(len(values), dtype=np.uint64))
    order = (packed & mask).astype(np.int64)
    out = values[order]
    return np.argsort(values, kind="stable") if (out[1:] < out[:-1]).any() else order


def _looked_up(grams: np.ndarray, asked: np.ndarray, counts: np.ndarray | None) -> np.ndarray:
    """Corpus-wide count of the n-gram that ends at each word where it was asked for, else 0.
    ``counts`` follow the sorted distinct n-grams, so ranks among equal values find them."""
    here = np.zeros(len(grams), np.int64)
    if counts is not None and asked.any():
        some = grams[asked]
        order = _order(some)
        ranked = some[order]
        new = np.zeros(len(ranked), np.int64)
        new[1:] = ranked[1:] != ranked[:-1]
        found = np.empty(len(some), np.int64)
        found[order] = counts[np.cumsum(new)]
        here[asked] = found
    return here


def _seen(words: np.ndarray, lengths: np.ndarray, order: int, counts: dict[int, np.ndarray], min_count: int):
    """N-gram hashes and corpus-wide counts by order; trigrams are asked for only where both bigrams are frequent."""
    grams = _ngrams(words, lengths, order)
    asked = [np.ones(len(words), bool), *(g != 0 for g in grams[1:])]
    seen = []
    for n in range(1, order + 1):
        if n == 3:
            frequent = seen[1] >= min_count
            asked[2] = asked[2] & frequent & np.roll(frequent, 1)
        seen.append(_looked_up(grams[n - 1], asked[n - 1], counts.get(n)))
    return grams, asked, seen


def _trigram_requests(parts: int, min_count: int):
    def run(blocks: pa.Table, answers: pa.Table) -> pa.Table:
        counts, rows = _by_order(answers), []
        for block in blocks.to_pylist():
            words, lengths = _load(block)
            grams, asked, _ = _seen(words, lengths, 3, counts, min_count)
            rows += _asked(block["block"], 3, *np.unique(grams[2][asked[2]], return_counts=True), parts)
        columns = list(zip(*rows)) or [()] * 5
        return pa.Table.from_arrays([pa.array(c, k) for c, k in zip(columns, REQUEST_KINDS)], names=REQUEST_NAMES)

    return run


def _answers(table: pa.Table) -> pa.Table:
    """Corpus-wide counts for every request of one hash partition."""
    rows = table.to_pylist()
    out = []
    for n in sorted({r["n"] for r in rows}):
        mine = [r for r in rows if r["n"] == n]
        hashes = [_sorted_in(r["hashes"]) for r in mine]
        flat = np.concatenate(hashes)
        counts = np.concatenate([_expand(r["counts"], "<u4") for r in mine]).astype(np.int64)
        distinct, back = np.unique(flat, return_inverse=True)
        total = np.zeros(len(distinct), np.int64)
        np.add.at(total, back, counts)
        answer, at = total[back], 0
        for r, h in zip(mine, hashes):
            out.append((r["part"], r["block"], n, _squeeze(answer[at : at + len(h)].astype("<i8"))))
            at += len(h)
    kinds = (pa.int32(), pa.int64(), pa.int32(), pa.binary())
    return pa.Table.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), kinds)], names=["part", "block", "n", "counts"])


def _scores(order: int, backoff: float, min_count: int, total: int):
    def run(blocks: pa.Table, answers: pa.Table) -> pa.Table:
        rows: list[tuple] = []
        counts = _by_order(answers)
        for block in blocks.to_pylist():
            words, lengths = _load(block)
            _, _, seen = _seen(words, lengths, order, counts, min_count)
            at = np.arange(len(words)) - np.repeat(np.cumsum(lengths) - lengths, lengths)
            level, value = np.zeros(len(words), np.int64), np.zeros(len(words))
            for n in range(order, 0, -1):
                fits = (level == 0) & (at >= n - 1) & ((seen[n - 1] >= min_count) if n > 1 else True)
                context = np.roll(seen[n - 2], 1)[fits] if n > 1 else float(total)
                skipped = np.minimum(at[fits] + 1, order) - n
                value[fits] = np.floor((np.log(seen[n - 1][fits] / context) + skipped * log(backoff)) * MICRO + 0.5)
                level[fits] = n
            ends = np.cumsum(lengths)
            sums = []
            for x in (value.astype(np.int64), level == 3, level == 2, level == 1):
                running = np.concatenate(([0], np.cumsum(x, dtype=np.int64)))
                sums.append(running[ends] - running[ends - lengths])
            rows += zip(block["doc_ids"], lengths.tolist(), *(s.tolist() for s in sums))
        columns = list(zip(*rows)) or [()] * 6
        return pa.Table.from_arrays([pa.array(c, pa.int64()) for c in columns], names=["doc_id", "n_words", "score_micro", "n_order3", "n_order2", "n_order1"])

    return run


def score(
    docs: DataFrame, order: int = ORDER, backoff: float = BACKOFF, min_count: int = MIN_COUNT, doc_id: str = "doc_id", text: str = "text",
    block_chars: int = BLOCK_CHARS,
) -> DataFrame:
    """``(doc_id, n_words, score_micro, n_order3, n_order2, n_order1)``, one row per row.

    Counts are taken over all rows of ``docs``. A word scores c(n-gram) / c(context) for the
    longest n-gram of at most ``order`` words within its document that occurs ``min_count``
    times or more, times ``backoff`` for each order given up; a single word scores its
    share of all words. score_micro sums natural logarithms in millionths, each rounded,
    so sums don't depend on their order; n_orderN counts the words scored at order N.
    Words are split at ASCII spaces and A-Z are lower-cased. Null and empty texts score 0.
    Null ids stay null, repeated rows are counted and scored as often as they occur, other
    columns are ignored, and no rows give no rows.
    """
    if not 1 <= order <= 3:
        raise ValueError("order must be 1, 2 or 3")
    if min_count < 1:
        raise ValueError("min_count must be 1 or more")
    blocks = cut(docs.select(F.col(doc_id).cast("long"), F.col(text)).mapInArrow(_blocks(block_chars), BLOCK_SCHEMA), "lm-blocks")
    total = blocks.agg(F.sum("n_words")).first()[0] or 0
    parts = max(LEAST_PARTS, math.ceil(total * order / PART_ENTRIES))
    asked = blocks.mapInArrow(_requests(parts, min(order, 2)), REQUEST_SCHEMA)
    answers = cut(asked.groupBy("part").applyInArrow(_answers, ANSWER_SCHEMA), "lm-answers")
    if order == 3:
        more = blocks.groupBy("block").cogroup(answers.groupBy("block")).applyInArrow(_trigram_requests(parts, min_count), REQUEST_SCHEMA)
        answers = answers.unionByName(cut(more.groupBy("part").applyInArrow(_answers, ANSWER_SCHEMA), "lm-answers"))
    return (
        blocks.groupBy("block")
        .cogroup(answers.groupBy("block"))
        .applyInArrow(_scores(order, backoff, min_count, total), SCORE_SCHEMA)
    )
