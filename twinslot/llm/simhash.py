"""SimHash near-duplicates by meet-in-the-middle ball hashing.

Two fingerprints within ``radius`` differing bits share a variant that lies within
``radius / 2`` of both. So each distinct fingerprint emits its ball of half the
radius, variants are shuffled, and a shared variant proposes links. All members of
one variant are within the radius of each other, so a star from the smallest member
carries every connection of the bucket without emitting its pairs; each star link is
still verified by counting bits.
"""

from __future__ import annotations

from itertools import combinations
from math import comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.incidence import dense_ids
from . import worker
from .common import components, cut, free_name, scratch, small_batches

BITS, SEED, CHUNK = 64, 42, 1 << 16
#: Variants that a task emits.
VARIANTS = 1_000_000


def fingerprint(text: str | None, shingle: int = 3) -> int:
    """The 64-bit fingerprint of one whole text (unsigned)."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()  # bytes: only A-Z and ASCII spaces count
    if not words:
        return 0
    k = min(shingle, len(words))
    line = b" ".join(words)
    lengths = np.fromiter(map(len, words), np.int64, len(words))
    starts = np.concatenate(([0], np.cumsum(lengths + 1)[:-1]))
    ends = (starts + lengths)[k - 1 :].tolist()
    hash_of = xxhash.xxh64_intdigest
    hashes = np.array([hash_of(line[s:e], SEED) for s, e in zip(starts.tolist(), ends)], dtype=">u8")
    ones = np.zeros(BITS, np.int64)
    for at in range(0, len(hashes), CHUNK):  # bounded memory for very long texts
        part = hashes[at : at + CHUNK]
        ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > len(hashes)).tobytes(), "big")


def _udf(shingle: int):
    def fingerprints(texts: pa.Array) -> pa.Array:
        worker.enter("simhash")
        found = np.array([fingerprint(t.as_py(), shingle) for t in texts], dtype=np.uint64)
        return pa.array(found.view(np.int64), pa.int64())

    return F.arrow_udf(fingerprints, "long")


def ball(radius: int) -> list[int]:
    """All 64-bit masks of up to ``radius`` bits, as signed longs."""
    masks = [sum(1 << b for b in bits) for n in range(radius + 1) for bits in combinations(range(BITS), n)]
    return [m - (1 << BITS) if m >> (BITS - 1) else m for m in masks]


def links(prints: DataFrame, radius: int = 2) -> DataFrame:
    """Links ``(a, b)`` between distinct fingerprints ``fp`` that span the graph of all
    pairs within ``radius`` (even) bits: same connected components, no pair emitted twice.

    A bucket holds at most as many fingerprints as the ball has members, since they
    are distinct and within half the radius of its variant; a larger one means that ``prints``
    repeats a fingerprint, and is an error. The few small files that fingerprints come in are
    dealt to tasks by the rows they grow to before they do.
    """
    if radius % 2 or not 0 <= radius <= 4:
        raise ValueError("radius must be 0, 2 or 4: half of it is the radius of the emitted balls")
    half = radius // 2
    masks = F.array(*(F.lit(m).cast("long") for m in ball(half)))
    size = sum(comb(BITS, n) for n in range(half + 1))
    tasks = max(prints.sparkSession.sparkContext.defaultParallelism, -(-prints.count() * size // VARIANTS))
    variants = prints.repartition(tasks, "fp").select("fp", F.explode(masks).alias("mask")).select("fp", F.col("fp").bitwiseXOR(F.col("mask")).alias("variant"))
    members = F.collect_list("fp")
    sound = F.when(F.size(members) <= size, members).otherwise(F.raise_error(F.lit("a fingerprint is repeated")).cast("array<long>"))
    buckets = variants.groupBy("variant").agg(sound.alias("members")).where(F.size("members") > 1)
    return (
        buckets.select(F.array_min("members").alias("b"), F.explode("members").alias("a"))
        .where((F.col("a") != F.col("b")) & (F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= radius))
        .distinct()
        .select("a", "b")
    )


def near_groups(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", radius: int = 2, shingle: int = 3) -> DataFrame:
    """``(doc_id, fingerprint, component_id)``: one row per input row.

    component_id is the smallest id reachable through links. Null and empty texts have
    fingerprint zero and are linked like others. Rows with a null id take part (their
    text links others) and keep a null doc_id; their component_id is null only if
    no id is reachable. Repeated rows are repeated in the result. Only ``doc_id`` and
    ``text`` are read, so further columns of any name don't matter. Texts become 8
    bytes before anything is shuffled, and equal fingerprints become one row before
    balls are emitted, so a third of all rows being copies costs one partial count.
    """
    with scratch() as keep:
        fps = keep(cut(docs.select(F.col(doc_id).cast("long").alias("doc_id"), _udf(shingle)(F.col(text)).alias("fp")), "prints"))
        reps = cut(fps.groupBy("fp").agg(F.min("doc_id").alias("first_id")), "reps")
        joined = cut(components(links(reps.select("fp"), radius)), "components")
        labelled = joined.join(reps.withColumnRenamed("fp", "node"), "node")
        least = cut(labelled.groupBy("component").agg(F.min("first_id").alias("component_id")), "least")
        of_fp = cut(reps.join(joined.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "first_id", "component"), "of")
        ids = of_fp.join(least, "component", "left").select("fp", F.coalesce("component_id", "first_id").alias("component_id"))
        ids = keep(cut(ids, "ids"))
    return fps.join(ids, "fp").select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


# Near copies: fingerprints that move little under small edits propose, shingles decide.

WORD_SEEDS = (101,)
SIMILARITY, SHINGLE = 0.8, 5
#: A proposed pair is looked at exactly if this share of its sketches' bins agrees, which
#: is four standard deviations below the similarity that counts.
BINS, SKETCH_SHARE = 64, 0.6
#: Bands of minimum hashes over the shingles: a pair of similarity s shares none of them with
#: probability (1 - s^5)^20, which is 0.0004 at 0.8.
BANDS, BAND_ROWS = 20, 5
_RNG = np.random.default_rng(SEED)
_XOR, _ODD = (_RNG.integers(0, 1 << 32, BANDS * BAND_ROWS, dtype=np.uint32) for _ in range(2))
_ODD |= np.uint32(1)
#: Shingles that are mixed at once: the products stay in a core's cache.
MIXED = 256
#: Members of a band's bucket meet in blocks of about so many.
BLOCK = 256
#: Buckets of more members, where some are apart, are crowds, whose shingles meet in blocks of
#: ``BLOCK * CROWD_GROWTH`` texts or ``BLOCK * CROWD_SHINGLES`` shingles a side, so many columns of them at a time.
CROWD, CROWD_GROWTH, CROWD_SHINGLES, COLUMNS = 64, 2, 2000, 2048


def word_prints(text: str | None, seeds: tuple[int, ...] = WORD_SEEDS) -> list[int]:
    """Fingerprints of the words of a text, each weighted by its count: an edit of a few
    words moves few of their bits, where it would move many of a shingle fingerprint's."""
    counts: dict[bytes, int] = {}
    for word in (text or "").encode("utf-8", "surrogatepass").lower().split():
        counts[word] = counts.get(word, 0) + 1
    if not counts:
        return [0] * len(seeds)
    weight = np.fromiter(counts.values(), np.float64, len(counts))
    half, out = weight.sum() / 2, []
    for seed in seeds:
        hashes = np.array([xxhash.xxh64_intdigest(w, seed) for w in counts], dtype=">u8")
        ones = np.zeros(BITS)
        for at in range(0, len(hashes), CHUNK):
            ones += weight[at : at + CHUNK] @ np.unpackbits(hashes[at : at + CHUNK].view(np.uint8).reshape(-1, 8), axis=1)
        out.append(int.from_bytes(np.packbits(ones > half).tobytes(), "big"))
    return out


def shingle_set(text: str | None) -> np.ndarray:
    """Sorted distinct hashes of the five-word shingles of one whole text."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    k = min(SHINGLE, len(words))
    hashes = [xxhash.xxh64_intdigest(b" ".join(words[i : i + k])) for i in range(len(words) - k + 1)] if k else []
    return np.unique(np.array(hashes, np.uint64))


def bin_sketch(hashes: np.ndarray) -> bytes:
    """One byte of the least hash in each of 64 equal ranges (zero: none there)."""
    edges = np.searchsorted(hashes, np.arange(BINS, dtype=np.uint64) << np.uint64(58))
    full = np.append(edges[1:], len(hashes)) > edges
    out = np.zeros(BINS, np.uint8)
    out[full] = 1 + (hashes[edges[full]] >> np.uint64(20)) % np.uint64(255)
    return out.tobytes()


def band_keys(hashes: np.ndarray) -> list[int]:
    """One signed 64-bit key a band; none for a text without words."""
    if not len(hashes):
        return []
    # The hashes are random already, so folded to 32 bits one odd multiple of each gives an order of its own.
    folded = (hashes ^ (hashes >> np.uint64(32))).astype(np.uint32)
    least = np.full(BANDS * BAND_ROWS, np.iinfo(np.uint32).max, np.uint32)
    space = np.empty((min(MIXED, len(folded)), BANDS * BAND_ROWS), np.uint32)
    for at in range(0, len(folded), MIXED):  # bounded memory for very long texts
        some = folded[at : at + MIXED, None]
        mixed = space[: len(some)]
        np.bitwise_xor(some, _XOR, out=mixed)
        np.multiply(mixed, _ODD, out=mixed)
        np.minimum(least, mixed.min(axis=0), out=least)
    rows = least.reshape(BANDS, BAND_ROWS)
    keys = [xxhash.xxh64_intdigest(row.tobytes(), k) for k, row in enumerate(rows)]
    return np.array(keys, np.uint64).view(np.int64).tolist()


def _sketches(texts: pa.Array) -> pa.Array:
    """Two halves of a 128-bit digest of the text, its shingle and word fingerprints, its bins and bands."""
    worker.enter("simhash")
    rows, bins, bands = [], [], []
    for t in texts:
        text = t.as_py() or ""
        digest = xxhash.xxh3_128_intdigest(text.encode("utf-8", "surrogatepass"))
        rows.append([digest >> 64, digest & ((1 << 64) - 1), fingerprint(text), *word_prints(text)])
        shingles = shingle_set(text)
        bins.append(bin_sketch(shingles))
        bands.append(band_keys(shingles))
    flat = np.array(rows, np.uint64).reshape(-1, 3 + len(WORD_SEEDS)).view(np.int64)
    names = ["t1", "t2", *(f"f{i}" for i in range(1 + len(WORD_SEEDS))), "bins", "bands"]
    columns = [*(pa.array(np.ascontiguousarray(c), pa.int64()) for c in flat.T), pa.array(bins, pa.binary()), pa.array(bands, pa.list_(pa.int64()))]
    return pa.StructArray.from_arrays(columns, names)


def _agree(left: pa.Array, right: pa.Array) -> pa.Array:
    """Do two sketches agree in enough of the bins that either fills?"""
    x, y = (np.frombuffer(b"".join(c.to_pylist()), np.uint8).reshape(-1, BINS) for c in (left, right))
    used = (x | y) != 0
    return pa.array(((x == y) & used).sum(axis=1) >= SKETCH_SHARE * used.sum(axis=1), pa.bool_())


def _shingle_sets(texts: pa.Array) -> pa.Array:
    worker.enter("simhash")
    out = [shingle_set(t.as_py()).view(np.int64) for t in texts]
    ends = np.cumsum([0] + [len(x) for x in out]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate([np.zeros(0, np.int64), *out]), pa.int64()))


def _text_links(texts: DataFrame, column: str, radius: int) -> DataFrame:
    """Links ``(a, b)`` between representatives of texts whose ``column`` is equal or within ``radius``."""
    reps = cut(texts.groupBy(F.col(column).alias("fp")).agg(F.min("rep").alias("r")), "fps")
    same = texts.select(F.col("rep").alias("a"), F.col(column).alias("fp")).join(reps, "fp").select("a", F.col("r").alias("b"))
    near = cut(links(reps.select("fp"), radius), "links")
    left, right = (reps.select(F.col("fp").alias(x), F.col("r").alias(f"r{x}")) for x in "ab")
    across = near.join(left, "a").join(right, "b").select(F.col("ra").alias("a"), F.col("rb").alias("b"))
    out = cut(same.unionByName(across).where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "text-links")
    return out


def _band_links(members: DataFrame) -> DataFrame:
    """Links ``(a, b)`` of the ``members(band, rep)`` of each bucket with its smallest one."""
    least = cut(members.groupBy("band").agg(F.min("rep").alias("b"), F.count("*").alias("n")).where("n > 1").select("band", "b"), "band-centres")
    linked = members.join(least, "band").where("rep <> b").select(F.col("rep").alias("a"), "b").distinct()
    return cut(linked, "band-links")


def _sifted(pairs: DataFrame, sketch: DataFrame) -> DataFrame:
    """The pairs ``(a, b)`` whose sketches agree."""
    for x in "ab":
        pairs = pairs.join(cut(sketch.select(F.col("rep").alias(x), F.col("bins").alias(f"bins_{x}")), "bins"), x)
    return cut(pairs.where(F.arrow_udf(_agree, "boolean")("bins_a", "bins_b")).select("a", "b"), "alike")


def _hub_pairs(members: DataFrame, joined: DataFrame, linked: DataFrame) -> DataFrame:
    """Pairs ``(a, b)`` of a member that lies outside its bucket's largest component with the text of
    that component that has most links: one pair a member and band."""
    degree = linked.select(F.col("a").alias("node")).union(linked.select("b")).groupBy("node").agg(F.count("*").alias("n"))
    best = degree.join(joined, "node").groupBy("component").agg(F.max_by("node", F.struct("n", -F.col("node"))).alias("hub"))
    labels = joined.select(F.col("node").alias("rep"), F.col("component").alias("c"))
    named = cut(members.join(labels, "rep", "left").select("band", "rep", F.coalesce("c", "rep").alias("label")), "hub-labels")
    sizes = named.groupBy("band", "label").agg(F.count("*").alias("n")).groupBy("band").agg(F.max_by("label", F.struct("n", -F.col("label"))).alias("component"), F.count("*").alias("labels"))
    open_ = cut(sizes.where("labels > 1").join(best, "component").select("band", "component", "hub"), "hubs")
    outside = named.join(open_, "band").where("label <> component AND rep <> hub")
    return outside.select(F.greatest("rep", "hub").alias("a"), F.least("rep", "hub").alias("b")).distinct()


def _cross(blocks: pa.Array) -> pa.Array:
    """For blocks of (rep, label, side, bins): the pairs of members that lie in different components,
    on different sides if there are two blocks, and whose sketches agree."""
    worker.enter("simhash")
    out = []
    for block in blocks:
        rows = block.values
        rep, label, side = (np.asarray(rows.field(k).to_numpy(zero_copy_only=False)) for k in ("rep", "label", "side"))
        bins = np.frombuffer(b"".join(rows.field("bins").to_pylist()), np.uint8).reshape(-1, BINS)
        two, found = len(np.unique(side)) > 1, []
        for i in range(len(rep) - 1):
            fine = label[i + 1 :] != label[i]
            if two:
                fine &= side[i + 1 :] != side[i]
            at = i + 1 + np.flatnonzero(fine)
            if len(at):
                used = (bins[at] | bins[i]) != 0
                at = at[((bins[at] == bins[i]) & used).sum(axis=1) >= SKETCH_SHARE * used.sum(axis=1)]
                found += [{"a": int(max(rep[i], rep[j])), "b": int(min(rep[i], rep[j]))} for j in at]
        out.append(found)
    return pa.array(out, pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64())])))


def _same(similarity: float):
    """For blocks of (rep, label, side, bands, x): links between members that lie in different components,
    share a band and are similar enough, exactly; no more of them than join what they join."""

    def same(blocks: pa.Array) -> pa.Array:
        worker.enter("simhash")
        out = []
        for block in blocks:
            rows = block.values
            rep, label, side = (np.asarray(rows.field(k).to_numpy(zero_copy_only=False)) for k in ("rep", "label", "side"))
            sizes = rows.field("x").value_lengths().to_numpy().astype(np.int64)
            shingles, back = np.unique(rows.field("x").flatten().to_numpy(), return_inverse=True)
            several = np.bincount(back, minlength=len(shingles)) > 1  # a shingle of one member is common to none
            owner, column = np.repeat(np.arange(len(rep)), sizes)[several[back]], (np.cumsum(several) - 1)[back[several[back]]]
            order = np.argsort(column, kind="stable")
            owner, column = owner[order], column[order]
            common = np.zeros((len(rep), len(rep)), np.float32)
            for at in range(0, int(several.sum()), COLUMNS):
                lo, hi = np.searchsorted(column, (at, at + COLUMNS))
                held = np.zeros((len(rep), COLUMNS), np.float32)
                held[owner[lo:hi], column[lo:hi] - at] = 1
                common += held @ held.T
            common = np.rint(common).astype(np.int64)
            i, j = np.nonzero(np.triu(common >= similarity * (sizes[:, None] + sizes[None, :] - common), 1))
            fine = (label[i] != label[j]) & ((side[i] != side[j]) | (len(np.unique(side)) == 1))
            i, j = i[fine], j[fine]
            bands = rows.field("bands").flatten().to_numpy().reshape(-1, BANDS)
            joins = (bands[i] == bands[j]).any(axis=1) if len(i) else np.zeros(0, bool)
            parent, found = {}, []

            def root(of):
                while parent.setdefault(of, of) != of:
                    of = parent[of]
                return of

            for one, other in zip(i[joins].tolist(), j[joins].tolist()):
                x, y = root(int(label[one])), root(int(label[other]))
                if x != y:
                    parent[max(x, y)] = min(x, y)
                    found.append({"a": int(max(rep[one], rep[other])), "b": int(min(rep[one], rep[other]))})
            out.append(found)
        return pa.array(out, pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64())])))

    return same


def _apart(members: DataFrame, joined: DataFrame) -> DataFrame:
    """``(band, rep, label, out)`` of the buckets that no component joins yet: a member is outside if it lies
    in another component than the bucket's smallest one."""
    labels = joined.select(F.col("node").alias("rep"), F.col("component").alias("c"))
    named = cut(members.join(labels, "rep", "left").select("band", "rep", F.coalesce("c", "rep").alias("label")), "band-labels")
    open_ = named.groupBy("band").agg(F.min("label").alias("low"), F.max("label").alias("high"), F.min_by("label", "rep").alias("centre")).where("low < high")
    open_ = cut(open_.select("band", "centre"), "open-bands")
    return cut(named.join(open_, "band").withColumn("out", F.col("label") != F.col("centre")), "open-members")


def _meetings(placed: DataFrame, *more: str) -> DataFrame:
    """``(band, p, q, rep, label, side, *more)``: members of ``placed`` (see ``_apart``, with their ``weight``) in
    blocks of a weight of about ``BLOCK``. Pairs with an outside member all meet, so a bucket with few members outside is
    linear in its size. A block has about two times ``BLOCK`` members at most."""
    share = lambda n: F.greatest(F.ceil(n / F.lit(BLOCK)), F.lit(1)).cast("int")
    weigh = lambda c: F.coalesce(F.sum(F.when(c, F.col("weight"))), F.lit(0))
    sizes = cut(placed.groupBy("band").agg(share(weigh(F.col("out"))).alias("nout"), share(weigh(~F.col("out"))).alias("nin")), "open-sizes")
    mix = F.xxhash64("rep", F.lit(SEED))
    at = placed.join(sizes, "band").withColumn("s", F.when(F.col("out"), F.pmod(mix, F.col("nout"))).otherwise(-1 - F.pmod(mix, F.col("nin"))).cast("int"))
    outside = F.sequence(F.lit(0), F.col("nout") - 1)
    inside = F.sequence(F.lit(1), F.col("nin"))
    meets = F.when(
        F.col("out"),
        F.concat(
            F.transform(outside, lambda k: F.struct(F.least("s", k).alias("p"), F.greatest("s", k).alias("q"))),
            F.transform(inside, lambda k: F.struct(F.col("s").alias("p"), (-k).alias("q"))),
        ),
    ).otherwise(F.transform(outside, lambda k: F.struct(k.alias("p"), F.col("s").alias("q"))))
    found = at.select("band", "rep", "label", F.col("s").alias("side"), F.explode(meets).alias("m"), *more)
    return found.select("band", "m.p", "m.q", "rep", "label", "side", *more)


def _block_pairs(met: DataFrame, row: list[str], kernel) -> DataFrame:
    """The distinct pairs ``(a, b)`` that ``kernel`` makes of each block of ``met``."""
    blocks = met.groupBy("band", "p", "q").agg(F.collect_list(F.struct(*row)).alias("x"), F.min("label").alias("low"), F.max("label").alias("high")).where("low < high")
    return blocks.select(F.explode(F.arrow_udf(kernel, "array<struct<a:long,b:long>>")("x")).alias("y")).select("y.a", "y.b").distinct()


def _unmet(members: DataFrame, joined: DataFrame | None, sketch: DataFrame) -> DataFrame:
    """Pairs ``(a, b)`` of one bucket of ``members`` that no component of ``joined`` joins yet and whose sketches
    agree: only they become rows. Without ``joined`` members are those of ``_apart``."""
    placed = members if joined is None else _apart(members, joined)
    met = cut(_meetings(placed.withColumn("weight", F.lit(1))), "meetings")
    fuller = met.join(sketch.withColumnRenamed("rep", "id"), F.col("rep") == F.col("id"))
    with small_batches(placed.sparkSession, 64):
        return cut(_block_pairs(fuller, ["rep", "label", "side", "bins"], _cross), "unmet")


def _crowd_links(placed: DataFrame, bands: DataFrame, read: DataFrame, similarity: float) -> DataFrame:
    """Links ``(a, b)`` that are exact already, between members of the same bucket of ``placed`` (see ``_apart``).

    A large group of texts just too far from each other would make a row of each pair that a sketch can't tell from
    a near copy. Here buckets that share a member are one, so texts that meet in many bands meet once, and their sets of
    shingles are compared where they meet: rows are the links that join components, no pair that fails is one."""
    least = placed.groupBy("band").agg(F.min("rep").alias("b"))
    groups = components(placed.join(least, "band").select(F.col("rep").alias("a"), "b"))
    texts = cut(placed.select("rep", "label").distinct().join(groups.select(F.col("node").alias("rep"), F.col("component").alias("band")), "rep"), "crowd")
    ids = texts.select(F.col("rep").alias("id"))
    wanted = read.join(ids.hint("shuffle_hash"), F.col("doc_id") == F.col("id"), "left_semi")
    with small_batches(read.sparkSession):
        sets = cut(wanted.select(F.col("doc_id").alias("id"), F.arrow_udf(_shingle_sets, "array<long>")("text").alias("x")), "crowd-shingles")
    centres = texts.groupBy("band").agg(F.min_by("label", "rep").alias("centre"))
    weighed = texts.join(centres, "band").join(sets.select(F.col("id").alias("rep"), F.greatest(F.lit(1 / CROWD_GROWTH), F.size("x") / CROWD_SHINGLES).alias("weight")), "rep")
    weighed = cut(weighed.select("band", "rep", "label", "weight", (F.col("label") != F.col("centre")).alias("out")), "weighed")
    met = cut(_meetings(weighed), "crowd-meetings")
    known = sets.join(bands.withColumnRenamed("rep", "own"), F.col("id") == F.col("own")).select("id", "bands", "x")
    fuller = met.join(known, F.col("rep") == F.col("id")).drop("id")
    with small_batches(placed.sparkSession, 1):
        return cut(_block_pairs(fuller, ["rep", "label", "side", "bands", "x"], _same(similarity)), "crowd-links")


def _proven(read: DataFrame, pairs: DataFrame, similarity: float) -> DataFrame:
    """The pairs ``(a, b)`` of texts whose sets of shingles are similar enough, exactly."""
    ids = cut(pairs.select(F.col("a").alias("id")).union(pairs.select("b")).distinct(), "proposed-ids")
    wanted = read.join(ids.hint("shuffle_hash"), F.col("doc_id") == F.col("id"), "left_semi")
    with small_batches(read.sparkSession):
        sets = cut(wanted.select("doc_id", F.arrow_udf(_shingle_sets, "array<long>")("text").alias("x")), "shingles")
    left = sets.select(F.col("doc_id").alias("a"), F.col("x").alias("xa"))
    right = sets.select(F.col("doc_id").alias("b"), F.col("x").alias("xb"))
    common = F.size(F.array_intersect("xa", "xb"))
    alike = common >= F.lit(similarity) * (F.size("xa") + F.size("xb") - common)
    return cut(pairs.join(left, "a").join(right, "b").where(alike).select("a", "b"), "proven")  # nothing that binds a hub's rows


def near_copies(docs: DataFrame, similarity: float = SIMILARITY, radius: int = 2, doc_id: str = "doc_id", text: str = "text") -> tuple[DataFrame, DataFrame]:
    """``(texts, groups)``: texts has ``(t1, t2, rep)``, each distinct text with its smallest
    doc_id; groups has ``(node, component)`` of the representatives that have near copies.

    Pairs that word fingerprints or bands propose are sifted by 64-byte sketches before sets of
    shingles are shuffled. Texts are near copies if their shingle fingerprints are within ``radius`` bits, or if
    one of their word fingerprints is or they share a band of minimum hashes, and their sets of
    five-word shingles have a Jaccard similarity of ``similarity`` or more (exact, over whole
    texts; ASCII case is ignored). A variant's and a band's members are compared with its
    smallest member first; then all members of a band that are still apart are compared, in crowds by their shingles. Copies of one text are one
    row from the first shuffle on. Rows with a null id take no part, null texts are empty; ids
    must not repeat with other texts (see ``keyed``).
    """
    with scratch() as keep:
        schema = "t1 long, t2 long, " + ", ".join(f"f{i} long" for i in range(1 + len(WORD_SEEDS))) + ", bins binary, bands array<long>"
        read = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text")).where("doc_id IS NOT NULL")
        sketched = read.select("doc_id", F.arrow_udf(_sketches, schema)("text").alias("s")).select("doc_id", "s.*")
        prints = [f"f{i}" for i in range(1 + len(WORD_SEEDS))]
        distinct = sketched.groupBy("t1", "t2").agg(F.min("doc_id").alias("rep"), *(F.min(p).alias(p) for p in prints), F.first("bins").alias("bins"), F.first("bands").alias("bands"))
        with small_batches(docs.sparkSession):
            texts = keep(cut(distinct, "texts"))
        sure, *more = (_text_links(texts, p, radius) for p in prints)
        members = cut(texts.select("rep", F.explode("bands").alias("band")).distinct(), "bands")
        proposed = _band_links(members)
        for part in more:
            proposed = proposed.unionByName(part)
        proposed = cut(proposed.distinct().join(sure, ["a", "b"], "left_anti"), "proposed")
        sketch = cut(texts.groupBy("rep").agg(F.first("bins").alias("bins")), "sketch")
        asked = proposed
        proposed = _sifted(proposed, sketch)
        # One partner for each text first: most other proposals then join texts already joined.
        one = cut(proposed.groupBy("a").agg(F.min("b").alias("b")), "first-partners")
        proven = _proven(read, one, similarity)
        joined = cut(components(sure.unionByName(proven)), "joined")
        rest = proposed.join(one, ["a", "b"], "left_anti")
        for x in "ab":
            where = joined.select(F.col("node").alias(x), F.col("component").alias(f"c{x}"))
            rest = cut(rest.join(where, x, "left"), "rest")
        rest = cut(rest.where(F.coalesce("ca", "a") != F.coalesce("cb", "b")).select("a", "b"), "rest")
        proven = proven.unionByName(_proven(read, rest, similarity))
        # What the centres of the bands left apart: first against the best linked text of the largest
        # component around, which is the text that copies were made from, then all pairs that remain.
        joined = cut(components(sure.unionByName(proven)), "joined")
        hubs = cut(_hub_pairs(members, joined, sure.unionByName(proven)).join(asked, ["a", "b"], "left_anti"), "hub-pairs")
        proven = proven.unionByName(_proven(read, _sifted(hubs, sketch), similarity))
        asked = asked.unionByName(hubs)
        joined = cut(components(sure.unionByName(proven)), "joined")
        placed = _apart(members, joined)
        crowds = cut(placed.groupBy("band").agg(F.count("*").alias("n")).where(F.col("n") > CROWD).select("band"), "crowds")
        last = cut(_unmet(placed.join(crowds, "band", "left_anti"), None, sketch).join(asked, ["a", "b"], "left_anti"), "last")
        proven = proven.unionByName(_proven(read, last, similarity))
        crowded = cut(placed.join(crowds, "band", "left_semi"), "crowded")
        proven = proven.unionByName(_crowd_links(crowded, texts.select("rep", "bands"), read, similarity))
        return texts.select("t1", "t2", "rep"), keep(cut(components(sure.unionByName(proven)), "groups"))


def survivors(docs: DataFrame, **how) -> DataFrame:
    """``(id)``: the smallest doc_id of each group of near copies, and of each other text."""
    with scratch() as keep:
        texts, groups = near_copies(docs, **how)
        losers = groups.where("node <> component").select(F.col("node").alias("rep"))
        return keep(cut(texts.select("rep").join(losers, "rep", "left_anti").select(F.col("rep").alias("id")).distinct(), "survivors"))


def keyed(docs: DataFrame, key: str, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Rows of ``docs`` that have an id, with a number ``key`` in place of ids that repeat: one
    number for each (id, text), in the order of ids. Null texts count as empty."""
    digest = free_name(docs, "text_digest")
    named = docs.where(F.col(doc_id).isNotNull()).withColumn(digest, F.md5(F.coalesce(F.col(text), F.lit("")).cast("binary")))
    numbers = dense_ids(named.select(F.col(doc_id).alias("k_id"), F.col(digest).alias("k_digest")).distinct(), "k_id", "k_digest").withColumnRenamed("id", "k_number")
    joined = named.join(numbers, (F.col(doc_id) == F.col("k_id")) & (F.col(digest) == F.col("k_digest")))
    return joined.select(*(F.col(f"`{c}`") for c in docs.columns), F.col("k_number").alias(key))
