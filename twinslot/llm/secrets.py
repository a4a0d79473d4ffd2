"""Secret scans in DataFrame functions: fixed patterns, and character Markov models.

The base kinds are patterns. A further kind is found by two first-order character models,
one of random strings and one of ordinary identifiers, trained from labelled samples by a
grouped count of character pairs; a run of credential characters is a secret when its
log-likelihood ratio says random. Scores are integers (thousandths of a nat), so they
don't depend on the order of a sum.
"""

from __future__ import annotations

from math import log

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import free_name

#: Kinds in their order, patterns, and the least length that counts.
ASSIGN = r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]+"
ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/=_-"
RUN = r"[A-Za-z0-9+/=_-]{20,}"
KINDS = ("assign", "access", "hex", "markov")
#: A run is random at this many thousandths of a nat a pair on average.
THRESHOLD = 400
#: A run that isn't random as a whole is searched for random stretches of ``LEAST`` characters;
#: one ends where the sum over the threshold has fallen by ``DROP`` thousandths of a nat.
LEAST, DROP = 20, 10_000
#: Characters of ``ALPHABET`` from here on separate words.
SEPARATORS_AFTER = 62
#: Steps of a scan whose outputs are one array; code points in a chunk of text (a power of two).
BLOCK, CHUNK = 64, 1024
SPANS = "array<struct<start:int,k:int,end:int,hit:string>>"
#: Bounds of the training sample: random strings and documents read for ordinary words.
RANDOM_STRINGS, SAMPLE_DOCS = 4000, 2000


def _let(value: Column, body) -> Column:
    """``body(value)`` with the value computed once, however often the body's lambdas use it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _constant(values: list[int]) -> Column:
    """An array of integers as one literal, which the optimizer folds."""
    return F.split(F.lit(",".join(map(str, values))), ",").cast("array<int>")


def _scan(n: Column, state: Column, kind: str, step) -> Column:
    """Left fold over 0 .. n - 1 that also lists: struct of the last state ``s`` and ``out``, an array of ``kind``.

    ``step(state, i)`` gives the next state, whether it lists something, and what. An array
    grows by copying, so outputs are collected in blocks of ``BLOCK`` steps and blocks in an array of arrays:
    time is in proportion to n for any text that fits a row."""
    none, nothing = F.array().cast(f"array<{kind}>"), F.array().cast(f"array<array<{kind}>>")

    def inner(acc: Column, i: Column) -> Column:
        now, some, one = step(acc["s"], i)
        return F.struct(now.alias("s"), F.when(some, F.concat(acc["out"], F.array(one))).otherwise(acc["out"]).alias("out"))

    def whole(size: Column) -> Column:
        def outer(acc: Column, at: Column) -> Column:
            done = F.aggregate(F.sequence(at, F.least(at + BLOCK, size) - 1), F.struct(acc["s"].alias("s"), none.alias("out")), inner)
            return _let(done, lambda r: F.struct(r["s"].alias("s"), F.concat(acc["out"], F.array(r["out"])).alias("out")))

        blocks = F.sequence(F.lit(0), F.greatest(size - 1, F.lit(0)), F.lit(BLOCK))
        folded = F.aggregate(blocks, F.struct(state.alias("s"), nothing.alias("out")), outer, lambda acc: F.struct(acc["s"].alias("s"), F.flatten(acc["out"]).alias("out")))
        return F.when(size > 0, folded).otherwise(F.struct(state.alias("s"), none.alias("out")))

    return _let(n, whole)


def _spans(text: Column, pattern: str, kind: str, keep, only: str | None = None) -> Column:
    """Spans of all matches that ``keep(hit)`` accepts: array of (start, k, end, hit).

    Matches and the stretches between them alternate, so offsets are running sums of
    lengths (in code points). ``only`` is a cheaper necessary pattern."""
    k = KINDS.index(kind)
    read = F.struct(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)).alias("h"), F.transform(F.split(text, pattern, -1), F.length).alias("g"))

    def placed(v: Column) -> Column:
        def step(at: Column, i: Column):
            end = at + F.get(v["g"], i) + F.length(F.get(v["h"], i))
            return end, F.lit(True), end

        one = lambda ends: lambda h, i: F.struct((F.get(ends, i) - F.length(h)).alias("start"), F.lit(k).alias("k"), F.get(ends, i).alias("end"), h.alias("hit"))
        made = _let(_scan(F.size(v["h"]), F.lit(0), "int", step)["out"], lambda ends: F.transform(v["h"], one(ends)))
        return F.filter(made, lambda s: keep(s["hit"]))

    return F.when(text.rlike(only or pattern), _let(read, placed)).otherwise(F.array().cast(SPANS))


def _chunks(text: Column) -> Column:
    """The text in strings of ``CHUNK`` code points, so that a place in it is reached without a walk from its start."""
    return F.regexp_extract_all(text, F.lit(f"(?s).{{1,{CHUNK}}}"), F.lit(0))


def _cut_out(chunks: Column, lo: Column, hi: Column) -> Column:
    """Code points ``lo`` to ``hi`` (exclusive) of the text that ``_chunks`` cut."""
    bits = CHUNK.bit_length() - 1
    first, last = F.shiftright(lo, bits), F.shiftright(hi - 1, bits)
    some = F.when(first == last, F.get(chunks, first)).otherwise(F.array_join(F.transform(F.sequence(first, last), lambda j: F.get(chunks, j)), ""))
    return F.when(hi <= lo, F.lit("")).otherwise(F.substr(some, lo.bitwiseAND(CHUNK - 1) + 1, hi - lo))


def _covered(spans: Column) -> Column:
    """For spans by start: ``out`` has the end of all spans before each, ``s`` the end of all."""
    return _scan(F.size(spans), F.lit(0), "int", lambda at, i: (F.greatest(at, F.get(spans, i)["end"]), F.lit(True), at))


def base_spans(text: Column) -> list[Column]:
    """Spans of the three fixed kinds, each an array. A run of [0-9a-f] is one match and
    every suffix of a failed access key fails too, so those two need no failed matches."""
    value = lambda hit: F.length(F.regexp_extract(hit, ASSIGN, 1)) >= 12
    return [
        _spans(text, ASSIGN, "assign", value),
        _spans(text, r"AKIA[A-Z0-9]{14,}", "access", lambda h: F.lit(True)),
        _spans(text, r"(?<![0-9a-f])[0-9a-f]{16,}", "hex", lambda h: F.lit(True), r"[0-9a-f]{16}"),
    ]


def samples(spark: SparkSession, docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Labelled strings ``(text, random, n)``, n times each: digests in two alphabets (random), and words of
    a bounded sample of documents, alone and joined as identifiers (ordinary).

    The sample is the ``SAMPLE_DOCS`` documents whose ids hash lowest; it grows no further."""
    ids = spark.range(RANDOM_STRINGS)
    digest = F.unhex(F.sha2(F.concat(F.lit("sample"), F.col("id").cast("string")), 256))
    strings = F.array(F.base64(digest), F.translate(F.base64(digest), "+/", "-_"), F.lower(F.hex(digest)))
    made = ids.select(F.explode(strings).alias("text"), F.lit(1).alias("random"), F.lit(1).cast("long").alias("n"))
    chosen = docs.select(F.col(doc_id).alias("id")).where("id IS NOT NULL").distinct().orderBy(F.xxhash64("id"), "id").limit(SAMPLE_DOCS)
    words = (
        docs.select(F.col(doc_id).alias("id"), F.col(text).alias("t"))
        .join(F.broadcast(chosen), "id", "left_semi")
        .select(F.explode(F.regexp_extract_all("t", F.lit("[A-Za-z]{2,}"), F.lit(0))).alias("w"))
        .where("length(w) < 20")
        .groupBy("w")
        .agg(F.count("*").alias("n"))
    )
    low = F.lower("w")
    ordinary = words.select(
        F.explode(
            F.array(
                F.concat(low, low), F.concat(F.upper("w"), F.upper("w")), F.concat(F.initcap(low), F.initcap(low)), F.concat(low, F.lit("_"), low),
                F.concat(F.upper("w"), F.lit("_"), F.upper("w")), F.concat(low, F.lit("-"), low), F.concat(low, F.lit("/"), low), F.concat(low, F.lit("-2024-01")),
            )
        ).alias("text"),
        F.lit(0).alias("random"), "n",
    )
    rules = spark.createDataFrame([(c * 200, 0, 20) for c in "-=_/+0"], "text string, random int, n long")
    return made.unionByName(ordinary).unionByName(rules)


def train(labelled: DataFrame) -> list[int]:
    """The table of log-likelihood ratios of character pairs, thousandths of a nat.

    ``labelled(text, random, n)``: n says how often a string counts. Counting is one grouped
    aggregation; what reaches the driver is at most two rows per pair of alphabet characters."""
    pair = F.explode(F.transform(F.sequence(F.lit(1), F.greatest(F.length("text") - 1, F.lit(1))), lambda i: F.substr(F.col("text"), i, F.lit(2))))
    rows = labelled.where("length(text) > 1").select("random", pair.alias("pair"), "n").groupBy("random", "pair").agg(F.sum("n").alias("n")).collect()
    place = {c: i for i, c in enumerate(ALPHABET)}
    n = len(ALPHABET)
    counts = [[[1.0] * n for _ in range(n)] for _ in range(2)]
    for r in rows:
        if len(r["pair"]) == 2 and r["pair"][0] in place and r["pair"][1] in place:
            counts[r["random"]][place[r["pair"][0]]][place[r["pair"][1]]] += r["n"]
    totals = [[sum(row) for row in table] for table in counts]
    return [
        round(1000 * (log(counts[1][a][b] / totals[1][a]) - log(counts[0][a][b] / totals[0][a]))) for a in range(n) for b in range(n)
    ]


def _codes(hit: Column):
    """The place in ``ALPHABET`` (from 1, 0 for others) of a string's character i (from 1), read from its bytes."""
    places = [0] * 256
    for i, c in enumerate(ALPHABET):
        places[ord(c)] = i + 1
    known = _constant(places)
    return lambda raw, i: F.get(known, F.ascii(F.substr(raw, i, F.lit(1)).cast("string")).bitwiseAND(255))


def pair_ratios(hit: Column, model: list[int]) -> Column:
    """The ratio of each character's pair with the one before it (the first's is zero), for
    strings over the alphabet."""
    table, n, code = _constant(model), len(ALPHABET), _codes(hit)

    def rated(raw: Column) -> Column:
        def one(i: Column) -> Column:
            was, now = code(raw, F.greatest(i - 1, F.lit(1))), code(raw, i)
            return F.when((i > 1) & (was > 0) & (now > 0), F.element_at(table, (was - 1) * n + now)).otherwise(0)

        return F.when(F.length(raw) > 0, F.transform(F.sequence(F.lit(1), F.length(raw)), one)).otherwise(F.array().cast("array<int>"))

    return _let(F.encode(hit, "utf-8"), rated)


def ratio(hit: Column, model: list[int]) -> Column:
    """Log-likelihood ratio of a string over the alphabet, thousandths of a nat."""
    return F.aggregate(pair_ratios(hit, model), F.lit(0).cast("long"), lambda acc, v: acc + v)


def _ends(spans: Column, last: Column) -> Column:
    return F.concat(spans, F.array(last))


def stretches(hit: Column, ratios: Column) -> Column:
    """Random stretches of a string over the alphabet with its ``pair_ratios``: array of (start, end), not overlapping.

    The ratios less the threshold are summed; a stretch runs from where the sum was
    last below zero to its peak. A stretch is widened to the separators around it if it
    is still random then. All steps are scans, linear in the string."""
    zero, pair = F.lit(0).cast("long"), "struct<start:int,end:int>"
    first = F.struct(zero.alias("sum"), zero.alias("peak"), F.lit(0).alias("lo"), F.lit(0).alias("hi"))
    span = lambda lo, hi: F.struct(lo.alias("start"), hi.alias("end"))
    code = _codes(hit)

    def found(x: Column) -> Column:  # x: ratios, bytes and length
        n = x["n"]
        separator = lambda i: code(x["raw"], i + 1) > SEPARATORS_AFTER

        def step(s: Column, i: Column):
            total = s["sum"] + F.get(x["v"], i) - THRESHOLD
            # The sum is lower here than anywhere since the peak, so nothing random spans this place.
            over = (total < 0) | (total < s["peak"] - DROP)
            best = total > s["peak"]
            now = F.struct(
                F.when(over, zero).otherwise(total).alias("sum"), F.when(over, zero).when(best, total).otherwise(s["peak"]).alias("peak"),
                F.when(over, i).otherwise(s["lo"]).alias("lo"), F.when(over | best, i + 1).otherwise(s["hi"]).alias("hi"),
            )
            return now, over & (s["peak"] > 0), span(s["lo"], s["hi"])

        raw = _let(_scan(n, first, pair, step), lambda r: _ends(r["out"], span(r["s"]["lo"], r["s"]["hi"])))

        def running(s: Column, i: Column):
            total = s + F.get(x["v"], i) - THRESHOLD
            return total, F.lit(True), total

        def left(s: Column, i: Column):
            at = F.when(separator(i), i + 1).otherwise(s)
            return at, F.lit(True), at

        def right(s: Column, i: Column):
            at = F.when(separator(n - 1 - i), n - 1 - i).otherwise(s)
            return at, F.lit(True), at

        marks = F.struct(
            _scan(n, zero, "bigint", running)["out"].alias("sums"), _scan(n, F.lit(0), "int", left)["out"].alias("left"), _scan(n, n, "int", right)["out"].alias("right"),
        )

        def widened(m: Column):
            def wide(p: Column) -> Column:
                lo = F.when(p["start"] > 0, F.get(m["left"], p["start"] - 1)).otherwise(0)
                hi = F.when(p["end"] < n, F.get(m["right"], n - 1 - p["end"])).otherwise(n)
                fine = F.get(m["sums"], hi - 1) - F.get(m["sums"], lo) >= 0
                return F.when(hi - lo < LEAST, span(p["start"], p["start"])).when(fine, span(lo, hi)).otherwise(p)

            return lambda some: F.filter(F.transform(some, wide), lambda p: p["end"] - p["start"] >= LEAST)

        long = F.filter(raw, lambda p: p["end"] > p["start"] + 1)
        return F.when(F.size(long) > 0, _let(marks, lambda m: widened(m)(long))).otherwise(F.array().cast(f"array<{pair}>"))

    def apart(some: Column) -> Column:  # two stretches widened over each other are one
        def step(s: Column, i: Column):
            one = F.get(some, i)
            meets = one["start"] < s["end"]
            return F.when(meets, span(s["start"], F.greatest(s["end"], one["end"]))).otherwise(one), ~meets & (s["end"] > 0), s

        joined = _scan(F.size(some), span(F.lit(0), F.lit(0)), pair, step)
        return F.when(F.size(some) > 0, _let(joined, lambda r: _ends(r["out"], r["s"]))).otherwise(some)

    bound = F.struct(ratios.alias("v"), F.encode(hit, "utf-8").alias("raw"), F.length(hit).alias("n"))
    return _let(_let(bound, found), apart)


def _runs(text: Column, base: Column) -> Column:
    """Runs of credential characters that base spans leave, ``LEAST`` or more each: array of (start, hit)."""
    pieces = "array<struct<start:int,hit:string>>"

    def around(x: Column) -> Column:  # x: base spans, what they cover, chunks of the text
        n = F.size(x["base"])
        lo = lambda i: F.when(i < n, F.get(x["cover"]["out"], i)).otherwise(x["cover"]["s"])
        hi = lambda i: F.when(i < n, F.get(x["base"], i)["start"]).otherwise(F.length(text))
        wide = F.filter(F.sequence(F.lit(0), n), lambda i: hi(i) - lo(i) >= LEAST)
        return F.transform(wide, lambda i: F.struct(lo(i).alias("start"), _cut_out(x["chunks"], lo(i), hi(i)).alias("hit")))

    parts = F.struct(base.alias("base"), _covered(base).alias("cover"), _chunks(text).alias("chunks"))
    gaps = F.when(F.size(base) > 0, _let(parts, around)).otherwise(F.array(F.struct(F.lit(0).alias("start"), text.alias("hit"))))
    moved = lambda g: F.transform(_spans(g["hit"], RUN, "markov", lambda h: F.lit(True)), lambda s: F.struct((g["start"] + s["start"]).alias("start"), s["hit"].alias("hit")))
    return F.when(text.rlike(RUN), F.flatten(F.transform(gaps, moved))).otherwise(F.array().cast(pieces))


def scan(df: DataFrame, model: list[int], text: str = "text") -> DataFrame:
    """``df`` with a column ``secrets`` (``secrets_`` if taken): struct of ``base`` and
    ``all``, arrays of (start, k, end, hit) by start, then kind; k indexes ``KINDS``.

    Offsets are code points of the whole text, end exclusive. Base spans always stay and
    are cut out of runs; what they leave of a run is a Markov span if it is random as a
    whole, else its random stretches are. Null and empty texts have no spans. Very long texts
    take time in proportion to their length and number of spans; one row's text and
    spans must fit a task's memory. Rows, repeats and other columns pass through unchanged; an
    empty table gives none.
    """
    name, raw, run = (free_name(df, x) for x in ("secrets", "secret_spans", "secret_runs"))
    body = F.coalesce(F.col(text), F.lit(""))
    out = df.withColumn(raw, F.sort_array(F.concat(*base_spans(body))))
    base, k = F.col(f"`{raw}`"), KINDS.index("markov")
    out = out.withColumn(run, _runs(body, base))

    def judged(p: Column) -> Column:
        n = F.length(p["hit"])

        def parts(v: Column) -> Column:
            random = F.aggregate(v, F.lit(0).cast("long"), lambda acc, x: acc + x) >= THRESHOLD * (n - 1)
            return F.when(random, F.array(F.struct(F.lit(0).alias("start"), n.alias("end")))).otherwise(stretches(p["hit"], v))

        def made(chunks: Column):
            one = lambda x: F.struct((p["start"] + x["start"]).alias("start"), F.lit(k).alias("k"), (p["start"] + x["end"]).alias("end"), _cut_out(chunks, x["start"], x["end"]).alias("hit"))
            return F.transform(_let(pair_ratios(p["hit"], model), parts), one)

        return _let(_chunks(p["hit"]), made)

    free = F.flatten(F.transform(F.col(f"`{run}`"), judged))
    return out.withColumn(name, F.struct(base.alias("base"), F.sort_array(F.concat(base, free)).alias("all"))).drop(raw, run)


def listed(spans: Column) -> Column:
    """``kind:start:end`` of each span, comma-joined."""
    kinds = F.array(*(F.lit(k) for k in KINDS))
    one = lambda s: F.concat_ws(":", F.element_at(kinds, s["k"] + 1), s["start"].cast("string"), s["end"].cast("string"))
    return F.array_join(F.transform(spans, one), ",")


def redact(text: Column, spans: Column, mark: str = "[SECRET]") -> Column:
    """``text`` with every span (sorted by start) replaced by ``mark`` (overlapping spans by one)."""

    def done(x: Column) -> Column:
        start = lambda i: F.get(x["spans"], i)["start"]
        before = lambda i: F.get(x["cover"]["out"], i)
        fresh = F.filter(F.sequence(F.lit(0), F.size(x["spans"]) - 1), lambda i: start(i) >= before(i))
        parts = F.transform(fresh, lambda i: F.concat(_cut_out(x["chunks"], before(i), start(i)), F.lit(mark)))
        return F.concat(F.array_join(parts, ""), _cut_out(x["chunks"], x["cover"]["s"], F.length(text)))

    bound = F.struct(spans.alias("spans"), _covered(spans).alias("cover"), _chunks(text).alias("chunks"))
    return F.when(F.size(spans) > 0, _let(bound, done)).otherwise(text)
