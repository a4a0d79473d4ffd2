"""Language identification by fusing evidence.

Log-likelihoods of the text under character-trigram models are added to the log
probabilities of the declared markup language and of the address suffix, and to a prior
of the host. Host priors come from grouped aggregation of text-only votes, smoothed
towards the host's parent domain, which is smoothed towards all documents.
"""

from __future__ import annotations

from math import log

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import worker
from .common import cut, discard, free_name

BUCKETS, CHUNK = 1 << 15, 1 << 18
#: A classifier is fitted on at most this many labelled documents.
SAMPLE_DOCS = 4000
#: Text evidence counts as that of at most so many trigrams (they aren't independent).
EFFECTIVE = 200
#: How often a declaration and a suffix tell the truth; weight of the parent in a prior.
DECLARED_RIGHT, SUFFIX_RIGHT, PARENT_WEIGHT = 0.9, 0.8, 20.0
MIN_POSTERIOR = 0.5
#: A text is in none of the languages if its mean score is further than this share of the way from
#: what its language's training text scores to what trigrams score that training never saw. Both ends
#: move with the amount of training data, so the share doesn't depend on it: held-out texts of sf0.1
#: stay below 0.38 with 4000 training documents and below 0.57 with 60, random letters are above 0.9.
FLOOR_SHARE = 0.7
#: Host priors are broadcast up to so many hosts, else joined by a salted shuffle.
BROADCAST_HOSTS, SALTS = 100_000, 16
#: Country suffixes of addresses and their languages.
SUFFIXES = {"uk": "en", "us": "en", "au": "en", "ie": "en", "nz": "en", "de": "de", "at": "de", "li": "de", "fr": "fr", "mc": "fr", "es": "es", "mx": "es", "ar": "es", "co": "es", "cl": "es", "pe": "es"}

_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_LETTER = np.zeros(256, bool)
_LETTER[97:123] = True
_LETTER[128:] = True


def _trigrams(text: str | None):
    """Buckets of the byte trigrams that hold a letter, in chunks of bounded size."""
    raw = np.frombuffer(f" {text or ''} ".encode("utf-8", "surrogatepass"), np.uint8)
    for at in range(0, len(raw) - 2, CHUNK):
        low = _LOWER[raw[at : at + CHUNK + 2]]
        letter = _LETTER[low]
        some = letter[:-2] | letter[1:-1] | letter[2:]
        code = low[:-2].astype(np.uint32) << 16 | low[1:-1].astype(np.uint32) << 8 | low[2:]
        yield (code * np.uint32(2654435761) >> np.uint32(17))[some]


class Model:
    """Languages, their tables of log-probabilities (thousandths of a nat) and the least mean that
    a text of each may have (by default any)."""

    def __init__(self, languages: list[str], table: np.ndarray, floors: list[int] | None = None):
        self.languages, self.table = languages, table
        self.floors = floors if floors is not None else table.min(axis=1).tolist()


def train(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", lang: str = "lang", sample: int = SAMPLE_DOCS) -> Model:
    """Fit on the ``sample`` labelled documents whose ids hash lowest."""
    ids = docs.where(F.col(lang).isNotNull() & F.col(doc_id).isNotNull()).select(F.col(doc_id).alias("id")).distinct()
    chosen = ids.orderBy(F.xxhash64("id"), "id").limit(sample)
    labelled = docs.select(F.col(doc_id).alias("id"), F.col(text).alias("t"), _tag(F.col(lang)).alias("l")).where("l <> ''")
    labelled = labelled.join(F.broadcast(chosen), "id", "left_semi").select("l", "t")

    def count(batches):
        tables: dict[str, np.ndarray] = {}
        for batch in batches:
            for name, words in zip(batch.column(0).to_pylist(), batch.column(1)):
                table = tables.setdefault(name, np.zeros(BUCKETS, np.int64))
                for some in _trigrams(words.as_py()):
                    table += np.bincount(some, minlength=BUCKETS)
        for name, table in tables.items():
            at = np.flatnonzero(table)
            yield pa.RecordBatch.from_arrays([pa.array([name] * len(at)), pa.array(at, pa.int32()), pa.array(table[at], pa.int64())], ["l", "bucket", "n"])

    counts = labelled.mapInArrow(count, "l string, bucket int, n long").groupBy("l", "bucket").agg(F.sum("n").alias("n"))
    rows = counts.collect()  # at most languages x buckets rows
    languages = sorted({r["l"] for r in rows})
    table = np.full((max(1, len(languages)), BUCKETS), 0.5)
    for r in rows:
        table[languages.index(r["l"]), r["bucket"]] += r["n"]
    total = table.sum(axis=1, keepdims=True)
    scores = 1000 * np.log(table / total)
    seen, unseen = table - 0.5, 1000 * np.log(0.5 / total[:, 0])
    expected = (seen * scores).sum(axis=1) / np.maximum(seen.sum(axis=1), 1)
    floors = np.floor(expected + FLOOR_SHARE * (unseen - expected)).astype(int).tolist()
    return Model(languages, np.round(scores).astype(np.int32), floors)


def _tag(declared: Column) -> Column:
    """Primary part of a language tag, lower case; empty if there is none."""
    return F.coalesce(F.regexp_extract(F.lower(F.trim(declared)), "^([a-z]{2,3})(?:[-_].*)?$", 1), F.lit(""))


def _score(spark, model: Model):
    shared = spark.sparkContext.broadcast(model.table)  # languages x 32768 integers

    def scores(texts: pa.Array) -> pa.Array:
        worker.enter("langid")
        table = shared.value
        rows, sizes = [], []
        for t in texts:
            total, n = np.zeros(len(table), np.int64), 0
            for some in _trigrams(t.as_py()):
                total += table[:, some].sum(axis=1, dtype=np.int64)
                n += len(some)
            rows.append(total.tolist())
            sizes.append(n)
        return pa.StructArray.from_arrays([pa.array(rows, pa.list_(pa.int64())), pa.array(sizes, pa.int64())], ["ll", "n"])

    return F.arrow_udf(scores, "ll array<long>, n long")


def _argmax(values: Column) -> Column:
    return F.array_position(values, F.array_max(values)).cast("int")


def identify(
    df: DataFrame, model: Model, text: str = "text", declared: Column | None = None, suffix: Column | None = None,
    host: Column | None = None, parent: Column | None = None,
) -> DataFrame:
    """``df`` with a struct ``language`` (``language_`` if taken): lang, posterior, n, mean, kept.

    Missing evidence (a null declaration, suffix or host, or a value outside the model)
    adds nothing; a null host has its parent's prior, without that the general one. A
    text without letters has no likelihood; it isn't kept, nor is one whose posterior is
    below ``MIN_POSTERIOR`` or whose mean log-likelihood is below its language's floor
    (see ``FLOOR_SHARE``). Ties go to the first language in order. Very long texts are read in
    chunks of bounded size. Rows, repeats and other columns pass through; an empty table gives
    none. A model without languages keeps nothing. ``declared`` must be evidence apart from the
    labels that the model was trained on.
    """
    spark, n_lang = df.sparkSession, len(model.languages)
    name = free_name(df, "language")
    if not n_lang:
        return df.withColumn(name, F.expr("named_struct('lang', cast(null as string), 'posterior', 0d, 'n', 0l, 'mean', 0l, 'kept', false)"))
    s, h, p, jh, jp, js, prior_name = (free_name(df, x) for x in ("lid_score", "lid_host", "lid_parent", "lid_jh", "lid_jp", "lid_js", "lid_prior"))
    none = F.lit(None).cast("string")
    scored = df.withColumns({s: _score(spark, model)(F.col(text)), h: F.coalesce(host if host is not None else none, F.lit("")), p: F.coalesce(parent if parent is not None else none, F.lit(""))})
    votes = scored.where(F.col(f"`{s}`.n") > 0).select(F.col(f"`{h}`").alias("h"), F.col(f"`{p}`").alias("p"), _argmax(F.col(f"`{s}`.ll")).alias("v"))
    sums = [F.count_if(F.col("v") == i + 1).alias(f"n{i}") for i in range(n_lang)]
    hosts = cut(votes.groupBy("h", "p").agg(*sums), "hosts")  # deleted when the priors are written
    add = [F.sum(f"n{i}").alias(f"p{i}") for i in range(n_lang)]
    whole = hosts.agg(*add).first()
    n_all = [(whole[i] or 0) + 1.0 for i in range(n_lang)]
    general = [x / sum(n_all) for x in n_all]
    parents = hosts.groupBy("p").agg(*add)
    a = PARENT_WEIGHT
    total = lambda c: sum((F.col(f"{c}{i}") for i in range(1, n_lang)), F.col(f"{c}0"))
    by_parent = [(F.col(f"p{i}") + a * general[i]) / (total("p") + a) for i in range(n_lang)]
    by_host = [F.when(F.col("h") == "", by_parent[i]).otherwise((F.col(f"n{i}") + a * by_parent[i]) / (total("n") + a)) for i in range(n_lang)]
    priors = cut(hosts.join(parents, "p").select(F.col("h").alias(jh), F.col("p").alias(jp), F.array(*(F.log(x) for x in by_host)).alias(prior_name)), "priors")
    discard(hosts)
    if priors.count() <= BROADCAST_HOSTS:
        joined = scored.join(F.broadcast(priors), (F.col(h) == F.col(jh)) & (F.col(p) == F.col(jp)), "left")
    else:
        salt = free_name(df, "lid_salt")
        spread = priors.withColumn(js, F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        salted = scored.withColumn(salt, F.pmod(F.xxhash64(F.col(text)), F.lit(SALTS)).cast("int"))
        joined = salted.join(spread, (F.col(h) == F.col(jh)) & (F.col(p) == F.col(jp)) & (F.col(salt) == F.col(js)), "left").drop(salt, js)
    prior = F.coalesce(F.col(prior_name), F.array(*(F.lit(log(x)) for x in general)))

    def told(value: Column | None, right: float) -> list[Column]:
        if value is None or n_lang < 2:
            return [F.lit(0.0)] * n_lang
        known = value.isin(model.languages)
        wrong = (1 - right) / (n_lang - 1)
        return [F.when(known, F.when(value == x, log(right)).otherwise(log(wrong))).otherwise(0.0) for x in model.languages]

    n = F.col(f"`{s}`.n")
    weight = F.least(n, F.lit(EFFECTIVE)) / F.greatest(n, F.lit(1)) / 1000.0
    d, u = told(_tag(declared) if declared is not None else None, DECLARED_RIGHT), told(suffix, SUFFIX_RIGHT)
    sums = F.array(*(F.element_at(F.col(f"`{s}`.ll"), i + 1) * weight + F.element_at(prior, i + 1) + d[i] + u[i] for i in range(n_lang)))
    f = free_name(df, "lid_fused")
    fused = joined.withColumn(f, sums)
    best, at = F.array_max(F.col(f)), _argmax(F.col(f))
    posterior = F.round(1 / F.aggregate(F.col(f), F.lit(0.0), lambda acc, x: acc + F.exp(x - best)), 6)
    mean = F.floor(F.element_at(F.col(f"`{s}`.ll"), at) / F.greatest(n, F.lit(1)))
    lang = F.element_at(F.array(*(F.lit(x) for x in model.languages)), at)
    floor = F.element_at(F.array(*(F.lit(int(x)) for x in model.floors)), at)
    kept = (n > 0) & (posterior >= MIN_POSTERIOR) & (mean >= floor)
    result = F.struct(lang.alias("lang"), posterior.alias("posterior"), n.alias("n"), mean.alias("mean"), kept.alias("kept"))
    return fused.withColumn(name, result).select(*(F.col(f"`{c}`") for c in df.columns), name)


def suffix_language(host: Column) -> Column:
    """Language of a host's country suffix, null where it has none."""
    suffixes = F.create_map(*(F.lit(x) for pair in SUFFIXES.items() for x in pair))
    return F.try_element_at(suffixes, F.coalesce(F.regexp_extract(F.lower(host), r"\.([a-z]+)\.?$", 1), F.lit("")))


def pages_evidence(url: Column, html: Column) -> dict[str, Column]:
    """Evidence of a raw web page: visible text, declared language, suffix, host and parent domain."""
    host = F.lower(F.regexp_extract(F.coalesce(url, F.lit("")), r"^[a-zA-Z][a-zA-Z0-9+.-]*://([^/?#:]*)", 1))
    body = F.coalesce(html, F.lit(""))
    bare = F.regexp_replace(body, r"(?is)<(script|style)\b.*?</\1\s*>|<!--.*?-->", " ")
    return {
        "text": F.regexp_replace(bare, r"(?s)<[^>]*>", " "),
        "declared": F.regexp_extract(body, r"""(?i)<html\b[^>]*\blang\s*=\s*["']?([A-Za-z-]+)""", 1),
        "suffix": suffix_language(host),
        "host": host,
        "parent": F.regexp_extract(host, r"([^.]+\.[^.]+)$", 1),
    }
