"""Corpus pipeline: five stages over ``documents``, each written and read again.

All stages ignore the names of further columns: those pass through, however they clash."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from twinslot.llm import langid, packing, quality, secrets, simhash
from twinslot.llm.common import cut, free_name
from twinslot.shipping import ship
from twinslot.stages import discard, scratch


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in one of the languages that ``lang`` names.

    The labels train the text model, so they are no evidence: text and source decide. Null and empty
    texts and texts without letters go; rows that repeat are judged alike; a null ``lang`` or
    source is no label and no evidence. If no row has a label no language is known and
    all rows stay. Very long texts are read in chunks; an empty table gives none."""
    ship(spark)
    model = langid.train(docs)
    if not model.languages:
        return docs
    found = langid.identify(docs, model, host=F.col("source"))
    return found.where(F.col(f"`{found.columns[-1]}`.kept")).select(*docs.columns)


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the production policy keeps.

    A null text counts as empty and fails, like every text of under 20 words. Only the text
    decides, so null ids and repeated rows are judged like others. Very long texts are measured
    whole; an empty table gives none."""
    ship(spark)
    entries = quality.ledger(docs)
    kept = quality.apply_policy(entries, bits=f"{entries.columns[-1]}.bits")
    return kept.where(F.col(kept.columns[-1])).select(*docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies: the one with the smallest id.

    Documents without an id stay. Rows that repeat an id and its text are one document; rows that
    repeat an id with another text are documents of their own (of two that are near copies, the one
    whose text has the smaller digest stays). Null texts count as empty, and empty texts as copies of each
    other. Very long texts are compared whole; an empty table gives none."""
    ship(spark)
    named = docs.where("doc_id IS NOT NULL")
    key = "doc_id"
    if repeated := not named.groupBy("doc_id").count().where("count > 1").isEmpty():
        key = free_name(docs, "document")
        named = cut(simhash.keyed(named, key), "keyed", "zstd")
    first = simhash.survivors(named, doc_id=key)
    # The ids are the side that is hashed, so texts are shuffled once and never sorted.
    kept = named.join(first.hint("shuffle_hash"), F.col(f"`{key}`") == F.col("id"), "left_semi")
    if repeated:
        kept = kept.dropDuplicates([key])
    return kept.select(*docs.columns).unionByName(docs.where("doc_id IS NULL"))


def secret_scan(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document, with its secrets replaced by a mark; ``n_chars`` (where there is such a
    column) becomes the length of the new text.

    Null texts stay null, with a null ``n_chars``; empty texts have no secrets. Rows and repeats all
    stay. Very long texts take time in proportion to their length; an empty table gives none."""
    ship(spark)
    found = secrets.scan(docs, secrets.train(secrets.samples(spark, docs)))
    spans = F.col(f"`{found.columns[-1]}`.all")
    text = free_name(found, "redacted")
    done = found.withColumn(text, secrets.redact(F.col("text"), spans))
    return done.select(
        *(
            F.col(text).alias(c) if c == "text" else F.length(text).cast("long").alias(c) if c == "n_chars" else F.col(f"`{c}`")
            for c in docs.columns
        )
    )


def best_fit_packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sequences of 2048 tokens: ``(doc_id, piece, start, length, ids_crc32, sequence_id, offset)``.

    A null or empty text is one piece with the final id; null ids stay null; rows that repeat are packed
    as often as they occur. Very long texts are cut into pieces of 2048; an empty table gives none."""
    ship(spark)
    return packing.pack(docs, public_tokenizers.path("word_bpe_49k.json"), 2048)


STAGES = [
    ("language_id", language_id),
    ("quality_rules", quality_rules),
    ("simhash_near_dedup", near_duplicates),
    ("secret_scan", secret_scan),
    ("best_fit_packing", best_fit_packing),
]

#: Language models and tokenizers aren't SQL; tests/llm compares stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written to the shared folder and read again. What a stage
    wrote besides its result, and the result before it, are deleted when the next result is written."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        before = docs
        with scratch() as keep:
            docs = keep(cut(stage(spark, docs, sf_dir), name, "zstd"))
        discard(before)
    return STAGES[-1][1](spark, docs, sf_dir)
