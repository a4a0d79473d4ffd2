"""The opN_ queries: each operator on its whole table with production parameters."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, chat, langid, lm, packing, quality, secrets, simhash, topk, warc
from .common import table


def op1_lm_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Trigram stupid-backoff scores of all documents against all documents."""
    return lm.score(table(spark, sf_dir, "documents", "doc_id", "text"))


def op2_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rule ledger of all documents under the production policy."""
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    entries = quality.apply_policy(quality.ledger(docs))
    base = quality.POLICIES[0].rejects(F.col("ledger.bits"))
    return entries.select("doc_id", "ledger.*", base.alias("base_failed"), (F.col("kept") & ~base).alias("kept"))


def op2_ablations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What each policy rejects, whole and without each rule, from the stored bits."""
    return quality.ablations(quality.ledger(table(spark, sf_dir, "documents", "doc_id", "text")))


def op3_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprints of three-word shingles and components at two differing bits."""
    return simhash.near_groups(table(spark, sf_dir, "documents", "doc_id", "text"), radius=2, shingle=3)


def op4_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The 20 best rows for every twentieth embedding."""
    return topk.top_k(table(spark, sf_dir, "embeddings", "vec_id", "embedding"), k=20, every=20)


def op5_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Base and Markov spans of all documents."""
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    found = secrets.scan(docs, secrets.train(secrets.samples(spark, docs)))
    n = lambda k: F.size(F.filter("secrets.base", lambda s: s["k"] == k)).cast("long")
    return found.select(
        "doc_id", n(0).alias("n_assign"), n(1).alias("n_access"), n(2).alias("n_hex"),
        F.sha2(secrets.listed(F.col("secrets.base")), 256).alias("base_sha256"), secrets.listed(F.col("secrets.all")).alias("spans"),
    )


def op6_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Byte-level ids of all documents, and the bytes that they decode to."""
    path, pattern = public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    coded = docs.select("doc_id", bpe.encode(F.col("text"), path, pattern).alias("ids"))
    back = coded.select("doc_id", "ids", bpe.decode(F.col("ids"), path, pattern).alias("bytes"))
    return back.select(
        "doc_id",
        F.size("ids").cast("long").alias("n_tokens"),
        F.sha2(F.array_join(F.col("ids").cast("array<string>"), " "), 256).alias("ids_sha256"),
        F.sha2("bytes", 256).alias("decoded_sha256"),
    )


def op7_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Language of all documents: text, and the source as host. Their ``lang`` labels the training
    sample, so it is no evidence."""
    docs = table(spark, sf_dir, "documents", "doc_id", "text", "lang", "source")
    found = langid.identify(docs, langid.train(docs), host=F.col("source"))
    return found.select("doc_id", "language.*")


def op7_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Language of all web pages, with all four kinds of evidence."""
    model = langid.train(table(spark, sf_dir, "documents", "doc_id", "text", "lang"))
    pages = table(spark, sf_dir, "pages", "page_id", "url", "html")
    seen = pages.select("page_id", *(v.alias(k) for k, v in langid.pages_evidence(F.col("url"), F.col("html")).items()))
    found = langid.identify(seen, model, declared=F.col("declared"), suffix=F.col("suffix"), host=F.col("host"), parent=F.col("parent"))
    return found.select("page_id", "language.*")


def op8_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Archive of all pages, written and read back."""
    paths = warc.write(table(spark, sf_dir, "pages", "page_id", "url", "html"), min_bytes=0)
    return warc.read(spark, *paths)


def op9_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rendered maximal conversations."""
    return chat.render(table(spark, sf_dir, "conversations", "conv_id", "turn", "role", "text"))


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in sequences of 2048 tokens."""
    return packing.pack(table(spark, sf_dir, "documents", "doc_id", "text"), public_tokenizers.path("word_bpe_49k.json"), 2048)


def queries() -> dict:
    return {k: f for k, f in globals().items() if k.startswith("op") and k[2].isdigit()}
