"""Registered queries against SQL, and the pipeline."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from twinslot.llm import oracles

from ..conftest import DATA


@pytest.mark.parametrize("name", sorted(oracles.oracle_sql()))
def test_query_equals_its_sql(same_as_sql, name):
    same_as_sql(name)


def test_pipeline(spark):
    docs = spark.read.parquet(f"{DATA}/sf0.001/documents.parquet")
    columns = docs.columns
    at, seen = docs, {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, at, f"{DATA}/sf0.001")
        assert out.columns == columns
        rows = {r["doc_id"]: r for r in out.collect()}
        assert set(rows) <= {r["doc_id"] for r in at.select("doc_id").collect()}
        seen[name], at = rows, out
    good = {r["doc_id"] for r in spark.read.parquet(f"{DATA}/sf0.001/labels.parquet").where("quality = 1 AND toxic = 0").collect()}
    long = {r["doc_id"] for r in docs.where(F.size(F.split("text", r"\s+")) >= 25).collect()}
    assert len(good & long - set(seen["quality_rules"])) <= 0.02 * len(good & long)
    assert seen["secret_scan"].keys() == seen["simhash_near_dedup"].keys()
    assert not any("AKIA" in (r["text"] or "") for r in seen["secret_scan"].values())
    packed = corpus_pipeline.run(spark, f"{DATA}/sf0.001")
    assert {r["doc_id"] for r in packed.select("doc_id").distinct().collect()} == set(seen["secret_scan"])


def test_stages_on_odd_documents(spark):
    rows = [(1, None, None, None, None), (1, None, None, None, None), (None, "x", "en", "s", 1), (2, "", "en", None, 0), (3, "a " * 30, "en", "s", 60)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").withColumn("kept", F.lit(1)).withColumn("ledger", F.lit("x"))
    for df in (docs, docs.where("doc_id > 99")):
        for _, stage in corpus_pipeline.STAGES[:-1]:
            out = stage(spark, df, f"{DATA}/sf0.001")
            assert out.columns == df.columns and out.count() <= df.count()
        assert corpus_pipeline.STAGES[-1][1](spark, df, f"{DATA}/sf0.001").count() == df.count()


def test_documents_that_share_an_id(spark):
    """Rows of one id with other texts are documents of their own; equal rows are one."""
    long = " ".join(f"w{i}" for i in range(60))
    other, near = " ".join(f"v{i}" for i in range(60)), long.replace("w30", "x")
    rows = [(5, long), (5, other), (5, other), (3, near), (7, other + " z"), (8, None), (8, ""), (None, long)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("document", F.lit("clash"))
    out = corpus_pipeline.near_duplicates(spark, docs, "")
    assert out.columns == docs.columns
    got = sorted((r["doc_id"] or 0, r["text"] or "") for r in out.collect())
    assert got == sorted([(0, long), (3, near), (5, other), (8, "")])


def test_pages_query(spark, monkeypatch):
    """op7_pages on pages whose language is plain from text, declaration, suffix or host alone."""
    from twinslot.llm import langid, queries

    docs = spark.read.parquet(f"{DATA}/sf0.001/documents.parquet")
    text = {r["lang"]: r["text"] for r in docs.where("length(text) > 300").orderBy("doc_id").collect()}
    rows = [
        (1, "http://a.example/x", f"<html><style>p {{}} le la les</style><!-- der die das --><p>{text['en']}</p></html>"),
        (2, "http://b.example/x", f"<p>{text['de']}</p><script>the of and</script>"),
        (3, "http://c.fr/", "<html lang='fr-CA'><p>1 a 2</p></html>"),
        (4, "https://d.example.es:80/", '<HTML class=x LANG="es">'),
        (5, None, None),
    ]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    monkeypatch.setattr(queries, "table", lambda s, d, name, *columns: (pages if name == "pages" else docs).select(*columns))
    out = {r["page_id"]: r for r in queries.op7_pages(spark, "").collect()}
    assert set(out) == {1, 2, 3, 4, 5}
    assert (out[1]["lang"], out[2]["lang"], out[3]["lang"]) == ("en", "de", "fr") and out[1]["kept"] and out[2]["kept"]
    assert out[4]["n"] == 0 and not out[4]["kept"] and out[4]["lang"] == "es" and not out[5]["kept"]
    seen = pages.select("page_id", *(v.alias(k) for k, v in langid.pages_evidence(F.col("url"), F.col("html")).items()))
    seen = {r["page_id"]: r for r in seen.collect()}
    assert (seen[3]["declared"], seen[3]["suffix"], seen[3]["host"], seen[3]["parent"]) == ("fr-CA", "fr", "c.fr", "c.fr")
    assert (seen[4]["declared"], seen[4]["suffix"], seen[4]["host"], seen[4]["parent"]) == ("es", "es", "d.example.es", "example.es")
    assert "le la les" not in seen[1]["text"] and "der die" not in seen[1]["text"] and "the of" not in seen[2]["text"]
