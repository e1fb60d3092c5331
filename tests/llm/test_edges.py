"""Every text operator on empty tables, nulls, empty, short and long texts, repeated rows and columns with clashing names."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from privsurv.llm import chunk_dedup, fingerprints, html_extract, jaccard_join, mixing, packing, queries, sharding, suffix_dedup, toxicity, url_trust
from privsurv.llm.common import ready

DOCS = "doc_id long, text string, lang string, source string, n_chars long, h string, cell string, key string, kept string, rank string, text_sha256 string, n string, p string, leaf string, begin string"


def docs(spark):
    long = " ".join(f"word{i % 997} and more." for i in range(30_000))
    texts = [None, "", " \t\n", "one", "two words", "same text here of six words", "same  text here\nof six words", "!!! ???", "ünïcödé 日本語 \U0001f600 x", long, long + " end", "a" * 3000]
    rows = [(i, t) for i, t in enumerate(texts)] + [(None, "null id"), (None, None), (5, "same text here of six words"), (5, "another text with the id five")]
    return spark.createDataFrame([(i, t, None, None, None, *["x"] * 10) for i, t in rows], DOCS)


def labels(spark):
    return spark.createDataFrame([(1, 1, 0), (4, 0, 0), (5, 1, 1), (5, 1, 0), (9, None, 1), (None, 1, 1), (99, 1, None)], "doc_id long, quality int, toxic int")


OPS = {
    "toxicity": lambda s, d: toxicity.toxicity(d, labels(s)),
    "spans": lambda s, d: toxicity.score_documents(d, toxicity.train_on(d, labels(s))),
    "join": lambda s, d: jaccard_join.jaccard_join(d),
    "bands": lambda s, d: fingerprints.near_copies(d),
    "fingerprints": lambda s, d: fingerprints.with_edits(d),
    "repeats": lambda s, d: suffix_dedup.remove_repeats(d, keep_text=True),
    "exact": lambda s, d: chunk_dedup.exact_dedup(d),
    "mixing": lambda s, d: mixing.mix_documents(d, labels(s)),
    "sharding": lambda s, d: sharding.shard(d),
}


@pytest.mark.parametrize("name", OPS)
def test_documents(spark, name):
    ready(spark)
    d = docs(spark)
    assert OPS[name](spark, d).count() == d.count()
    assert OPS[name](spark, d.where("false")).count() == 0


def test_packing(spark):
    ready(spark)
    d = docs(spark)
    out = packing.pack(d, queries.tokenizer())
    assert out.where("piece = 0").count() == d.count()
    assert packing.pack(d.where("false"), queries.tokenizer()).count() == 0
    assert packing.pack(d.where("text is null"), queries.tokenizer()).agg(F.sum("length")).first()[0] == 2


def test_pages(spark):
    ready(spark)
    rows = [(1, None, None), (2, "no scheme", ""), (3, "HTTP://A.Org/x?y", "<p>hi"), (3, "HTTP://A.Org/x?y", "<p>hi"), (None, "ftp://b.net", "plain &amp; text"), (4, "http://c.com/de/z#q", "<div" * 500), (5, "https://d.net/" + "x" * 5000, "<b>" * 3000 + "deep")]
    p = spark.createDataFrame([(*r, "x", "y") for r in rows], "page_id long, url string, html string, host string, verdict string")
    got = html_extract.extract_pages(p)
    assert got.count() == len(rows) and got.where("text is null").isEmpty()
    assert html_extract.extract_pages(p.where("false")).count() == 0
    url = {(r.page_id, r.host, r.path, r.rule, r.verdict) for r in url_trust.url_filter(p).collect()}
    assert (3, "a.org", "/x", "org/", "allow") in url and (4, "c.com", "/de/z", "com/de/", "block") in url and (1, "", "", None, "allow") in url
    assert url_trust.url_filter(p.where("false")).count() == 0


def test_pipeline_stages_keep_columns_and_rows_without_faults(spark, tmp_path):
    d = docs(spark)
    folder = str(tmp_path)
    d.write.parquet(f"{folder}/documents.parquet")
    labels(spark).write.parquet(f"{folder}/labels.parquet")
    now = spark.read.parquet(f"{folder}/documents.parquet")
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, now, folder)
        out.write.parquet(f"{folder}/{k}")
        out = spark.read.parquet(f"{folder}/{k}")
        if name != "packing":
            assert out.columns == d.columns and 0 < out.count()
            assert stage(spark, now.where("false"), folder).count() == 0
            now = out
    assert out.columns[:2] == ["doc_id", "piece"]
    assert 4 <= len(corpus_pipeline.STAGES) <= 5
