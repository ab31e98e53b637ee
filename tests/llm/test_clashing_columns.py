"""Extra columns, whatever their names, change nothing."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from tracedigest.llm import bin_packing, decontaminate, histogram_shard, language_id, preference_format, probminhash, secret_scan, substring_dedup, url_filter, vamana

SF = "/root/testdata/sf0.001"
NAMES = ["tag", "spans", "items", "n_words", "k0", "row", "h", "key", "shard", "salt", "bucket", "size", "rep", "sig", "keys", "label", "word", "n", "lang_pred", "score", "a", "b", "s1", "class_id", "length", "piece", "host", "path", "v", "block", "base", "repo", "owner", "p", "turns"]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet").filter("doc_id < 60").persist()


def crowded(df):
    return df.withColumns({c: F.lit("x") for c in NAMES if c not in df.columns})


def same(a, b):
    assert sorted(map(str, a.collect())) == sorted(map(str, b.collect()))


def test_document_operators(spark, docs):
    more = crowded(docs)
    bench = spark.read.parquet(f"{SF}/benchmark.parquet")
    same(substring_dedup.dedup(docs, cell_bits=20), substring_dedup.dedup(more, cell_bits=20))
    same(decontaminate.hits(docs, bench), decontaminate.hits(more, crowded(bench)))
    same(secret_scan.scan(docs, owner=F.col("source")), secret_scan.scan(more, owner=F.col("source")))
    same(secret_scan.redact(docs), secret_scan.redact(more).select(*docs.columns))
    assert decontaminate.clean(more, bench).columns == more.columns == secret_scan.redact(more).columns == probminhash.keep_one(more).columns
    same(histogram_shard.histogram_shards(docs), histogram_shard.histogram_shards(more))
    a, b = (bin_packing.pack_documents(x).select("doc_id", "piece", "length", "ids_crc32") for x in (docs, more))
    same(a, b)
    same(probminhash.dedup(docs).select("doc_id", "class_id"), probminhash.dedup(more).select("doc_id", "class_id"))
    model = language_id.train(more, sample_rows=50, steps=1)
    same(language_id.predict(docs, model), language_id.predict(more, model))


def test_other_tables(spark):
    pages = spark.read.parquet(f"{SF}/pages.parquet")
    same(url_filter.judge(pages), url_filter.judge(crowded(pages)))
    vectors = spark.read.parquet(f"{SF}/embeddings.parquet")
    same(vamana.nearest(vectors), vamana.nearest(crowded(vectors)))
    turns = spark.read.parquet(f"{SF}/conversations.parquet")
    same(preference_format.format_pairs(preference_format.swapped_reply_pairs(turns)), preference_format.format_pairs(preference_format.swapped_reply_pairs(crowded(turns))))


def test_pipeline_stages(spark, docs):
    for name, stage in corpus_pipeline.STAGES[:4]:
        assert stage(spark, crowded(docs), SF).columns == corpus_pipeline.COLUMNS, name
