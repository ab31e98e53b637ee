"""The corpus pipeline: five stages over `documents`, each written and read again before the next.

Language identification (texts without a letter, and those of no one language go), near-duplicates (one document of each class stays),
benchmark decontamination (documents that hold a benchmark window go), secret scans (found spans are masked), packing.
Nulls and odd rows: as the operators say; a null text has no letter, so it goes in the first stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tracedigest.llm import bin_packing, decontaminate, language_id, probminhash, secret_scan
from tracedigest.llm.common import materialize

#: Texts of one language score near 1; evenly mixed ones, and letters that are no words, less than this.
LEAST_SCORE = 0.4
COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents with a predicted language of score LEAST_SCORE or more; learns from the labelled training folds."""
    model = language_id.train(docs.filter(~language_id.held_out()))
    out = language_id.predict(docs, model, keep=tuple(COLUMNS))
    return out.filter((F.col("lang_pred") != "und") & (F.col("score") >= LEAST_SCORE)).select(*[F.col(f"k{i}").alias(c) for i, c in enumerate(COLUMNS)])


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document with the smallest id of each class, once if its row is repeated; rows with a null id stay."""
    return probminhash.keep_one(docs).select(*COLUMNS)


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents in which a benchmark window occurs."""
    return decontaminate.clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"), mode="document").select(*COLUMNS)


def secret_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Masks every found span; n_chars follows the text."""
    out = secret_scan.redact(docs, repo=F.concat_ws("/", "source", "lang"), owner=F.col("source"))
    return out.withColumn("n_chars", F.when(F.col("text").isNotNull(), F.length("text").cast("long"))).select(*COLUMNS)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Places every piece of every document left in sequences of at most 1,024 tokens."""
    return bin_packing.pack_documents(docs)


STAGES = [
    ("language_id", language_stage),
    ("near_duplicates", near_duplicate_stage),
    ("decontamination", decontamination_stage),
    ("secrets", secret_stage),
    ("packing", packing_stage),
]

#: Segment sums, signatures and tokenization aren't SQL; tests compare run() with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = materialize(stage(spark, docs, sf_dir), f"stage-{name}")
    return docs
