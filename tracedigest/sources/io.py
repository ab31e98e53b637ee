"""Payloads from files and verdicts to files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..schemas import TRACE


def from_files(spark: SparkSession, path: str, glob: str = "*") -> DataFrame:
    """One packet per file; the flow is the file, the time its modification."""
    files = spark.read.format("binaryFile").option("pathGlobFilter", glob).load(path)
    return files.select(
        F.lit(0).alias("interval_id"), F.col("modificationTime").alias("ts"), F.col("path").alias("flow_key"), F.lit("file").alias("src"), F.col("path").alias("dst"), F.lit("file").alias("proto"),
        F.lit(0).cast("bigint").alias("seq"), F.col("content").alias("payload"),
    )


def from_text(spark: SparkSession, path: str, flow: str = "text") -> DataFrame:
    """One packet per line of text files."""
    rows = spark.read.text(path).select("value", F.input_file_name().alias("file"))
    return rows.select(
        F.lit(0).alias("interval_id"), F.lit(None).cast("timestamp").alias("ts"), F.col("file").alias("flow_key"), F.lit(flow).alias("src"), F.col("file").alias("dst"), F.lit("line").alias("proto"),
        F.lit(0).cast("bigint").alias("seq"), F.encode("value", "UTF-8").alias("payload"),
    )


RECORD = "interval_id int, ts timestamp, flow_key string, src string, dst string, proto string, seq bigint, payload string"


def _decoded(rows: DataFrame) -> DataFrame:
    return rows.withColumn("payload", F.unhex("payload"))


def from_json(spark: SparkSession, path: str) -> DataFrame:
    """The trace's columns as JSON lines, payload in hexadecimal."""
    return _decoded(spark.read.schema(RECORD).json(path))


def from_csv(spark: SparkSession, path: str) -> DataFrame:
    """The same as CSV with a header."""
    return _decoded(spark.read.schema(RECORD).option("header", True).csv(path))


def from_parquet(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(TRACE).parquet(path)


def to_json(trace: DataFrame, path: str) -> None:
    trace.withColumn("payload", F.hex("payload")).write.json(path)


def to_csv(trace: DataFrame, path: str) -> None:
    trace.withColumn("payload", F.hex("payload")).write.option("header", True).csv(path)


def to_parquet(trace: DataFrame, path: str) -> None:
    """By interval, so that investigations read the intervals they name."""
    trace.write.partitionBy("interval_id").parquet(path)


def report(verdict: DataFrame, path: str, format: str = "json") -> None:
    """A verdict report: flows by excerpt."""
    verdict.groupBy("excerpt_id", "interval_id").agg(F.sort_array(F.collect_list("flow_key")).alias("flows"), F.count("*").alias("n_flows")).write.format(format).save(path)
