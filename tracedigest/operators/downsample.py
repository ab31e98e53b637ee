"""Downsampling: small blocks say little, so they are not stored."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def keep_large(blocks: DataFrame, threshold: int, keep_equal: bool = True) -> DataFrame:
    return blocks.filter(F.col("size") >= threshold if keep_equal else F.col("size") > threshold)


def safe_threshold(excerpt_blocks: DataFrame, quantile: float = 0.0) -> DataFrame:
    """safe: the largest threshold under which the given share of excerpts at most loses its last block (0: none does)."""
    largest = excerpt_blocks.groupBy("excerpt_id").agg(F.max("size").alias("largest"))
    return largest.agg(F.percentile("largest", F.lit(quantile)).cast("int").alias("safe"))


def counts(blocks: DataFrame, thresholds: list[int], keep_equal: bool = True) -> DataFrame:
    """threshold, blocks kept and the reduction factor d, for a grid of thresholds in one pass: a histogram first, then a
    join of its few rows with the grid."""
    hist = blocks.groupBy("size").agg(F.count("*").alias("n"))
    grid = blocks.sparkSession.createDataFrame([(t,) for t in thresholds], "threshold int")
    kept = F.sum(F.when(F.col("size") >= F.col("threshold") if keep_equal else F.col("size") > F.col("threshold"), F.col("n")).otherwise(0))
    out = hist.crossJoin(F.broadcast(grid)).groupBy("threshold").agg(F.sum("n").alias("seen"), kept.alias("kept"))
    return out.select("threshold", "seen", "kept", F.round(F.col("seen") / F.col("kept"), 6).alias("d"))
