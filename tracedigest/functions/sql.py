"""The SQL surface: views of a trace and a digest, block functions, and attribution by SQL.

register(spark, packets, digest) makes the views td_trace, td_flows, td_filter and td_index and the functions of `arrow`; ask(spark, excerpts)
makes td_verdict.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..operators import attribution
from ..operators.digest import Digest
from . import arrow


def register(spark: SparkSession, packets: DataFrame, digest: Digest) -> None:
    arrow.register(spark)
    packets.createOrReplaceTempView("td_trace")
    digest.flows.createOrReplaceTempView("td_flows")
    attribution.words_of_sections(digest).createOrReplaceTempView("td_filter")
    if digest.flowbits is not None:
        digest.flowbits.createOrReplaceTempView("td_index")


def ask(spark: SparkSession, excerpts: str, digest: Digest, **how) -> DataFrame:
    """The verdict on a view of (excerpt_id, excerpt); also as the view td_verdict."""
    out = attribution.attribute(spark.table(excerpts), digest, **how)
    out.createOrReplaceTempView("td_verdict")
    return out
