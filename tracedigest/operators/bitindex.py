"""The bitmap index: for each flow the sections that its blocks touched, to rule out flows before they are probed."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def flow_list(trace: DataFrame) -> DataFrame:
    """interval_id, flow_key, src, dst, packets, bytes."""
    return trace.groupBy("interval_id", "flow_key").agg(F.min("src").alias("src"), F.min("dst").alias("dst"), F.count("*").alias("packets"), F.sum(F.octet_length("payload")).cast("bigint").alias("bytes"))


def flow_words(sectioned: DataFrame) -> DataFrame:
    """interval_id, flow_key, word_ix, word: 32 sections a word, from rows with interval_id, flow_key and section. Partial OR in
    each task; flows without a block have no rows."""
    bit = F.expr("shiftleft(1L, section % 32)")
    return sectioned.groupBy("interval_id", "flow_key", F.floor(F.col("section") / 32).cast("int").alias("word_ix")).agg(F.bit_or(bit).alias("word"))


def flow_bitmaps(words: DataFrame, flows: DataFrame, sections: int) -> DataFrame:
    """interval_id, flow_key, bitmap (sections / 8 bytes, least bit first); flows without blocks have zeros."""
    n = -(-sections // 32)
    held = words.groupBy("interval_id", "flow_key").agg(F.map_from_entries(F.collect_list(F.struct("word_ix", "word"))).alias("w"))
    every = F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda i: F.lpad(F.hex(F.coalesce(F.element_at("w", i), F.lit(0).cast("bigint"))), 8, "0"))
    flip = lambda x: F.concat(F.substring(x, 7, 2), F.substring(x, 5, 2), F.substring(x, 3, 2), F.substring(x, 1, 2))
    out = flows.select("interval_id", "flow_key").join(held, ["interval_id", "flow_key"], "left")
    out = out.withColumn("w", F.coalesce("w", F.expr("cast(map() as map<int,bigint>)")))
    return out.select("interval_id", "flow_key", F.substring(F.unhex(F.array_join(F.transform(every, flip), "")), 1, -(-sections // 8)).alias("bitmap"))


def construct_bitmaps(sectioned: DataFrame, sections: int) -> DataFrame:
    """The same by the built-in bitmap aggregate; its buffer is 4,096 bytes a flow whatever the width, so for wide
    indexes (near 32,768 sections) only."""
    return sectioned.groupBy("interval_id", "flow_key").agg(F.substring(F.bitmap_construct_agg(F.bitmap_bit_position(F.col("section").cast("bigint") + 1)), 1, -(-sections // 8)).alias("bitmap"))


def required_words(hits: DataFrame) -> DataFrame:
    """excerpt_id, interval_id, word_ix, need: the sections that an excerpt's blocks were found in, as masks."""
    bit = F.expr("shiftleft(1L, section % 32)")
    return hits.groupBy("excerpt_id", "interval_id", F.floor(F.col("section") / 32).cast("int").alias("word_ix")).agg(F.bit_or(bit).alias("need"))


def prune(words: DataFrame, required: DataFrame, flows: DataFrame, asked: DataFrame) -> DataFrame:
    """excerpt_id, interval_id, flow_key: flows with a one in every required section. asked: the (excerpt_id, interval_id) in
    question; one without a requirement keeps all flows of its interval."""
    needed = required.groupBy("excerpt_id", "interval_id").agg(F.count("*").alias("n"))
    met = words.join(required, ["interval_id", "word_ix"]).filter(F.col("word").bitwiseAND(F.col("need")) == F.col("need"))
    met = met.groupBy("excerpt_id", "interval_id", "flow_key").agg(F.count("*").alias("met")).join(needed, ["excerpt_id", "interval_id"])
    kept = met.filter("met = n").select("excerpt_id", "interval_id", "flow_key")
    free = asked.join(needed, ["excerpt_id", "interval_id"], "left_anti").join(flows.select("interval_id", "flow_key"), "interval_id")
    return kept.unionByName(free.select("excerpt_id", "interval_id", "flow_key"))


def invert(sectioned: DataFrame) -> DataFrame:
    """The section-major form: interval_id, section, flow_key, once each."""
    return sectioned.select("interval_id", "section", "flow_key").distinct()


def prune_inverted(postings: DataFrame, hits: DataFrame) -> DataFrame:
    """Candidates from the section-major form: flows that all required sections list."""
    need = hits.select("excerpt_id", "interval_id", "section").distinct()
    n = need.groupBy("excerpt_id", "interval_id").agg(F.count("*").alias("n"))
    met = postings.join(need, ["interval_id", "section"]).groupBy("excerpt_id", "interval_id", "flow_key").agg(F.count("*").alias("met"))
    return met.join(n, ["excerpt_id", "interval_id"]).filter("met = n").select("excerpt_id", "interval_id", "flow_key")


def ones_share(words: DataFrame, flows: DataFrame, sections: int) -> DataFrame:
    n = flows.agg(F.count("*").alias("flows"))
    ones = words.agg(F.coalesce(F.sum(F.bit_count("word")), F.lit(0)).cast("bigint").alias("ones"))
    return ones.crossJoin(n).select("flows", "ones", F.lit(sections).alias("sections"), F.round(F.col("ones") / (F.col("flows") * sections), 6).alias("share"))


#: The worked example, sections set per flow, of ten sections.
EXAMPLE = {1: [2, 3, 6, 10], 2: [1, 3, 4, 6, 7, 8], 3: [4, 5], 4: [1, 2, 3, 4, 6, 7, 8, 9, 10], 5: [3, 5, 7, 9, 10]}
EXAMPLE_NEEDS = {1: [6], 2: [3, 6, 10], 3: [], 4: [5], 5: [1, 5]}


def example(spark) -> DataFrame:
    """excerpt_id, flow_key: what the worked example leaves for each requirement."""
    rows = spark.createDataFrame([(0, str(f), s) for f, own in EXAMPLE.items() for s in own], "interval_id int, flow_key string, section int")
    return example_of(rows)


def example_of(rows: DataFrame) -> DataFrame:
    """excerpt_id, flow_key: what the example's requirements leave of flows given as rows interval_id (0), flow_key, section."""
    spark = rows.sparkSession
    hits = spark.createDataFrame([(q, 0, s) for q, own in EXAMPLE_NEEDS.items() for s in own], "excerpt_id long, interval_id int, section int")
    asked = spark.createDataFrame([(q, 0) for q in EXAMPLE_NEEDS], "excerpt_id long, interval_id int")
    return prune(flow_words(rows), F.broadcast(required_words(hits)), rows.select("interval_id", "flow_key").distinct(), F.broadcast(asked)).select("excerpt_id", "flow_key")
