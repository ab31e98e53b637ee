"""Membership filters as rows of 32-bit words, conventional and sectioned, and packed bits of them.

A sectioned filter is `sections` small filters: a selector hash picks one, k more pick bits inside it. One section is the
conventional filter. Words are merged by OR, which may be repeated and reordered freely.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import position_of, section_of


def probes(elements: DataFrame, m_bits: int, sections: int = 1, k: int = 1, digest: str = "digest", tag: Column | None = None) -> DataFrame:
    """Each element's rows with section, word_ix and mask of its k bits. tag: forces the section (filters chosen by something else)."""
    m_sub = max(1, m_bits // sections)
    section = tag.cast("int") if tag is not None else section_of(F.col(digest), sections)
    rows = elements.withColumn("section", section).withColumn("r", F.explode(F.array(*[F.lit(r) for r in range(k)])))
    rows = rows.withColumn("pos", position_of(F.col(digest), F.col("r"), m_sub))
    return rows.withColumns({"word_ix": (F.col("pos") / 32).cast("int"), "mask": F.expr("shiftleft(1L, cast(pos % 32 as int))")}).drop("pos")


def build_sectioned(elements: DataFrame, m_bits: int, sections: int, k: int, digest: str = "digest", keys: tuple[str, ...] = ("interval_id",), tag: Column | None = None) -> DataFrame:
    """Words of the filter: partial OR in each task, one exchange of words."""
    rows = probes(elements.select(*keys, digest, *(["tag"] if tag is not None else [])), m_bits, sections, k, digest, tag)
    return rows.groupBy(*keys, "section", "word_ix").agg(F.bit_or("mask").alias("word"))


def build(elements: DataFrame, m_bits: int, k: int, digest: str = "digest", keys: tuple[str, ...] = ("interval_id",)) -> DataFrame:
    return build_sectioned(elements, m_bits, 1, k, digest, keys)


def merge(*filters: DataFrame) -> DataFrame:
    """OR of digests taken at different places."""
    out = filters[0]
    for other in filters[1:]:
        out = out.unionByName(other)
    keys = [c for c in out.columns if c != "word"]
    return out.groupBy(*keys).agg(F.bit_or("word").alias("word"))


def probe(elements: DataFrame, words: DataFrame, m_bits: int, sections: int = 1, k: int = 1, keys: tuple[str, ...] = ("interval_id",), digest: str = "digest") -> DataFrame:
    """Each element's columns with present and section. Elements have the filter's key columns. A word without a row is zero."""
    own = [c for c in elements.columns]
    rows = probes(elements, m_bits, sections, k, digest)
    joined = rows.join(words, [*keys, "section", "word_ix"], "left")
    hit = (F.coalesce("word", F.lit(0)).bitwiseAND(F.col("mask")) != 0).alias("hit")
    return joined.select(*own, "section", hit).groupBy(*own, "section").agg(F.bool_and("hit").alias("present"))


def packed(words: DataFrame, m_bits: int, sections: int, keys: tuple[str, ...] = ("interval_id",)) -> DataFrame:
    """keys, section, bits: the section's words as bytes (little endian), absent words as zeros."""
    n = -(-max(1, m_bits // sections) // 32)
    held = words.groupBy(*keys, "section").agg(F.map_from_entries(F.collect_list(F.struct("word_ix", "word"))).alias("w"))
    every = F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda i: F.lpad(F.hex(F.coalesce(F.element_at("w", i), F.lit(0))), 8, "0"))
    flip = lambda x: F.concat(F.substring(x, 7, 2), F.substring(x, 5, 2), F.substring(x, 3, 2), F.substring(x, 1, 2))
    return held.select(*keys, "section", F.unhex(F.array_join(F.transform(every, flip), "")).alias("bits"))


def to_array(words: DataFrame, m_bits: int, sections: int) -> np.ndarray:
    """One interval's filter in the driver, for kernels that hold it whole: [section, word]. Up to 512 MB."""
    if m_bits > 1 << 32:
        raise ValueError(f"a filter of {m_bits} bits is not for one array")
    n = -(-max(1, m_bits // sections) // 32)
    out = np.zeros((sections, n), np.uint32)
    for section, word_ix, word in words.select("section", "word_ix", "word").collect():
        out[section, word_ix] = word
    return out


def fill(words: DataFrame, m_bits: int, keys: tuple[str, ...] = ("interval_id",)) -> DataFrame:
    """Share of bits that are set."""
    return words.groupBy(*keys).agg(F.sum(F.bit_count("word")).cast("bigint").alias("ones")).withColumn("fill", F.round(F.col("ones") / m_bits, 6))


def best_k(m_bits: int, elements: int) -> int:
    """Hashes that fit the load best: at least one."""
    return max(1, round(m_bits / max(1, elements) * 0.6931471805599453))
