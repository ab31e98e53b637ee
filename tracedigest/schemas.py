"""The persistent schemas. Nothing is ever inferred."""

from pyspark.sql import types as T


def _schema(text: str) -> T.StructType:
    return T._parse_datatype_string(text)  # noqa: SLF001


TRACE = "interval_id int, ts timestamp, flow_key string, src string, dst string, proto string, seq bigint, payload binary"
BLOCKS = "interval_id int, flow_key string, seq bigint, block_no int, start int, size int, block binary"
FILTER = "interval_id int, section int, word_ix int, word bigint"
FLOWBITS = "interval_id int, flow_key string, bitmap binary"
MANIFEST = (
    "interval_id int, raw_bytes bigint, flows bigint, m_bits bigint, sections int, k int, window int, overlap int, threshold int, keep_equal boolean, "
    "hash_family string, salt string, assembly string, filter_bytes bigint, index_bytes bigint"
)
EXCERPTS = "excerpt_id bigint, excerpt binary, true_flow string"
VERDICT = "excerpt_id bigint, interval_id int, flow_key string"
