"""Blocks as SQL functions: an Arrow function, a table function, and their registration with views of a trace."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators import blocking

BLOCK = T.StructType([T.StructField("block_no", T.IntegerType()), T.StructField("start", T.IntegerType()), T.StructField("size", T.IntegerType()), T.StructField("block", T.BinaryType())])


@F.arrow_udf(T.ArrayType(BLOCK))
def winnow_blocks(payload: pa.Array) -> pa.Array:
    """All blocks of each payload, window 64 and overlap 4."""
    row, number, start, size, blocks = blocking.winnow_batch(payload.to_pylist())
    out: list[list[dict]] = [[] for _ in range(len(payload))]
    for r, n, s, z, b in zip(row.tolist(), number.tolist(), start.tolist(), size.tolist(), blocks, strict=True):
        out[r].append({"block_no": n, "start": s, "size": z, "block": b})
    return pa.array(out, pa.list_(pa.struct([("block_no", pa.int32()), ("start", pa.int32()), ("size", pa.int32()), ("block", pa.binary())])))


@F.arrow_udf(T.IntegerType())
def section(block: pa.Array, sections: pa.Array) -> pa.Array:
    """The section of a filter that a block's content digest selects."""
    from .hashing import digests, md5_parts

    sel, _, _ = md5_parts(digests([b or b"" for b in block.to_pylist()]))
    return pa.array((sel % sections.to_numpy(zero_copy_only=False)).tolist(), pa.int32())


class Winnow:
    """td_winnow(payload, window, overlap, threshold): a row per kept block."""

    def eval(self, payload: bytes, window: int, overlap: int, threshold: int):
        _, number, start, size, blocks = blocking.winnow_batch([payload], window, overlap, threshold)
        yield from zip(number.tolist(), start.tolist(), size.tolist(), blocks, strict=True)


def register(spark: SparkSession) -> None:
    """td_blocks, td_section and td_winnow for SQL."""
    spark.udf.register("td_blocks", winnow_blocks)
    spark.udf.register("td_section", section)
    spark.udtf.register("td_winnow", F.udtf(Winnow, returnType=BLOCK))
