"""SQL surface: formulas as SQL functions that Catalyst inlines, and a table function that decodes a block."""

from __future__ import annotations

import zlib

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from ratiobin.functions.bits import unpack_bits

FUNCTIONS = {
    "ratio_change(prev DOUBLE, cur DOUBLE) RETURNS DOUBLE": "CASE WHEN prev IS NOT NULL AND prev <> 0 AND NOT isnan(prev) AND NOT isnan(cur) AND abs(prev) < double('Infinity') AND abs(cur) < double('Infinity') THEN try_divide(cur - prev, prev) END",
    "grid_bin(ratio DOUBLE, lo DOUBLE, error_bound DOUBLE) RETURNS BIGINT": "CAST(floor((ratio - lo) / (2 * error_bound)) AS BIGINT)",
    "estimated_size(bits INT, n BIGINT, elem_bytes INT, n_exact BIGINT) RETURNS DOUBLE": "pow(2, bits) * elem_bytes + n * bits / 8.0D + n_exact * elem_bytes",
    "predicted_cr(bits DOUBLE, zlib_ratio DOUBLE, alpha DOUBLE, elem_bits INT) RETURNS DOUBLE": "elem_bits / (bits / zlib_ratio + alpha * elem_bits)",
}


@udtf(returnType="pos bigint, idx int")
class DecodeRange:
    """decode_range(payload, bits, first_pos, n, start, stop): positions start .. stop - 1 of a block and their index."""

    def eval(self, payload: bytes, bits: int, first_pos: int, n: int, start: int, stop: int):
        idx = unpack_bits(zlib.decompress(payload), bits, n)
        for at in range(max(start - first_pos, 0), min(stop - first_pos, n)):
            yield first_pos + at, int(idx[at])


def register(spark: SparkSession) -> None:
    for head, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    spark.udtf.register("decode_range", DecodeRange)
