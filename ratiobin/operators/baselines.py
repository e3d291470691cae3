"""Comparison coders and lossless sizes, each working on one step alone.

The two lossy coders stand in for published families whose internals the blueprint doesn't know: `sorted_fit` sorts windows
and fits smooth curves under a relative bound; `predictive` predicts from the reconstructed neighbour and quantises the miss
under an absolute bound.
"""

from __future__ import annotations

import bz2
import zlib

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ratiobin.functions.bits import pack_bits

STEP = ["var", "step"]
CHUNK = 1 << 16


def sorted_fit_encode(x: np.ndarray, rel_bound: float, window: int = 1024, degree: int = 3, elem_bytes: int = 8) -> tuple[int, np.ndarray]:
    """Bytes and reconstruction of one array: each window sorted, a polynomial fitted, misses corrected on a relative grid."""
    size, out = 0, np.empty_like(x)
    for a in range(0, len(x), window):
        part = x[a : a + window]
        order = np.argsort(part, kind="stable")
        t = np.linspace(-1, 1, len(part))
        fit = np.polynomial.polynomial.polyval(t, np.polynomial.polynomial.polyfit(t, part[order], min(degree, len(part) - 1)))
        step = 2 * rel_bound * np.abs(part[order])
        grid = np.where(step > 0, step, 1.0)
        # The grid is set by each value's power of two, which the decoder knows once the exponent is sent with the miss.
        scale = np.exp2(np.floor(np.log2(np.where(grid > 0, grid, 1.0))))
        miss = np.rint((part[order] - fit) / scale)
        big = np.abs(miss) > 1 << 30
        value = np.where(big, part[order], fit + np.where(big, 0, miss) * scale)
        value[part[order] == 0] = 0.0
        back = np.empty_like(part)
        back[order] = value
        out[a : a + window] = back
        bits = max(1, int(len(part) - 1).bit_length())
        exponents = np.log2(scale).astype(np.int16)
        size += len(zlib.compress(pack_bits(order, bits))) + elem_bytes * (degree + 1)
        size += len(zlib.compress(np.diff(exponents, prepend=0).astype("<i2").tobytes())) + len(zlib.compress(np.where(big, 0, miss).astype("<i4").tobytes())) + elem_bytes * int(big.sum())
    return size, out


def predictive_encode(x: np.ndarray, abs_bound: float, elem_bytes: int = 8) -> tuple[int, np.ndarray]:
    """Bytes and reconstruction: each value is the one before, as reconstructed, plus a whole number of 2 * bound steps."""
    step = 2 * abs_bound
    level = np.rint(x / step)
    fits = np.isfinite(level) & (np.abs(level) < 1 << 52)
    level = np.where(fits, level, 0)
    out = np.where(fits, level * step, x)
    miss = np.diff(level, prepend=0.0)
    coded = (np.abs(miss) < 1 << 15) & fits
    symbols = np.where(coded, miss, 1 << 15).astype("<i4")
    kept = ~coded
    out[kept] = x[kept]
    return len(zlib.compress((symbols + (1 << 15)).astype("<u4").view(np.uint8).reshape(-1, 4)[:, :3].T.tobytes())) + elem_bytes * int(kept.sum()), out


def chunks(df: DataFrame, size: int = CHUNK) -> DataFrame:
    """(var, step, pos, value) with the chunk that holds the position."""
    return df.withColumn("chunk_id", F.floor(F.col("pos") / size))


def _per_chunk(df: DataFrame, encode) -> DataFrame:
    def run(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values("pos")
        x = frame["value"].to_numpy(dtype=np.float64)
        bound = frame["bound"].iloc[0]
        size, hat = encode(x, bound)
        return pd.DataFrame({"var": frame["var"].iloc[0], "step": frame["step"].iloc[0], "pos": frame["pos"], "value": x, "value_hat": hat, "chunk_bytes": np.r_[size, np.zeros(len(x) - 1, dtype=np.int64)]})

    return chunks(df).groupBy(*STEP, "chunk_id").applyInPandas(run, "var string, step int, pos long, value double, value_hat double, chunk_bytes long")


def sorted_fit_codec(df: DataFrame, rel_bound: float, window: int = 1024, degree: int = 3, elem_bytes: int = 8) -> DataFrame:
    """Points with their reconstruction and the bytes of each chunk (on its first point), under a relative bound."""
    return _per_chunk(df.where("value IS NOT NULL").withColumn("bound", F.lit(rel_bound)), lambda x, b: sorted_fit_encode(x, b, window, degree, elem_bytes))


def absolute_bound(df: DataFrame, rel: float) -> DataFrame:
    """(var, step, bound): |mean| times the relative bound; a mean of zero is an error, since no bound follows from it."""
    mean = F.abs(F.avg("value"))
    return df.groupBy(*STEP).agg(F.when(mean == 0, F.raise_error(F.lit("a step averages zero"))).otherwise(mean * rel).alias("bound"))


def predictive_codec(df: DataFrame, rel: float, elem_bytes: int = 8) -> DataFrame:
    """Points with their reconstruction and chunk bytes, under the absolute bound that belongs to a relative one."""
    return _per_chunk(df.where("value IS NOT NULL").join(F.broadcast(absolute_bound(df, rel)), STEP), lambda x, b: predictive_encode(x, b, elem_bytes))  # one row a step


def lossless_size(df: DataFrame, codec: str = "zlib", elem_bytes: int = 8) -> DataFrame:
    """(var, step, raw_bytes, stored_bytes): raw values of each chunk through a byte compressor."""
    squeeze = {"zlib": lambda b: zlib.compress(b, 6), "bz2": bz2.compress, "none": lambda b: b}[codec]

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        raw = frame.sort_values("pos")["value"].to_numpy(dtype="<f4" if elem_bytes == 4 else "<f8").tobytes()
        return pd.DataFrame({"var": [frame["var"].iloc[0]], "step": [frame["step"].iloc[0]], "raw_bytes": [len(raw)], "stored_bytes": [len(squeeze(raw))]})

    per = chunks(df).groupBy(*STEP, "chunk_id").applyInPandas(run, "var string, step int, raw_bytes long, stored_bytes long")
    return per.groupBy(*STEP).agg(F.sum("raw_bytes").alias("raw_bytes"), F.sum("stored_bytes").alias("stored_bytes"))


def coded_size(coded: DataFrame, elem_bytes: int = 8) -> DataFrame:
    """Size and errors of a comparison coder's output, by step."""
    error = F.abs((F.col("value") - F.col("value_hat")) / F.when(F.col("value") != 0, F.col("value")))
    sums = coded.groupBy(*STEP).agg(F.count("*").alias("n"), F.sum("chunk_bytes").alias("stored_bytes"), F.avg(error).alias("mean_error"), F.max(error).alias("max_error"), F.max(F.abs(F.col("value") - F.col("value_hat"))).alias("max_abs_error"))
    return sums.withColumn("cr", F.col("n") * elem_bytes / F.col("stored_bytes"))
