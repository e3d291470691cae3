"""Cost and accuracy measures."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

STEP = ["var", "step"]
#: Bytes of a block's entries in the two offset tables.
OFFSET_BYTES = 12


def mean_error(orig: DataFrame, hat: DataFrame) -> DataFrame:
    """Mean of |value - hat| / |value| over points that are not zero; zeros are counted apart."""
    both = orig.join(hat, [*STEP, "pos"])
    error = F.abs((F.col("value") - F.col("value_hat")) / F.when(F.col("value") != 0, F.col("value")))
    return both.groupBy(*STEP).agg(F.count("*").alias("n"), F.count(F.when(F.col("value") == 0, 1)).alias("n_zero"), F.avg(error).alias("mean_error"), F.max(error).alias("max_error"))


def bound_report(indexed: DataFrame, error_bound: float) -> DataFrame:
    """Largest distance of a ratio from its centre and points beyond the bound.

    Bins have half-width E, so a ratio lies beyond it by rounding alone, at the scale of the grid's origin.
    """
    off = F.abs(F.col("ratio") - F.col("centre"))
    slack = 4 * 2.0**-52 * F.greatest(F.abs("ratio"), F.abs(F.coalesce("lo", F.lit(0.0))))
    return indexed.groupBy(*STEP).agg(F.count("*").alias("n"), F.max(off).alias("max_ratio_error"), F.count(F.when(off > error_bound + slack, 1)).alias("violations"))


def exact_ratio(indexed: DataFrame, *by: str) -> DataFrame:
    """Points without a centre: count and share, by step unless told otherwise."""
    keys = by or tuple(STEP)
    return indexed.groupBy(*keys).agg(F.count("*").alias("n"), F.count(F.when(F.col("centre").isNull(), 1)).alias("n_exact"), F.avg(F.col("centre").isNull().cast("double")).alias("exact_ratio"))


def space_breakdown(blocks: DataFrame, header: DataFrame) -> DataFrame:
    """Bytes of centres, index, exact values and offsets of each step, their sum, the ratio of compression and of zlib."""
    sums = blocks.groupBy(*STEP).agg(
        F.sum(F.octet_length("payload")).alias("index_bytes"), F.sum("raw_bytes").alias("raw_index_bytes"), F.sum("n_exact").alias("n_exact_stored"), F.count("*").alias("n_blocks")
    )
    out = header.select(*STEP, "n", "bits", "n_centres", "elem_bytes").join(sums, STEP)
    out = out.withColumn("centre_bytes", F.col("n_centres") * F.col("elem_bytes")).withColumn("exact_bytes", F.col("n_exact_stored") * F.col("elem_bytes"))
    out = out.withColumn("offset_bytes", F.col("n_blocks") * OFFSET_BYTES)
    out = out.withColumn("stored_bytes", F.col("centre_bytes") + F.col("index_bytes") + F.col("exact_bytes") + F.col("offset_bytes"))
    return (
        out.withColumn("cr", F.col("n") * F.col("elem_bytes") / F.col("stored_bytes")).withColumn("zlib_ratio", F.col("raw_index_bytes") / F.col("index_bytes"))
        .withColumn("index_share", F.col("index_bytes") / F.col("stored_bytes"))
    )


def bits_regret(sweep: DataFrame) -> DataFrame:
    """(var, step, bits, stored_bytes, auto) to the size at the chosen length over the least size."""
    best = sweep.groupBy(*STEP).agg(F.min(F.struct("stored_bytes", "bits")).alias("b"), F.max(F.when(F.col("auto"), F.col("stored_bytes"))).alias("chosen"), F.max(F.when(F.col("auto"), F.col("bits"))).alias("auto_bits"))
    return best.select(*STEP, "auto_bits", F.col("b.bits").alias("best_bits"), (F.col("chosen") / F.col("b.stored_bytes")).alias("regret"))
