"""Change ratios between successive steps, their range and their distribution."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ratiobin.functions.columns import change_ratio, zero_bin


def change_ratios(df: DataFrame, zero_prev: str = "exact", stride: int = 1, anchor_every: int | None = None) -> DataFrame:
    """(var, step, pos, value) to (var, step, pos, prev, cur, ratio) for every step but the first of each variable.

    One shuffle by point.  A point that the step before lacks has no ratio; so has one at zero.  stride: distance of the
    steps that are compared; anchor_every: each step at a multiple of it after the first is left out as well.
    """
    order = Window.partitionBy("var", "pos").orderBy("step")
    before = df.withColumn("prev", F.when(F.lag("step").over(order) == F.col("step") - stride, F.lag("value").over(order)))
    first = df.groupBy("var").agg(F.min("step").alias("_first"))
    rows = before.join(F.broadcast(first), "var").where("step > _first")  # one row for each variable
    if anchor_every:
        rows = rows.where((F.col("step") - F.col("_first")) % anchor_every != 0)
    return rows.select("var", "step", "pos", "prev", F.col("value").alias("cur"), change_ratio(F.col("prev"), F.col("value"), zero_prev).alias("ratio"))


def every_nth(df: DataFrame, n: int) -> DataFrame:
    """Every n-th step, renumbered."""
    return df.where(F.col("step") % n == 0).withColumn("step", F.floor(F.col("step") / n).cast("int"))


def ratio_range(ratios: DataFrame, *more: str) -> DataFrame:
    """Least and largest ratio, points and defined ratios of each step, and its last position."""
    last = [F.max("pos").alias("last_pos")] if "pos" in ratios.columns else []
    return ratios.groupBy("var", "step", *more).agg(F.min("ratio").alias("lo"), F.max("ratio").alias("hi"), F.count("*").alias("n"), F.count("ratio").alias("n_defined"), *last)


def ratio_profile(ratios: DataFrame, error_bound: float) -> DataFrame:
    """Share of barely changed points, range and occupied bins of each step."""
    return ratios.groupBy("var", "step").agg(
        F.count("*").alias("n"), F.count("ratio").alias("n_defined"), F.count(F.when(F.abs("ratio") <= error_bound, 1)).alias("n_small"),
        F.min("ratio").alias("lo"), F.max("ratio").alias("hi"), F.count_distinct(zero_bin(F.col("ratio"), error_bound)).alias("occupied"),
    )
