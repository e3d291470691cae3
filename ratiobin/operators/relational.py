"""Relational operators around the codec: dense positions, densified steps, step windows, comparisons of stored sets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ratiobin.session import saved, small_side

LOCAL_BITS = 33


def dense_positions(keys: DataFrame, columns: list[str], name: str = "pos") -> DataFrame:
    """Distinct key rows with their rank from 0 in ascending order, without a single-partition sort.

    Keys are range-partitioned and sorted; a row's place in its partition plus the sizes of the partitions before it is its
    rank.  Only one row for each partition is summed up in one place.
    """
    placed = keys.select(*columns).distinct().repartitionByRange(*columns).sortWithinPartitions(*columns).withColumn("_id", F.monotonically_increasing_id())
    placed = saved(placed, "positions").withColumn("_part", F.shiftright("_id", LOCAL_BITS)).withColumn("_at", F.col("_id").bitwiseAND(F.lit((1 << LOCAL_BITS) - 1)))
    before = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    base = placed.groupBy("_part").agg(F.count("*").alias("_n")).select("_part", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_base"))
    return placed.join(small_side(base), "_part").select(*columns, (F.col("_base") + F.col("_at")).alias(name))


def densify(sums: DataFrame, points: DataFrame, steps: DataFrame, carried: str) -> DataFrame:
    """(pos, step, carried) at some steps to every step of every point: running sum of `carried`, 0 before the first.

    steps is small (one row a step) and is broadcast after its size is checked.
    """
    grid = points.select("pos").crossJoin(small_side(steps.select("step")))
    full = grid.join(sums, ["pos", "step"], "left")
    run = Window.partitionBy("pos").orderBy("step").rowsBetween(Window.unboundedPreceding, 0)
    return full.withColumn(carried, F.sum(F.coalesce(carried, F.lit(0))).over(run))


def carry_forward(observed: DataFrame, points: DataFrame, steps: DataFrame) -> DataFrame:
    """As-of densification: each step has the last value observed at or before it, null before the first."""
    grid = points.select("pos").crossJoin(small_side(steps.select("step")))
    run = Window.partitionBy("pos").orderBy("step").rowsBetween(Window.unboundedPreceding, 0)
    return grid.join(observed, ["pos", "step"], "left").withColumn("value", F.last("value", ignorenulls=True).over(run))


def pair_steps(prev: DataFrame, cur: DataFrame, how: str = "inner") -> DataFrame:
    """Two steps (var, pos, value) side by side; 'full' keeps points that vanish or appear."""
    a = prev.select("var", "pos", F.col("value").alias("prev"))
    return a.join(cur.select("var", "pos", F.col("value").alias("cur")), ["var", "pos"], how)


def assign_steps(events: DataFrame, windows: DataFrame) -> DataFrame:
    """Interval join: each event (ts) with the step window [start, end) it falls in; joined on the day, then bounded."""
    days = windows.withColumn("day", F.explode(F.sequence(F.to_date("start"), F.to_date(F.col("end") - F.expr("INTERVAL 1 MICROSECOND")))))
    return events.withColumn("day", F.to_date("ts")).join(small_side(days), "day").where((F.col("ts") >= F.col("start")) & (F.col("ts") < F.col("end"))).drop("day")


def common_points(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.join(b, ["var", "pos"], "left_semi")


def stored_exactly(ratios: DataFrame, centres: DataFrame) -> DataFrame:
    """Points whose bin was not chosen."""
    return ratios.join(centres.select("var", "step", "bin"), ["var", "step", "bin"], "left_anti")


def strategy_overlap(a: DataFrame, b: DataFrame) -> DataFrame:
    """Points that both of two sets of compressible points hold, and those that only the first holds."""
    both = a.intersect(b).select("*", F.lit("both").alias("held_by"))
    return both.unionByName(a.exceptAll(b).select("*", F.lit("first").alias("held_by")))


def random_segment(df: DataFrame, share: float, n: int, seed: int = 0) -> tuple[int, int]:
    """Start and end of a contiguous segment of a share of n positions; the seed fixes the start."""
    import random

    length = max(1, int(n * share))
    start = random.Random(seed).randrange(max(n - length, 0) + 1)
    return start, start + length


def slice_series(df: DataFrame, var: str | None = None, step: int | None = None, start: int | None = None, stop: int | None = None) -> DataFrame:
    """Filters that reach the Parquet scan."""
    for condition in (None if var is None else F.col("var") == var, None if step is None else F.col("step") == step, None if start is None else F.col("pos") >= start, None if stop is None else F.col("pos") < stop):
        df = df if condition is None else df.where(condition)
    return df


def speedup(rows: DataFrame) -> DataFrame:
    """(workers, seconds) with speedup and efficiency against the smallest run, which counts as perfectly scaled."""
    first = Window.orderBy("workers").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    base = F.first("seconds").over(first) * F.first("workers").over(first)
    return rows.withColumn("speedup", base / F.col("seconds")).withColumn("efficiency", base / F.col("seconds") / F.col("workers"))


def month_index(ts: Column) -> Column:
    return F.year(ts) * 12 + F.month(ts) - 1


def cents(x: Column) -> Column:
    """Money as whole cents, so that sums don't depend on their order."""
    return F.round(x * 100).cast("long")
