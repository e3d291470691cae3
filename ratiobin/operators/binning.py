"""Bin centres by five strategies, and the choice of the index length.

All functions work on ratios (var, step, pos, prev, cur, ratio) of any number of steps at once, one set of centres a step.
Centres are (var, step, idx, centre, cnt), with `bin` where they lie on the grid.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ratiobin.functions.columns import bin_centre, estimated_size, grid_bin, zero_bin, zero_centre
from ratiobin.operators.ratios import ratio_range
from ratiobin.session import saved, small_side, stored_bytes

STEP = ["var", "step"]
MOST_BINS = (1 << 16) - 1
#: Occupied bins of a step that one task ranks; steps with more are cut to their fullest bins before.
RANK_BINS = 1 << 20
#: Neighbouring bins of equal count that are kept or left together by that cut.
SLAB = 1 << 16
#: Cells of a step's fine histogram for k-means, at most.
MOST_CELLS = 1 << 22


def with_bins(ratios: DataFrame, error_bound: float, anchor: str = "min", *more: str, ranges: DataFrame | None = None) -> DataFrame:
    """ratios plus lo and bin; undefined ratios have no bin.  ranges: a small side with ratio_range(), if it is at hand."""
    if anchor == "zero":
        return ratios.withColumn("lo", F.lit(None).cast("double")).withColumn("bin", zero_bin(F.col("ratio"), error_bound))
    keys = [*STEP, *more]
    ranges = small_side(ratio_range(ratios, *more)) if ranges is None else ranges
    return ratios.join(ranges.select(*keys, "lo"), keys, "left").withColumn("bin", grid_bin(F.col("ratio"), F.col("lo"), error_bound))


def centre_of(error_bound: float, anchor: str) -> Column:
    return zero_centre(F.col("bin"), error_bound) if anchor == "zero" else bin_centre(F.col("bin"), F.col("lo"), error_bound)


def ratio_histogram(binned: DataFrame, *more: str) -> DataFrame:
    """Counts of occupied bins; partial counts leave each task, never points."""
    return binned.where("bin IS NOT NULL").groupBy(*STEP, *more, "bin").agg(F.count("*").alias("cnt"), F.first("lo").alias("lo"))


def _fullest(hist: DataFrame, most: int, keys: list[str]) -> DataFrame:
    """A superset of the `most` fullest bins of each step (ties: lower bin first), of less than `most` + SLAB bins.

    The bins with one count are counted first, which gives the count of the last bin that has a place; of the bins with that
    very count, slabs of neighbouring bins are counted and kept from the lowest until the places are taken.  Only counts
    meet in one task.
    """
    down = Window.partitionBy(*keys).orderBy(F.desc("cnt")).rowsBetween(Window.unboundedPreceding, -1)
    by_count = hist.groupBy(*keys, "cnt").agg(F.count("*").alias("_bins")).withColumn("_above", F.coalesce(F.sum("_bins").over(down), F.lit(0)))
    last = small_side(by_count.where(F.col("_above") < most).groupBy(*keys).agg(F.min("cnt").alias("_least"), F.max("_above").alias("_above")))
    told = hist.join(last, keys)
    tied = told.where("cnt = _least").withColumn("_slab", F.floor(F.col("bin") / SLAB))
    up = Window.partitionBy(*keys).orderBy("_slab").rowsBetween(Window.unboundedPreceding, -1)
    slabs = tied.groupBy(*keys, "_slab").agg(F.count("*").alias("_n"), F.first("_above").alias("_above")).withColumn("_before", F.col("_above") + F.coalesce(F.sum("_n").over(up), F.lit(0)))
    some = small_side(slabs.where(F.col("_before") < most).select(*keys, "_slab"))
    return told.where("cnt > _least").select(*hist.columns).unionByName(tied.join(some, [*keys, "_slab"], "left_semi").select(*hist.columns))


def rank_bins(hist: DataFrame, most: int = MOST_BINS, *more: str, rank_bins: int = RANK_BINS) -> DataFrame:
    """Bins of each step from the fullest (ties: lower bin first) with rank 1.., cut at `most`."""
    keys = [*STEP, *more]
    hist = saved(hist, "histogram", plain=True)
    cut = hist if stored_bytes(hist) <= 16 * rank_bins else _fullest(hist, most, keys)  # bin and count alone take 16 bytes a row
    return cut.withColumn("rank", F.row_number().over(Window.partitionBy(*keys).orderBy(F.desc("cnt"), F.asc("bin")))).where(F.col("rank") <= most)


def top_k_bins(hist: DataFrame, k: int, error_bound: float, anchor: str = "min", *more: str) -> DataFrame:
    """The k fullest bins of each step as centres."""
    top = rank_bins(hist, k, *more)
    return top.select(*STEP, *more, (F.col("rank") - 1).cast("int").alias("idx"), "bin", centre_of(error_bound, anchor).alias("centre"), "cnt")


def size_by_bits(ranked: DataFrame, counts: DataFrame, elem_bytes: int, candidates=range(1, 17), *more: str) -> DataFrame:
    """(var, step, n) to one row for each index length: covered, n_exact, used bins, estimated bytes, index entropy in bits."""
    keys = [*STEP, *more]
    sums = [F.sum(F.when(F.col("rank") <= (1 << b) - 1, F.col("cnt"))).alias(f"c{b}") for b in candidates]
    used = [F.count(F.when(F.col("rank") <= (1 << b) - 1, 1)).alias(f"u{b}") for b in candidates]
    logs = [F.sum(F.when(F.col("rank") <= (1 << b) - 1, F.col("cnt") * F.log2("cnt"))).alias(f"e{b}") for b in candidates]
    per = counts.select(*keys, "n").join(ranked.groupBy(*keys).agg(*sums, *used, *logs), keys, "left")
    rows = F.explode(F.array(*[F.struct(
        F.lit(b).alias("bits"), F.coalesce(F.col(f"c{b}"), F.lit(0)).alias("covered"), F.coalesce(F.col(f"u{b}"), F.lit(0)).alias("used"), F.coalesce(F.col(f"e{b}"), F.lit(0.0)).alias("logs")
    ) for b in candidates]))
    flat = per.select(*keys, "n", rows.alias("s")).select(*keys, "n", "s.*").withColumn("n_exact", F.col("n") - F.col("covered"))
    entropy = F.log2("n") - (F.col("logs") + F.when(F.col("n_exact") > 0, F.col("n_exact") * F.log2("n_exact")).otherwise(0.0)) / F.col("n")
    return flat.withColumn("est_bytes", estimated_size(F.col("bits"), F.col("n"), elem_bytes, F.col("n_exact"))).withColumn(
        "entropy_bytes", F.col("used") * elem_bytes + F.col("n") * entropy / 8.0 + F.col("n_exact") * elem_bytes
    ).drop("logs")


def choose_bits(sizes: DataFrame, objective: str = "size", *more: str) -> DataFrame:
    """The index length of least estimated size in each step (ties: the shorter)."""
    by = "entropy_bytes" if objective == "entropy" else "est_bytes"
    pick = F.min(F.struct(F.col(by).alias("_size"), "bits", "n", "covered", "n_exact", "est_bytes", "entropy_bytes"))
    return sizes.groupBy(*STEP, *more).agg(pick.alias("p")).select(*STEP, *more, "p.bits", "p.n", "p.covered", "p.n_exact", "p.est_bytes", "p.entropy_bytes")


def fixed_bits(sizes: DataFrame, bits: int, *more: str) -> DataFrame:
    return sizes.where(F.col("bits") == bits).select(*STEP, *more, "bits", "n", "covered", "n_exact", "est_bytes", "entropy_bytes")


def equal_width_bins(ratios: DataFrame, k: int) -> DataFrame:
    """Centres of k equal slices of each step's range, in closed form; a range of one value gives one centre."""
    slices = F.explode(F.sequence(F.lit(0), F.when(F.col("hi") > F.col("lo"), F.lit(k - 1)).otherwise(F.lit(0)))).alias("idx")
    rows = ratio_range(ratios).where("lo IS NOT NULL").select(*STEP, "lo", "hi", slices)
    return rows.select(*STEP, "idx", (F.col("lo") + (F.col("idx") + F.lit(0.5)) * ((F.col("hi") - F.col("lo")) / F.lit(k))).alias("centre"))


def nearest_equal(ratios: DataFrame, k: int) -> DataFrame:
    """ratios plus the centre of their equal-width slice, without a join over centres."""
    rng = small_side(ratio_range(ratios).select(*STEP, "lo", "hi"))
    step = (F.col("hi") - F.col("lo")) / F.lit(k)
    at = F.when(F.col("hi") > F.col("lo"), F.least(F.floor((F.col("ratio") - F.col("lo")) / step), F.lit(k - 1))).otherwise(F.lit(0))
    return ratios.join(rng, STEP, "left").withColumn("idx", at.cast("int")).withColumn("centre", F.col("lo") + (F.col("idx") + F.lit(0.5)) * step).drop("lo", "hi")


def log_ranges(ratios: DataFrame, k: int) -> DataFrame:
    """For each step and sign: range of log10|ratio| and its share of the k bins (one bin for zero where it occurs)."""
    sign = F.signum("ratio").cast("int").alias("sign")
    size = F.log10(F.abs("ratio"))
    per = ratios.where("ratio IS NOT NULL").groupBy(*STEP, sign).agg(F.count("*").alias("cnt"), F.min(F.when(F.col("ratio") != 0, size)).alias("a"), F.max(F.when(F.col("ratio") != 0, size)).alias("b"))
    of = Window.partitionBy(*STEP)
    zero = F.max(F.when(F.col("sign") == 0, 1).otherwise(0)).over(of)
    signed = F.sum(F.when(F.col("sign") != 0, F.col("cnt"))).over(of)
    negative = F.sum(F.when(F.col("sign") == -1, F.col("cnt")).otherwise(0)).over(of)
    left = F.lit(k) - zero
    share = F.greatest(F.least(F.round(left * negative / signed), left - F.when(negative < signed, 1).otherwise(0)), F.when(negative > 0, 1).otherwise(0))
    return per.withColumn("m", F.when(F.col("sign") == 0, F.lit(1)).when(F.col("sign") == -1, share).otherwise(left - share).cast("int")).drop("cnt")


def nearest_log(ratios: DataFrame, k: int) -> DataFrame:
    """ratios plus the centre of their slice of log10|ratio|."""
    sign = F.signum("ratio").cast("int")
    rng = small_side(log_ranges(ratios, k))
    joined = ratios.withColumn("sign", sign).join(rng, [*STEP, "sign"], "left")
    step = (F.col("b") - F.col("a")) / F.col("m")
    at = F.when(step > 0, F.least(F.floor((F.log10(F.abs("ratio")) - F.col("a")) / step), F.col("m") - 1)).otherwise(F.lit(0))
    centre = F.when(F.col("sign") == 0, F.lit(0.0)).otherwise(F.col("sign") * F.pow(F.lit(10.0), F.col("a") + (at + F.lit(0.5)) * step))
    return joined.withColumn("centre", centre).drop("sign", "a", "b", "m")


def log_scale_bins(ratios: DataFrame, k: int) -> DataFrame:
    """Centres of the log-scale slices of each step, ascending."""
    rng = log_ranges(ratios, k)
    slices = F.explode(F.sequence(F.lit(0), F.when(F.col("b") > F.col("a"), F.col("m") - 1).otherwise(F.lit(0)))).alias("i")
    step = (F.col("b") - F.col("a")) / F.col("m")
    rows = rng.where("m > 0").select("*", slices)
    centre = F.when(F.col("sign") == 0, F.lit(0.0)).otherwise(F.col("sign") * F.pow(F.lit(10.0), F.col("a") + (F.col("i") + F.lit(0.5)) * step))
    idx = (F.row_number().over(Window.partitionBy(*STEP).orderBy("centre")) - 1).alias("idx")
    return rows.select(*STEP, centre.alias("centre")).select(*STEP, idx, "centre")


def lloyd(values: np.ndarray, weights: np.ndarray, k: int, rounds: int, init: str = "quantile") -> np.ndarray:
    """Weighted one-dimensional k-means over ascending values: centres, ascending."""
    if not len(values):
        return np.zeros(0)
    k = min(k, len(values))
    running = np.cumsum(weights)
    if init == "equal":
        centres = values[0] + (np.arange(k) + 0.5) * (values[-1] - values[0]) / k
    else:
        centres = np.unique(values[np.searchsorted(running, (np.arange(k) + 0.5) / k * running[-1])])
    mass = np.concatenate(([0.0], np.cumsum(weights)))
    moment = np.concatenate(([0.0], np.cumsum(weights * values)))
    for _ in range(rounds):
        cut = np.concatenate(([0], np.searchsorted(values, (centres[1:] + centres[:-1]) / 2, side="right"), [len(values)]))
        m = mass[cut[1:]] - mass[cut[:-1]]
        new = np.where(m > 0, (moment[cut[1:]] - moment[cut[:-1]]) / np.where(m > 0, m, 1), centres)
        if np.array_equal(new, centres):
            break
        centres = new
    return centres


def kmeans_bins(ratios: DataFrame, k: int, max_iter: int = 20, init: str = "quantile", error_bound: float = 0.001, cells: int = 16) -> DataFrame:
    """k-means centres of each step, by weighted rounds over a fine histogram (cells of 2E / `cells`, mean and count each).

    Points are summed into the histogram in Spark; a step's occupied cells then meet in one task.  Where the range has more
    than MOST_CELLS such cells, they are widened to that many, so the task is bounded; a cell that a border between two
    centres cuts then goes whole to the centre nearer its mean.
    """
    fine = 2 * error_bound / cells
    wide = small_side(ratio_range(ratios).select(*STEP, F.greatest(F.lit(fine), (F.col("hi") - F.col("lo")) / F.lit(MOST_CELLS)).alias("_fine")))
    defined = ratios.where("ratio IS NOT NULL").select(*STEP, "ratio").join(wide, STEP)
    hist = defined.groupBy(*STEP, F.floor(F.col("ratio") / F.col("_fine")).alias("cell")).agg(F.avg("ratio").alias("x"), F.count("*").alias("w"))

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values("x")
        centres = lloyd(frame["x"].to_numpy(), frame["w"].to_numpy(dtype=float), k, max_iter, init)
        return pd.DataFrame({"var": frame["var"].iloc[0], "step": frame["step"].iloc[0], "idx": np.arange(len(centres)), "centre": centres})

    return hist.groupBy(*STEP).applyInPandas(run, "var string, step int, idx int, centre double")


def kmeans_ml_bins(ratios: DataFrame, k: int, max_iter: int = 20, seed: int = 0) -> DataFrame:
    """k-means of one step's ratios by the library's distributed algorithm."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.feature import VectorAssembler

    rows = ratios.where("ratio IS NOT NULL").select(*STEP, "ratio")
    keys = rows.select(*STEP).distinct().limit(2).collect()
    if len(keys) != 1:
        raise ValueError("one step at a time")
    model = KMeans(k=k, maxIter=max_iter, seed=seed).fit(VectorAssembler(inputCols=["ratio"], outputCol="features").transform(rows))
    centres = sorted(float(c[0]) for c in model.clusterCenters())
    return ratios.sparkSession.createDataFrame([(keys[0]["var"], keys[0]["step"], i, c) for i, c in enumerate(centres)], "var string, step int, idx int, centre double")


def nearest_centre(ratios: DataFrame, centres: DataFrame, error_bound: float) -> DataFrame:
    """ratios plus the nearest centre (ties: the lower) among those within E.

    An equi join on cells of width 2E: a centre is offered to its own cell and both neighbours, so no pair of all points and
    centres is formed.
    """
    width = 2 * error_bound
    offered = centres.select(*STEP, "centre", F.explode(F.array(*[F.floor(F.col("centre") / width) + d for d in (-1, 0, 1)])).alias("cell"))
    lists = small_side(offered.groupBy(*STEP, "cell").agg(F.array_sort(F.collect_set("centre")).alias("near")))
    joined = ratios.withColumn("cell", F.floor(F.col("ratio") / width)).join(lists, [*STEP, "cell"], "left")
    nearest = F.array_min(F.transform("near", lambda c: F.struct(F.abs(F.col("ratio") - c).alias("d"), c.alias("c"))))
    found = joined.withColumn("_n", nearest)
    return found.withColumn("centre", F.when(F.col("_n.d") <= error_bound, F.col("_n.c"))).drop("cell", "near", "_n")


def covered_by(ratios: DataFrame, strategy: str, bits: int, error_bound: float, init: str = "quantile") -> DataFrame:
    """ratios plus `covered`: whether a centre of the strategy lies within E."""
    k = (1 << bits) - 1
    if strategy == "topk":
        binned = with_bins(ratios, error_bound)
        top = small_side(top_k_bins(ratio_histogram(binned), k, error_bound).select(*STEP, "bin", F.lit(True).alias("covered")))
        return binned.join(top, [*STEP, "bin"], "left").withColumn("covered", F.coalesce("covered", F.lit(False))).drop("lo", "bin")
    if strategy == "kmeans":
        near = nearest_centre(ratios, saved(kmeans_bins(ratios, k, init=init, error_bound=error_bound), "centres"), error_bound)
        return near.withColumn("covered", F.col("centre").isNotNull()).drop("centre")
    near = nearest_equal(ratios, k) if strategy == "equal" else nearest_log(ratios, k)
    return near.withColumn("covered", F.coalesce(F.abs(F.col("ratio") - F.col("centre")) <= error_bound, F.lit(False))).drop("centre", *(["idx"] if strategy == "equal" else []))


def size_of_bits(bits: int, n: int, elem_bytes: int, n_exact: int) -> float:
    """The size estimate for plain numbers."""
    return 2.0**bits * elem_bytes + n * bits / 8 + n_exact * elem_bytes


def entropy_bits(counts: list[int]) -> float:
    total = sum(counts)
    return -sum(c / total * math.log2(c / total) for c in counts if c)


def sampled(ratios: DataFrame, share: float, seed: int = 0) -> DataFrame:
    """Ratios of a share of the positions, picked by a hash, so that an index length can be chosen from fewer points.

    Only the length may come from a sample: centres and indices are always made of all points.
    """
    return ratios.where(F.pmod(F.xxhash64("pos", F.lit(seed)), F.lit(1_000_000)) < int(share * 1_000_000))
