"""Most points that k windows of a given width can cover: the yardstick for binning strategies."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

STEP = ["var", "step"]
#: Cells of the (value, windows) table above which a step is refused; one bit or eight bytes a cell are held.
MOST_CELLS = 400_000_000


def cover(values: np.ndarray, weights: np.ndarray, k: int, width: float, windows: bool = False) -> tuple[int, list[float]]:
    """Weight of the best cover of ascending distinct values by k closed windows, and the windows' left ends if asked.

    Values are taken from the largest down.  The best for suffix i and any number of windows is either that of the suffix
    without value i, or a window that starts at value i plus the best with one window fewer for what lies beyond it.  Only
    as many suffixes are kept as the widest window reaches; recovering windows keeps one bit for each cell.
    """
    row, opened, beyond = _table(values, weights, k, width, windows)
    k = len(row) - 1
    lefts = []
    i, m = 0, k
    while windows and i < len(values) and m:
        if opened[i, m // 8] >> (7 - m % 8) & 1:
            lefts.append(float(values[i]))
            i, m = int(beyond[i]), m - 1
        else:
            i += 1
    return int(row[k]), lefts


def _table(values: np.ndarray, weights: np.ndarray, k: int, width: float, windows: bool = False) -> tuple[np.ndarray, np.ndarray | None, np.ndarray]:
    """The optimum for 0, 1, ... min(k, values) windows, the bits that recover windows, and how far each window reaches."""
    n = len(values)
    k = max(min(k, n), 0)
    beyond = np.searchsorted(values, values + width, side="right")
    if not n or not k:
        return np.zeros(1, dtype=np.int64), None, beyond
    mass = np.concatenate(([0], np.cumsum(weights.astype(np.int64))))
    ring = int((beyond - np.arange(n)).max()) + 1
    held = np.zeros((ring, k + 1), dtype=np.int64)
    opened = np.zeros((n, (k + 8) // 8), dtype=np.uint8) if windows else None
    for i in range(n - 1, -1, -1):
        skip = held[(i + 1) % ring]
        start = held[beyond[i] % ring][:-1] + (mass[beyond[i]] - mass[i])
        row = skip.copy()
        np.maximum(skip[1:], start, out=row[1:])
        if windows:
            opened[i] = np.packbits(np.concatenate(([False], start > skip[1:])))[: opened.shape[1]]
        held[i % ring] = row
    return held[0].copy(), opened, beyond


def _values(ratios: DataFrame, k: int, most_cells: int) -> DataFrame:
    """Distinct ratios of each step with their counts; a step whose table would have more than `most_cells` cells is refused."""
    values = ratios.where("ratio IS NOT NULL").groupBy(*STEP, "ratio").agg(F.count("*").alias("w"))
    worst = values.groupBy(*STEP).count().agg(F.max("count")).first()[0] or 0
    if worst * min(k, worst) > most_cells:
        raise MemoryError(f"optimal cover of {worst} values by {k} windows needs {worst * min(k, worst)} cells; the limit is {most_cells}")
    return values


def optimal_cover(ratios: DataFrame, k: int, width: float, most_cells: int = MOST_CELLS) -> DataFrame:
    """(var, step, n, covered): each step's optimum over its distinct ratios; steps run side by side.

    Refuses a step whose table would have more than `most_cells` cells: the full table grows with points times bins.
    """
    values = _values(ratios, k, most_cells)

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values("ratio")
        w = frame["w"].to_numpy()
        best, _ = cover(frame["ratio"].to_numpy(), w, k, width)
        return pd.DataFrame({"var": [frame["var"].iloc[0]], "step": [frame["step"].iloc[0]], "n": [int(w.sum())], "covered": [best]})

    return values.groupBy(*STEP).applyInPandas(run, "var string, step int, n long, covered long")


def relaxed(beyond: np.ndarray, mass: np.ndarray, prices: np.ndarray) -> np.ndarray:
    """For each price of a window, the most that weight covered less prices paid can be, for any number of windows.

    beyond: how far a window from each ascending value reaches; mass: weight before each value and in all.  Values are taken
    from the largest down, in runs within one width of each other: what a window of such a run leaves over lies beyond the
    run, so a run is a running maximum and takes no loop over its values.  Only the suffixes are held that windows further
    down still reach.
    """
    held = np.zeros((1, len(prices)), dtype=np.int64)
    end = len(beyond)
    while end:
        # the first value whose window reaches the run's last
        start = int(np.searchsorted(beyond[:end], end, side="left"))
        rows = held[beyond[start:end] - end] + (mass[beyond[start:end]] - mass[start:end])[:, None] - prices
        rows[-1] = np.maximum(rows[-1], held[0])
        held = np.concatenate((np.maximum.accumulate(rows[::-1], axis=0)[::-1], held[: beyond[start] - end + 1]))
        end = start
    return held[0]


def most_covered(values: np.ndarray, weights: np.ndarray, ks: tuple[int, ...], width: float) -> list[int]:
    """Weight of the best cover by k closed windows for each k, as cover() gives it, in memory that doesn't grow with k.

    The optimum is concave in k (the windows are intervals, so the linear programme has whole solutions), hence it is the least
    of relaxed(price) + k * price over whole prices; that is convex in the price and its least is found by bisection.
    """
    if not len(values):
        return [0 for _ in ks]
    known: dict[int, int] = {}
    beyond = np.searchsorted(values, values + width, side="right")
    mass = np.concatenate(([0], np.cumsum(weights, dtype=np.int64)))

    def at(prices: list[int]) -> None:
        new = np.array(sorted({p for p in prices if p not in known}), dtype=np.int64)
        if len(new):
            known.update(zip(new.tolist(), relaxed(beyond, mass, new).tolist(), strict=True))

    top = int((mass[beyond] - mass[:-1]).max())  # no window is worth more
    low, high = [0 for _ in ks], [top for _ in ks]
    while any(a < b for a, b in zip(low, high, strict=True)):
        middle = [(a + b) // 2 for a, b in zip(low, high, strict=True)]
        at([p for m in middle for p in (m, m + 1)])
        for i, (k, m) in enumerate(zip(ks, middle, strict=True)):
            if low[i] < high[i]:
                if known[m + 1] + k * (m + 1) < known[m] + k * m:
                    low[i] = m + 1
                else:
                    high[i] = m
    at(low)
    return [known[p] + k * p for p, k in zip(low, ks, strict=True)]


def optimal_covers(ratios: DataFrame, ks: tuple[int, ...], width: float) -> DataFrame:
    """(var, step, k, n, covered) for several numbers of windows; a step's distinct ratios, 32 bytes each, meet in one task."""
    values = ratios.where("ratio IS NOT NULL").groupBy(*STEP, "ratio").agg(F.count("*").alias("w"))

    def run(batches):
        held: list[tuple[np.ndarray, np.ndarray]] = []
        key = None

        def done():
            x, w = (np.concatenate(c) for c in zip(*held, strict=True))
            held.clear()
            rows = [(*key, k, int(w.sum()), c) for k, c in zip(ks, most_covered(x, w, ks, width), strict=True)]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.string(), pa.int32(), pa.int32(), pa.int64(), pa.int64()), strict=True)], ["var", "step", "k", "n", "covered"])

        for batch in batches:
            runs = pa.Table.from_batches([batch]).select(STEP).group_by(STEP, use_threads=False).aggregate([([], "count_all")]).to_pylist()
            at = 0
            for r in runs:
                if key is not None and key != (r["var"], r["step"]):
                    yield done()
                key = r["var"], r["step"]
                part = batch.slice(at, r["count_all"])
                held.append((part.column("ratio").to_numpy().copy(), part.column("w").to_numpy().copy()))  # else the whole batch is held
                at += r["count_all"]
        if held:
            yield done()

    return values.repartition(*STEP).sortWithinPartitions(*STEP, "ratio").mapInArrow(run, "var string, step int, k int, n long, covered long")


def optimal_windows(ratios: DataFrame, k: int, width: float, most_cells: int = MOST_CELLS) -> DataFrame:
    """(var, step, idx, centre): centres of the windows of an optimal cover, midway between the outermost values that they hold.

    Midway, so that rounding takes no value at a window's end out of reach.
    """
    values = _values(ratios, k, most_cells)

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values("ratio")
        values = frame["ratio"].to_numpy()
        _, lefts = cover(values, frame["w"].to_numpy(), k, width, windows=True)
        rights = values[np.searchsorted(values, np.array(lefts) + width, side="right") - 1]
        return pd.DataFrame({"var": frame["var"].iloc[0], "step": frame["step"].iloc[0], "idx": np.arange(len(lefts)), "centre": (np.array(lefts) + rights) / 2})

    return values.groupBy(*STEP).applyInPandas(run, "var string, step int, idx int, centre double")
