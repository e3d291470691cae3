"""Compression of a stream with centres that an earlier step has fixed.

Chunks of steps arrive; the state of a chunk is its last reconstructed values.  No step has to be whole before it is coded,
at the price of more exact values when the ratios drift away from the frozen centres.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ratiobin.functions.bits import pack_bits

OUTPUT = "var string, step int, chunk_id long, n int, bits int, payload binary, exact array<double>, hat array<double>"
STATE = "step int, hat array<double>"


def code_chunk(prev: np.ndarray, cur: np.ndarray, centres: np.ndarray, error_bound: float) -> tuple[np.ndarray, np.ndarray]:
    """Index of each point (the number of centres where none is near enough) and its reconstruction."""
    before = np.full(len(cur), np.nan)
    before[: min(len(prev), len(cur))] = prev[: len(cur)]
    with np.errstate(all="ignore"):
        ratio = np.where(np.isfinite(before) & np.isfinite(cur) & (before != 0), (cur - before) / before, np.nan)
    right = np.clip(np.searchsorted(centres, ratio), 1, max(len(centres) - 1, 1))
    left = right - 1
    right = np.minimum(right, len(centres) - 1)
    near = np.where(np.abs(ratio - centres[left]) <= np.abs(centres[right] - ratio), left, right)
    good = np.abs(ratio - centres[near]) <= error_bound
    return np.where(good, near, len(centres)), np.where(good, before * (1 + centres[near]), cur)


def compress_frozen(chunks: DataFrame, centres: list[float], error_bound: float = 0.001) -> DataFrame:
    """Stream of (var, step, chunk_id, values) to coded chunks; a chunk's first step is kept as exact values.

    Rows of a step that is coded already are left out, so a replayed batch changes nothing.
    """
    table = np.unique(np.array(centres, dtype=np.float64))
    if not len(table):
        raise ValueError("at least one centre is needed")
    bits = int(len(table)).bit_length()
    none = (1 << bits) - 1

    def run(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        step, hat = state.get if state.exists else (-1, None)
        rows = []
        for _, row in pd.concat(list(frames)).sort_values("step").iterrows():
            if row["step"] <= step:
                continue
            cur = np.array([np.nan if v is None else v for v in row["values"]], dtype=np.float64)
            prev = np.zeros(0) if hat is None else np.array(hat, dtype=np.float64)
            idx, made = code_chunk(prev, cur, table, error_bound)
            idx = np.where(idx == len(table), none, idx)
            step, hat = int(row["step"]), made.tolist()
            rows.append((key[0], step, key[1], len(cur), bits, zlib.compress(pack_bits(idx, bits)), cur[idx == none].tolist(), hat))
        if rows:
            state.update((step, hat))
        yield pd.DataFrame(rows, columns=[c.split()[0] for c in OUTPUT.split(", ")])

    return chunks.groupBy("var", "chunk_id").applyInPandasWithState(run, OUTPUT, STATE, "append", GroupStateTimeout.NoTimeout)
