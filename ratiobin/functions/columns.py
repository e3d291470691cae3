"""Formulas of the codec as Column expressions (inside whole-stage codegen)."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

INFINITY = float("inf")


def is_finite(x: Column) -> Column:
    return x.isNotNull() & ~F.isnan(x) & (F.abs(x) < INFINITY)


def is_defined_ratio(prev: Column, cur: Column) -> Column:
    return is_finite(prev) & is_finite(cur) & (prev != 0)


def change_ratio(prev: Column, cur: Column, zero_prev: str = "exact") -> Column:
    """(cur - prev) / prev; null where it is undefined.  'unchanged' takes zero after zero as ratio 0."""
    ratio = F.when(is_defined_ratio(prev, cur), F.try_divide(cur - prev, prev))
    ratio = F.when(is_finite(ratio), ratio)
    return F.when((prev == 0) & (cur == 0), F.lit(0.0)).otherwise(ratio) if zero_prev == "unchanged" else ratio


def grid_bin(ratio: Column, lo: Column, error_bound: float) -> Column:
    """Number of the bin of width 2E, counted from lo."""
    return F.floor((ratio - lo) / F.lit(2 * error_bound)).cast("long")


def zero_bin(ratio: Column, error_bound: float) -> Column:
    """Number of the bin of width 2E when bin 0 is centred on zero."""
    return F.floor((ratio + F.lit(error_bound)) / F.lit(2 * error_bound)).cast("long")


def bin_centre(bin_: Column, lo: Column, error_bound: float) -> Column:
    return lo + (bin_ + F.lit(0.5)) * F.lit(2 * error_bound)


def zero_centre(bin_: Column, error_bound: float) -> Column:
    return bin_ * F.lit(2 * error_bound)


def estimated_size(bits, n: Column, elem_bytes: int, n_exact: Column) -> Column:
    """Bytes of centres, index and exact values for an index length, before lossless compression."""
    bits = bits if isinstance(bits, Column) else F.lit(bits)
    return F.pow(F.lit(2.0), bits) * elem_bytes + n * bits / F.lit(8.0) + n_exact * elem_bytes


def predicted_cr(bits: Column, zlib_ratio: Column, alpha: Column, elem_bits: int) -> Column:
    """Back-of-envelope compression ratio of one value."""
    return F.lit(float(elem_bits)) / (bits / zlib_ratio + alpha * elem_bits)


def dp_memory_bytes(n: Column, bits: Column, cell: int = 4) -> Column:
    """Bytes of the full table of the optimal cover."""
    return n * F.pow(F.lit(2.0), bits) * cell


def flatten_position(index: list[Column], dims: list[int]) -> Column:
    """Row-major position of a multi-dimensional cell."""
    return reduce(lambda at, i: at * dims[i] + index[i], range(1, len(dims)), index[0].cast("long"))


def in_interior(index: list[Column], dims: list[int], guard: int = 2) -> Column:
    """Whether a cell of a mesh block lies inside its guard cells (`guard` on each side; dims without them)."""
    return reduce(lambda a, b: a & b, [(i >= guard) & (i < guard + n) for i, n in zip(index, dims, strict=True)])


def bit_text(idx: Column, bits: Column) -> Column:
    """Index as text of exactly `bits` binary digits."""
    return F.lpad(F.bin(idx), bits, F.lit("0"))
