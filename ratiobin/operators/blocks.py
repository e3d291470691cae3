"""Index assignment, block alignment, packing and offsets."""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ratiobin.functions.bits import indices_per_block, pack_bits
from ratiobin.session import BROADCAST_BYTES, is_saved, join_spread, saved

STEP = ["var", "step"]
BLOCKS_SCHEMA = "var string, step int, block_id int, first_pos long, n int, payload binary, raw_bytes int, exact array<double>, n_exact long"


def assign_index(binned: DataFrame, centres: DataFrame, bits: DataFrame, limit: Column | None = None, most: int = BROADCAST_BYTES) -> DataFrame:
    """Points (with bin) to idx and centre; the sentinel 2^bits - 1 where no centre holds the ratio.

    centres: (var, step, bin, idx, centre); bits: (var, step, bits), a row a step, ready to be joined.  Centres are broadcast up to `most` bytes; beyond, the
    points of a bin are spread, since one bin may hold most of them.  limit: checks the
    distance from the centre again, as it is stored, and keeps points exactly that are farther.
    """
    hit = join_spread(binned, centres.select(*STEP, "bin", "idx", "centre"), [*STEP, "bin"], "pos", most=most).join(bits.select(*STEP, "bits"), STEP)
    if limit is not None:
        good = F.abs(F.col("ratio") - F.col("centre")) <= limit
        hit = hit.withColumn("idx", F.when(good, F.col("idx"))).withColumn("centre", F.when(good, F.col("centre")))
    return hit.withColumn("idx", F.coalesce("idx", sentinel(F.col("bits"))).cast("int"))


def sentinel(bits: Column) -> Column:
    return (F.pow(F.lit(2), bits) - 1).cast("int")


def is_exact(idx: Column, bits: Column) -> Column:
    return idx == sentinel(bits)


def exact_store(indexed: DataFrame) -> DataFrame:
    """Values that no centre holds, kept as they are."""
    return indexed.where(F.col("centre").isNull()).select(*STEP, "pos", F.col("cur").alias("value"))


def block_width(bits: Column, block_bytes: int, round_block: bool = False) -> Column:
    width = F.floor(F.lit(block_bytes * 8) / bits)
    return (F.greatest(F.floor(width / 8192) * 8192, F.lit(8192)) if round_block else width).cast("long")


def align(indexed: DataFrame, block_bytes: int, round_block: bool = False) -> DataFrame:
    """Each point with the block that holds it."""
    return indexed.withColumn("block_id", F.floor(F.col("pos") / block_width(F.col("bits"), block_bytes, round_block)).cast("int"))


def build_blocks(indexed: DataFrame, block_bytes: int = 1 << 20, level: int = 6, round_block: bool = False, elem_bytes: int = 8) -> DataFrame:
    """One row for each block: bit-packed and zlib-compressed on its own, with its exact values in order of position.

    Points missing from a block take an exact slot holding null, so positions stay implicit.  Exact values have elem_bytes each.
    """
    value, schema = (pa.float32(), BLOCKS_SCHEMA.replace("array<double>", "array<float>")) if elem_bytes == 4 else (pa.float64(), BLOCKS_SCHEMA)

    def run(block: pa.Table) -> pa.Table:
        block = block.sort_by("pos")
        bits, block_id = block.column("bits")[0].as_py(), block.column("block_id")[0].as_py()
        width = indices_per_block(block_bytes, bits, round_block)
        at = block.column("pos").to_numpy() - block_id * width
        if len(np.unique(at)) != len(at):
            raise ValueError("a point occurs twice in one step")
        n = int(at[-1]) + 1
        idx = np.full(n, (1 << bits) - 1, dtype=np.int64)
        idx[at] = block.column("idx").to_numpy()
        place = np.full(n, len(at), dtype=np.int64)
        place[at] = np.arange(len(at))
        values = pa.concat_arrays([block.column("cur").combine_chunks().cast(value, safe=False), pa.nulls(1, value)])
        exact = values.take(pa.array(place[idx == (1 << bits) - 1]))
        raw = pack_bits(idx, bits)
        row = [block.column("var")[0].as_py(), block.column("step")[0].as_py(), block_id, block_id * width, n, zlib.compress(raw, level), len(raw), exact, len(exact)]
        kinds = [pa.string(), pa.int32(), pa.int32(), pa.int64(), pa.int32(), pa.binary(), pa.int32(), pa.list_(value), pa.int64()]
        names = [c.split()[0] for c in BLOCKS_SCHEMA.split(", ")]
        cells = [pa.array([v], k) if n != "exact" else pa.ListArray.from_arrays(pa.array([0, len(v)], pa.int32()), v) for v, k, n in zip(row, kinds, names, strict=True)]
        return pa.table(cells, names=names)

    dealt = align(indexed, block_bytes, round_block).select(*STEP, "block_id", "pos", "idx", "cur", "bits")
    return dealt.groupBy(*STEP, "block_id").applyInArrow(run, schema)


def with_offsets(blocks: DataFrame, group: int = 1024) -> DataFrame:
    """Blocks plus byte_offset and exact_before: a prefix sum in two levels, over groups of blocks and then inside them."""
    sized = (blocks if is_saved(blocks) else saved(blocks, "blocks")).withColumn("_bytes", F.octet_length("payload")).withColumn("_group", F.floor(F.col("block_id") / group))
    keys = [*STEP, "_group"]
    outer = Window.partitionBy(*STEP).orderBy("_group").rowsBetween(Window.unboundedPreceding, -1)
    base = sized.groupBy(*keys).agg(F.sum("_bytes").alias("b"), F.sum("n_exact").alias("x")).select(*keys, F.coalesce(F.sum("b").over(outer), F.lit(0)).alias("_b"), F.coalesce(F.sum("x").over(outer), F.lit(0)).alias("_x"))
    inner = Window.partitionBy(*keys).orderBy("block_id").rowsBetween(Window.unboundedPreceding, -1)
    out = sized.join(F.broadcast(base), keys)  # one row for `group` blocks
    return out.select(
        *blocks.columns, (F.col("_b") + F.coalesce(F.sum("_bytes").over(inner), F.lit(0))).alias("byte_offset"), (F.col("_x") + F.coalesce(F.sum("n_exact").over(inner), F.lit(0))).alias("exact_before")
    )


def packed_bits_text(indexed: DataFrame, block_bytes: int) -> DataFrame:
    """Digest of each block's bits as text, with built-in functions only."""
    from ratiobin.functions.columns import bit_text

    dealt = align(indexed, block_bytes).select(*STEP, "block_id", F.struct("pos", bit_text(F.col("idx"), F.col("bits")).alias("b")).alias("p"))
    text = F.array_join(F.transform(F.array_sort(F.collect_list("p")), lambda p: p["b"]), "")
    return dealt.groupBy(*STEP, "block_id").agg(F.count("*").alias("n"), F.md5(text).alias("bits_md5"))
