"""Decoding: one step, a chain of steps, and ranges of positions that touch only their blocks."""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ratiobin.functions.bits import unpack_bits
from ratiobin.session import BROADCAST_BYTES, join_spread

STEP = ["var", "step"]
#: Positions whose steps are decoded together in one task.
CHAIN = 8192


def decode_blocks(blocks: DataFrame, header: DataFrame, centres: DataFrame, most: int = BROADCAST_BYTES) -> DataFrame:
    """Blocks to points (var, step, pos, factor, exact, is_exact): the centre to scale by, or the exact value.

    Centres reach a block as one array of its step, so the lookup is an array index in the task that unpacks the block.  The
    arrays are broadcast up to `most` bytes; beyond, the blocks of a step are spread over tasks.
    """
    told = join_spread(blocks.select(*STEP, "block_id", "first_pos", "n", "payload", "exact"), centre_arrays(header, centres), STEP, "block_id", "inner", most)

    def run(batches):
        for batch in batches:
            column = {c: batch.column(i) for i, c in enumerate(batch.schema.names)}
            for i in range(batch.num_rows):
                n, bits = column["n"][i].as_py(), column["bits"][i].as_py()
                idx = unpack_bits(zlib.decompress(column["payload"][i].as_buffer()), bits, n)
                kept = idx == (1 << bits) - 1
                table = column["centres"][i].values.to_numpy().astype(np.float64) if column["centres"][i].is_valid and len(column["centres"][i]) else np.zeros(1)
                factor = table[np.where(kept, 0, np.minimum(idx, len(table) - 1))]
                place = np.where(kept, np.cumsum(kept) - 1, 0)
                exact = column["exact"][i].values.take(pa.array(place, mask=~kept))
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.repeat(pa.scalar(column["var"][i].as_py(), pa.string()), n), pa.array(np.full(n, column["step"][i].as_py(), dtype=np.int32)), pa.array(column["first_pos"][i].as_py() + np.arange(n)),
                        pa.array(factor), exact.cast(pa.float64()), pa.array(kept),
                    ],
                    ["var", "step", "pos", "factor", "exact", "is_exact"],
                )

    return told.mapInArrow(run, "var string, step int, pos long, factor double, exact double, is_exact boolean")


def centre_arrays(header: DataFrame, centres: DataFrame) -> DataFrame:
    """(var, step, bits, centres): one array a step, in order of the index."""
    lists = centres.groupBy(*STEP).agg(F.transform(F.array_sort(F.collect_list(F.struct("idx", "centre"))), lambda c: c["centre"]).alias("centres"))
    if "centres_step" not in header.columns:
        return header.select(*STEP, "bits").join(lists, STEP, "left")
    return header.select(*STEP, "bits", "centres_step").join(lists.withColumnRenamed("step", "centres_step"), ["var", "centres_step"], "left").drop("centres_step")


def centre_map(header: DataFrame, centres: DataFrame) -> DataFrame:
    """(var, step, attributes, centres): a step's header as a map of texts, and its centres as a map from index to centre."""
    names = [c for c in header.columns if c not in STEP]
    attributes = F.map_from_arrays(F.array(*map(F.lit, names)), F.array(*[F.col(c).cast("string") for c in names]))
    maps = centres.groupBy(*STEP).agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("idx", "centre")))).alias("centres"))
    return header.select(*STEP, attributes.alias("attributes")).join(maps, STEP, "left")


def reconstruct(prev_hat: Column, factor: Column, exact: Column, is_exact: Column) -> Column:
    return F.when(is_exact, exact).otherwise(prev_hat * (1 + factor))


def decompress_step(points: DataFrame, prev_hat: DataFrame) -> DataFrame:
    """Decoded points of one step on the reconstructed step before it (var, pos, value_hat)."""
    before = prev_hat.select("var", "pos", F.col("value_hat").alias("_prev"))
    out = points.join(before, ["var", "pos"], "left").withColumn("value_hat", reconstruct(F.col("_prev"), F.col("factor"), F.col("exact"), F.col("is_exact")))
    return out.select(*STEP, "pos", "value_hat")


def chain_of(group: pa.Table) -> pa.Table:
    """Decoded rows of one run of positions to their values, step after step over the whole run at once."""
    group = group.sort_by("step")
    step, pos = group.column("step").to_numpy(), group.column("pos").to_numpy()
    kept, factor = group.column("is_exact").to_numpy().astype(bool), group.column("factor").to_numpy()
    exact = group.column("exact").combine_chunks()
    null = exact.is_null().to_numpy(zero_copy_only=False)
    value = exact.fill_null(0.0).to_numpy()
    at = pos - pos.min()
    now, gone = np.zeros(int(at.max()) + 1), np.ones(int(at.max()) + 1, dtype=bool)
    out, lost = np.empty(len(at)), np.empty(len(at), dtype=bool)
    edges = [0, *(np.flatnonzero(np.diff(step)) + 1).tolist(), len(step)]
    for a, b in zip(edges, edges[1:], strict=False):
        here = at[a:b]
        with np.errstate(all="ignore"):
            now[here] = np.where(kept[a:b], value[a:b], now[here] * (1 + factor[a:b]))
        gone[here] = np.where(kept[a:b], null[a:b], gone[here])
        out[a:b], lost[a:b] = now[here], gone[here]
    return pa.table([group.column("var"), group.column("step"), group.column("pos"), pa.array(out, mask=lost)], names=["var", "step", "pos", "value_hat"])


def decompress_chain(points: DataFrame, anchors: DataFrame) -> DataFrame:
    """All steps at once: one shuffle by runs of CHAIN positions, then a product that restarts at each exact value.

    anchors: (var, step, pos, value) stored as they are.  A task holds one run at a time, all steps of it.
    """
    rows = points.select(*STEP, "pos", "factor", "exact", "is_exact").unionByName(
        anchors.select(*STEP, "pos", F.lit(0.0).alias("factor"), F.col("value").alias("exact"), F.lit(True).alias("is_exact"))
    )
    runs = rows.withColumn("_run", F.floor(F.col("pos") / CHAIN))
    return runs.groupBy("var", "_run").applyInArrow(chain_of, "var string, step int, pos long, value_hat double")


def block_range(start: int, stop: int, width: int) -> tuple[int, int]:
    """First and last block that hold positions start .. stop - 1."""
    return start // width, (stop - 1) // width


def blocks_for_range(blocks: DataFrame, step: int, start: int, stop: int, width: int) -> DataFrame:
    """Only the blocks that a range of positions touches; the filters reach the Parquet scan."""
    first, last = block_range(start, stop, width)
    return blocks.where((F.col("step") == step) & (F.col("block_id") >= first) & (F.col("block_id") <= last))
