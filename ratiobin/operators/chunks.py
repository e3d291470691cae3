"""The chunk form of the codec: one row holds a few ten thousand consecutive points as arrays.

Joins and shuffles then see one row for each chunk, ratios and bins are NumPy arrays inside a task, and blocks are cut where
chunks are, so packing moves no points.  A chunk is a multiple of 8192 points, which ends on a byte for every index length.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ratiobin.functions.bits import pack_bits
from ratiobin.operators import binning as bn
from ratiobin.operators.blocks import BLOCKS_SCHEMA
from ratiobin.session import BROADCAST_BYTES, join_spread, saved, small_side
from ratiobin.spec import CodecSpec

STEP = ["var", "step"]
CHUNK = 8192 * 8


def to_chunks(df: DataFrame, size: int = CHUNK) -> DataFrame:
    """(var, step, pos, value) to (var, step, chunk_id, values); positions missing inside a chunk are null."""
    if size % 8192:
        raise ValueError("chunks are multiples of 8192 points")

    def run(group: pa.Table) -> pa.Table:
        at = group.column("pos").to_numpy() % size
        values = np.full(int(at.max()) + 1, np.nan)
        null = np.ones(len(values), dtype=bool)
        values[at], null[at] = group.column("value").to_numpy(), group.column("value").is_null().to_numpy()
        return pa.table([group.column("var")[:1], group.column("step")[:1], group.column("chunk_id")[:1], _lists([pa.array(values, mask=null)])], names=["var", "step", "chunk_id", "values"])

    placed = df.withColumn("chunk_id", F.floor(F.col("pos") / size))
    return placed.groupBy(*STEP, "chunk_id").applyInArrow(run, "var string, step int, chunk_id long, values array<double>")


def from_chunks(chunks: DataFrame, column: str = "values", name: str = "value", size: int = CHUNK) -> DataFrame:
    flat = chunks.select(*STEP, "chunk_id", F.posexplode(column).alias("_at", name))
    return flat.select(*STEP, (F.col("chunk_id") * size + F.col("_at")).alias("pos"), name)


def _lists(parts: list) -> pa.ListArray:
    """Arrays as one list column, without a Python object for each element."""
    parts = [p if isinstance(p, pa.Array) else pa.array(p, pa.float64()) for p in parts]
    offsets = np.concatenate(([0], np.cumsum([len(p) for p in parts]))).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.concat_arrays(parts) if parts else pa.array([], pa.float64()))


def _array(column: pa.Array, i: int) -> np.ndarray:
    """A list element as doubles, NaN for null; an absent list is empty."""
    cell = column[i]
    return cell.values.to_numpy(zero_copy_only=False).astype(np.float64) if cell.is_valid else np.zeros(0)


def change_ratios_chunked(chunks: DataFrame) -> DataFrame:
    """(var, step, chunk_id, values) to (…, cur, ratio, lo, hi); undefined ratios are null, the first step is left out.

    One shuffle, of whole chunks.
    """
    order = Window.partitionBy("var", "chunk_id").orderBy("step")
    first = chunks.groupBy("var").agg(F.min("step").alias("_first"))
    paired = chunks.withColumn("_prev", F.when(F.lag("step").over(order) == F.col("step") - 1, F.lag("values").over(order)))
    paired = paired.join(F.broadcast(first), "var").where("step > _first").select(*STEP, "chunk_id", "values", "_prev")  # one row for each variable

    def run(batches):
        for batch in batches:
            rows = []
            for i in range(batch.num_rows):
                cur, before = _array(batch.column(3), i), _array(batch.column(4), i)
                prev = np.full(len(cur), np.nan)
                prev[: min(len(cur), len(before))] = before[: len(cur)]
                with np.errstate(all="ignore"):
                    ratio = np.where(np.isfinite(prev) & np.isfinite(cur) & (prev != 0), (cur - prev) / prev, np.nan)
                good = np.isfinite(ratio)
                rows.append((pa.array(ratio, mask=~good), float(ratio[good].min()) if good.any() else None, float(ratio[good].max()) if good.any() else None))
            yield pa.RecordBatch.from_arrays(
                [*(batch.column(i) for i in range(4)), _lists([r[0] for r in rows]), pa.array([r[1] for r in rows], pa.float64()), pa.array([r[2] for r in rows], pa.float64())],
                ["var", "step", "chunk_id", "cur", "ratio", "lo", "hi"],
            )

    return paired.mapInArrow(run, "var string, step int, chunk_id long, cur array<double>, ratio array<double>, lo double, hi double")


def histogram_chunked(ratios: DataFrame, error_bound: float) -> DataFrame:
    """Occupied bins of each step: every chunk is counted in its task, and only (bin, count) rows are shuffled."""
    lows = small_side(ratios.groupBy(*STEP).agg(F.min("lo").alias("step_lo")))

    def run(batches):
        for batch in batches:
            out = []
            for i in range(batch.num_rows):
                r = _array(batch.column(2), i)
                r = r[~np.isnan(r)]
                if len(r):
                    lo = batch.column(3)[i].as_py()
                    bins, cnt = np.unique(np.floor((r - lo) / (2 * error_bound)).astype(np.int64), return_counts=True)
                    out.append((batch.column(0)[i].as_py(), batch.column(1)[i].as_py(), lo, bins, cnt))
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array([v for v, _, _, b, _ in out for _ in range(len(b))], pa.string()), pa.array(np.concatenate([np.full(len(o[3]), o[1]) for o in out]) if out else [], pa.int32()),
                    pa.array(np.concatenate([o[3] for o in out]) if out else [], pa.int64()), pa.array(np.concatenate([o[4] for o in out]) if out else [], pa.int64()),
                    pa.array(np.concatenate([np.full(len(o[3]), o[2]) for o in out]) if out else [], pa.float64()),
                ],
                ["var", "step", "bin", "cnt", "lo"],
            )

    parts = ratios.select(*STEP, "ratio").join(lows, STEP).mapInArrow(run, "var string, step int, bin long, cnt long, lo double")
    return parts.groupBy(*STEP, "bin").agg(F.sum("cnt").alias("cnt"), F.first("lo").alias("lo"))


@dataclass
class ChunkCompressed:
    header: DataFrame
    centres: DataFrame
    blocks: DataFrame


def compress_chunks(chunks: DataFrame, spec: CodecSpec = CodecSpec(), size: int = CHUNK, most: int = BROADCAST_BYTES) -> ChunkCompressed:
    """All steps of a chunked series: ratios, histogram, index lengths, packed blocks of one chunk each.

    The bins of all steps are broadcast up to `most` bytes; beyond, the chunks of a step are spread over tasks.
    """
    ratios = saved(change_ratios_chunked(chunks), "ratio-chunks")
    counts = ratios.groupBy(*STEP).agg(F.sum(F.size("cur")).alias("n"), F.count("*").cast("int").alias("n_blocks"))
    ranked = saved(bn.rank_bins(histogram_chunked(ratios, spec.error_bound), (1 << (spec.bits or max(spec.candidates))) - 1), "ranked")
    sizes = bn.size_by_bits(ranked, counts, spec.elem_bytes, (spec.bits,) if spec.bits else spec.candidates)
    bits = saved(bn.fixed_bits(sizes, spec.bits) if spec.bits else bn.choose_bits(sizes, "entropy" if spec.objective == "entropy" else "size"), "bits")
    top = ranked.join(small_side(bits.select(*STEP, "bits")), STEP).where(F.col("rank") < F.pow(F.lit(2), "bits"))
    centres = saved(top.select(*STEP, (F.col("rank") - 1).cast("int").alias("idx"), "bin", bn.centre_of(spec.error_bound, "min").alias("centre"), "cnt", "lo"), "centres")
    lists = centres.groupBy(*STEP).agg(F.first("lo").alias("step_lo"), F.array_sort(F.collect_list(F.struct("bin", "idx"))).alias("_bins"))
    keyed = bits.select(*STEP, "bits").join(lists, STEP, "left").select(*STEP, "bits", "step_lo", F.col("_bins.bin").alias("bins"), F.col("_bins.idx").alias("idx"))
    told = join_spread(ratios.select(*STEP, "chunk_id", "cur", "ratio"), keyed, STEP, "chunk_id", "inner", most)
    error_bound, level = spec.error_bound, spec.level

    def run(batches):
        for batch in batches:
            rows = []
            for i in range(batch.num_rows):
                width, cur, r = batch.column(5)[i].as_py(), batch.column(3)[i].values, _array(batch.column(4), i)
                none = (1 << width) - 1
                idx = np.full(len(r), none, dtype=np.int64)
                if batch.column(7)[i].is_valid:
                    bins, at = batch.column(7)[i].values.to_numpy(), batch.column(8)[i].values.to_numpy()
                    good = np.flatnonzero(~np.isnan(r))
                    mine = np.floor((r[good] - batch.column(6)[i].as_py()) / (2 * error_bound)).astype(np.int64)
                    place = np.minimum(np.searchsorted(bins, mine), len(bins) - 1)
                    hit = bins[place] == mine
                    idx[good[hit]] = at[place[hit]]
                raw = pack_bits(idx, width)
                kept = cur.take(pa.array(np.flatnonzero(idx == none)))
                chunk = batch.column(2)[i].as_py()
                rows.append((batch.column(0)[i].as_py(), batch.column(1)[i].as_py(), chunk, chunk * size, len(r), zlib.compress(raw, level), len(raw), kept, len(kept)))
            kinds = [pa.string(), pa.int32(), pa.int32(), pa.int64(), pa.int32(), pa.binary(), pa.int32(), pa.list_(pa.float64()), pa.int64()]
            names = [c.split()[0] for c in BLOCKS_SCHEMA.split(", ")]
            yield pa.RecordBatch.from_arrays([_lists([r[j] for r in rows]) if names[j] == "exact" else pa.array([r[j] for r in rows], k) for j, k in enumerate(kinds)], names)

    header = bits.join(counts.drop("n"), STEP).withColumn("indices_per_block", F.lit(size)).withColumn("elem_bytes", F.lit(spec.elem_bytes)).withColumn("error_bound", F.lit(error_bound))
    used = centres.groupBy(*STEP).agg(F.count("*").cast("int").alias("n_centres"))
    header = header.join(used, STEP, "left").withColumn("n_centres", F.coalesce("n_centres", F.lit(0)))
    return ChunkCompressed(saved(header, "header"), centres, told.mapInArrow(run, BLOCKS_SCHEMA))
