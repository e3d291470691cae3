"""Whole codec runs: compress a series or a step, decode chains and ranges, closed loop."""

from __future__ import annotations

import zlib
from dataclasses import dataclass, replace
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ratiobin.functions.bits import indices_per_block, pack_bits
from ratiobin.functions.columns import change_ratio
from ratiobin.operators import binning as bn
from ratiobin.operators import blocks as bl
from ratiobin.operators import decode as dc
from ratiobin.operators.measures import OFFSET_BYTES, space_breakdown
from ratiobin.operators.optimal import optimal_windows
from ratiobin.operators.ratios import change_ratios, ratio_range
from ratiobin.session import is_saved, join_spread, new_path, saved, small_side
from ratiobin.spec import CodecSpec

STEP = ["var", "step"]
#: Points of a block in a sweep over index lengths.
SWEEP_POINTS = 1 << 19


@dataclass
class Indexed:
    """Points with their index, and what decoding needs besides: centres, index lengths, ranges of the ratios."""

    spec: CodecSpec
    points: DataFrame
    centres: DataFrame
    bits: DataFrame
    ranges: DataFrame


@dataclass
class Compressed:
    """header: one row a step; centres; blocks; anchors: steps stored without loss as (var, step, pos, value)."""

    spec: CodecSpec
    header: DataFrame
    centres: DataFrame
    blocks: DataFrame
    anchors: DataFrame


def _bits(counts: DataFrame, ranked: DataFrame, spec: CodecSpec) -> DataFrame:
    if spec.bits is not None:
        return bn.fixed_bits(bn.size_by_bits(ranked, counts, spec.elem_bytes, (spec.bits,)), spec.bits)
    return bn.choose_bits(bn.size_by_bits(ranked, counts, spec.elem_bytes, spec.candidates), spec.objective)


def _limit(spec: CodecSpec, strict: bool) -> Column | None:
    """How far a ratio may lie from its centre as stored, where the bin alone doesn't ensure it."""
    if spec.bound == "value":
        return F.lit(spec.error_bound) * F.least(F.lit(1.0), F.abs(1 + F.col("ratio")))
    return F.lit(spec.error_bound) if strict or spec.elem_bytes == 4 else None


def _index_pooled(ratios: DataFrame, spec: CodecSpec, strict: bool) -> Indexed:
    """One set of centres and one index length for all steps of a variable; the centres belong to its first step."""
    pooled = index_ratios(ratios.withColumn("_step", F.col("step")).withColumn("step", F.lit(0)), replace(spec, centres_scope="step"), strict)
    points = pooled.points.withColumn("step", F.col("_step")).drop("_step")
    ranges = small_side(ratio_range(ratios))
    first = ranges.groupBy("var").agg(F.min("step").alias("step"))
    return Indexed(spec, points, pooled.centres.drop("step").join(first, "var"), _counted(points), ranges)


def _counted(points: DataFrame) -> DataFrame:
    sizes = points.groupBy(*STEP, "bits").agg(F.count("*").alias("n"), F.count("centre").alias("covered"), F.count(F.when(F.col("centre").isNull(), 1)).alias("n_exact"))
    return sizes.withColumn("est_bytes", F.lit(None).cast("double")).withColumn("entropy_bytes", F.lit(None).cast("double"))


def index_ratios(ratios: DataFrame, spec: CodecSpec, strict: bool = False) -> Indexed:
    """Bins, index lengths, centres and index of all steps of the ratios at once."""
    if spec.centres_scope == "series":
        return _index_pooled(ratios, spec, strict)
    ranges = small_side(ratio_range(ratios))
    if spec.strategy == "topk":
        binned = bn.with_bins(ratios, spec.error_bound, spec.anchor, ranges=ranges)
        ranked = saved(bn.rank_bins(bn.ratio_histogram(binned), (1 << (spec.bits or max(spec.candidates))) - 1), "ranked")
        bits = small_side(_measured_bits(ratios, spec) if spec.objective == "measured" and spec.bits is None else _bits(ranges, ranked, spec))
        top = ranked.join(bits.select(*STEP, "bits"), STEP).where(F.col("rank") < F.pow(F.lit(2), "bits"))
        centre = bn.centre_of(spec.error_bound, spec.anchor)
        centre = centre.cast("float").cast("double") if spec.elem_bytes == 4 else centre
        centres = top.select(*STEP, (F.col("rank") - 1).cast("int").alias("idx"), "bin", centre.alias("centre"), "cnt")
        return Indexed(spec, bl.assign_index(binned, centres, bits, _limit(spec, strict)), centres, bits, ranges)
    if spec.bits is None:
        raise ValueError("only top-k binning chooses the index length")
    k = (1 << spec.bits) - 1
    if spec.strategy == "equal":
        near = bn.nearest_equal(ratios, k)
        near = near.withColumn("centre", F.when(F.abs(F.col("ratio") - F.col("centre")) <= spec.error_bound, F.col("centre"))).drop("idx")
    elif spec.strategy == "log":
        near = bn.nearest_log(ratios, k)
        near = near.withColumn("centre", F.when(F.abs(F.col("ratio") - F.col("centre")) <= spec.error_bound, F.col("centre")))
    else:
        found = bn.kmeans_bins(ratios, k, error_bound=spec.error_bound) if spec.strategy == "kmeans" else optimal_windows(ratios, k, spec.width)
        near = bn.nearest_centre(ratios, saved(found, "centres"), spec.error_bound)
    if spec.bound == "value":
        near = near.withColumn("centre", F.when(F.abs(F.col("ratio") - F.col("centre")) <= _limit(spec, strict), F.col("centre")))
    near = saved(near, "near")
    used = near.where("centre IS NOT NULL").groupBy(*STEP, "centre").agg(F.count("*").alias("cnt"))
    centres = saved(used.withColumn("idx", (F.row_number().over(Window.partitionBy(*STEP).orderBy("centre")) - 1).cast("int")).withColumn("bin", F.col("idx").cast("long")), "centres")
    points = near.join(small_side(centres.select(*STEP, "centre", "idx")), [*STEP, "centre"], "left").withColumn("bits", F.lit(spec.bits))
    points = points.withColumn("lo", F.lit(None).cast("double")).withColumn("idx", F.coalesce("idx", bl.sentinel(F.col("bits"))).cast("int"))
    return Indexed(spec, points, centres, _counted(points), ranges)


def _measured_bits(ratios: DataFrame, spec: CodecSpec) -> DataFrame:
    """The index length of least stored size, by packing every candidate."""
    sweep = bits_sweep(ratios, spec, spec.candidates)
    pick = sweep.groupBy(*STEP).agg(F.min(F.struct("stored_bytes", "bits", "n", "n_exact", "est_bytes")).alias("p"))
    return pick.select(*STEP, "p.bits", "p.n", (F.col("p.n") - F.col("p.n_exact")).alias("covered"), "p.n_exact", "p.est_bytes", F.lit(None).cast("double").alias("entropy_bytes"))


def header_of(indexed: Indexed) -> DataFrame:
    """One row a step with all that decoding and reports need to know of it."""
    spec = indexed.spec
    rng = indexed.ranges.select(*STEP, F.col("lo").alias("ratio_min"), F.col("hi").alias("ratio_max"), F.col("last_pos").alias("_last"))
    used = indexed.centres.groupBy(*STEP).agg(F.count("*").cast("int").alias("n_centres"))
    width = bl.block_width(F.col("bits"), spec.block_bytes, spec.round_block)
    told = indexed.bits.join(rng, STEP).join(used, STEP, "left")
    told = told.withColumn("centres_step", F.min("step").over(Window.partitionBy("var")) if spec.centres_scope == "series" else F.col("step"))
    return (
        told.select(
            *STEP, "n", F.lit("delta").alias("kind"), "bits", F.lit(spec.strategy).alias("strategy"), F.lit(spec.error_bound).alias("error_bound"), F.lit(spec.elem_bytes).alias("elem_bytes"),
            F.coalesce("n_centres", F.lit(0)).alias("n_centres"), width.cast("int").alias("indices_per_block"), (F.floor(F.col("_last") / width) + 1).cast("int").alias("n_blocks"),
            "n_exact", "ratio_min", "ratio_max", F.lit(spec.reference).alias("reference"), F.lit(spec.anchor).alias("anchor"), "est_bytes", "centres_step",
        )
    )


def compress_ratios(ratios: DataFrame, spec: CodecSpec, anchors: DataFrame) -> Compressed:
    indexed = index_ratios(ratios, spec)
    points = kept(indexed.points, spec, "indexed")
    indexed = replace_points(indexed, points)
    blocks = bl.with_offsets(bl.build_blocks(points, spec.block_bytes, spec.level, spec.round_block, spec.elem_bytes))
    centres = indexed.centres.withColumn("centre", F.col("centre").cast("float")) if spec.elem_bytes == 4 else indexed.centres
    return Compressed(spec, saved(header_of(indexed), "header"), saved(centres, "centres"), saved(blocks, "store"), anchors)


def kept(df: DataFrame, spec: CodecSpec, tag: str) -> DataFrame:
    """A step that is read more than once: on disk in the shared folder, or in the executors' memory (spilling to their disks)."""
    return saved(df, tag) if spec.cache == "disk" else df.persist()


def replace_points(indexed: Indexed, points: DataFrame) -> Indexed:
    return replace(indexed, points=points)


def is_anchor(spec: CodecSpec):
    """Steps stored without loss: the first, and every anchor_every-th after it."""
    first = F.col("step") == F.col("_first")
    return first if not spec.anchor_every else first | ((F.col("step") - F.col("_first")) % spec.anchor_every == 0)


def grouped(df: DataFrame, size: int) -> DataFrame:
    """A series whose runs of `size` positions are variables of their own: 'var#run', positions from 0."""
    run = F.floor(F.col("pos") / size)
    return df.select(F.concat_ws("#", "var", run.cast("string")).alias("var"), "step", (F.col("pos") - run * size).alias("pos"), "value")


def ungrouped(hat: DataFrame, size: int) -> DataFrame:
    run = F.substring_index("var", "#", -1).cast("long")
    name = F.expr("substring(var, 1, length(var) - length(substring_index(var, '#', -1)) - 1)")
    return hat.select(name.alias("var"), "step", (F.col("pos") + run * size).alias("pos"), "value_hat")


def compress_series(df: DataFrame, spec: CodecSpec = CodecSpec(), ratios: DataFrame | None = None) -> Compressed:
    """All steps of a series in one run, with ratios to the original step before; the first step is kept as it is.

    ratios: change_ratios(df), if they are saved already.
    """
    ratios = ratios if (spec.reference, spec.bits_scope, spec.zero_prev, spec.anchor_every) == ("original", "step", "exact", None) else None
    df = grouped(df, spec.group_points) if spec.bits_scope == "group" else df
    if spec.reference == "reconstructed":
        return compress_closed_loop(df, spec)
    df = df if is_saved(df) else kept(df, spec, "series")
    first = df.groupBy("var").agg(F.min("step").alias("_first"))
    anchors = df.join(F.broadcast(first), "var").where(is_anchor(spec)).drop("_first")  # one row for each variable
    ratios = kept(change_ratios(df, spec.zero_prev, anchor_every=spec.anchor_every), spec, "ratios") if ratios is None else ratios
    return compress_ratios(ratios, spec, anchors)


def compress_step(prev: DataFrame, cur: DataFrame, spec: CodecSpec = CodecSpec()) -> Compressed:
    """One step (var, step, pos, value) against a step before it (var, pos, value), which may be a reconstruction."""
    joined = cur.join(prev.select("var", "pos", F.col("value").alias("prev")), ["var", "pos"], "left")
    ratios = joined.select(*STEP, "pos", "prev", F.col("value").alias("cur"), change_ratio(F.col("prev"), F.col("value"), spec.zero_prev).alias("ratio"))
    return compress_ratios(saved(ratios, "ratios"), spec, cur.limit(0))


def compress_closed_loop(df: DataFrame, spec: CodecSpec) -> Compressed:
    """Ratios to the reconstructed step before, so errors don't build up.

    Steps follow one another; each is added to the same four folders, so the result is one scan of each and not of every step.
    """
    df = saved(df, "series")
    steps = sorted(r["step"] for r in df.select("step").distinct().collect())  # one row a step
    if len(steps) < 2:
        raise ValueError("a closed loop needs two steps at least")
    spark, path = df.sparkSession, new_path(df.sparkSession, "closed-loop")
    schemas, hat = {}, None
    one_spec = replace(spec, reference="original", bits_scope="step")
    for i, step in enumerate(steps):
        cur = df.where(F.col("step") == step)
        if i == 0 or (spec.anchor_every and i % spec.anchor_every == 0):
            cur.write.mode("append").parquet(f"{path}/anchors")
            hat = cur.select("var", "pos", F.col("value").alias("value_hat"))
            continue
        one = compress_step(hat.withColumnRenamed("value_hat", "value"), cur, one_spec)
        for name in ("header", "centres", "blocks"):
            schemas[name] = getattr(one, name).schema
            getattr(one, name).write.mode("append").parquet(f"{path}/{name}")
        hat = saved(dc.decompress_step(dc.decode_blocks(one.blocks, one.header, one.centres), hat), "hat").select("var", "pos", "value_hat")
    read = {name: spark.read.schema(schema).parquet(f"{path}/{name}") for name, schema in schemas.items()}
    return Compressed(spec, read["header"].withColumn("reference", F.lit("reconstructed")), read["centres"], read["blocks"], spark.read.schema(df.schema).parquet(f"{path}/anchors"))


def decompress_series(c: Compressed, upto: int | None = None) -> DataFrame:
    """(var, step, pos, value_hat) of all steps, or of those up to one."""
    blocks, anchors = c.blocks, c.anchors
    if upto is not None:
        blocks, anchors = blocks.where(F.col("step") <= upto), anchors.where(F.col("step") <= upto)
    points = dc.decode_blocks(blocks, c.header, c.centres)
    hat = dc.decompress_chain(points, anchors)
    # A slot that only pads a block (the point is missing from the step) decodes to null and isn't a point.
    hat = hat.where("value_hat IS NOT NULL")
    return ungrouped(hat, c.spec.group_points) if c.spec.bits_scope == "group" else hat


def decompress_range(c: Compressed, var: str, step: int, start: int, stop: int) -> DataFrame:
    """Positions start .. stop - 1 of one step: only their blocks are read, in this and earlier steps back to an anchor.

    One scan: the steps' block ranges are one filter of (step and block_id) terms, which reaches the Parquet files.
    """
    if c.spec.bits_scope == "group":
        size = c.spec.group_points
        parts = [
            decompress_range(replace(c, spec=replace(c.spec, bits_scope="step")), f"{var}#{run}", step, max(start - run * size, 0), min(stop - run * size, size))
            for run in range(start // size, (stop - 1) // size + 1)
        ]
        return ungrouped(reduce(DataFrame.unionByName, parts), size)
    header = {r["step"]: r["indices_per_block"] for r in c.header.where((F.col("var") == var) & (F.col("step") <= step)).select("step", "indices_per_block").collect()}  # one row a step
    anchor = c.anchors.where((F.col("var") == var) & (F.col("step") <= step)).agg(F.max("step")).first()[0]
    if anchor is None:
        return c.anchors.limit(0).select("var", "step", "pos", F.col("value").alias("value_hat"))
    anchors = c.anchors.where((F.col("var") == var) & (F.col("step") == anchor) & (F.col("pos") >= start) & (F.col("pos") < stop))
    terms = []
    for s in range(anchor + 1, step + 1):
        if s in header:
            first, last = dc.block_range(start, stop, header[s])
            terms.append((F.col("step") == s) & (F.col("block_id") >= first) & (F.col("block_id") <= last))
    if not terms:
        return anchors.select("var", "step", "pos", F.col("value").alias("value_hat"))
    blocks = c.blocks.where(F.col("var") == var).where(reduce(lambda a, b: a | b, terms))
    points = dc.decode_blocks(blocks, c.header, c.centres).where((F.col("pos") >= start) & (F.col("pos") < stop))
    return dc.decompress_chain(points, anchors).where((F.col("step") == step) & F.col("value_hat").isNotNull())


def touched_blocks(n: int, bits: int, block_bytes: int, start: int, stop: int) -> int:
    first, last = dc.block_range(start, stop, indices_per_block(block_bytes, bits))
    return last - first + 1


def bits_sweep(ratios: DataFrame, spec: CodecSpec, lengths, size: int = SWEEP_POINTS) -> DataFrame:
    """Sizes as stored for hand-set index lengths: all of them are packed where the points of a block lie, in one pass.

    Blocks of the sweep hold `size` points for every length (1 MB at 16 bits).
    """
    lengths, level = tuple(lengths), spec.level
    ranges = small_side(ratio_range(ratios))
    binned = bn.with_bins(ratios, spec.error_bound, spec.anchor, ranges=ranges)
    ranked = saved(bn.rank_bins(bn.ratio_histogram(binned), (1 << max(lengths)) - 1), "ranked")
    placed = join_spread(binned, ranked.select(*STEP, "bin", "rank"), [*STEP, "bin"], "pos").select(*STEP, F.floor(F.col("pos") / size).alias("block"), "pos", "rank")

    def run(block: pa.Table) -> pa.Table:
        at = block.column("pos").to_numpy() % size
        rank = np.zeros(int(at.max()) + 1, dtype=np.int64)  # 0: no centre, or no point
        rank[at] = block.column("rank").fill_null(0).to_numpy()
        rows = []
        for bits in lengths:
            none = (1 << bits) - 1
            idx = np.where((rank > 0) & (rank <= none), rank - 1, none)
            raw = pack_bits(idx, bits)
            rows.append((bits, len(zlib.compress(raw, level)), len(raw), int((idx == none).sum())))
        names = ["bits", "index_bytes", "raw_index_bytes", "n_exact_stored"]
        told = [pa.array([r[j] for r in rows], pa.int32() if j == 0 else pa.int64()) for j in range(4)]
        return pa.table([pa.repeat(block.column(c)[0], len(rows)) for c in STEP] + told, names=[*STEP, *names])

    packed = placed.groupBy(*STEP, "block").applyInArrow(run, "var string, step int, bits int, index_bytes long, raw_index_bytes long, n_exact_stored long")
    sums = packed.groupBy(*STEP, "bits").agg(*[F.sum(c).alias(c) for c in ("index_bytes", "raw_index_bytes", "n_exact_stored")], F.count("*").alias("n_blocks"))
    sizes = bn.size_by_bits(ranked, ranges, spec.elem_bytes, lengths).select(*STEP, "bits", "n", "n_exact", "est_bytes", F.col("used").alias("n_centres"))
    out = sums.join(sizes, [*STEP, "bits"]).withColumn("elem_bytes", F.lit(spec.elem_bytes))
    stored = (F.col("n_centres") + F.col("n_exact_stored")) * spec.elem_bytes + F.col("index_bytes") + F.col("n_blocks") * OFFSET_BYTES
    out = out.withColumn("stored_bytes", stored).withColumn("cr", F.col("n") * spec.elem_bytes / F.col("stored_bytes"))
    return saved(out.withColumn("zlib_ratio", F.col("raw_index_bytes") / F.col("index_bytes")), "sweep")


def report(c: Compressed) -> DataFrame:
    return space_breakdown(c.blocks, c.header)


def anchor_bytes(anchors: DataFrame, level: int = 6, chunk: int = 1 << 16) -> DataFrame:
    """Anchor steps as compressed chunks of raw doubles."""
    import pandas as pd

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values("pos")
        raw = frame["value"].to_numpy(dtype="<f8").tobytes()
        return pd.DataFrame({"var": [frame["var"].iloc[0]], "step": [frame["step"].iloc[0]], "chunk_id": [frame["chunk_id"].iloc[0]], "n": [len(frame)], "payload": [zlib.compress(raw, level)]})

    return anchors.withColumn("chunk_id", F.floor(F.col("pos") / chunk)).groupBy(*STEP, "chunk_id").applyInPandas(run, "var string, step int, chunk_id long, n int, payload binary")
