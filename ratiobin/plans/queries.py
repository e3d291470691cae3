"""Queries of every method, variant, measure, baseline, workload and operator, with SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ratiobin.functions import sql as sql_functions
from ratiobin.functions.columns import dp_memory_bytes, estimated_size, predicted_cr
from ratiobin.operators import baselines as bs
from ratiobin.operators import binning as bn
from ratiobin.operators import blocks as bl
from ratiobin.operators import chunks as ck
from ratiobin.operators import decode as dc
from ratiobin.operators import measures as ms
from ratiobin.operators import relational as rl
from ratiobin.operators.optimal import optimal_cover, optimal_covers
from ratiobin.operators.ratios import change_ratios, every_nth, ratio_profile, ratio_range
from ratiobin.plans import codec as cd
from ratiobin.plans.codec_sql import E, ctes, decoded, double
from ratiobin.session import exists, is_saved, new_path, once, saved
from ratiobin.sources import ncfile, store, table
from ratiobin.sources.series import BUILDERS, ELEM_BYTES, SERIES_SQL, load_series
from ratiobin.sources.tables import load_table
from ratiobin.spec import CodecSpec
from ratiobin.streaming import frozen
from ratiobin.streaming import steps as st

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}

STEP = ["var", "step"]
#: Blocks of the workloads on small tables, so that a step has several.
SMALL_BLOCK = 4096


def query(name: str, sql: str | None = None):
    def put(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return put


def ratios_of(spark: SparkSession, sf: str, series: str, steps: tuple[int, ...] | None = None) -> DataFrame:
    ratios = once(spark, ("ratios", sf, series), lambda: change_ratios(load_series(spark, sf, series)))
    return ratios if steps is None else ratios.where(F.col("step").isin(*steps))


def binned_of(spark: SparkSession, sf: str, series: str, anchor: str = "min", steps: tuple[int, ...] | None = None) -> DataFrame:
    return bn.with_bins(ratios_of(spark, sf, series, steps), E, anchor)


def indexed_of(spark: SparkSession, sf: str, series: str, steps: tuple[int, ...] | None = None, **kw) -> cd.Indexed:
    return cd.index_ratios(ratios_of(spark, sf, series, steps), CodecSpec(error_bound=E, elem_bytes=ELEM_BYTES[series], **kw))


_compressed: dict[tuple, cd.Compressed] = {}


def compressed_of(spark: SparkSession, sf: str, series: str, **kw) -> cd.Compressed:
    """A compressed series; kept for other queries of the same session while its files are there."""
    key = (spark.sparkContext.applicationId, id(spark), sf, series, *sorted(kw.items()))
    if key not in _compressed or not exists(spark, f"{_compressed[key].header._ratiobin_path}/_SUCCESS"):
        spec = CodecSpec(error_bound=E, elem_bytes=ELEM_BYTES[series], **kw)
        made = cd.compress_series(load_series(spark, sf, series), spec, ratios_of(spark, sf, series))
        if not is_saved(made.header):
            return made
        _compressed[key] = made
    return _compressed[key]


def union(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def each(names, template: str) -> str:
    """One SQL select for each series, joined up; the template's ctes are nested so that names don't meet."""
    return " UNION ALL ".join(f"SELECT * FROM ({template(n)})" for n in names)


ALL = tuple(BUILDERS)
RATIO_COLUMNS = [*STEP, "pos", "ratio"]

# --- methods: ratios, ranges, histograms


@query("m_change_ratio", ctes("price_states") + "SELECT var, step, pos, ratio FROM r")
def m_change_ratio(spark, sf):
    return ratios_of(spark, sf, "price_states").select(*RATIO_COLUMNS)


@query("m_change_ratio_join", ctes("part_volume") + "SELECT var, pos, prev, cur, ratio FROM r WHERE step = 14")
def m_change_ratio_join(spark, sf):
    from ratiobin.functions.columns import change_ratio

    series = load_series(spark, sf, "part_volume")
    pairs = rl.pair_steps(rl.slice_series(series, step=13), rl.slice_series(series, step=14))
    return pairs.withColumn("ratio", change_ratio(F.col("prev"), F.col("cur")))


@query("m_change_ratio_ragged", f"""WITH s AS ({SERIES_SQL["turn_lengths"]}) SELECT coalesce(a.var, b.var) AS var, coalesce(a.pos, b.pos) AS pos, a.value AS prev, b.value AS cur,
  CASE WHEN a.value <> 0 AND b.value IS NOT NULL THEN (b.value - a.value) / a.value END AS ratio
  FROM (SELECT * FROM s WHERE step = 1) a FULL JOIN (SELECT * FROM s WHERE step = 2) b ON a.pos = b.pos""")
def m_change_ratio_ragged(spark, sf):
    from ratiobin.functions.columns import change_ratio

    series = load_series(spark, sf, "turn_lengths")
    pairs = rl.pair_steps(rl.slice_series(series, step=1), rl.slice_series(series, step=2), "full")
    return pairs.withColumn("ratio", change_ratio(F.col("prev"), F.col("cur")))


@query("m_ratio_range", each(ALL, lambda n: ctes(n) + "SELECT var, step, lo, hi, n, n_defined FROM g"))
def m_ratio_range(spark, sf):
    return union([ratio_range(ratios_of(spark, sf, n)) for n in ALL]).drop("last_pos")


@query("m_ratio_profile", each(ALL, lambda n: ctes(n, anchor="zero") + f"SELECT var, step, count(*) AS n, count(ratio) AS n_defined, count(*) FILTER (abs(ratio) <= {double(E)}) AS n_small, min(ratio) AS lo, max(ratio) AS hi, count(DISTINCT bin) AS occupied FROM b GROUP BY ALL"))
def m_ratio_profile(spark, sf):
    return union([ratio_profile(ratios_of(spark, sf, n), E) for n in ALL])


@query("m_ratio_histogram", ctes("part_volume") + "SELECT var, step, bin, cnt FROM h")
def m_ratio_histogram(spark, sf):
    return bn.ratio_histogram(binned_of(spark, sf, "part_volume")).select(*STEP, "bin", "cnt")


@query("m_ratio_histogram_zero", ctes("price_states", anchor="zero") + "SELECT var, step, bin, cnt FROM h")
def m_ratio_histogram_zero(spark, sf):
    return bn.ratio_histogram(binned_of(spark, sf, "price_states", "zero")).select(*STEP, "bin", "cnt")


@query("m_topk_bins", ctes("part_volume", bits=4) + "SELECT var, step, idx, bin, centre, cnt FROM c WHERE step = 14")
def m_topk_bins(spark, sf):
    return bn.top_k_bins(bn.ratio_histogram(binned_of(spark, sf, "part_volume", steps=(14,))), 15, E)


@query("m_topk_all_steps", ctes("drift_field", bits=4) + "SELECT var, step, idx, bin, centre, cnt FROM c")
def m_topk_all_steps(spark, sf):
    return bn.top_k_bins(bn.ratio_histogram(binned_of(spark, sf, "drift_field")), 15, E)


def sizes_of(spark, sf, series, objective="size", group=None):
    binned = binned_of(spark, sf, series)
    more = []
    if group is not None:
        ratios = ratios_of(spark, sf, series).withColumn("grp", group)
        binned, more = bn.with_bins(ratios, E, "min", "grp"), ["grp"]
    hist = bn.rank_bins(bn.ratio_histogram(binned, *more), bn.MOST_BINS, *more)
    counts = binned.groupBy(*STEP, *more).agg(F.count("*").alias("n"))
    return bn.size_by_bits(hist, counts, ELEM_BYTES[series], range(1, 17), *more), more


SIZE_COLUMNS = "var, step, bits, n, n_exact, est_bytes"


@query("m_estimated_size", ctes("part_volume") + f"SELECT {SIZE_COLUMNS}, covered, used FROM z")
def m_estimated_size(spark, sf):
    return sizes_of(spark, sf, "part_volume")[0].select(*SIZE_COLUMNS.split(", "), "covered", "used")


@query("m_choose_bits", each(("part_volume", "customer_balance", "price_states"), lambda n: ctes(n) + f"SELECT {SIZE_COLUMNS} FROM p"))
def m_choose_bits(spark, sf):
    return union([bn.choose_bits(sizes_of(spark, sf, n)[0]).select(*SIZE_COLUMNS.split(", ")) for n in ("part_volume", "customer_balance", "price_states")])


@query("m_choose_bits_group", ctes("customer_balance", group="pos % 4") + f"SELECT grp, {SIZE_COLUMNS} FROM p")
def m_choose_bits_group(spark, sf):
    sizes, more = sizes_of(spark, sf, "customer_balance", group=F.col("pos") % 4)
    return bn.choose_bits(sizes, "size", *more).select("grp", *SIZE_COLUMNS.split(", "))


@query("m_choose_bits_entropy", ctes("part_volume") + "SELECT var, step, bits, n, n_exact, round(entropy_bytes, 3) AS entropy_bytes FROM z QUALIFY row_number() OVER (PARTITION BY var, step ORDER BY round(entropy_bytes, 6), bits) = 1")
def m_choose_bits_entropy(spark, sf):
    sizes = sizes_of(spark, sf, "part_volume")[0].withColumn("entropy_bytes", F.round("entropy_bytes", 6))
    return bn.choose_bits(sizes, "entropy").select(*STEP, "bits", "n", "n_exact", F.round("entropy_bytes", 3).alias("entropy_bytes"))


@query("m_choose_bits_measured")
def m_choose_bits_measured(spark, sf):
    ratios = ratios_of(spark, sf, "part_volume")
    return cd.index_ratios(ratios, CodecSpec(error_bound=E, objective="measured")).bits.select(*STEP, "bits", "n", "n_exact")


# --- methods: other strategies

COVER = "count(*) AS n, count(*) FILTER (covered) AS covered"


def covered_sql(series: str, strategy: str, bits: int, where: str, pool: bool = False) -> str:
    k, e = (1 << bits) - 1, double(E)
    body = ctes(series, bits=bits, where=where)
    rr = "SELECT var, 0 AS step, pos, ratio FROM r" if pool else "SELECT var, step, pos, ratio FROM r"
    if strategy == "equal":
        return body + f""", q AS ({rr}), x AS (SELECT var, step, min(ratio) AS lo, max(ratio) AS hi FROM q GROUP BY ALL),
          y AS (SELECT var, step, coalesce(abs(ratio - (lo + (CASE WHEN hi > lo THEN least(floor((ratio - lo) / ((hi - lo) / {k})), {k} - 1) ELSE 0 END + {double(0.5)}) * ((hi - lo) / {k}))) <= {e}, false) AS covered
          FROM q JOIN x USING (var, step)) SELECT var, step, {COVER} FROM y GROUP BY ALL"""
    return body + f"""SELECT var, step, count(*) AS n, count(centre) AS covered FROM i GROUP BY ALL"""


def covered(spark, sf, series, strategy, bits, steps=None, pool=False, drop_small=False):
    ratios = ratios_of(spark, sf, series, steps)
    ratios = ratios.where(F.abs("ratio") > E) if drop_small else ratios
    ratios = ratios.withColumn("step", F.lit(0)) if pool else ratios
    if strategy == "optimal":
        return optimal_cover(ratios, (1 << bits) - 1, 2 * E).select(*STEP, "n", "covered")
    return bn.covered_by(ratios, strategy, bits, E).groupBy(*STEP).agg(F.count("*").alias("n"), F.count(F.when(F.col("covered"), 1)).alias("covered"))


@query("m_equal_width", covered_sql("part_volume", "equal", 6, "true"))
def m_equal_width(spark, sf):
    return covered(spark, sf, "part_volume", "equal", 6)


@query("m_equal_width_centres", ctes("part_volume") + f"SELECT var, step, CAST(idx AS INTEGER) AS idx, lo + (idx + {double(0.5)}) * ((hi - lo) / 15) AS centre FROM g, (SELECT unnest(range(0, 15)) AS idx) WHERE lo IS NOT NULL AND (hi > lo OR idx = 0)")
def m_equal_width_centres(spark, sf):
    return bn.equal_width_bins(ratios_of(spark, sf, "part_volume"), 15)


@query("m_log_scale", ctes("supplier_month", where=f"abs(ratio) > {double(E)}") + f""", q AS (SELECT var, step, ratio, CAST(sign(ratio) AS INTEGER) AS sg, log10(abs(ratio)) AS l FROM r),
  t AS (SELECT var, step, count(*) FILTER (sg = -1) AS neg, count(*) AS cnt FROM q GROUP BY ALL),
  m0 AS (SELECT *, greatest(least(round(63 * neg / cnt), 63 - CASE WHEN neg < cnt THEN 1 ELSE 0 END), CASE WHEN neg > 0 THEN 1 ELSE 0 END) AS mneg FROM t),
  x AS (SELECT var, step, sg, min(l) AS a, max(l) AS b FROM q GROUP BY ALL),
  y AS (SELECT q.*, a, b, CASE WHEN sg = -1 THEN mneg ELSE 63 - mneg END AS m FROM q JOIN x USING (var, step, sg) JOIN m0 USING (var, step)),
  v AS (SELECT *, (b - a) / m AS w FROM y)
  SELECT var, step, count(*) AS n, count(*) FILTER (abs(ratio - sg * pow(10.0, a + (CASE WHEN w > 0 THEN least(floor((l - a) / w), m - 1) ELSE 0 END + {double(0.5)}) * w)) <= {double(E)}) AS covered FROM v GROUP BY ALL""")
def m_log_scale(spark, sf):
    ratios = change_ratios(load_series(spark, sf, "supplier_month")).where(F.abs("ratio") > E)
    near = bn.covered_by(saved(ratios, "ratios"), "log", 6, E)
    return near.groupBy(*STEP).agg(F.count("*").alias("n"), F.count(F.when(F.col("covered"), 1)).alias("covered"))


@query("m_log_scale_centres")
def m_log_scale_centres(spark, sf):
    return bn.log_scale_bins(ratios_of(spark, sf, "part_volume"), 63)


@query("m_kmeans")
def m_kmeans(spark, sf):
    return bn.kmeans_bins(ratios_of(spark, sf, "supplier_month"), 15, error_bound=E)


@query("m_kmeans_one_round", ctes("supplier_month") + f""", x AS (SELECT var, step, floor(ratio / {double(2 * E / 16)}) AS cell, avg(ratio) AS x, count(*) AS w FROM r WHERE ratio IS NOT NULL GROUP BY ALL),
  lim AS (SELECT var, step, min(x) AS a, max(x) AS b, least(count(*), 7) AS m FROM x GROUP BY ALL),
  c0 AS (SELECT var, step, a + (j + {double(0.5)}) * (b - a) / m AS c, j FROM lim, (SELECT unnest(range(0, 7)) AS j) WHERE j < m),
  near AS (SELECT var, step, x.x, x.w, c0.j, row_number() OVER (PARTITION BY var, step, x.cell ORDER BY abs(x.x - c0.c), c0.c) AS n FROM x JOIN c0 USING (var, step))
  SELECT var, step, CAST(j AS INTEGER) AS idx, round(coalesce(sum(near.x * near.w) FILTER (n = 1) / sum(near.w) FILTER (n = 1), any_value(c0.c)), 9) AS centre FROM near JOIN c0 USING (var, step, j) GROUP BY var, step, j""")
def m_kmeans_one_round(spark, sf):
    centres = bn.kmeans_bins(ratios_of(spark, sf, "supplier_month"), 7, max_iter=1, init="equal", error_bound=E)
    return centres.select(*STEP, "idx", F.round("centre", 9).alias("centre"))


@query("m_kmeans_ml")
def m_kmeans_ml(spark, sf):
    """The library's k-means over the ratios of all steps together."""
    return bn.kmeans_ml_bins(ratios_of(spark, sf, "supplier_month").withColumn("step", F.lit(0)), 7)


@query("m_optimal_cover")
def m_optimal_cover(spark, sf):
    return union([covered(spark, sf, "customer_balance", "optimal", 4, drop_small=True), covered(spark, sf, "supplier_month", "optimal", 4, pool=True, drop_small=True)])


WINDOWS = ctes("supplier_month", where=f"abs(ratio) > {double(E)}") + f""", w AS (SELECT var, step, ratio, count(*) OVER (PARTITION BY var, step ORDER BY ratio RANGE BETWEEN CURRENT ROW AND {double(2 * E)} FOLLOWING) AS c FROM r) """


@query("m_optimal_cover_k1", WINDOWS + "SELECT var, step, count(*) AS n, max(c) AS covered FROM w GROUP BY ALL")
def m_optimal_cover_k1(spark, sf):
    return covered(spark, sf, "supplier_month", "optimal", 1, drop_small=True)


@query("m_optimal_cover_k2", WINDOWS + f"SELECT a.var, a.step, max(a.n) AS n, max(a.c + coalesce(b.c, 0)) AS covered FROM (SELECT *, count(*) OVER (PARTITION BY var, step) AS n FROM w) a LEFT JOIN w b ON a.var = b.var AND a.step = b.step AND b.ratio > a.ratio + {double(2 * E)} GROUP BY a.var, a.step")
def m_optimal_cover_k2(spark, sf):
    return optimal_cover(ratios_of(spark, sf, "supplier_month").where(F.abs("ratio") > E), 2, 2 * E)


# --- methods: index, blocks, decoding


@query("m_assign_index", each(("price_states", "part_volume"), lambda n: ctes(n) + "SELECT var, step, pos, idx, bits FROM i"))
def m_assign_index(spark, sf):
    return union([indexed_of(spark, sf, n).points.select(*STEP, "pos", "idx", "bits") for n in ("price_states", "part_volume")])


@query("m_exact_store", ctes("part_volume") + "SELECT var, step, pos, cur AS value FROM i WHERE centre IS NULL")
def m_exact_store(spark, sf):
    return bl.exact_store(indexed_of(spark, sf, "part_volume").points)


@query("m_block_of", ctes("part_volume") + f"SELECT var, step, CAST(pos // ({SMALL_BLOCK // 16} * 8 // bits) AS INTEGER) AS block_id, count(*) AS n, min(pos) AS first_pos FROM i GROUP BY ALL")
def m_block_of(spark, sf):
    dealt = bl.align(indexed_of(spark, sf, "part_volume").points, SMALL_BLOCK // 16)
    return dealt.groupBy(*STEP, "block_id").agg(F.count("*").alias("n"), F.min("pos").alias("first_pos"))


@query("m_packed_bits", ctes("part_volume") + f"SELECT var, step, CAST(pos // ({SMALL_BLOCK // 16} * 8 // bits) AS INTEGER) AS block_id, count(*) AS n, md5(string_agg(lpad(bin(idx), bits, '0'), '' ORDER BY pos)) AS bits_md5 FROM i GROUP BY ALL")
def m_packed_bits(spark, sf):
    return bl.packed_bits_text(indexed_of(spark, sf, "part_volume").points, SMALL_BLOCK // 16)


@query("m_blocks")
def m_blocks(spark, sf):
    blocks = bl.build_blocks(indexed_of(spark, sf, "part_volume").points, SMALL_BLOCK // 16)
    return blocks.select(*STEP, "block_id", "first_pos", "n", F.octet_length("payload").alias("stored"), "raw_bytes", "n_exact")


@query("m_offsets", ctes("part_volume") + f""", bb AS (SELECT var, step, CAST(pos // ({SMALL_BLOCK // 16} * 8 // bits) AS INTEGER) AS block_id, count(*) FILTER (centre IS NULL) AS n_exact FROM i GROUP BY ALL)
  SELECT var, step, block_id, n_exact, CAST(coalesce(sum(n_exact) OVER (PARTITION BY var, step ORDER BY block_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS exact_before FROM bb""")
def m_offsets(spark, sf):
    return bl.with_offsets(bl.build_blocks(indexed_of(spark, sf, "part_volume").points, SMALL_BLOCK // 16), group=2).select(*STEP, "block_id", "n_exact", "exact_before")


HAT = "SELECT var, step, pos, value_hat FROM d"


@query("m_decode_step", decoded("price_states") + HAT + " WHERE step = 1")
def m_decode_step(spark, sf):
    c = compressed_of(spark, sf, "price_states")
    points = dc.decode_blocks(c.blocks.where("step = 1"), c.header, c.centres)
    return dc.decompress_step(points, c.anchors.withColumnRenamed("value", "value_hat"))


@query("m_decode_chain", each(("part_volume", "drift_field"), lambda n: decoded(n) + HAT))
def m_decode_chain(spark, sf):
    return union([cd.decompress_series(compressed_of(spark, sf, n, block_bytes=SMALL_BLOCK)) for n in ("part_volume", "drift_field")])


@query("m_decode_closed_loop")
def m_decode_closed_loop(spark, sf):
    c = compressed_of(spark, sf, "drift_field", reference="reconstructed")
    return cd.decompress_series(c)


@query("m_decode_range", decoded("drift_field") + HAT + " WHERE step = 2 AND pos >= 5000 AND pos < 9000")
def m_decode_range(spark, sf):
    return cd.decompress_range(compressed_of(spark, sf, "drift_field", block_bytes=SMALL_BLOCK), "drift_field", 2, 5000, 9000)


GROUP_POINTS = 512


@query("m_decode_group_bits", decoded("customer_balance", group=f"pos // {GROUP_POINTS}") + HAT)
def m_decode_group_bits(spark, sf):
    """Every run of positions has its own centres and index length."""
    return cd.decompress_series(compressed_of(spark, sf, "customer_balance", bits_scope="group", group_points=GROUP_POINTS))


@query("m_pooled_centres")
def m_pooled_centres(spark, sf):
    """One set of centres for all steps of the small steps' series: index length, centres, exact values, ratio."""
    c = compressed_of(spark, sf, "supplier_month", centres_scope="series")
    return cd.report(c).select(*STEP, "n", "bits", "n_centres", "n_exact_stored", F.round("cr", 6).alias("cr"))


@query("m_value_bound")
def m_value_bound(spark, sf):
    """Exact values with the bound on the ratio and on the value, and the largest error against the current value."""
    out = []
    for bound in ("ratio", "value"):
        points = indexed_of(spark, sf, "part_volume", bound=bound).points
        off = F.abs(F.col("ratio") - F.col("centre")) / F.abs(1 + F.col("ratio"))
        out.append(points.groupBy(*STEP).agg(F.lit(bound).alias("bound"), F.count(F.when(F.col("centre").isNull(), 1)).alias("n_exact"), F.round(F.max(off), 9).alias("max_value_error")))
    return union(out)


@query("m_centre_map")
def m_centre_map(spark, sf):
    """Header and centres of a step as maps, looked up by name and by index."""
    c = compressed_of(spark, sf, "part_volume")
    maps = dc.centre_map(c.header, c.centres)
    return maps.select(*STEP, F.element_at("attributes", F.lit("bits")).cast("int").alias("bits"), F.size("centres").alias("n_centres"), F.try_element_at("centres", F.lit(0)).alias("first_centre"))


@query("m_read_store", decoded("price_states") + HAT)
def m_read_store(spark, sf):
    """The store read as a table of decoded values, runs of positions side by side and without a shuffle."""
    path = new_path(spark, "store")
    store.write_compressed(compressed_of(spark, sf, "price_states", block_bytes=SMALL_BLOCK), path)
    return table.read_decoded(spark, path, points=16_384)


@query("m_read_store_range", decoded("drift_field") + HAT + " WHERE step = 2 AND pos >= 5000 AND pos < 9000")
def m_read_store_range(spark, sf):
    path = new_path(spark, "store")
    store.write_compressed(compressed_of(spark, sf, "drift_field", block_bytes=SMALL_BLOCK), path)
    return table.read_decoded(spark, path, step=2, start=5000, stop=9000, points=1000)


@query("m_roundtrip_store", decoded("price_states") + HAT)
def m_roundtrip_store(spark, sf):
    path = new_path(spark, "roundtrip")
    store.write_compressed(compressed_of(spark, sf, "price_states", block_bytes=SMALL_BLOCK), path)
    return cd.decompress_series(store.read_compressed(spark, path))


@query("m_roundtrip_array_file", each(("price_states", "part_volume"), lambda n: decoded(n) + HAT))
def m_roundtrip_array_file(spark, sf):
    """Two variables in common files, steps stored without loss included; decoded from the files alone."""
    path = new_path(spark, "arrays")
    parts = [compressed_of(spark, sf, n, block_bytes=SMALL_BLOCK) for n in ("price_states", "part_volume")]
    blocks, header, centres, anchors = (union([getattr(c, x) for c in parts]) for x in ("blocks", "header", "centres", "anchors"))
    ncfile.write_array_files(blocks, header, centres, path, anchors)
    blocks, header, centres = ncfile.read_array_files(spark, path)
    hat = dc.decompress_chain(dc.decode_blocks(blocks, header, centres), ncfile.read_anchors(spark, path))
    return hat.where("value_hat IS NOT NULL")


@query("m_anchors")
def m_anchors(spark, sf):
    c = compressed_of(spark, sf, "customer_balance", anchor_every=20)
    return cd.anchor_bytes(c.anchors).groupBy(*STEP).agg(F.sum("n").alias("n"), F.sum(F.octet_length("payload")).alias("stored_bytes"))


# --- baselines

COMPARED = ("part_volume", "customer_balance")
CODED = [*STEP, "n", "stored_bytes", "cr", "mean_error", "max_error"]


@query("b_sorted_fit")
def b_sorted_fit(spark, sf):
    return bs.coded_size(bs.sorted_fit_codec(load_series(spark, sf, "part_volume"), E)).select(*CODED)


@query("b_predictive")
def b_predictive(spark, sf):
    return bs.coded_size(bs.predictive_codec(load_series(spark, sf, "part_volume"), E)).select(*CODED)


@query("b_lossless")
def b_lossless(spark, sf):
    return bs.lossless_size(load_series(spark, sf, "part_volume"))


@query("b_strategies_fixed")
def b_strategies_fixed(spark, sf):
    """Stored sizes of all five strategies at one index length."""
    ratios = ratios_of(spark, sf, "part_volume")
    out = []
    for s in ("topk", "equal", "log", "kmeans", "optimal"):
        indexed = cd.index_ratios(ratios, CodecSpec(error_bound=E, bits=6, strategy=s))
        out.append(ms.space_breakdown(saved(bl.build_blocks(indexed.points), "blocks"), cd.header_of(indexed)).select(F.lit(s).alias("strategy"), *STEP, "n", "n_exact_stored", "stored_bytes", "cr"))
    return union(out)


# --- measures


@query("c_mean_error", decoded("part_volume") + "SELECT d.var, d.step, count(*) AS n, count(*) FILTER (value = 0) AS n_zero, round(avg(abs((value - value_hat) / CASE WHEN value <> 0 THEN value END)), 12) AS mean_error FROM d JOIN s USING (var, step, pos) GROUP BY ALL")
def c_mean_error(spark, sf):
    out = ms.mean_error(load_series(spark, sf, "part_volume"), cd.decompress_series(compressed_of(spark, sf, "part_volume")))
    return out.select(*STEP, "n", "n_zero", F.round("mean_error", 12).alias("mean_error"))


@query("c_bound_report", ctes("drift_field") + f"SELECT var, step, count(*) AS n, round(max(abs(ratio - centre)), 9) AS max_ratio_error, count(*) FILTER (abs(ratio - centre) > {double(E)} + 8.881784197001252e-16 * greatest(abs(ratio), abs(lo))) AS violations FROM i GROUP BY ALL")
def c_bound_report(spark, sf):
    return ms.bound_report(indexed_of(spark, sf, "drift_field").points, E).withColumn("max_ratio_error", F.round("max_ratio_error", 9))


EXACT = "count(*) AS n, count(*) FILTER (centre IS NULL) AS n_exact, round(avg(CASE WHEN centre IS NULL THEN 1.0 ELSE 0.0 END), 9) AS exact_ratio"


@query("c_exact_ratio", ctes("user_activity") + f"SELECT var, step, {EXACT} FROM i GROUP BY ALL")
def c_exact_ratio(spark, sf):
    return ms.exact_ratio(indexed_of(spark, sf, "user_activity").points).withColumn("exact_ratio", F.round("exact_ratio", 9))


@query("c_exact_ratio_rollup", "SELECT var, step, CAST(sum(n) AS BIGINT) AS n, CAST(sum(n_exact) AS BIGINT) AS n_exact FROM (" + each(("price_states", "part_volume"), lambda n: ctes(n) + "SELECT var, step, count(*) AS n, count(*) FILTER (centre IS NULL) AS n_exact FROM i GROUP BY ALL") + ") GROUP BY ROLLUP (var, step)")
def c_exact_ratio_rollup(spark, sf):
    points = union([indexed_of(spark, sf, n).points.select(*STEP, "centre") for n in ("price_states", "part_volume")])
    return points.rollup(*STEP).agg(F.count("*").alias("n"), F.count(F.when(F.col("centre").isNull(), 1)).alias("n_exact"))


@query("c_coverage", covered_sql("part_volume", "topk", 6, f"abs(ratio) > {double(E)}"))
def c_coverage(spark, sf):
    return covered(spark, sf, "part_volume", "topk", 6, drop_small=True)


INDEX_BYTES = "greatest(entropy_bytes - used * 8 - n_exact * 8, CAST(1 AS DOUBLE))"


@query("c_predicted_cr", ctes("part_volume") + f"SELECT var, step, bits, round(n * bits / 8.0 / {INDEX_BYTES}, 6) AS lossless_ratio, round(n_exact / n, 9) AS alpha, round(64.0 :: DOUBLE / (bits / (n * bits / 8.0 / {INDEX_BYTES}) + n_exact / n * 64), 6) AS cr FROM z WHERE bits IN (12, 13)")
def c_predicted_cr(spark, sf):
    """The back-of-envelope ratio of every step at two lengths; the index is taken to shrink to its entropy."""
    rows = sizes_of(spark, sf, "part_volume")[0].where("bits IN (12, 13)")
    lossless, alpha = F.col("n") * F.col("bits") / F.lit(8.0) / F.expr(INDEX_BYTES), F.col("n_exact") / F.col("n")
    return rows.select(*STEP, "bits", F.round(lossless, 6).alias("lossless_ratio"), F.round(alpha, 9).alias("alpha"), F.round(predicted_cr(F.col("bits"), lossless, alpha, 64), 6).alias("cr"))


def breakdown(spark, sf, names=("price_states", "part_volume", "customer_balance"), **kw):
    return saved(union([cd.report(compressed_of(spark, sf, n, **kw)) for n in names]), "breakdown")


@query("c_compression_ratio")
def c_compression_ratio(spark, sf):
    return breakdown(spark, sf).select(*STEP, "n", "bits", "stored_bytes", F.round("cr", 6).alias("cr"))


@query("c_zlib_ratio")
def c_zlib_ratio(spark, sf):
    return breakdown(spark, sf, ("part_volume",)).select(*STEP, "bits", "raw_index_bytes", "index_bytes", F.round("zlib_ratio", 6).alias("zlib_ratio"))


@query("c_space_breakdown")
def c_space_breakdown(spark, sf):
    return breakdown(spark, sf, ("part_volume",)).select(*STEP, "centre_bytes", "index_bytes", "exact_bytes", "offset_bytes", "stored_bytes", F.round("index_share", 6).alias("index_share"))


# --- workloads


@query("w_series_summary", " UNION ALL ".join(f"SELECT '{n}' AS var, count(DISTINCT step) AS steps, count(DISTINCT pos) AS points, count(*) AS n, count(*) * {ELEM_BYTES[n]} AS bytes FROM ({SERIES_SQL[n]})" for n in ALL))
def w_series_summary(spark, sf):
    return union([load_series(spark, sf, n).groupBy("var").agg(F.count_distinct("step").alias("steps"), F.count_distinct("pos").alias("points"), F.count("*").alias("n"), (F.count("*") * ELEM_BYTES[n]).alias("bytes")) for n in ALL])


@query("w_alignment_moves", ctes("drift_field") + f"SELECT var, step, count(DISTINCT pos // ({SMALL_BLOCK} * 8 // bits)) AS blocks, count(*) AS points_moved, count(DISTINCT pos // 8192) AS chunk_rows FROM i GROUP BY ALL")
def w_alignment_moves(spark, sf):
    """Rows that alignment moves: every point in point form, none but whole chunks in chunk form."""
    points = bl.align(indexed_of(spark, sf, "drift_field").points, SMALL_BLOCK)
    return points.groupBy(*STEP).agg(F.count_distinct("block_id").alias("blocks"), F.count("*").alias("points_moved"), F.count_distinct(F.floor(F.col("pos") / 8192)).alias("chunk_rows"))


W8 = ("embedding_field", "customer_balance", "part_volume", "user_activity", "price_states", "drift_field")


@query("w_cr_by_step")
def w_cr_by_step(spark, sf):
    return breakdown(spark, sf, W8).select(*STEP, "n", "bits", F.round("cr", 6).alias("cr"), F.round("zlib_ratio", 6).alias("zlib_ratio"))


@query("w_cr_compare")
def w_cr_compare(spark, sf):
    """Compression ratio of the codec and of both comparison coders: mean over all coded steps, and the last step's."""
    out = []
    for n in W8:
        series, size = load_series(spark, sf, n).where("step > 0"), ELEM_BYTES[n]
        codec = cd.report(compressed_of(spark, sf, n)).select(*STEP, F.lit("ratio_bin").alias("coder"), "cr")
        a = bs.coded_size(bs.sorted_fit_codec(series, E, elem_bytes=size), size).select(*STEP, F.lit("sorted_fit").alias("coder"), "cr")
        b = bs.coded_size(bs.predictive_codec(series, E, size), size).select(*STEP, F.lit("predictive").alias("coder"), "cr")
        out += [codec, a, b]
    rows = union(out).groupBy("var", "coder").agg(F.avg("cr").alias("mean_cr"), F.max_by("cr", "step").alias("last_cr"), F.count("*").alias("steps"))
    return rows.select("var", "coder", F.round("mean_cr", 6).alias("mean_cr"), F.round("last_cr", 6).alias("last_cr"), "steps")


@query("w_exact_ratio", "SELECT var, count(*) AS steps, CAST(sum(n_exact) AS BIGINT) AS n_exact, round(avg(n_exact / n), 9) AS mean_exact_ratio FROM (" + each(ALL, lambda n: ctes(n, elem_bytes=ELEM_BYTES[n]) + "SELECT var, step, n, n_exact FROM p") + ") GROUP BY var")
def w_exact_ratio(spark, sf):
    rows = union([bn.choose_bits(sizes_of(spark, sf, n)[0]).select(*STEP, "n", "n_exact") for n in ALL])
    return rows.groupBy("var").agg(F.count("*").alias("steps"), F.sum("n_exact").alias("n_exact"), F.round(F.avg(F.col("n_exact") / F.col("n")), 9).alias("mean_exact_ratio"))


@query("w_predicted_cr")
def w_predicted_cr(spark, sf):
    """The back-of-envelope ratio beside the measured one."""
    rows = breakdown(spark, sf, ("part_volume", "drift_field"))
    alpha = F.col("n_exact_stored") / F.col("n")
    return rows.select(*STEP, "bits", F.round(predicted_cr(F.col("bits"), F.col("zlib_ratio"), alpha, 64), 6).alias("predicted"), F.round("cr", 6).alias("cr"))


@query("w_bits_by_step", ctes("customer_balance") + "SELECT var, step, bits, n_exact FROM p")
def w_bits_by_step(spark, sf):
    return bn.choose_bits(sizes_of(spark, sf, "customer_balance")[0]).select(*STEP, "bits", "n_exact")


@query("w_cr_fixed_bits")
def w_cr_fixed_bits(spark, sf):
    auto = breakdown(spark, sf, ("customer_balance",)).select(*STEP, F.lit("auto").alias("run"), "bits", F.round("cr", 6).alias("cr"))
    return auto.unionByName(breakdown(spark, sf, ("customer_balance",), bits=4).select(*STEP, F.lit("fixed").alias("run"), "bits", F.round("cr", 6).alias("cr")))


@query("w_cr_group_bits")
def w_cr_group_bits(spark, sf):
    """The ratio of each step when every run of positions chooses its own length, and the range of lengths chosen."""
    c = compressed_of(spark, sf, "customer_balance", bits_scope="group", group_points=GROUP_POINTS)
    sizes = cd.report(c).groupBy("step").agg(
        F.min("bits").alias("least_bits"), F.max("bits").alias("most_bits"), F.count("*").alias("groups"), (F.sum(F.col("n") * F.col("elem_bytes")) / F.sum("stored_bytes")).alias("cr")
    )
    return sizes.withColumn("cr", F.round("cr", 6))


SHARES = (20, 40, 60, 80, 100)


def segments(n: int):
    return [(s, *rl.random_segment(None, s / 100, n, seed=s)) for s in SHARES]


@query("w_partial_decode")
def w_partial_decode(spark, sf):
    """Decoded points and blocks read for growing shares of the last step from a random start.

    drift_field and part_volume have small blocks; customer_balance has a single one a step, which every share reads.
    """
    out = []
    for name, kw in (("drift_field", {"block_bytes": SMALL_BLOCK}), ("part_volume", {"block_bytes": SMALL_BLOCK // 16}), ("customer_balance", {})):
        c = compressed_of(spark, sf, name, **kw)
        step, n, width = c.header.orderBy(F.desc("step")).select("step", "n", "indices_per_block").first()
        hat = None
        for share, a, b in segments(n):
            one = cd.decompress_range(c, name, step, a, b).agg(F.count("*").alias("points"))
            blocks = dc.blocks_for_range(c.blocks.where(F.col("var") == name), step, a, b, width).agg(F.count("*").alias("blocks"))
            row = one.crossJoin(F.broadcast(blocks)).select(F.lit(name).alias("var"), F.lit(step).alias("step"), F.lit(share).alias("share"), "points", "blocks")  # one row each
            hat = row if hat is None else hat.unionByName(row)
        out.append(hat)
    return union(out)


@query("w_partial_blocks", f"SELECT var, step, n, CAST(bits AS INTEGER) AS bits, CAST(share AS INTEGER) AS share, CAST(ceil(n * share / 100.0 / ({SMALL_BLOCK} * 8 // bits)) AS BIGINT) AS blocks, CAST(ceil(n / ({SMALL_BLOCK} * 8 // bits)) AS BIGINT) AS all_blocks FROM (SELECT var, step, count(*) AS n FROM ({SERIES_SQL['part_volume']}) GROUP BY ALL), (SELECT unnest([8, 10, 12, 13, 14]) AS bits), (SELECT unnest([20, 40, 60, 80, 100]) AS share)")
def w_partial_blocks(spark, sf):
    """Blocks under a leading segment of each step, by index length and share."""
    sizes = load_series(spark, sf, "part_volume").groupBy(*STEP).agg(F.count("*").alias("n"))
    lengths, shares = F.explode(F.array(*map(F.lit, (8, 10, 12, 13, 14)))).alias("bits"), F.explode(F.array(*map(F.lit, SHARES))).alias("share")
    grid = sizes.select(*STEP, "n", lengths).select(*STEP, "n", "bits", shares)
    width = bl.block_width(F.col("bits"), SMALL_BLOCK)
    return grid.select(*STEP, "n", "bits", "share", F.ceil(F.col("n") * F.col("share") / 100.0 / width).alias("blocks"), F.ceil(F.col("n") / width).alias("all_blocks"))


def coverage_table(spark, sf, series, bits, pool=False):
    """Points covered by each strategy at each length, points of ratios below E left out.

    One table of the optimum holds all lengths, and one ranking of the bins all of top-k's.
    """
    ratios = ratios_of(spark, sf, series).where(F.abs("ratio") > E)
    ratios = saved(ratios.withColumn("step", F.lit(0)) if pool else ratios, "large-ratios")
    length = F.round(F.log2(F.col("k") + 1)).cast("int").alias("bits")
    best = optimal_covers(ratios, tuple((1 << b) - 1 for b in bits), 2 * E).select(F.lit("optimal").alias("strategy"), length, *STEP, "n", "covered")
    ranked = bn.rank_bins(bn.ratio_histogram(bn.with_bins(ratios, E)), (1 << max(bits)) - 1)
    top = bn.size_by_bits(ranked, ratio_range(ratios), ELEM_BYTES[series], bits).select(F.lit("topk").alias("strategy"), "bits", *STEP, "n", "covered")
    out = [best, top]
    for b in bits:
        for s in ("kmeans", "log", "equal"):
            near = bn.covered_by(ratios, s, b, E).groupBy(*STEP).agg(F.count("*").alias("n"), F.count(F.when(F.col("covered"), 1)).alias("covered"))
            out.append(near.select(F.lit(s).alias("strategy"), F.lit(b).alias("bits"), *STEP, "n", "covered"))
    return union(out)


@query("w_coverage_customer_balance")
def w_coverage_customer_balance(spark, sf):
    return coverage_table(spark, sf, "customer_balance", (4, 8))


@query("w_coverage_supplier_month")
def w_coverage_supplier_month(spark, sf):
    return coverage_table(spark, sf, "supplier_month", (4, 6, 8), pool=True)


@query("w_coverage_part_volume")
def w_coverage_part_volume(spark, sf):
    return coverage_table(spark, sf, "part_volume", (4, 6, 8, 14))


@query("w_coverage_embedding")
def w_coverage_embedding(spark, sf):
    return coverage_table(spark, sf, "embedding_field", (8,))


@query("w_coverage_topk", each(("part_volume", "customer_balance"), lambda n: ctes(n, where=f"abs(ratio) > {double(E)}") + "SELECT var, step, bits, n, covered FROM z WHERE bits IN (4, 8, 14)"))
def w_coverage_topk(spark, sf):
    """What top-k covers at the lengths of the coverage experiments, all steps."""
    out = []
    for n in ("part_volume", "customer_balance"):
        ratios = ratios_of(spark, sf, n).where(F.abs("ratio") > E)
        ranked = bn.rank_bins(bn.ratio_histogram(bn.with_bins(ratios, E)), (1 << 14) - 1)
        out.append(bn.size_by_bits(ranked, ratio_range(ratios), 8, (4, 8, 14)).select(*STEP, "bits", "n", "covered"))
    return union(out)


#: Lengths swept on each series: the first list on those like the climate and weather sets, the second on those like the blast sets.
SWEEPS = {
    "part_volume": (8, 10, 12, 13, 14, 15, 16), "embedding_field": (8, 10, 12, 13, 14, 15, 16),
    "customer_balance": (2, 3, 4, 6, 8, 10, 12), "user_activity": (2, 3, 4, 6, 8, 10, 12),
}


@query("w_bits_sweep_size", each(SWEEPS, lambda n: ctes(n, elem_bytes=ELEM_BYTES[n]) + f"SELECT {SIZE_COLUMNS} FROM z"))
def w_bits_sweep_size(spark, sf):
    return union([sizes_of(spark, sf, n)[0].select(*SIZE_COLUMNS.split(", ")) for n in SWEEPS])


def sweep(spark, sf, name):
    """Stored sizes of all lengths and steps of a series; kept for the queries that read it."""
    return once(spark, ("sweep", sf, name), lambda: cd.bits_sweep(ratios_of(spark, sf, name), CodecSpec(error_bound=E, elem_bytes=ELEM_BYTES[name]), range(1, 17)))


def swept(spark, sf):
    return union([sweep(spark, sf, n).where(F.col("bits").isin(*lengths)) for n, lengths in SWEEPS.items()])


@query("w_bits_sweep_actual")
def w_bits_sweep_actual(spark, sf):
    return swept(spark, sf).select(*STEP, "bits", "est_bytes", "stored_bytes", F.round("cr", 6).alias("cr"))


@query("w_cr_by_bits")
def w_cr_by_bits(spark, sf):
    """Mean ratio over all steps for each hand-set length, and for the length chosen by the estimate (bits 0)."""
    fixed = swept(spark, sf).groupBy("var", "bits").agg(F.avg("cr").alias("mean_cr"))
    auto = union([sweep(spark, sf, n) for n in SWEEPS]).groupBy(*STEP).agg(F.min(F.struct("est_bytes", "bits", "cr")).alias("p"))
    return fixed.unionByName(auto.groupBy("var").agg(F.avg("p.cr").alias("mean_cr")).withColumn("bits", F.lit(0))).withColumn("mean_cr", F.round("mean_cr", 6))


@query("w_zlib_by_bits")
def w_zlib_by_bits(spark, sf):
    return swept(spark, sf).groupBy("var").pivot("bits", sorted({b for v in SWEEPS.values() for b in v})).agg(F.round(F.avg("zlib_ratio"), 6))


@query("w_bits_regret")
def w_bits_regret(spark, sf):
    """Stored size at the length chosen by estimate, over the least stored size of lengths 1 to 16."""
    rows = union([sweep(spark, sf, n) for n in SWEEPS])
    auto = rows.groupBy(*STEP).agg(F.min(F.struct("est_bytes", "bits"))["bits"].alias("auto_bits"))
    marked = rows.join(auto, STEP).withColumn("auto", F.col("bits") == F.col("auto_bits"))
    return ms.bits_regret(marked.select(*STEP, "bits", "stored_bytes", "auto")).withColumn("regret", F.round("regret", 6))


@query("w_small_change_share", each(ALL, lambda n: ctes(n) + f"SELECT var, step, count(*) AS n, count(*) FILTER (abs(ratio) <= {double(E)}) AS n_small, round(count(*) FILTER (abs(ratio) <= {double(E)}) / count(*), 9) AS share FROM r GROUP BY ALL"))
def w_small_change_share(spark, sf):
    rows = union([ratios_of(spark, sf, n).select(*STEP, "ratio") for n in ALL])
    return rows.groupBy(*STEP).agg(F.count("*").alias("n"), F.count(F.when(F.abs("ratio") <= E, 1)).alias("n_small"), F.round(F.count(F.when(F.abs("ratio") <= E, 1)) / F.count("*"), 9).alias("share"))


@query("w_every_fifth", f"WITH s AS (SELECT var, step // 5 AS step, pos, value FROM ({SERIES_SQL['customer_balance']}) WHERE step % 5 = 0), r AS (SELECT var, CAST(step AS INTEGER) AS step, pos, value, lag(value) OVER (PARTITION BY pos ORDER BY step) AS prev FROM s) SELECT var, step, count(*) AS n, min((value - prev) / CASE WHEN prev <> 0 THEN prev END) AS lo, max((value - prev) / CASE WHEN prev <> 0 THEN prev END) AS hi FROM r WHERE step > 0 GROUP BY ALL")
def w_every_fifth(spark, sf):
    return ratio_range(change_ratios(every_nth(load_series(spark, sf, "customer_balance"), 5))).select(*STEP, "n", "lo", "hi")


EVERY_FIFTH = f"SELECT var, CAST(step // 5 AS INTEGER) AS step, pos, value FROM ({SERIES_SQL['customer_balance']}) WHERE step % 5 = 0"


def fifth_of(spark, sf):
    return once(spark, ("every-fifth", sf), lambda: every_nth(load_series(spark, sf, "customer_balance"), 5))


@query("w_every_fifth_bits", ctes(EVERY_FIFTH) + f"SELECT {SIZE_COLUMNS} FROM p")
def w_every_fifth_bits(spark, sf):
    """Lengths chosen when only every fifth step is kept."""
    return cd.index_ratios(change_ratios(fifth_of(spark, sf)), CodecSpec(error_bound=E)).bits.select(*SIZE_COLUMNS.split(", "))


@query("w_every_fifth_cr")
def w_every_fifth_cr(spark, sf):
    """Every fifth step compressed."""
    c = cd.compress_series(fifth_of(spark, sf), CodecSpec(error_bound=E))
    return cd.report(c).select(*STEP, "n", "bits", F.round("cr", 6).alias("cr"), F.round("zlib_ratio", 6).alias("zlib_ratio"))


@query("w_dp_memory", each(("part_volume", "customer_balance"), lambda n: ctes(n) + "SELECT var, step, n_defined AS n, CAST(bits AS INTEGER) AS bits, n_defined * pow(2.0, bits) * 4 AS bytes FROM g, (SELECT unnest([4, 8, 10, 14]) AS bits)"))
def w_dp_memory(spark, sf):
    """Bytes of the full table of the optimal cover for the ratios of each step."""
    sizes = union([ratios_of(spark, sf, n).groupBy(*STEP).agg(F.count("ratio").alias("n")) for n in ("part_volume", "customer_balance")])
    grid = sizes.select("*", F.explode(F.array(*map(F.lit, (4, 8, 10, 14)))).alias("bits"))
    return grid.withColumn("bytes", dp_memory_bytes(F.col("n"), F.col("bits")))


WORKERS = (320, 480, 640, 800, 960, 1120, 1280, 1440, 1600)


@query("w_speedup", f"WITH d AS (SELECT workers, l_partkey % workers AS worker, count(*) AS n FROM lineitem, (SELECT CAST(unnest({list(WORKERS)}) AS INTEGER) AS workers) GROUP BY ALL), t AS (SELECT workers, CAST(max(n) AS DOUBLE) AS seconds FROM d GROUP BY workers), f AS (SELECT arg_min(seconds, workers) * min(workers) AS base FROM t) SELECT workers, seconds, round(base / seconds, 6) AS speedup, round(base / seconds / workers, 6) AS efficiency FROM t, f")
def w_speedup(spark, sf):
    """Speedups where the lines of a part are one worker's and a run lasts as long as its busiest worker, at one second a line."""
    parts = load_table(spark, sf, "lineitem", "l_partkey").groupBy("l_partkey").agg(F.count("*").alias("n"))
    dealt = parts.select("l_partkey", "n", F.explode(F.array(*map(F.lit, WORKERS))).alias("workers"))
    loads = dealt.groupBy("workers", (F.col("l_partkey") % F.col("workers")).alias("worker")).agg(F.sum("n").alias("n"))
    out = rl.speedup(loads.groupBy("workers").agg(F.max("n").cast("double").alias("seconds")))
    return out.withColumn("speedup", F.round("speedup", 6)).withColumn("efficiency", F.round("efficiency", 6))


# --- operators around the methods


@query("o_densify", f"SELECT step, pos, value FROM ({SERIES_SQL['user_activity']})")
def o_densify(spark, sf):
    """Running sums carried to every day, built anew."""
    return BUILDERS["user_activity"](spark, sf).select("step", "pos", "value")


@query("o_densify_all", f"SELECT step, pos, value FROM ({SERIES_SQL['user_activity']})")
def o_densify_all(spark, sf):
    """Like o_densify, over all points."""
    return load_series(spark, sf, "user_activity").select("step", "pos", "value")


@query("o_as_of_steps", """WITH d AS (SELECT user_id, CAST(ts AS DATE) AS day, max_by(value, (ts, event_id)) AS value FROM events GROUP BY ALL), g AS (SELECT user_id, day FROM (SELECT DISTINCT user_id FROM d), (SELECT DISTINCT day FROM d))
  SELECT g.user_id AS pos, g.day AS step, d.value FROM g ASOF LEFT JOIN d ON g.user_id = d.user_id AND g.day >= d.day""")
def o_as_of_steps(spark, sf):
    """The last event of each user at or before each day."""
    events = load_table(spark, sf, "events", "event_id", "user_id", "ts", "value")
    daily = events.groupBy(F.col("user_id").alias("pos"), F.to_date("ts").alias("step")).agg(F.max_by("value", F.struct("ts", "event_id")).alias("value"))
    return rl.carry_forward(daily, daily.select("pos").distinct(), daily.select("step").distinct())


@query("o_common_points", f"WITH s AS ({SERIES_SQL['turn_lengths']}) SELECT var, step, pos, value FROM s WHERE step = 3 AND pos IN (SELECT pos FROM s WHERE step = 5)")
def o_common_points(spark, sf):
    series = load_series(spark, sf, "turn_lengths")
    return rl.common_points(rl.slice_series(series, step=3), rl.slice_series(series, step=5))


@query("o_stored_exactly", ctes("part_volume", bits=4) + "SELECT var, step, pos FROM i WHERE centre IS NULL")
def o_stored_exactly(spark, sf):
    binned = saved(binned_of(spark, sf, "part_volume"), "binned")
    return rl.stored_exactly(binned, bn.top_k_bins(bn.ratio_histogram(binned), 15, E)).select(*STEP, "pos")


@query("o_cube", "SELECT r_name, n_name, count(*) AS suppliers, CAST(sum(CAST(round(s_acctbal * 100) AS BIGINT)) AS BIGINT) AS cents FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY CUBE (r_name, n_name)")
def o_cube(spark, sf):
    s, n, r = (load_table(spark, sf, t) for t in ("supplier", "nation", "region"))
    joined = s.join(F.broadcast(n), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))  # 25 and 5 rows
    return joined.cube("r_name", "n_name").agg(F.count("*").alias("suppliers"), F.sum(rl.cents(F.col("s_acctbal"))).alias("cents"))


@query("o_exact_by_region", ctes("supplier_month") + ", sp AS (SELECT s_nationkey, row_number() OVER (ORDER BY s_suppkey) - 1 AS pos FROM supplier WHERE s_suppkey IN (SELECT l_suppkey FROM lineitem)) SELECT r_name, count(*) AS n, count(*) FILTER (centre IS NULL) AS n_exact FROM i JOIN sp USING (pos) JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL")
def o_exact_by_region(spark, sf):
    """Exact values of the supplier series, by region."""
    points = indexed_of(spark, sf, "supplier_month").points
    sold = load_table(spark, sf, "lineitem", "l_suppkey").distinct()
    place = rl.dense_positions(sold, ["l_suppkey"]).join(load_table(spark, sf, "supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
    n, r = load_table(spark, sf, "nation"), load_table(spark, sf, "region")
    joined = points.join(place, "pos").join(F.broadcast(n), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))  # 25 and 5 rows
    return joined.groupBy("r_name").agg(F.count("*").alias("n"), F.count(F.when(F.col("centre").isNull(), 1)).alias("n_exact"))


@query("o_bits_pivot", ctes("part_volume") + "SELECT step, " + ", ".join(f"max(est_bytes) FILTER (bits = {b}) AS \"{b}\"" for b in (4, 6, 8, 10)) + " FROM z GROUP BY step")
def o_bits_pivot(spark, sf):
    return sizes_of(spark, sf, "part_volume")[0].groupBy("step").pivot("bits", [4, 6, 8, 10]).agg(F.max("est_bytes"))


@query("o_strategy_overlap", "SELECT held_by, count(*) AS n FROM (WITH t AS (" + ctes("part_volume", bits=4) + "SELECT pos FROM i WHERE step = 14 AND centre IS NOT NULL), u AS (" + ctes("part_volume", bits=4, anchor="zero") + "SELECT pos FROM i WHERE step = 14 AND centre IS NOT NULL) SELECT CASE WHEN pos IN (SELECT pos FROM u) THEN 'both' ELSE 'first' END AS held_by FROM t) GROUP BY held_by")
def o_strategy_overlap(spark, sf):
    """Points compressible with the grid from the minimum, against those with the grid around zero."""
    a, b = (indexed_of(spark, sf, "part_volume", (14,), bits=4, anchor=x).points.where("centre IS NOT NULL").select("pos") for x in ("min", "zero"))
    return rl.strategy_overlap(saved(a, "held"), saved(b, "held")).groupBy("held_by").agg(F.count("*").alias("n"))


@query("o_dense_positions", "SELECT o_orderkey, row_number() OVER (ORDER BY o_orderkey) - 1 AS pos FROM (SELECT DISTINCT o_orderkey FROM orders)")
def o_dense_positions(spark, sf):
    return rl.dense_positions(load_table(spark, sf, "orders", "o_orderkey"), ["o_orderkey"])


@query("o_interval_join", "SELECT window_id, count(*) AS n, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS cents FROM events JOIN (SELECT w AS window_id, TIMESTAMP '2024-01-01 00:00:00' + w * INTERVAL 36 HOUR AS a, TIMESTAMP '2024-01-01 00:00:00' + (w + 1) * INTERVAL 36 HOUR AS b FROM range(0, 20) t(w)) ON ts >= a AND ts < b GROUP BY ALL")
def o_interval_join(spark, sf):
    windows = spark.range(20).select(F.col("id").alias("window_id"), (F.expr("timestamp_ntz'2024-01-01 00:00:00'") + F.col("id") * F.expr("INTERVAL '36' HOUR")).alias("start"), (F.expr("timestamp_ntz'2024-01-01 00:00:00'") + (F.col("id") + 1) * F.expr("INTERVAL '36' HOUR")).alias("end"))
    joined = rl.assign_steps(load_table(spark, sf, "events", "ts", "value"), windows)
    return joined.groupBy("window_id").agg(F.count("*").alias("n"), F.sum(rl.cents(F.col("value"))).alias("cents"))


@query("o_sql_functions", ctes("part_volume") + "SELECT var, step, pos, ratio, bin FROM b WHERE step = 14")
def o_sql_functions(spark, sf):
    """Ratios and bins through SQL functions."""
    sql_functions.register(spark)
    load_series(spark, sf, "part_volume").createOrReplaceTempView("ratiobin_series")
    return spark.sql(f"""WITH r AS (SELECT c.var, c.step, c.pos, ratio_change(p.value, c.value) AS ratio FROM ratiobin_series c JOIN ratiobin_series p ON p.pos = c.pos AND p.step = 13 WHERE c.step = 14),
      g AS (SELECT min(ratio) AS lo FROM r) SELECT var, step, pos, ratio, grid_bin(ratio, lo, {E}D) AS bin FROM r CROSS JOIN g""")


@query("o_udtf_decode", ctes("price_states") + "SELECT step, pos, idx FROM i WHERE step = 1 AND pos >= 100 AND pos < 2000")
def o_udtf_decode(spark, sf):
    """A range of positions unpacked from blocks by a table function."""
    sql_functions.register(spark)
    c = compressed_of(spark, sf, "price_states", block_bytes=512)
    c.blocks.join(c.header.select(*STEP, "bits"), STEP).createOrReplaceTempView("ratiobin_blocks")
    return spark.sql("SELECT b.step, d.pos, d.idx FROM ratiobin_blocks b, LATERAL decode_range(b.payload, b.bits, b.first_pos, b.n, 100, 2000) d WHERE b.step = 1")


@query("o_json_filter", "SELECT event_type, count(*) AS n, count(json_extract_string(props, '$.page')) AS with_page FROM events WHERE props IS NOT NULL GROUP BY ALL")
def o_json_filter(spark, sf):
    events = load_table(spark, sf, "events", "event_type", "props").where("props IS NOT NULL")
    return events.groupBy("event_type").agg(F.count("*").alias("n"), F.count(F.get_json_object("props", "$.page")).alias("with_page"))


@query("o_approx_top_k")
def o_approx_top_k(spark, sf):
    """Fullest bins of each step by a sketch instead of a full histogram."""
    binned_of(spark, sf, "part_volume").createOrReplaceTempView("ratiobin_binned")
    return spark.sql("SELECT var, step, t.item AS bin, t.count AS cnt FROM (SELECT var, step, explode(approx_top_k(bin, 15)) AS t FROM ratiobin_binned GROUP BY var, step)")


@query("o_sketches")
def o_sketches(spark, sf):
    """Occupied bins and the median ratio of each step by mergeable sketches."""
    binned_of(spark, sf, "embedding_field").createOrReplaceTempView("ratiobin_sketched")
    return spark.sql("""SELECT var, step, hll_sketch_estimate(hll_sketch_agg(bin, 14)) AS occupied, kll_sketch_get_quantile_double(kll_sketch_agg_double(ratio, 400), 0.5D) AS median
      FROM ratiobin_sketched WHERE bin IS NOT NULL GROUP BY var, step""")


@query("o_grouping_sets", "SELECT var, step, count(*) AS n, count(*) FILTER (ratio IS NULL) AS undefined FROM (" + each(("part_volume", "user_activity"), lambda n: ctes(n) + "SELECT var, step, ratio FROM r") + ") GROUP BY GROUPING SETS ((var, step), (var), ())")
def o_grouping_sets(spark, sf):
    union([ratios_of(spark, sf, n).select(*STEP, "ratio") for n in ("part_volume", "user_activity")]).createOrReplaceTempView("ratiobin_ratios")
    return spark.sql("SELECT var, step, count(*) AS n, count_if(ratio IS NULL) AS undefined FROM ratiobin_ratios GROUP BY GROUPING SETS ((var, step), (var), ())")


@query("o_quantiles", ctes("embedding_field") + "SELECT var, step, quantile_disc(ratio, 0.5) AS median FROM r WHERE ratio IS NOT NULL GROUP BY ALL")
def o_quantiles(spark, sf):
    return ratios_of(spark, sf, "embedding_field").where("ratio IS NOT NULL").groupBy(*STEP).agg(F.percentile_approx("ratio", 0.5, 1_000_000).alias("median"))


@query("o_size_estimate_rows", ctes("part_volume") + "SELECT var, step, n, n - n_defined AS n_undefined, CAST(bits AS INTEGER) AS bits, pow(2.0, bits) * 8 + n * bits / 8.0 + (n - n_defined) * 8 AS est FROM g, (SELECT unnest(range(1, 17)) AS bits)")
def o_size_estimate_rows(spark, sf):
    """The size estimate of each step by index length, where only undefined ratios are stored exactly."""
    sizes = ratios_of(spark, sf, "part_volume").groupBy(*STEP).agg(F.count("*").alias("n"), (F.count("*") - F.count("ratio")).alias("n_undefined"))
    grid = sizes.select("*", F.explode(F.sequence(F.lit(1), F.lit(16))).alias("bits"))
    return grid.select(*STEP, "n", "n_undefined", "bits", estimated_size(F.col("bits"), F.col("n"), 8, F.col("n_undefined")).alias("est"))


# --- streaming

CENTS = "CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS cents"


@query("s_daily_steps", f"SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) AS start, event_type, count(*) AS n, {CENTS} FROM events GROUP BY ALL")
def s_daily_steps(spark, sf):
    return st.run_to_end(st.tumbling(st.stream_events(spark, sf), watermark=None), "daily").select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n", "cents")


CLOSED = "date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 DAY"


@query("s_daily_closed", f"SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) AS start, event_type, count(*) AS n, {CENTS} FROM events WHERE {CLOSED} GROUP BY ALL")
def s_daily_closed(spark, sf):
    """Daily steps that a watermark of one day behind the latest event has closed."""
    return st.run_to_end(st.tumbling(st.stream_events(spark, sf)), "closed", "append").select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n", "cents")


@query("s_sliding_steps", f"SELECT CAST(time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '2024-01-01 00:00:00') - k * INTERVAL 6 HOUR AS TIMESTAMP) AS start, event_type, count(*) AS n, {CENTS} FROM events, (SELECT unnest(range(0, 4)) AS k) GROUP BY ALL")
def s_sliding_steps(spark, sf):
    return st.run_to_end(st.sliding(st.stream_events(spark, sf), watermark=None), "sliding").select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n", "cents")


@query("s_session_steps", f"WITH o AS (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events), g AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM o) SELECT user_id, CAST(min(ts) AS TIMESTAMP) AS start, count(*) AS n, {CENTS} FROM g GROUP BY user_id, s")
def s_session_steps(spark, sf):
    return st.run_to_end(st.sessions(st.stream_events(spark, sf), watermark=None), "session").select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "n", "cents")


@query("s_compress_stream", decoded("price_states") + HAT)
def s_compress_stream(spark, sf):
    """Steps that arrive as files are compressed one by one and decode to the batch answer."""
    source, out = new_path(spark, "stream-source"), new_path(spark, "stream-codec")
    series = load_series(spark, sf, "price_states")
    for step in range(3):
        series.where(F.col("step") == step).coalesce(1).write.mode("append").parquet(source)
    stream = spark.readStream.schema(series.schema).option("maxFilesPerTrigger", 1).parquet(source)
    return st.compress_stream(stream, out, CodecSpec(error_bound=E, reference="original"))


# --- chunk form


@query("m_change_ratio_chunked", ctes("part_volume") + "SELECT var, step, pos, ratio FROM r")
def m_change_ratio_chunked(spark, sf):
    ratios = ck.change_ratios_chunked(ck.to_chunks(load_series(spark, sf, "part_volume"), 8192))
    return ck.from_chunks(ratios, "ratio", "ratio", 8192)


@query("m_choose_bits_chunked", each(("drift_field", "customer_balance"), lambda n: ctes(n) + f"SELECT {SIZE_COLUMNS} FROM p"))
def m_choose_bits_chunked(spark, sf):
    return union([ck.compress_chunks(ck.to_chunks(load_series(spark, sf, n), 8192)).header.select(*SIZE_COLUMNS.split(", ")) for n in ("drift_field", "customer_balance")])


@query("m_decode_chunked", decoded("drift_field") + HAT)
def m_decode_chunked(spark, sf):
    """Blocks cut along chunks decode to the same values as blocks of points."""
    series = load_series(spark, sf, "drift_field")
    c = ck.compress_chunks(ck.to_chunks(series, 8192), size=8192)
    return dc.decompress_chain(dc.decode_blocks(c.blocks, c.header, c.centres), series.where("step = 0"))


@query("m_choose_bits_sampled")
def m_choose_bits_sampled(spark, sf):
    """Index lengths from a quarter of the points, beside those from all; sizes are scaled by the share."""
    ratios = ratios_of(spark, sf, "drift_field")
    full = cd.index_ratios(ratios, CodecSpec(error_bound=E)).bits.select(*STEP, F.col("bits").alias("bits_all"))
    some = cd.index_ratios(saved(bn.sampled(ratios, 0.25), "sample"), CodecSpec(error_bound=E)).bits.select(*STEP, F.col("bits").alias("bits_sample"), F.col("n").alias("n_sample"))
    return full.join(some, STEP)


@query("s_daily_unique", f"SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) AS start, event_type, count(*) AS n, {CENTS} FROM events GROUP BY ALL")
def s_daily_unique(spark, sf):
    """Daily sums of a stream in which every event is sent twice."""
    events = st.stream_events(spark, sf)
    twice = st.deduplicated(events.unionAll(events))
    days = twice.groupBy(F.date_trunc("day", "ts").alias("start"), "event_type").agg(F.count("*").alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents"))
    return st.run_to_end(days, "unique").select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n", "cents")


@query("s_frozen_centres")
def s_frozen_centres(spark, sf):
    """Chunks coded as they arrive, with the centres of step 1: points, exact values and bytes of each step."""
    series = load_series(spark, sf, "drift_field")
    centres = [r["centre"] for r in cd.index_ratios(ratios_of(spark, sf, "drift_field", (1,)), CodecSpec(error_bound=E)).centres.collect()]  # 65535 at most
    source = new_path(spark, "stream-chunks")
    chunks = ck.to_chunks(series, 8192)
    chunks.write.parquet(source)
    stream = spark.readStream.schema(chunks.schema).parquet(source)
    coded = st.run_to_end(frozen.compress_frozen(stream, centres, E), "frozen", "append")
    return coded.groupBy(*STEP).agg(F.sum("n").alias("n"), F.sum(F.size("exact")).alias("n_exact"), F.sum(F.octet_length("payload")).alias("index_bytes"))
