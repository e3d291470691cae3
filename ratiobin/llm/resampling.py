"""Importance resampling with hashed n-gram generative models.

Unigrams and bigrams of words are hashed into a fixed number of buckets.  One pass over all texts counts buckets in the raw
corpus and in its target rows; a second adds up log(target / raw) over each text's n-grams, which is the log importance
weight.  Adding Gumbel noise and taking the k largest sums samples k rows without replacement in proportion to their
weights.  The noise is a hash of the row, so a lost task repeats it.  The k-th largest key comes from histograms that are
refined around it, never from a global sort.

Defined cases: null and empty texts have weight zero (log) and take part; with no target rows all weights are zero; rows
whose keys tie with the last selected are all selected; repeated rows share a key.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ratiobin.llm import textgrid as tg
from ratiobin.llm.common import saved, table

BUCKET_BITS = 14
SMOOTHING = 1.0
#: Share of all rows that the query samples.
FRACTION = 0.5
#: Target ids above this are joined by shuffle; below, their 8 bytes each are broadcast.
BROADCAST_IDS = 1_000_000


def gram_buckets(column: pa.Array, bits: int = BUCKET_BITS) -> tuple[np.ndarray, np.ndarray, int]:
    """(document index, bucket) of every unigram and bigram of a batch, and the number of documents."""
    words = tg.Words(column, tg.NOT_ALNUM)
    hashes, owner = words.hashes(), words.doc_of_word()
    pairs = tg.pair_hash(hashes[:-1], hashes[1:])[owner[:-1] == owner[1:]] if len(hashes) > 1 else hashes[:0]
    pair_owner = owner[:-1][owner[:-1] == owner[1:]] if len(hashes) > 1 else owner[:0]
    bucket = (np.concatenate((tg.mix64(hashes), pairs)) >> np.uint64(64 - bits)).astype(np.int64)
    return np.concatenate((owner, pair_owner)), bucket, words.n_docs


def bucket_counts(rows: DataFrame, bits: int = BUCKET_BITS) -> tuple[np.ndarray, np.ndarray]:
    """Bucket counts of all rows and of the rows marked `target` (2**bits numbers each)."""

    def run(batches):
        raw, target = np.zeros(1 << bits, dtype=np.int64), np.zeros(1 << bits, dtype=np.int64)
        for batch in tg.slices(batches):
            owner, bucket, _ = gram_buckets(batch.column(batch.schema.get_field_index("text")), bits)
            mark = batch.column(batch.schema.get_field_index("target")).to_numpy(zero_copy_only=False).astype(bool)
            raw += np.bincount(bucket, minlength=1 << bits)
            target += np.bincount(bucket[mark[owner]], minlength=1 << bits)
        some = np.flatnonzero(raw)
        yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(raw[some]), pa.array(target[some])], ["bucket", "raw", "target"])

    sums = rows.select("text", "target").mapInArrow(run, "bucket long, raw long, target long").groupBy("bucket").agg(F.sum("raw").alias("raw"), F.sum("target").alias("target")).collect()
    raw, target = np.zeros(1 << bits), np.zeros(1 << bits)
    for r in sums:
        raw[r["bucket"]], target[r["bucket"]] = r["raw"], r["target"]
    return raw, target


def log_ratios(raw: np.ndarray, target: np.ndarray, smoothing: float = SMOOTHING) -> np.ndarray:
    if not target.sum():
        return np.zeros(len(raw))
    return np.log((target + smoothing) / (target.sum() + smoothing * len(raw))) - np.log((raw + smoothing) / (raw.sum() + smoothing * len(raw)))


def log_weights(rows: DataFrame, ratios: np.ndarray, name: str = "log_weight") -> DataFrame:
    """rows plus their log importance weight."""
    bits = int(np.log2(len(ratios)))

    def run(batches):
        for batch in tg.slices(batches):
            owner, bucket, n = gram_buckets(batch.column(batch.schema.get_field_index("text")), bits)
            keep = [i for i, c in enumerate(batch.schema.names) if c != "text"]
            weight = np.bincount(owner, weights=ratios[bucket], minlength=n)
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in keep), pa.array(weight)], [*(batch.schema.names[i] for i in keep), name])

    return rows.mapInArrow(run, T.StructType([*rows.drop("text").schema.fields, T.StructField(name, T.DoubleType())]))


def gumbel(*columns: str, seed: int = 0) -> Column:
    """Standard Gumbel noise fixed by the columns' values."""
    uniform = (F.shiftrightunsigned(F.xxhash64(*columns, F.lit(f"gumbel{seed}")), 11).cast("double") + 0.5) / float(1 << 53)
    return -F.log(-F.log(uniform))


def kth_largest(values: DataFrame, column: str, k: int, bins: int = 1024, few: int = 4096) -> float | None:
    """The exact k-th largest value: histograms narrow its range until few rows are left in it."""
    if k <= 0:
        return None
    low, high, n = values.agg(F.min(column), F.max(column), F.count(column)).first()
    if n < k:
        return low
    above = 0
    while low < high:
        width = (high - low) / bins
        inside = values.where((F.col(column) >= low) & (F.col(column) <= high))
        counts = {r["bin"]: (r["n"], r["a"], r["b"]) for r in inside.groupBy(F.least(F.floor((F.col(column) - low) / width), F.lit(bins - 1)).alias("bin")).agg(F.count("*").alias("n"), F.min(column).alias("a"), F.max(column).alias("b")).collect()}
        for b in sorted(counts, reverse=True):
            if above + counts[b][0] >= k:
                break
            above += counts[b][0]
        n, low, high = counts[b]
        if n <= few:
            left = values.where((F.col(column) >= low) & (F.col(column) <= high)).select(column).collect()  # `few` rows at most
            return sorted((r[0] for r in left), reverse=True)[k - above - 1]
    return low


def resample(docs: DataFrame, target_ids: DataFrame, fraction: float = FRACTION, seed: int = 0) -> DataFrame:
    """doc_id, log_weight, key and selected for every row of docs (doc_id, text); target_ids: distinct doc_id."""
    ids = target_ids.where("doc_id IS NOT NULL").select(F.col("doc_id").alias("_target_id")).distinct()
    few = ids.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS
    rows = docs.select("doc_id", "text").join(F.broadcast(ids) if few else ids, F.col("doc_id") == F.col("_target_id"), "left")
    rows = rows.select("doc_id", "text", F.col("_target_id").isNotNull().alias("target"))
    ratios = log_ratios(*bucket_counts(rows))
    keyed = docs.select("doc_id", F.xxhash64("text").alias("text_hash"), "text")
    scored = log_weights(keyed, ratios).withColumn("key", F.col("log_weight") + gumbel("doc_id", "text_hash", seed=seed))
    kept = saved(scored.select("doc_id", "log_weight", "key"), "weights")
    least = kth_largest(kept, "key", int(round(fraction * kept.count())))
    return kept.withColumn("selected", F.lit(False) if least is None else F.col("key") >= least)


def op6_resampling(spark: SparkSession, sf_dir: str) -> DataFrame:
    good = table(spark, sf_dir, "labels").where("quality = 1").select("doc_id")
    return resample(table(spark, sf_dir, "documents"), good)
