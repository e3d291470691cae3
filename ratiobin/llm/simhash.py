"""SimHash near-duplicates found in BK-trees.

Each document gets a 64-bit fingerprint of its word shingles.  Equal fingerprints are one class.  Two fingerprints that
differ in at most three bits agree in at least one of four 16-bit bands, so classes are dealt to shards by (band, value)
and each shard builds a BK-tree: children are keyed by their integer Hamming distance to the parent, and a search follows
only edges within the radius of the distance to the node.  A tree is searched in the task that builds it, because a tree
that is broadcast to all tasks grows with the data.  Shards with many classes are dealt again by 12-bit bands of their
other 48 bits, which is as exact.  A shard returns a spanning forest of its links, so a group of m near copies costs m - 1
edges rather than all pairs; components are joined up in Spark.

Defined cases: null and wordless texts have fingerprint zero and link like any other; repeated rows and ids fall into one
component; a null doc_id gets a fingerprint and takes part, and it never names a component unless all ids there are null.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ratiobin.llm import textgrid as tg
from ratiobin.llm.common import join_dealt, placed, saved, table
from ratiobin.llm.graph import connected_components

SHINGLE_WORDS = 3
RADIUS = 3
BANDS = 4
#: Classes in one shard above which the shard is dealt again by bands of its other bits.
CROWDED = 2048


def simhash(text: bytes, size: int = SHINGLE_WORDS) -> int:
    """Fingerprint of one UTF-8 text: a bit is set if more than half of the shingle hashes have it."""
    words = text.lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    if len(words) <= size:
        return xxhash.xxh64_intdigest(joined, 42)
    ends = np.cumsum(np.fromiter(map(len, words), dtype=np.int64, count=len(words)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    digest = xxhash.xxh64_intdigest
    n = len(words) - size + 1
    hashes = np.fromiter((digest(joined[a:b], 42) for a, b in zip(starts[:n].tolist(), ends[size - 1 :].tolist(), strict=True)), dtype="<u8", count=n)
    set_ = np.zeros(64, dtype=np.int64)
    for at in range(0, n, 1 << 15):
        bits = np.unpackbits(hashes[at : at + (1 << 15)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        set_ += bits.sum(axis=0, dtype=np.int32)
    return int(np.packbits(set_ * 2 > n, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, size: int = SHINGLE_WORDS) -> DataFrame:
    """docs with a `fp` long column (the fingerprint's bits as a signed number)."""

    def run(batches):
        for batch in tg.slices(batches):
            data, at = tg.text_column(batch.column(batch.schema.get_field_index("text")))
            raw = data.tobytes()
            fp = np.fromiter((simhash(raw[a:b], size) for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)), dtype=np.uint64, count=batch.num_rows)
            keep = [i for i, name in enumerate(batch.schema.names) if name != "text"]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in keep), pa.array(fp.view(np.int64))], [*(batch.schema.names[i] for i in keep), "fp"])

    schema = docs.drop("text").schema.add("fp", "long")
    return docs.mapInArrow(run, schema)


class BKTree:
    """Burkhard-Keller tree over integers under Hamming distance; children keyed by distance to the parent."""

    def __init__(self) -> None:
        self.values: list[int] = []
        self.children: list[dict[int, int]] = []

    def add(self, value: int) -> int:
        node, new = 0, len(self.values)
        self.values.append(value)
        self.children.append({})
        while new:
            d = (value ^ self.values[node]).bit_count()
            after = self.children[node].get(d)
            if after is None:
                self.children[node][d] = new
                break
            node = after
        return new

    def within(self, value: int, radius: int) -> list[int]:
        """Indexes of the values at most radius bits away."""
        found, todo = [], [0] if self.values else []
        while todo:
            node = todo.pop()
            d = (value ^ self.values[node]).bit_count()
            if d <= radius:
                found.append(node)
            todo += [child for edge, child in self.children[node].items() if d - radius <= edge <= d + radius]
        return found


def shard_forest(values: list[int], radius: int = RADIUS) -> Iterator[tuple[int, int]]:
    """A spanning forest of the links between the values of one shard."""
    tree, parent = BKTree(), list(range(len(values)))

    def root(i: int) -> int:
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    for i, value in enumerate(values):
        for j in tree.within(value, radius):
            a, b = root(i), root(j)
            if a != b:
                parent[a] = b
                yield value, values[j]
        tree.add(value)


def _bands(bits: Column, width: int) -> Column:
    """The four bands of the low 4 * width bits, tagged with their place."""
    mask = (1 << width) - 1
    return F.array(*[F.lit(i << width).cast("long") + F.shiftrightunsigned(bits, i * width).bitwiseAND(F.lit(mask)) for i in range(BANDS)])


def _others(fp: Column, band: Column) -> Column:
    """The 48 bits outside a 16-bit band, moved together."""
    low = F.expr("CASE band WHEN 0 THEN 0L WHEN 1 THEN fp & 65535L WHEN 2 THEN fp & 4294967295L ELSE fp & 281474976710655L END")
    high = F.expr("CASE band WHEN 0 THEN shiftrightunsigned(fp, 16) WHEN 1 THEN shiftleft(shiftrightunsigned(fp, 32), 16) WHEN 2 THEN shiftleft(shiftrightunsigned(fp, 48), 32) ELSE 0L END")
    return low.bitwiseOR(high)


def shards(classes: DataFrame, crowded: int = CROWDED) -> DataFrame:
    """(fp) to (shard, fp): any two within three bits share a shard; crowded shards are dealt by finer keys."""
    first = classes.select("fp", F.explode(_bands(F.col("fp"), 16)).alias("shard"))
    crowds = first.groupBy("shard").count().where(F.col("count") > crowded).select("shard", F.lit(True).alias("crowd"))
    told = first.join(crowds, "shard", "left").withColumn("band", F.shiftright("shard", 16).cast("int"))
    calm = told.where("crowd IS NULL").select("shard", "fp")
    fine = told.where("crowd").select(
        "shard", "fp", F.explode(_bands(_others(F.col("fp"), F.col("band")), 12)).alias("sub")
    ).select(((F.col("sub") + 1) * F.lit(1 << 20) + F.col("shard")).alias("shard"), "fp")
    return calm.unionByName(fine)


def links(classes: DataFrame, radius: int = RADIUS, crowded: int = CROWDED) -> DataFrame:
    """Distinct fingerprints (fp) to edges (src, dst) that connect all fingerprints within the radius (3 at most)."""
    if not 0 <= radius < BANDS:
        raise ValueError("four bands find links of at most three bits")

    def run(batches):
        shard, values, src, dst = None, [], [], []

        def close():
            for a, b in shard_forest(values, radius):
                src.append(a)
                dst.append(b)

        for batch in batches:
            for key, fp in zip(batch.column(0).to_pylist(), batch.column(1).to_numpy().view(np.uint64).tolist(), strict=True):
                if key != shard:
                    close()
                    shard, values = key, []
                values.append(fp)
            if src:
                yield pa.RecordBatch.from_arrays([pa.array(np.array(x, dtype=np.uint64).view(np.int64)) for x in (src, dst)], ["src", "dst"])
                src, dst = [], []
        close()
        yield pa.RecordBatch.from_arrays([pa.array(np.array(x, dtype=np.uint64).view(np.int64)) for x in (src, dst)], ["src", "dst"])

    dealt = shards(classes, crowded).repartition("shard").sortWithinPartitions("shard", "fp")
    return dealt.mapInArrow(run, "src long, dst long")


def components(prints: DataFrame, radius: int = RADIUS, crowded: int = CROWDED) -> DataFrame:
    """(fp) rows, repeats allowed, to (fp, component): component is one fingerprint of the group."""
    classes = saved(prints.select("fp").distinct(), "classes")
    groups = connected_components(links(classes, radius, crowded)).withColumnRenamed("node", "fp")
    return classes.join(groups, "fp", "left").select("fp", F.coalesce("component", "fp").alias("component"))


def op8_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    prints = saved(fingerprints(docs), "prints")
    groups = components(prints)
    least = prints.groupBy("fp").agg(F.min("doc_id").alias("least")).join(groups, "fp")
    named = least.join(least.groupBy("component").agg(F.min("least").alias("component_id")), "component").select("fp", "component_id")
    return join_dealt(prints, named, "fp", "doc_id").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def one_of_each_group(docs: DataFrame) -> DataFrame:
    """docs without near copies: of each group the row with the smallest doc_id stays (null ids last), whole.

    Rows with equal ids are told apart by their file and place in it, which are the same whenever the rows are read.
    """
    row = ["_copy_file", "_copy_row"]
    rows = placed(docs, *row)
    prints = saved(fingerprints(rows.select("doc_id", *row, "text")), "prints")
    best = prints.groupBy("fp").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", *row)).alias("best"))
    stay = best.join(components(prints), "fp").groupBy("component").agg(F.min("best").alias("best")).select(*[F.col(f"best.{c}").alias(c) for c in row])
    return rows.join(stay, row, "left_semi").drop(*row)
