"""The compressed store: a folder of Parquet tables, partitioned by variable and step."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ratiobin.plans.codec import Compressed
from ratiobin.spec import CodecSpec

TABLES = ("header", "centres", "blocks", "anchors")


def write_compressed(c: Compressed, path: str, mode: str = "errorifexists") -> None:
    """Blocks lie sorted by block_id in their step's folder, so a range of positions prunes files and row groups.

    Tables are dealt by ranges of (var, step, place), so the blocks of one large step are written by many tasks.
    """
    c.header.coalesce(1).write.mode(mode).parquet(f"{path}/header")  # one row a step
    for name, place in (("centres", "idx"), ("blocks", "block_id"), ("anchors", "pos")):
        dealt = getattr(c, name).repartitionByRange("var", "step", place).sortWithinPartitions("var", "step", place)
        dealt.write.mode(mode).partitionBy("var", "step").parquet(f"{path}/{name}")


def read_compressed(spark: SparkSession, path: str, spec: CodecSpec = CodecSpec()) -> Compressed:
    """The store's tables, lazily; the folder names are typed by the header's schema rather than guessed."""
    header = spark.read.parquet(f"{path}/header")
    rest = [spark.read.parquet(f"{path}/{n}").withColumn("var", F.col("var").cast("string")).withColumn("step", F.col("step").cast("int")) for n in TABLES[1:]]
    return Compressed(spec, header, *rest)


def store_sizes(c: Compressed) -> DataFrame:
    return c.blocks.groupBy("var", "step").agg(F.sum(F.octet_length("payload")).alias("bytes"))
