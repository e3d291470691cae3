"""Shared Spark helpers of the text operators."""

from __future__ import annotations

import gc
import uuid
from collections.abc import Iterable

from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Used only where a local session has no spark.checkpoint.dir, as in tests on one machine.
FALLBACK_DIR = "/tmp/checkpoints"
#: Tasks over which the rows of one key are spread.
SPREAD = 16

_cleaned: set[str] = set()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """Folder that every executor sees, as the cluster names it; a cluster without one is an error."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder:
        return folder
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    return FALLBACK_DIR


def new_path(spark: SparkSession, tag: str) -> str:
    """A fresh folder for this application's files; all of them are removed when the driver's JVM ends."""
    folder = f"{shared_dir(spark)}/ratiobin/{spark.sparkContext.applicationId}"
    if folder not in _cleaned:
        where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
        fs = where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        fs.mkdirs(where)
        fs.deleteOnExit(where)
        _cleaned.add(folder)
    return f"{folder}/{tag}-{uuid.uuid4().hex}"


def saved(df: DataFrame, tag: str = "step") -> DataFrame:
    """Write a DataFrame as Parquet to the shared folder and read it back: cuts lineage and survives lost executors."""
    path = new_path(df.sparkSession, tag)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def saved_parts(spark: SparkSession, frames: Iterable[DataFrame], tag: str, schema) -> DataFrame:
    """saved() of DataFrames that are made, written and freed of their shuffle files one after the other."""
    path, i = new_path(spark, tag), -1
    for i, df in enumerate(frames):
        if i:
            drop_shuffles(spark)
        df.write.mode("append").parquet(path)
    if i < 0:
        spark.createDataFrame([], schema).write.parquet(path)
    return spark.read.schema(schema).parquet(path)


def drop_shuffles(spark: SparkSession) -> None:
    """Let Spark remove the shuffle files of plans that have ended: its cleaner waits for the driver's collector."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def placed(rows: DataFrame, file: str, row: str) -> DataFrame:
    """rows with the hash of their file and their place in it: the same whenever they are read again.

    Rows that don't come from files as they are, are written to the shared folder first.
    """
    both = lambda df: df.select("*", F.xxhash64("_metadata.file_path").alias(file), F.col("_metadata.row_index").alias(row))
    try:
        return both(rows)
    except AnalysisException:
        return both(saved(rows, "rows"))


def join_dealt(rows: DataFrame, side: DataFrame, key: str, by: str, how: str = "inner") -> DataFrame:
    """rows joined to side (one row for each key) when one key may have most of the rows.

    The rows of a key are dealt to SPREAD tasks by their column `by`; a key's row of the side goes to those of them only that
    have rows of the key, so the side is not multiplied for rare keys.
    """
    dealt = rows.withColumn("_lane", F.pmod(F.xxhash64(by), F.lit(SPREAD)).cast("int"))
    lanes = dealt.select(key, "_lane").distinct().join(side, key)
    return dealt.join(lanes, [key, "_lane"], how).drop("_lane")


def unsave(*frames: DataFrame) -> None:
    """Remove the files of saved() frames that no later plan reads."""
    for df in frames:
        spark = df.sparkSession
        jvm = spark.sparkContext._jvm
        for file in df.inputFiles()[:1]:
            folder = jvm.org.apache.hadoop.fs.Path(file).getParent()
            if "/ratiobin/" in folder.toString():
                folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(folder, True)


def crc_mod(column: str, n: int) -> Column:
    """crc32 of an id's decimal text, modulo n (null ids: null)."""
    return F.crc32(F.col(column).cast("string").cast("binary")) % n
