"""Session helpers: shared folder, materialised steps, and joins with sides of a checked size."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Used only where a local session has no spark.checkpoint.dir, as in tests on one machine.
FALLBACK_DIR = "/tmp/checkpoints"
#: Bytes, uncompressed, up to which a side is broadcast after it has been measured.
BROADCAST_BYTES = 64 << 20
#: Tasks over which the rows of one key are spread where a side is too large to broadcast.
SPREAD = 64

_cleaned: set[str] = set()


def shared_dir(spark: SparkSession) -> str:
    """Folder that every executor sees, as the cluster names it; a cluster without one is an error."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder:
        return folder
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    return FALLBACK_DIR


def hadoop_path(spark: SparkSession, path: str):
    """(file system, path) of the session's Hadoop configuration."""
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), where


def new_path(spark: SparkSession, tag: str) -> str:
    """A fresh folder for this application's files; all of them are removed when the driver's JVM ends."""
    folder = f"{shared_dir(spark)}/ratiobin/{spark.sparkContext.applicationId}"
    if folder not in _cleaned:
        fs, where = hadoop_path(spark, folder)
        fs.mkdirs(where)
        fs.deleteOnExit(where)
        _cleaned.add(folder)
    return f"{folder}/{tag}-{uuid.uuid4().hex}"


def saved(df: DataFrame, tag: str = "step", plain: bool = False) -> DataFrame:
    """Write a DataFrame as Parquet to the shared folder and read it back: cuts lineage and survives lost executors.

    plain: neither compressed nor with dictionaries, so that the bytes of its files tell what it takes in memory.
    """
    path = new_path(df.sparkSession, tag)
    writer = df.write.option("compression", "uncompressed").option("parquet.enable.dictionary", "false") if plain else df.write
    writer.parquet(path)
    kept = df.sparkSession.read.schema(df.schema).parquet(path)
    kept._ratiobin_path = path
    return kept


_once: dict[tuple, tuple] = {}


def exists(spark: SparkSession, path: str) -> bool:
    fs, where = hadoop_path(spark, path)
    return fs.exists(where)


def once(spark: SparkSession, key: tuple, build) -> DataFrame:
    """The saved result of build(), made once for each key in an application and read again afterwards."""
    key = (spark.sparkContext.applicationId, *key)
    if key not in _once or not exists(spark, f"{_once[key][0]}/_SUCCESS"):
        made = saved(build(), str(key[1]))
        _once[key] = made._ratiobin_path, made.schema
    path, schema = _once[key]
    kept = spark.read.schema(schema).parquet(path)
    kept._ratiobin_path = path
    return kept


def is_saved(df: DataFrame) -> bool:
    return hasattr(df, "_ratiobin_path")


def stored_bytes(kept: DataFrame) -> int:
    """Bytes of the files of a saved DataFrame, as the file system tells without a job."""
    fs, where = hadoop_path(kept.sparkSession, kept._ratiobin_path)
    return fs.getContentSummary(where).getLength()


def small_side(df: DataFrame, most: int = BROADCAST_BYTES) -> DataFrame:
    """A join side that is written once and measured: broadcast up to `most` bytes, left to a shuffle join beyond."""
    kept = saved(df, "side", plain=True)
    return F.broadcast(kept) if stored_bytes(kept) <= most else kept


def join_spread(rows: DataFrame, side: DataFrame, keys: list[str], by: str, how: str = "left", most: int = BROADCAST_BYTES) -> DataFrame:
    """rows joined to side on keys, however many rows a key has.

    side is broadcast up to `most` bytes.  Beyond, it is repeated SPREAD times and the rows of a key are dealt to that many
    tasks by their column `by`, so a key that holds most rows is no single task's work.
    """
    kept = saved(side, "side", plain=True)
    if stored_bytes(kept) <= most:
        return rows.join(F.broadcast(kept), keys, how)
    dealt = rows.withColumn("_spread", F.pmod(F.xxhash64(by), F.lit(SPREAD)).cast("int"))
    repeated = kept.withColumn("_spread", F.explode(F.sequence(F.lit(0), F.lit(SPREAD - 1))))
    return dealt.join(repeated, [*keys, "_spread"], how).drop("_spread")
