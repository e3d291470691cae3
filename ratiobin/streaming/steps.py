"""Steps from event streams, and compression step by step as they close.

Windows of event time are steps.  A watermark closes a window: append output returns closed windows only, and events of a
closed window that come later no longer change it.  The compressor sets the late rows of closed steps aside.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ratiobin.operators.decode import decode_blocks, decompress_step
from ratiobin.plans.codec import compress_step
from ratiobin.session import new_path
from ratiobin.spec import CodecSpec

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def stream_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream; ts is cast, since a watermark needs an instant (session zone UTC)."""
    rows = spark.readStream.schema(EVENTS).option("pathGlobFilter", "events.parquet").option("recursiveFileLookup", "true").parquet(sf_dir)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(events: DataFrame, length: str = "1 day", watermark: str | None = "1 day") -> DataFrame:
    rows = events.withWatermark("ts", watermark) if watermark else events
    return _sums(rows.groupBy(F.window("ts", length).alias("w"), "event_type"))


def sliding(events: DataFrame, length: str = "1 day", slide: str = "6 hours", watermark: str | None = "1 day") -> DataFrame:
    rows = events.withWatermark("ts", watermark) if watermark else events
    return _sums(rows.groupBy(F.window("ts", length, slide).alias("w"), "event_type"))


def sessions(events: DataFrame, gap: str = "30 minutes", watermark: str | None = "1 day") -> DataFrame:
    """Bursts of one user that pauses of `gap` part."""
    rows = events.withWatermark("ts", watermark) if watermark else events
    out = rows.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "n", "cents")


def _sums(grouped) -> DataFrame:
    out = grouped.agg(F.count("*").alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "event_type", "n", "cents")


def run_to_end(stream: DataFrame, tag: str, mode: str = "complete") -> DataFrame:
    """Run a stream over what there is and return the final table, kept in the shared folder.

    Complete output replaces the table in every batch; append output writes each batch's folder once, so that a replayed
    batch overwrites itself.
    """
    spark = stream.sparkSession
    out, state = new_path(spark, f"stream-{tag}"), new_path(spark, f"state-{tag}")

    def write(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(out if mode == "complete" else f"{out}/batch={batch_id}")

    query = stream.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", state).trigger(availableNow=True).start()
    query.awaitTermination()
    found = spark.read.parquet(out)
    return found.drop("batch") if mode != "complete" else found


class StreamCompressor:
    """foreachBatch target that compresses each closed step against the one before, original or reconstructed as the
    parameters say.  Both forms of the last step are kept as state.

    rows of a batch: (var, step, pos, value), whole steps.  Each step is written to its own folder, so a replayed batch
    overwrites it; rows of steps that are closed already go to the folder of late rows.
    """

    def __init__(self, spark: SparkSession, path: str, spec: CodecSpec = CodecSpec()):
        self.spark, self.path, self.spec = spark, path, spec

    def _closed(self) -> list[tuple[int, int]]:
        try:
            rows = self.spark.read.schema("step int, batch long").json(f"{self.path}/closed").distinct().collect()  # one row a step
        except Exception as e:
            if "PATH_NOT_FOUND" not in str(e):
                raise
            return []
        return sorted((r["step"], r["batch"]) for r in rows)

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        closed = [(s, b) for s, b in self._closed() if b != batch_id]
        last = max((s for s, _ in closed), default=None)
        batch = batch.dropDuplicates(["var", "step", "pos"]).persist()
        if last is not None:
            batch.where(F.col("step") <= last).write.mode("overwrite").parquet(f"{self.path}/late/batch={batch_id}")
            batch = batch.where(F.col("step") > last)
        for step in sorted(r["step"] for r in batch.select("step").distinct().collect()):  # steps of one batch
            cur = batch.where(F.col("step") == step)
            if last is None:
                hat = cur.select("var", "pos", F.col("value").alias("value_hat"))
            else:
                kept = self.spark.read.parquet(f"{self.path}/hat/step={last}")
                before = kept.select("var", "pos", F.col("value" if self.spec.reference == "original" else "value_hat").alias("value"))
                one = compress_step(before, cur, self.spec)
                for name in ("header", "centres", "blocks"):
                    getattr(one, name).drop("step").write.mode("overwrite").parquet(f"{self.path}/{name}/step={step}")
                hat = decompress_step(decode_blocks(one.blocks, one.header, one.centres), kept.select("var", "pos", "value_hat")).drop("step")
            hat.join(cur.select("var", "pos", "value"), ["var", "pos"]).write.mode("overwrite").parquet(f"{self.path}/hat/step={step}")
            self.spark.createDataFrame([(step, batch_id)], "step int, batch long").coalesce(1).write.mode("append").json(f"{self.path}/closed")
            last = step
        batch.unpersist()


def compress_stream(stream: DataFrame, path: str, spec: CodecSpec = CodecSpec(), prepare: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """Compress a stream of whole steps; returns the reconstructed steps."""
    spark = stream.sparkSession
    target = StreamCompressor(spark, path, spec)
    query = stream.writeStream.foreachBatch(lambda b, i: target(prepare(b) if prepare else b, i)).option("checkpointLocation", new_path(spark, "state-codec")).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.parquet(f"{path}/hat").select("var", F.col("step").cast("int").alias("step"), "pos", "value_hat")


def deduplicated(events: DataFrame, watermark: str = "1 day") -> DataFrame:
    """Each event once, however often its batch is sent again within the watermark."""
    return events.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])
