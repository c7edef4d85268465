"""Streaming twins of intake and aggregation, run to the end of the available input."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgrefine.plans.scratch import scratch_dir


def event_stream(spark: SparkSession, sf_dir: str, files_per_trigger: int = 1) -> DataFrame:
    """The events table as a file stream with zoned timestamps."""
    kind = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    path = f"{sf_dir}/events.parquet"
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    folder = where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(where).isDirectory()
    src = spark.readStream.schema(kind).option("maxFilesPerTrigger", files_per_trigger)
    raw = src.parquet(path) if folder else src.option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def drain(stream: DataFrame, tag: str, mode: str = "append", base: str | None = None) -> DataFrame:
    """Runs a stream over what is there and returns its result as a table in the shared folder; a run with the ``base`` of an earlier one goes on from its checkpoint."""
    spark = stream.sparkSession
    base = base or f"{scratch_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{base}/out")

    def keep(batch: DataFrame, n: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/out/batch={n}")

    q = stream.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    all_ = spark.read.parquet(f"{base}/out")
    if mode == "complete":
        all_ = all_.where(F.col("batch") == all_.agg(F.max("batch")).first()[0])
    return all_.drop("batch")


def normalize(stream: DataFrame) -> DataFrame:
    """Records of the event stream, the property parsed."""
    return stream.select(F.col("event_id").alias("record_id"), F.when(F.col("event_type") == "signup", "file").otherwise("inline").alias("kind"), F.col("event_id").alias("seq"),
                         F.get_json_object("props", "$.k").cast("long").alias("k"), (F.col("event_type") != "error").alias("ok"))


def dedup(stream: DataFrame, delay: str = "1 day") -> DataFrame:
    """Each record once: deliveries repeated within the watermark are dropped."""
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def windowed_counts(stream: DataFrame, size: str, slide: str | None = None, delay: str = "1 hour") -> DataFrame:
    """(w_start, event_type, n) by tumbling or sliding windows."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return stream.withWatermark("ts", delay).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("w_start"), "event_type", "n")


def session_counts(stream: DataFrame, gap: str = "30 minutes", delay: str = "1 hour") -> DataFrame:
    """(user_id, s_start, n) by session windows."""
    s = F.session_window("ts", gap)
    return stream.withWatermark("ts", delay).groupBy(s.alias("s"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("s.start").alias("s_start"), "n")


def request_completion_join(stream_a: DataFrame, stream_b: DataFrame, within: str = "10 minutes") -> DataFrame:
    """(request_id, completion_id, user_id): completions of the same user at most ``within`` after a request, an interval join of two streams."""
    a = stream_a.select(F.col("event_id").alias("request_id"), F.col("ts").alias("r_ts"), F.col("user_id").alias("r_user")).withWatermark("r_ts", "1 hour")
    b = stream_b.select(F.col("event_id").alias("completion_id"), F.col("ts").alias("c_ts"), F.col("user_id").alias("c_user")).withWatermark("c_ts", "1 hour")
    when = F.expr(f"r_user = c_user and c_ts >= r_ts and c_ts <= r_ts + interval {within}")
    return a.join(b, when).select("request_id", "completion_id", F.col("r_user").alias("user_id"))
