"""Streams against their batch twins, late rows, restarts and order."""

import pandas as pd
from pyspark.sql import functions as F

from kgrefine import workloads
from kgrefine.streaming.ordered import ordered_emitter, ordered_sink


def test_late_rows_are_dropped(spark, small):
    events = spark.read.parquet(f"{small}/events.parquet").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    out = workloads.queries()["stream_late_data"](spark, small)
    last = out.agg(F.max("w_start")).first()[0]
    closed = events.where(F.date_format(F.date_trunc("hour", "ts"), "yyyy-MM-dd HH:mm") <= last)
    kept, on_time = out.agg(F.sum("n")).first()[0], closed.where("event_id % 10 <> 0").count()
    assert on_time <= kept <= on_time + 5 < closed.count()


def test_release_is_in_order_for_each_channel(spark, small):
    rows = workloads.queries()["stream_stateful"](spark, small)
    n = rows.groupBy("channel").agg(F.count("*").alias("n"), F.max("seq").alias("m"), F.count_distinct("seq").alias("d")).collect()
    assert n and all(r["n"] == r["m"] + 1 == r["d"] for r in n)


def test_restart_goes_on_from_the_checkpoint(spark, tmp_path):
    base = f"file://{tmp_path}"
    kind = "channel string, seq long, payload string"

    def run(rows, part):
        spark.createDataFrame(rows, kind).coalesce(1).write.parquet(f"{base}/in/{part}")
        src = spark.readStream.schema(kind).option("recursiveFileLookup", True).parquet(f"{base}/in")
        ordered_sink(src).writeStream.format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start().awaitTermination()
        return sorted((r["seq"], r["payload"]) for r in spark.read.schema(kind).parquet(f"{base}/out").collect())

    assert run([("c", 0, "a"), ("c", 2, "c")], "one") == [(0, "a")]
    assert run([("c", 1, "b"), ("c", 4, "e")], "two") == [(0, "a"), (1, "b"), (2, "c")]


class State:
    exists = False

    def update(self, value):
        self.get, self.exists = value, True


def test_gap_policy():
    step, state = ordered_emitter(0, gap_after=1), State()
    got = [tuple(r) for pdf in step(("c",), iter([pd.DataFrame({"seq": [1, 2], "payload": ["b", "c"]})]), state) for r in pdf.itertuples(index=False)]
    assert got == [("c", 1, "b"), ("c", 2, "c")]
