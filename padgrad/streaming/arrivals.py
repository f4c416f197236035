"""Answers of devices as a stream of arrivals.

An event is an answer: its device is ``user_id mod 25``, its epoch the tumbling window of
its time. The server takes the first D - alpha + 1 distinct devices of an epoch;
everything later is a straggler. State is one row for each device of an open epoch.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from padgrad.shared import fresh_path

EVENTS = "event_id BIGINT, ts TIMESTAMP_NTZ, user_id BIGINT, event_type STRING, value DOUBLE, props STRING"
OUT = "epoch timestamp, device int, first_ts timestamp, place int"
STATE = "devices array<int>, times array<timestamp>, ids array<bigint>"


def answers(events: DataFrame, devices: int = 25, window: str = "1 day") -> DataFrame:
    """``(event_id, ts, device, epoch)``; watermarks need a zoned timestamp."""
    ts = F.col("ts").cast("timestamp")
    return events.select("event_id", ts.alias("ts"), F.pmod("user_id", F.lit(devices)).cast("int").alias("device"), F.window(ts, window).getField("start").alias("epoch"))


def epoch_counts(events: DataFrame, devices: int = 25, window: str = "1 day", lateness: str = "1 hour") -> DataFrame:
    """``(epoch, device, n)``: answers in each epoch."""
    rows = events.select(F.col("ts").cast("timestamp").alias("ts"), F.pmod("user_id", F.lit(devices)).cast("int").alias("device"))
    rows = rows.withWatermark("ts", lateness) if rows.isStreaming else rows
    out = rows.groupBy(F.window("ts", window), "device").agg(F.count("*").alias("n"))
    return out.select(F.col("window.start").alias("epoch"), "device", "n")


def first_answers(events: DataFrame, keep: int, devices: int = 25, window: str = "1 day", lateness: str = "1 hour") -> DataFrame:
    """``OUT`` of a stream: the ``keep`` first distinct devices of each epoch, in order of time, once the epoch is closed by the watermark; none if too few answered."""
    rows = answers(events, devices, window).withWatermark("ts", lateness)

    def update(key, frames, state):
        import pandas as pd

        best = {d: (t, i) for d, t, i in zip(*state.get, strict=True)} if state.exists else {}
        if state.hasTimedOut:
            order = sorted((t, i, d) for d, (t, i) in best.items())
            state.remove()
            if len(order) >= keep:
                yield pd.DataFrame([(key[0], d, t, p) for p, (t, _, d) in enumerate(order[:keep], 1)], columns=["epoch", "device", "first_ts", "place"])
            return
        for frame in frames:
            for d, t, i in zip(frame["device"], frame["ts"], frame["event_id"], strict=True):
                d, i = int(d), int(i)
                if d not in best or (t, i) < best[d]:
                    best[d] = (t, i)
        state.update(([*best], [best[d][0] for d in best], [best[d][1] for d in best]))
        end = pd.Timestamp(key[0]) + pd.Timedelta(window)
        state.setTimeoutTimestamp(max(int(end.timestamp() * 1000), state.getCurrentWatermarkMs() + 1))

    return rows.groupBy("epoch").applyInPandasWithState(update, OUT, STATE, "append", "EventTimeTimeout")


def first_answers_batch(events: DataFrame, keep: int, devices: int = 25, window: str = "1 day") -> DataFrame:
    """The same over a table, for checks and backfills."""
    from pyspark.sql import Window

    best = answers(events, devices, window).groupBy("epoch", "device").agg(F.min(F.struct("ts", "event_id")).alias("f"))
    order = Window.partitionBy("epoch").orderBy("f", "device")
    out = best.withColumn("place", F.row_number().over(order)).withColumn("got", F.count("*").over(Window.partitionBy("epoch")))
    return out.where((F.col("place") <= keep) & (F.col("got") >= keep)).select("epoch", "device", F.col("f.ts").alias("first_ts"), "place")


def late_devices(events: DataFrame, chosen: DataFrame, devices: int = 25, window: str = "1 day") -> DataFrame:
    """``(epoch, device)`` that answered in a decodable epoch but after the set was full."""
    seen = answers(events, devices, window).select("epoch", "device").distinct()
    return seen.join(chosen.select("epoch").distinct(), "epoch", "left_semi").join(chosen.select("epoch", "device"), ["epoch", "device"], "left_anti")


def run_available(stream: DataFrame, path: str | None = None) -> DataFrame:
    """Runs a stream over what is there into Parquet files of the shared folder; the result is read from them. With the ``path`` of an earlier run it goes on where that ended."""
    spark = stream.sparkSession
    path = path or fresh_path(spark, "arrivals")
    q = stream.writeStream.format("parquet").outputMode("append").option("path", f"{path}/rows").option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/rows")


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a file stream."""
    return spark.readStream.schema(EVENTS).option("pathGlobFilter", "events*.parquet").parquet(sf_dir)


def sliding_counts(events: DataFrame, window: str = "2 days", slide: str = "1 day", lateness: str = "1 hour") -> DataFrame:
    """``(start, n, devices)`` of overlapping windows."""
    rows = events.select(F.col("ts").cast("timestamp").alias("ts"), F.pmod("user_id", F.lit(25)).cast("int").alias("device"))
    rows = rows.withWatermark("ts", lateness) if rows.isStreaming else rows
    out = rows.groupBy(F.window("ts", window, slide)).agg(F.count("*").alias("n"), F.approx_count_distinct("device").alias("devices"))
    return out.select(F.col("window.start").alias("start"), "n", "devices")


def sessions(events: DataFrame, gap: str = "1 hour", devices: int = 25, lateness: str = "1 hour") -> DataFrame:
    """``(device, first_ts, n)``: runs of answers of a device without a pause of ``gap``."""
    rows = events.select(F.col("ts").cast("timestamp").alias("ts"), F.pmod("user_id", F.lit(devices)).cast("int").alias("device"))
    rows = rows.withWatermark("ts", lateness) if rows.isStreaming else rows
    out = rows.groupBy(F.session_window("ts", gap), "device").agg(F.count("*").alias("n"))
    return out.select("device", F.col("session_window.start").alias("first_ts"), "n")


def once(events: DataFrame, lateness: str = "1 hour") -> DataFrame:
    """A stream of answers without those sent again within the watermark."""
    rows = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", lateness)
    return rows.dropDuplicatesWithinWatermark(["event_id"])


def run_with_late_copies(spark: SparkSession, events: DataFrame, operator, delay: str = "2 days") -> DataFrame:
    """``operator`` on a stream of ``events`` that stops, finds answers sent again ``delay`` or more behind the last one, and goes on: the watermark drops those."""
    source, out = fresh_path(spark, "late-events"), fresh_path(spark, "arrivals")

    def stream():
        return operator(spark.readStream.schema(events.schema).parquet(source))

    events.write.parquet(source)
    run_available(stream(), out)
    last = F.broadcast(events.agg(F.max("ts").alias("last")))  # one row
    late = events.join(last, F.col("ts") < F.col("last") - F.expr(f"INTERVAL {delay}")).drop("last")
    late.withColumn("event_id", F.col("event_id") + 10**9).write.mode("append").parquet(source)
    return run_available(stream(), out)
