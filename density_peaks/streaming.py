"""Streaming over events: density by cell, labels, sessions, late rows, and batches into an index.

Sources are file streams; every query here runs what is available and ends, and its sink is
Parquet in the shared folder, so that a replay can be compared with a batch.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from density_peaks.iterate import shared_dir

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream; ts becomes a timestamp of the session's zone."""
    raw = spark.readStream.schema(EVENTS).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def replay(stream: DataFrame, mode: str = "append", each: Callable[[DataFrame, int], None] | None = None) -> DataFrame | None:
    """Runs a streaming plan over what is available; its rows come back from a Parquet sink."""
    spark = stream.sparkSession
    base = f"{shared_dir(spark).rstrip('/')}/stream-{uuid.uuid4().hex}"
    out = stream.writeStream.trigger(availableNow=True).option("checkpointLocation", f"{base}/state")
    if each is not None:
        out.outputMode(mode).foreachBatch(each).start().awaitTermination()
        return None
    if mode == "append":
        out.format("parquet").option("path", f"{base}/rows").outputMode("append").start().awaitTermination()
    else:  # results that change are written whole by each batch; the last one counts
        out.outputMode(mode).foreachBatch(lambda df, n: df.write.mode("overwrite").parquet(f"{base}/rows")).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{base}/rows")


def cell_density(stream: DataFrame, hours: float, values: float) -> DataFrame:
    """cell_x, cell_y, n: events by cell of hours since 2024 and value, kept up as events come."""
    x = (F.unix_micros("ts") - F.lit(1704067200000000)) / F.lit(3600000000.0)
    cells = stream.select(F.floor(x / F.lit(float(hours))).alias("cell_x"), F.floor(F.col("value") / F.lit(float(values))).alias("cell_y"))
    return cells.groupBy("cell_x", "cell_y").agg(F.count(F.lit(1)).alias("n"))


def windows(stream: DataFrame, length: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """start, event_type, n, total of tumbling or sliding windows; rows later than the watermark are left out."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    g = stream.withWatermark("ts", late).groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))
    return g.select(F.col("w.start").alias("start"), "event_type", "n", "total")


def sessions(stream: DataFrame, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    """user_id, start, end, n of each user's sessions."""
    g = stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return g.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def distinct_events(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    """Events without repeats of an id within the watermark."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def label(stream: DataFrame, centers: DataFrame) -> DataFrame:
    """event_id, cluster: the nearest center (id, x, y) of each event, the smaller id first. centers are few by choice."""
    x = (F.unix_micros("ts") - F.lit(1704067200000000)) / F.lit(3600000000.0)
    c = centers.agg(F.array_sort(F.collect_list(F.struct("id", "x", "y"))).alias("centers"))
    p = stream.select("event_id", F.round(x, 4).alias("ex"), F.col("value").alias("ey")).join(F.broadcast(c))
    gap = F.transform("centers", lambda k: F.struct(F.sqrt((F.col("ex") - k["x"]) * (F.col("ex") - k["x"]) + (F.col("ey") - k["y"]) * (F.col("ey") - k["y"])).alias("d"), k["id"].alias("id")))
    return p.select("event_id", F.array_min(gap)["id"].alias("cluster"))


def running_cells(stream: DataFrame, hours: float, values: float) -> DataFrame:
    """cell, n, first_event, last_event: stateful density by cell in a custom operator, one row a cell and batch."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    x = (F.unix_micros("ts") - F.lit(1704067200000000)) / F.lit(3600000000.0)
    cells = stream.select(F.concat_ws(":", F.floor(x / F.lit(float(hours))), F.floor(F.col("value") / F.lit(float(values)))).alias("cell"), "event_id")

    def grow(key, frames, state: GroupState):
        n, first, last = state.get if state.exists else (0, None, None)
        for f in frames:
            n += len(f)
            lo, hi = int(f["event_id"].min()), int(f["event_id"].max())
            first, last = lo if first is None else min(first, lo), hi if last is None else max(last, hi)
        state.update((n, first, last))
        yield pd.DataFrame({"cell": [key[0]], "n": [n], "first_event": [first], "last_event": [last]})

    schema = "cell string, n long, first_event long, last_event long"
    return cells.groupBy("cell").applyInPandasWithState(grow, schema, "n long, first_event long, last_event long", "update", GroupStateTimeout.NoTimeout)
