"""Event streams that keep graph inputs fresh; every one has a batch twin.

The tests' source is a table replayed as files; a drained stream returns what it
has written to the shared folder.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import ship, work_path
from ..sources.tables import load

LATE = "10 minutes"


def replay(spark: SparkSession, sf_dir: str, files: int = 4, per_trigger: int = 1) -> DataFrame:
    """Events as a stream of ``files`` files in time order, ``per_trigger`` per micro-batch."""
    path = work_path(spark, "replay")
    ev = load(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    micros = F.unix_micros("ts")
    cuts = ev.agg(F.percentile_approx(micros, [i / files for i in range(1, files)], 1000).alias("c")).first().c
    # the file source reads files by age, so the slices are written one after another
    for lo, hi in zip([None, *cuts], [*cuts, None]):
        part = ev.filter((F.lit(True) if lo is None else micros > lo) & (F.lit(True) if hi is None else micros <= hi))
        part.coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(ev.schema).option("maxFilesPerTrigger", per_trigger).parquet(path)


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over what its source holds now; return its output."""
    spark = stream.sparkSession
    folder = work_path(spark, "stream")
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/state").outputMode(mode)
    else:
        def keep(rows: DataFrame, batch: int) -> None:
            rows.write.mode("overwrite").parquet(f"{folder}/out")

        q = stream.writeStream.foreachBatch(keep).option("checkpointLocation", f"{folder}/state").outputMode(mode)
    q.trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{folder}/out")


def tumbling(events: DataFrame, width: str = "1 hour") -> DataFrame:
    """start, event_type, n, total (hundredths) per window and type."""
    g = events.withWatermark("ts", LATE) if events.isStreaming else events
    out = g.groupBy(F.window("ts", width), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents"))
    return out.select(F.col("window.start").alias("start"), "event_type", "n", "cents")


def sliding(events: DataFrame) -> DataFrame:
    g = events.withWatermark("ts", LATE) if events.isStreaming else events
    return g.groupBy(F.window("ts", "2 hours", "1 hour")).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    g = events.withWatermark("ts", LATE) if events.isStreaming else events
    return g.groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")


def unique_events(events: DataFrame) -> DataFrame:
    """Each event once, even if its row arrives again within the watermark."""
    return events.withWatermark("ts", LATE).dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id")


def with_part(events: DataFrame, parts: DataFrame) -> DataFrame:
    """Stream to static join: events with the part of their user."""
    return events.join(parts.select(F.col("id").alias("user_id"), "part"), "user_id").select("event_id", "user_id", "part")


def click_to_purchase(clicks: DataFrame, buys: DataFrame, within: str = "1 hour") -> DataFrame:
    """Stream to stream join: purchases at most ``within`` after a click of the same user."""
    c = clicks.filter("event_type = 'click'").select(F.col("event_id").alias("click"), "user_id", F.col("ts").alias("at"))
    b = buys.filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("buyer"), F.col("ts").alias("bought"))
    if clicks.isStreaming:
        c, b = c.withWatermark("at", LATE), b.withWatermark("bought", LATE)
    return c.join(b, F.expr(f"user_id = buyer AND bought > at AND bought <= at + INTERVAL {within}")).select("click", "purchase")


def user_counts(events: DataFrame) -> DataFrame:
    """Custom state per user: events seen and the time of the last, updated by every batch."""
    ship(events.sparkSession)

    def update(key, frames, state):
        n, last = state.get if state.exists else (0, 0)
        for f in frames:
            n += len(f)
            last = max(last, int(f["micros"].max()))
        state.update((n, last))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "last_micros": [last]})

    slim = events.select("user_id", F.unix_micros("ts").alias("micros"))
    return slim.groupBy("user_id").applyInPandasWithState(update, "user_id long, n long, last_micros long", "n long, last_micros long", "update", "NoTimeout")


def final_user_counts(stream: DataFrame) -> DataFrame:
    """The last state of every user after the stream is drained."""
    spark = stream.sparkSession
    folder = work_path(spark, "user-state")

    def keep(rows: DataFrame, batch: int) -> None:
        rows.write.mode("overwrite").parquet(f"{folder}/out/batch={batch}")

    user_counts(stream).writeStream.foreachBatch(keep).option("checkpointLocation", f"{folder}/state").outputMode("update").trigger(availableNow=True).start().awaitTermination()
    rows = spark.read.parquet(f"{folder}/out")
    return rows.groupBy("user_id").agg(F.max_by("n", "batch").alias("n"), F.max("last_micros").alias("last_micros"))


def refresh_sums(edges: DataFrame, old: DataFrame, changed: DataFrame) -> DataFrame:
    """(dst, k, s): neighbour sums after features change by ``changed`` (id, k, dx): only their out-edges are read.

    ``old`` holds the sums before; sums are linear, so a one-hop delta is exact.
    """
    delta = edges.join(changed, edges["src"] == changed["id"]).groupBy("dst", "k").agg(F.sum("dx").alias("dx"))
    return old.join(delta, ["dst", "k"], "full").select("dst", "k", (F.coalesce("s", F.lit(0)) + F.coalesce("dx", F.lit(0))).alias("s"))
