"""Incremental footprints over the event stream. Every transformation also runs on a static frame: its batch twin."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.types import StructType

EVENT = "event_id bigint, user_id bigint, ts timestamp_ntz, event_type string, props string"


def source(spark: SparkSession, path: str, schema: str | StructType, files_per_batch: int = 1) -> DataFrame:
    """A file stream; event time becomes a zoned timestamp, which watermarks need."""
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)
    return zoned(raw)


def zoned(events: DataFrame) -> DataFrame:
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def deduplicated(events: DataFrame, delay: str = "1 day") -> DataFrame:
    """Events once per id; a stream keeps ids only inside the watermark."""
    if events.isStreaming:
        return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])
    return events.dropDuplicates(["event_id"])


def windowed_counts(events: DataFrame, length: str = "1 day", slide: str | None = None, delay: str = "1 day") -> DataFrame:
    """(event_type, start, n) per tumbling or sliding window."""
    timed = events.withWatermark("ts", delay) if events.isStreaming else events
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return timed.groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select("event_type", F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes", delay: str = "1 day") -> DataFrame:
    """(user_id, start, n): runs of a user's events with gaps below `gap`."""
    timed = events.withWatermark("ts", delay) if events.isStreaming else events
    s = timed.groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count(F.lit(1)).alias("n"))
    return s.select("user_id", F.col("s.start").cast("timestamp_ntz").alias("start"), "n")


def by_place(events: DataFrame, authors: DataFrame) -> DataFrame:
    """Events joined with the static author sets: each event counts for every name its user wrote."""
    return events.join(authors.select("user_id", "place_name"), "user_id").select("event_id", "user_id", "ts", "event_type", "place_name")


def view_before_purchase(events: DataFrame, within: str = "1 hour", delay: str = "1 day") -> DataFrame:
    """Stream-stream interval join: views at most `within` before a purchase of the same user."""
    timed = events.withWatermark("ts", delay) if events.isStreaming else events
    v = timed.where("event_type = 'view'").select(F.col("user_id").alias("vu"), F.col("ts").alias("vt"), F.col("event_id").alias("view_id"))
    p = timed.where("event_type = 'purchase'").select(F.col("user_id").alias("pu"), F.col("ts").alias("pt"), F.col("event_id").alias("purchase_id"))
    return v.join(p, F.expr(f"vu = pu AND vt <= pt AND vt >= pt - INTERVAL {within}")).select("view_id", "purchase_id")


SUMS = "place_name string, slot int, since bigint, n bigint, lat_sum bigint, lon_sum bigint"


def running_sums(pings: DataFrame, delay: str = "1 day", expiry_ms: int = 30 * 86_400_000, slots: int = 16) -> DataFrame:
    """(place_name, slot, since, n, lat_sum, lon_sum) so far, from pings (event_id, place_name, ts, lat_u, lon_u).

    A stream updates keyed state and forgets a key `expiry_ms` of event time after its last ping. A name's pings are dealt over
    `slots` keys, so a name that many people write isn't the work of one task. A key that comes back after it was forgotten starts
    at zero under a later `since` (the watermark at its start); `latest_sums` adds slots and lives up again.
    """
    keyed = pings.withColumn("slot", F.pmod("event_id", F.lit(slots)).cast("int"))
    if not pings.isStreaming:
        sums = [F.count(F.lit(1)).alias("n"), F.sum("lat_u").alias("lat_sum"), F.sum("lon_u").alias("lon_sum")]
        return keyed.groupBy("place_name", "slot").agg(*sums).withColumn("since", F.lit(0).cast("bigint"))

    def update(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        since, n, lat, lon, last = state.get if state.exists else (state.getCurrentWatermarkMs(), 0, 0, 0, 0)
        for f in frames:
            n, lat, lon = n + len(f), lat + int(f["lat_u"].sum()), lon + int(f["lon_u"].sum())
            last = max(last, int(f["ms"].max()))
        state.update((since, n, lat, lon, last))
        state.setTimeoutTimestamp(max(last, state.getCurrentWatermarkMs()) + expiry_ms)
        yield pd.DataFrame({"place_name": [key[0]], "slot": [key[1]], "since": [since], "n": [n], "lat_sum": [lat], "lon_sum": [lon]})

    timed = keyed.withWatermark("ts", delay).withColumn("ms", F.unix_millis("ts")).groupBy("place_name", "slot")
    return timed.applyInPandasWithState(update, SUMS, "since bigint, n bigint, lat bigint, lon bigint, last bigint", "update", GroupStateTimeout.EventTimeTimeout)


def latest_sums(updates: DataFrame) -> DataFrame:
    """(place_name, n, lat_sum, lon_sum) from the rows that `running_sums` has put out; the fullest row of a life is its last."""
    last = updates.groupBy("place_name", "slot", "since").agg(F.max(F.struct("n", "lat_sum", "lon_sum")).alias("s"))
    return last.groupBy("place_name").agg(*[F.sum(f"s.{c}").alias(c) for c in ("n", "lat_sum", "lon_sum")])


def late_counts(events: DataFrame, batch: str, delay: str = "1 day") -> DataFrame:
    """(batch, n, late) for arrivals marked with a batch number: rows more than `delay` behind the newest row of earlier batches."""
    newest = events.groupBy(F.col(batch).alias("later")).agg(F.max("ts").alias("top"))
    marks = events.select(batch).distinct().join(F.broadcast(newest), F.expr(f"later < {batch}"), "left")
    marks = marks.groupBy(batch).agg((F.max("top") - F.expr(f"INTERVAL {delay}")).alias("mark"))
    late = F.count(F.when(F.col("ts") < F.col("mark"), 1))
    return events.join(F.broadcast(marks), batch).groupBy(batch).agg(F.count(F.lit(1)).alias("n"), late.alias("late"))


def late_rows(progress: list) -> int:
    """Rows that a running query's stateful operators have dropped behind the watermark, from its progress reports."""
    return sum(op["numRowsDroppedByWatermark"] for p in progress for op in p["stateOperators"])


def upsert_sums(target: str) -> Callable[[DataFrame, int], None]:
    """foreachBatch sink: partial sums of a batch under its id, so a replayed batch replaces itself."""

    def write(batch: DataFrame, batch_id: int) -> None:
        sums = batch.groupBy("place_name").agg(F.count(F.lit(1)).alias("n"))
        sums.write.mode("overwrite").parquet(f"{target}/batch={batch_id}")

    return write


def read_sums(spark: SparkSession, target: str) -> DataFrame:
    return spark.read.parquet(target).groupBy("place_name").agg(F.sum("n").alias("n"))


def start(df: DataFrame, name: str, checkpoint: str, mode: str = "append"):
    """Runs all available data into an in-memory table (tests)."""
    return df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
