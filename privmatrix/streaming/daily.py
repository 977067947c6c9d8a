"""Matrices over event streams: windows, sessions, release of closed windows, budgets over windows."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from privmatrix.sources.spec import MatrixSpec
from privmatrix.sources.store import shared_folder
from privmatrix.sources.tables import SCHEMAS, event_stream

LATENESS = "1 hour"
EVENT_COLUMNS = SCHEMAS["events"]


def _placed(events: DataFrame, spec: MatrixSpec) -> DataFrame:
    kept = events.select("ts", "event_id", "user_id", *[dim.index().alias(x) for dim, x in zip(spec.dims, spec.axes)])
    return kept.where(" AND ".join(f"{x} IS NOT NULL" for x in spec.axes))


def window_cells(events: DataFrame, spec: MatrixSpec, length: str = "1 day", slide: str | None = None, lateness: str = LATENESS) -> DataFrame:
    """start, x1..xd, f per window. Sliding windows share records: a record is in length / slide of them, which is then the sensitivity."""
    window = F.window("ts", length, slide) if slide else F.window("ts", length)
    counts = _placed(events.withWatermark("ts", lateness), spec).groupBy(window.alias("w"), *spec.axes).agg(F.count("*").alias("f"))
    return counts.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *spec.axes, "f")


def window_sensitivity(length_seconds: int, slide_seconds: int) -> int:
    return -(-length_seconds // slide_seconds)


def sessions(events: DataFrame, gap: str = "2 hours", lateness: str = LATENESS) -> DataFrame:
    """user_id, start, end, n: trajectories that end with a pause of ``gap``."""
    found = events.withWatermark("ts", lateness).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return found.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def without_repeats(events: DataFrame, lateness: str = LATENESS) -> DataFrame:
    """Each event id once within the watermark; state is dropped as the watermark passes."""
    return events.withWatermark("ts", lateness).dropDuplicatesWithinWatermark(["event_id"])


def with_home(events: DataFrame, homes: DataFrame) -> DataFrame:
    """Events joined with a static table by user."""
    return events.join(homes, "user_id", "left")


def legs(origins: DataFrame, destinations: DataFrame, within: str = "1 hour", lateness: str = LATENESS) -> DataFrame:
    """Pairs of an origin event and a later destination event of the same user within an interval; both sides' state is bounded by it."""
    a = origins.withWatermark("ts", lateness).select(F.col("user_id").alias("a_user"), F.col("ts").alias("a_ts"), F.col("value").alias("a_value"))
    b = destinations.withWatermark("ts", lateness).select(F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts"), F.col("value").alias("b_value"))
    return a.join(b, F.expr(f"a_user = b_user AND b_ts > a_ts AND b_ts <= a_ts + interval {within}"))


def run_to_end(stream: DataFrame, what: str, mode: str = "append") -> DataFrame:
    """Runs over all data at hand into Parquet in the shared folder and returns what was emitted. In append mode these are the
    windows that the watermark has closed; later data for them is dropped, and the progress reports count it."""
    spark = stream.sparkSession
    base = f"{shared_folder(spark)}/{what}-{uuid.uuid4().hex}"
    query = stream.writeStream.format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/state").outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{base}/out")


def daily_cells(spark: SparkSession, path: str, spec: MatrixSpec) -> DataFrame:
    """Closed days' cells of an event stream read from Parquet files."""
    return run_to_end(window_cells(event_stream(spark, path), spec), "daily-cells")


def release_closed(stream: DataFrame, release: Callable[[DataFrame, str], DataFrame], path: str, checkpoint: str):
    """Publishes every closed window once. ``release`` gets the window's cells and its start as text, which it uses as part of its salt:
    a batch that is run again after a failure then draws the same noise and overwrites its own output with equal values."""

    def publish(batch: DataFrame, number: int) -> None:
        batch = batch.persist()
        for row in batch.select("start").distinct().orderBy("start").collect():  # windows closed by one batch: a few
            one = batch.where(F.col("start") == F.lit(row[0])).drop("start", "end")
            label = row[0].isoformat()
            release(one, label).write.mode("overwrite").parquet(f"{path}/window={label.replace(':', '-')}")
        batch.unpersist()

    return stream.writeStream.outputMode("append").option("checkpointLocation", checkpoint).foreachBatch(publish).trigger(availableNow=True).start()


def odometer(memberships: DataFrame, eps: float) -> DataFrame:
    """unit, eps: budget of a unit over all windows that hold one of its records (unit, window). Disjoint windows of one record each cost
    eps once; a unit in several windows pays for each."""
    return memberships.distinct().groupBy("unit").agg((F.count("*") * eps).alias("eps"))
