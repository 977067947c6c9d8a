"""Event streams: windows, sessions, repeats, joins, release of closed windows."""

import pytest
from pyspark.sql import functions as F

from privmatrix.operators import grids
from privmatrix.plans import catalogue, matrices
from privmatrix.sources import tables
from privmatrix.streaming import daily


@pytest.fixture()
def source(spark, small, tmp_path):
    path = str(tmp_path / "events")
    tables.load(spark, small, "events").orderBy("ts").coalesce(1).write.parquet(path)
    return path


def test_closed_days_equal_batch(spark, small, source):
    got = daily.daily_cells(spark, source, catalogue.STREAM)
    assert got.agg(F.sum("f")).first()[0] > 0
    days = got.select(F.to_date("start").alias("day")).distinct().count()
    batch = tables.load(spark, small, "events").select(F.to_date("ts").alias("day")).distinct().count()
    assert batch - 2 <= days < batch


def test_sliding_windows_hold_records_several_times(spark, source):
    stream = tables.event_stream(spark, source)
    once = daily.run_to_end(daily.window_cells(stream, catalogue.STREAM, "1 day"), "w").agg(F.sum("f")).first()[0]
    four = daily.run_to_end(daily.window_cells(tables.event_stream(spark, source), catalogue.STREAM, "1 day", "6 hours"), "w").agg(F.sum("f")).first()[0]
    assert daily.window_sensitivity(86400, 21600) == 4 and 3.5 * once < four < 4.2 * once


def test_sessions_and_repeats(spark, source):
    assert daily.run_to_end(daily.sessions(tables.event_stream(spark, source)), "s").agg(F.sum("n")).first()[0] > 0
    doubled = tables.event_stream(spark, source)
    doubled = doubled.unionByName(tables.event_stream(spark, source))
    n = daily.run_to_end(daily.without_repeats(doubled).select("event_id"), "d")
    assert n.count() == n.distinct().count() == spark.read.parquet(source).count()


def test_stream_joins(spark, source):
    homes = spark.read.parquet(source).select("user_id").distinct().withColumn("home", F.lit(1))
    assert daily.run_to_end(daily.with_home(tables.event_stream(spark, source), homes).select("event_id", "home"), "h").where("home IS NULL").count() == 0
    a, b = tables.event_stream(spark, source), tables.event_stream(spark, source)
    pairs = daily.run_to_end(daily.legs(a, b), "l")
    assert pairs.where("b_ts <= a_ts OR a_user <> b_user").count() == 0 and pairs.count() > 0


def test_release_of_closed_windows_is_repeatable(spark, source, tmp_path):
    spec = catalogue.STREAM
    make = lambda one, label: grids.entropy_grid(one, spec, 0.5, salt="42" + label)
    for k in range(2):
        daily.release_closed(daily.window_cells(tables.event_stream(spark, source), spec), make, str(tmp_path / f"out{k}"), str(tmp_path / f"state{k}")).awaitTermination()
    a, b = (spark.read.parquet(str(tmp_path / f"out{k}")) for k in range(2))
    assert a.count() > 0 and a.exceptAll(b).count() == 0


def test_odometer(spark):
    rows = spark.createDataFrame([("u", 1), ("u", 2), ("u", 2), ("w", 1)], "unit string, window int")
    assert {r[0]: r[1] for r in daily.odometer(rows, 0.1).collect()} == {"u": pytest.approx(0.2), "w": pytest.approx(0.1)}
    assert matrices.SPECS["price2"].d == 2
