"""Streams end in the state that the batch fold of the same edges has."""

import uuid
from datetime import datetime, timedelta

import pytest
from pyspark.sql import functions as F

from edgefold.plans import program as P
from edgefold.sources import features
from edgefold.streaming import folds

START = datetime(2024, 1, 1)


@pytest.fixture
def files(spark, tmp_path):
    """Three files; the last holds one row that is very late and one that repeats an event."""
    rows = [(i, START + timedelta(minutes=7 * i), i % 3, ("click", "view", "purchase")[i % 3 if i % 2 else 1], float(i), "{}") for i in range(60)]
    parts = [rows[:30], rows[30:58], [*rows[58:], rows[57], (99, START - timedelta(days=2), 0, "click", 1.0, "{}")]]
    for k, part in enumerate(parts):
        df = spark.createDataFrame(part, "event_id long, ts timestamp, user_id long, event_type string, value double, props string")
        df.withColumn("ts", F.col("ts").cast("timestamp_ntz")).coalesce(1).write.mode("append").parquet(str(tmp_path / "in" / str(k)))
    return str(tmp_path / "in" / "*")


def name():
    return f"t{uuid.uuid4().hex}"


def rows(df):
    return {r["u"]: [round(v, 9) for v in r["z"]] for r in df.collect()}


def test_running_fold_and_distinct_edges(spark, files):
    y = features.hashed(spark.range(1, 6).select("id"), 4)
    batch = folds.as_edges(spark.read.schema(folds.EVENTS).parquet(files).withColumn("ts", F.col("ts").cast("timestamp")))
    got = folds.drain(folds.streaming_fold(folds.as_edges(folds.events(spark, files)), None, y, P.graph_conv("sum"), 4), name())
    assert rows(got) == rows(folds.streaming_fold(batch, None, y, P.graph_conv("sum"), 4))
    once = folds.drain(folds.distinct_edges(folds.as_edges(folds.events(spark, files)), "10 days"), name(), "append")
    assert once.count() == 61 and once.select("event_id").distinct().count() == 61


def test_windows_and_lateness(spark, files):
    y = features.hashed(spark.range(1, 6).select("id"), 4)
    for options in ({"size": "1 hour"}, {"size": "2 hours", "slide": "1 hour"}, {"size": "1 hour", "gap": "30 minutes"}):
        edges = folds.with_lateness(folds.as_edges(folds.events(spark, files)), "1 hour")
        got = folds.drain(folds.windowed_fold(edges, y, P.graph_conv("sum"), 4, **options), name(), "append")
        assert got.count() > 0
        batch = folds.as_edges(spark.read.schema(folds.EVENTS).parquet(files).withColumn("ts", F.col("ts").cast("timestamp")))
        whole = {(r["u"], r["start"], r["end"]) for r in folds.windowed_fold(batch, y, P.graph_conv("sum"), 4, **options).collect()}
        assert {(r["u"], r["start"], r["end"]) for r in got.collect()} <= whole


def test_joined_streams(spark, files):
    one, other = (folds.events(spark, files).where(f"event_type = '{t}'") for t in ("click", "view"))
    got = folds.drain(folds.joined_edges(one, other, "10 days", 600), name(), "append")
    e = spark.read.schema(folds.EVENTS).parquet(files)
    p, q = e.where("event_type = 'click'"), e.where("event_type = 'view'").select(F.col("user_id").alias("v"), F.col("ts").alias("t2"))
    want = p.join(q, (F.abs(F.unix_timestamp(p["ts"].cast("timestamp")) - F.unix_timestamp(F.col("t2").cast("timestamp"))) <= 600) & (p["user_id"] != F.col("v"))).count()
    assert got.count() == want


def test_refresh_writes_a_version_for_each_batch(spark, files, tmp_path):
    stream = folds.as_edges(folds.events(spark, files))
    folds.refresh(stream, str(tmp_path / "out"), lambda b, k: b.groupBy("u").agg(F.count("*").alias("n")), str(tmp_path / "log")).awaitTermination()
    out = spark.read.parquet(str(tmp_path / "out"))
    assert out.agg(F.sum("n")).first()[0] == 62 and out.select("version").distinct().count() >= 1
