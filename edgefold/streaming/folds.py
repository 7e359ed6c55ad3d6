"""Folds over edges that arrive as a stream, with windows, lateness, keyed state, joins and feature refreshes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, StructField, StructType

from edgefold.functions import steps as S
from edgefold.operators.fused import _reduction, _start, _wide_message
from edgefold.operators.two_phase import _shared
from edgefold.plans.program import Program, check

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def events(spark: SparkSession, path: str, schema: str = EVENTS) -> DataFrame:
    """A file source; event time becomes a timestamp, which watermarks ask for (session zone UTC)."""
    return spark.readStream.schema(schema).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def rate(spark: SparkSession, rows_per_second: int = 10) -> DataFrame:
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()


def as_edges(stream: DataFrame) -> DataFrame:
    """user <- type: v numbers the event types by their order in the alphabet of the given five."""
    kinds = F.array(*[F.lit(t) for t in ("click", "error", "purchase", "signup", "view")])
    return stream.select("ts", "event_id", F.col("user_id").alias("u"), F.array_position(kinds, F.col("event_type")).alias("v"), F.lit(1.0).alias("a"))


def _messages(edges: DataFrame, x, y: DataFrame, program: Program, d: int):
    check(program)
    both = edges.join(y.select(F.col("id").alias("v"), F.col("x").alias("y")), "v")
    if "x" in program.reads:
        both = both.join(x.select(F.col("id").alias("u"), "x"), "u")
    xs = [F.col("x").getItem(i) for i in range(d)] if "x" in program.reads else [F.lit(0.0)] * d
    h, operand, _ = _wide_message(program, xs, [F.col("y").getItem(i) for i in range(d)], F.col("a"))
    return both, [program.weigh.element(S.ColumnOps, hi, oi) for hi, oi in zip(h, operand, strict=True)]


def _reduced(grouped, w, program, *keys):
    reduce = _reduction(program)
    z = grouped.agg(*[reduce(wi).alias(f"z{i}") for i, wi in enumerate(w)])
    return z.select(*keys, F.array(*[_start(program, F.col(f"z{i}")) for i in range(len(w))]).alias("z"))


def streaming_fold(edges: DataFrame, x: DataFrame | None, y: DataFrame, program: Program, d: int) -> DataFrame:
    """The running fold of all edges so far; features are static. For update or complete output. Works on batches too."""
    both, w = _messages(edges, x, y, program, d)
    return _reduced(both.groupBy("u"), w, program, "u")


def with_lateness(stream: DataFrame, delay: str) -> DataFrame:
    return stream.withWatermark("ts", delay)


def windowed_fold(edges: DataFrame, y: DataFrame, program: Program, d: int, size: str, slide: str | None = None, gap: str | None = None, x: DataFrame | None = None) -> DataFrame:
    """Folds of tumbling or sliding windows, or of sessions that end after a gap: (u, start, end, z)."""
    both, w = _messages(edges, x, y, program, d)
    window = F.session_window("ts", gap) if gap else F.window("ts", size, slide) if slide else F.window("ts", size)
    return _reduced(both.groupBy("u", window.alias("w")), w, program, "u", F.col("w.start").alias("start"), F.col("w.end").alias("end"))


def distinct_edges(stream: DataFrame, delay: str) -> DataFrame:
    """Edges that repeat an event id within the delay count once; state older than that goes."""
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def stateful_fold(edges: DataFrame, y: DataFrame, d: int, ttl_ms: int) -> DataFrame:
    """(u, n, z): each vertex's running sum of neighbour features as keyed state of its own, dropped after an event time
    without edges. The stream has a watermark on ts; processing-time timeouts would keep a bounded run from ending."""
    import numpy as np
    import pandas as pd

    both = edges.join(y.select(F.col("id").alias("v"), F.col("x").alias("y")), "v").select("u", "y", "ts")

    def update(key, frames, state):
        if state.hasTimedOut:
            state.remove()
            return
        n, z = state.get if state.exists else (0, [0.0] * d)
        total, latest = np.asarray(z), state.getCurrentWatermarkMs()
        for f in frames:
            n += len(f)
            latest = max(latest, int(f["ts"].max().timestamp() * 1000))
            total = total + np.stack(f["y"].to_numpy()).sum(axis=0)
        state.update((n, total.tolist()))
        state.setTimeoutTimestamp(latest + ttl_ms)
        yield pd.DataFrame({"u": [key[0]], "n": [n], "z": [total.tolist()]})

    return both.groupBy("u").applyInPandasWithState(update, "u long, n long, z array<double>", "n long, z array<double>", "update", "EventTimeTimeout")


def joined_edges(one: DataFrame, other: DataFrame, delay: str, seconds: int) -> DataFrame:
    """(u, v, t1, t2): users of two streams' events at most `seconds` apart. Both have watermarks, so state is bounded.

    Streams join by equality: events meet in buckets of time, those of one side in the neighbouring buckets as well.
    """
    bucket = F.floor(F.unix_timestamp("ts") / seconds)
    p = one.withWatermark("ts", delay).select(F.col("user_id").alias("u"), F.col("ts").alias("t1"), bucket.alias("bucket"))
    q = other.withWatermark("ts", delay).select(F.col("user_id").alias("v"), F.col("ts").alias("t2"), F.explode(F.array(bucket - 1, bucket, bucket + 1)).alias("near"))
    near = (F.col("t1") >= F.col("t2") - F.make_dt_interval(F.lit(0), F.lit(0), F.lit(0), F.lit(seconds))) & (F.col("t1") <= F.col("t2") + F.make_dt_interval(F.lit(0), F.lit(0), F.lit(0), F.lit(seconds)))
    return p.join(q, (F.col("bucket") == F.col("near")) & near & (F.col("u") != F.col("v"))).drop("bucket", "near")


def refresh(stream: DataFrame, path: str, step, checkpoint: str):
    """Each micro-batch makes a new version of the features: step(batch, version) gives a frame, written under its number."""

    def run(batch: DataFrame, version: int) -> None:
        step(batch, version).write.mode("overwrite").parquet(f"{path}/version={version}")

    return stream.writeStream.foreachBatch(run).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def drain(stream: DataFrame, name: str, mode: str = "complete", checkpoint: str | None = None) -> DataFrame:
    """Run over what is there now into files of the shared checkpoint folder, and read these.

    Of complete output the last version counts; of update and append output every row that came.
    """
    spark = stream.sparkSession
    path = f"{_shared(spark)}/streams/{name}"

    def run(batch: DataFrame, version: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/version={version}")

    # an empty version first, so that a stream without a batch gives no rows rather than no files
    spark.createDataFrame([], stream.schema).write.mode("overwrite").parquet(f"{path}/version=-1")
    writer = stream.writeStream.foreachBatch(run).outputMode(mode).trigger(availableNow=True)
    writer.option("checkpointLocation", checkpoint or f"{path}-log").start().awaitTermination()
    out = spark.read.schema(StructType([*stream.schema.fields, StructField("version", IntegerType())])).parquet(path)
    if mode == "complete":
        last = out.agg(F.max("version")).first()[0]
        out = spark.read.schema(stream.schema).parquet(f"{path}/version={-1 if last is None else last}")
    return out.select(*stream.columns)
