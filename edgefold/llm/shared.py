"""What the operators of this subpackage share: null-safe columns, checkpoints and the workers' import path."""

from __future__ import annotations

import tempfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"
#: Rows handed to a Python worker at a time.
BATCH_ROWS = 1_000
ROOT = str(Path(__file__).resolve().parents[2])


def prepare(spark: SparkSession) -> None:
    """Let Python workers import this package and make sure that checkpoints have a place.

    The folder is the one that the cluster names in spark.checkpoint.dir; on a single machine (tests) that names none, a
    temporary one is taken.
    """
    context = spark.sparkContext
    known = context.environment.get("PYTHONPATH", "")
    if ROOT not in known.split(":"):
        context.environment["PYTHONPATH"] = f"{ROOT}:{known}".rstrip(":")
    if int(spark.conf.get(_BATCH)) > BATCH_ROWS:  # whole texts are long: fewer of them at a time bound a worker's memory
        spark.conf.set(_BATCH, BATCH_ROWS)
    if not context.getCheckpointDir():
        named = context.getConf().get("spark.checkpoint.dir", "")
        if not named and not context.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        context.setCheckpointDir(named or tempfile.mkdtemp(prefix="edgefold-checkpoints-"))


def settle(df: DataFrame) -> DataFrame:
    """Materialise in the shared checkpoint folder, so that a lost executor costs nothing upstream."""
    prepare(df.sparkSession)
    return df.checkpoint(eager=True)


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """The named columns of a table; others, whatever their names, are left out."""
    prepare(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet").select(*columns)


def long_id(df: DataFrame, column: str) -> DataFrame:
    return df.withColumn(column, F.col(column).cast("long"))


def numbered(rows: DataFrame, keys: list[str], order: list, name: str = "nth") -> DataFrame:
    """rows with a number from 0 on among those that share the keys (null-safe), in the given order; ties as they come.

    Keys that no other row shares get 0 without a shuffle of rows. The others' rows are sorted by ranges, which cut
    through the rows of one key, and settled; a row's number is its place less that of its key's first. So no task gets
    more than its range, whatever share of the rows has one key. Range bounds are sampled from keys and order: keep
    these short.
    """
    spark = rows.sparkSession
    key = F.xxhash64(*[F.struct(F.col(k), F.col(k).isNull()) for k in keys])
    shared = settle(rows.select(key.alias("key")).groupBy("key").agg(F.count("*").alias("n")).where("n > 1").select("key"))
    if shared.isEmpty():
        return rows.withColumn(name, F.lit(0).cast("long"))
    whole = F.struct(*[F.col(c) for c in rows.columns]).alias("row")
    held = rows.select(key.alias("key"), *[o.alias(f"order{i}") for i, o in enumerate(order)], whole)
    alone = held.join(shared, "key", "left_anti").select("row.*", F.lit(0).cast("long").alias(name))
    by = ["key", *[f"order{i}" for i in range(len(order))]]
    several = held.join(shared, "key", "left_semi").withColumn("tie", F.monotonically_increasing_id())
    ranged = settle(several.repartitionByRange(partitions(spark), *by, "tie").sortWithinPartitions(*by, "tie"))
    placed = ranged.withColumn("id", F.monotonically_increasing_id())
    placed = placed.select("row", "key", F.shiftright("id", 33).alias("part"), F.col("id").bitwiseAND(F.lit((1 << 33) - 1)).alias("at"))
    # one row for each range of a settled table: as many as partitions
    sizes = {r["part"]: r["n"] for r in placed.groupBy("part").agg(F.count("*").alias("n")).collect()}
    before, total = [], 0
    for part in range(max(sizes) + 1):
        before.append(total)
        total += sizes.get(part, 0)
    place = (F.get(F.array(*[F.lit(b).cast("long") for b in before]), F.col("part").cast("int")) + F.col("at")).alias("place")
    placed = placed.select("row", "key", place)
    first = placed.groupBy("key").agg(F.min("place").alias("first"))
    return alone.unionByName(placed.join(first, "key").select("row.*", (F.col("place") - F.col("first")).alias(name)))


def pieces(rows, limit: int = 2_000_000, most: int = 2_000):
    """Cut an iterator of tuples, whose last item is a text, into lists of at most `limit` characters of text."""
    held, size = [], 0
    for row in rows:
        held.append(row)
        size += len(row[-1])
        if size >= limit or len(held) >= most:
            yield held
            held, size = [], 0
    if held:
        yield held
