"""Edge lists and triplets from files, the clustered edge store, and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgefold.operators.edges import merge_parallel, symmetrise


def edge_list(spark: SparkSession, path: str, fmt: str = "csv", base: int = 0, symmetric: bool = False, sep: str = ",") -> DataFrame:
    """(u, v, a) from csv (u, v and perhaps a), json (objects with u, v, a) or text (fields between white space).

    Lines of text that begin with # or % are left out. Ids start from `base`. A missing weight is 1; repeats are summed.
    """
    if fmt == "csv":
        raw = spark.read.csv(path, sep=sep, schema="u long, v long, a double", mode="PERMISSIVE")
    elif fmt == "json":
        raw = spark.read.json(path, schema="u long, v long, a double")
    elif fmt == "text":
        lines = spark.read.text(path).where("NOT value RLIKE '^[#%]' AND trim(value) <> ''")
        parts = F.split(F.trim("value"), r"\s+")
        raw = lines.select(F.get(parts, F.lit(0)).cast("long").alias("u"), F.get(parts, F.lit(1)).cast("long").alias("v"), F.get(parts, F.lit(2)).cast("double").alias("a"))
    else:
        raise ValueError(f"unknown format {fmt}")
    out = raw.select((F.col("u") - base).alias("u"), (F.col("v") - base).alias("v"), F.coalesce("a", F.lit(1.0)).alias("a"))
    return symmetrise(out) if symmetric else merge_parallel(out)


def triplets(spark: SparkSession, path: str) -> DataFrame:
    """A coordinate matrix file: comments begin with %, then a line of sizes (rows, columns, entries), then entries from 1.

    The line of sizes is the one without a weight among files with weights, or is told apart by its position: the
    first that is no comment, as files are read with their byte order kept in one partition each.
    """
    lines = spark.read.text(path, wholetext=False).where("NOT value LIKE '\\%%' AND trim(value) <> ''")
    numbered = lines.select("value", F.monotonically_increasing_id().alias("n"))
    first = numbered.agg(F.min("n")).first()[0]
    parts = F.split(F.trim("value"), r"\s+")
    rows = numbered.where(F.col("n") != F.lit(first if first is not None else -1))
    return rows.select((F.get(parts, F.lit(0)).cast("long") - 1).alias("u"), (F.get(parts, F.lit(1)).cast("long") - 1).alias("v"), F.coalesce(F.get(parts, F.lit(2)).cast("double"), F.lit(1.0)).alias("a"))


def write_clustered(edges: DataFrame, path: str, t: int) -> None:
    """Ranges of targets in folders of their own, sorted: slices of targets then read few files."""
    ranged = edges.repartitionByRange(t, "u").withColumn("part", F.spark_partition_id())
    ranged.sortWithinPartitions("u", "v").write.mode("overwrite").partitionBy("part").parquet(path)


def write_bucketed(edges: DataFrame, table: str, t: int) -> None:
    """A bucketed table by target, so that later joins on u need no shuffle."""
    edges.write.mode("overwrite").bucketBy(t, "u").sortBy("u", "v").saveAsTable(table)


def write(df: DataFrame, kind: str, path: str | None = None):
    """parquet, csv, json to a path; noop runs the plan without output; memory gives an Arrow table (small results alone)."""
    if kind in ("parquet", "csv", "json"):
        return getattr(df.write.mode("overwrite"), kind)(path)
    if kind == "noop":
        return df.write.format("noop").mode("overwrite").save()
    if kind == "memory":
        return df.toArrow()
    raise ValueError(f"unknown sink {kind}")
