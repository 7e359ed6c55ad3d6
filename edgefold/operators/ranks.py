"""Running sums and dense ids over a total order, in two levels: within ranges, then over the ranges' totals."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def _ranged(df: DataFrame, *order: str) -> DataFrame:
    """Rows with the range that they lie in, settled in the shared folder: bounds of ranges are sampled anew wherever they
    are worked out, so rows and totals must come from one and the same dealing."""
    from edgefold.operators.two_phase import _shared  # which imports this module

    spark = df.sparkSession
    _shared(spark)
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    return df.repartitionByRange(n, *order).withColumn("__range", F.spark_partition_id()).checkpoint(eager=True)


def prefix_sum(df: DataFrame, order: str, value: str, name: str) -> DataFrame:
    """Adds the sum of value over all rows before, by `order` (which is unique)."""
    ranged = _ranged(df.select(*df.columns), order)
    window = Window.partitionBy("__range").orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    within = ranged.withColumn("__within", F.coalesce(F.sum(value).over(window), F.lit(0)))
    # one row for each range: a window over them all is bounded by the number of partitions
    totals = within.groupBy("__range").agg(F.sum(value).alias("__total"))
    before = Window.orderBy("__range").rowsBetween(Window.unboundedPreceding, -1)
    totals = totals.select("__range", F.coalesce(F.sum("__total").over(before), F.lit(0)).alias("__before"))
    out = within.join(F.broadcast(totals), "__range")
    return out.select(*df.columns, (F.col("__before") + F.col("__within")).cast("long").alias(name))


def tiles(deg: DataFrame, order: list[str], n: int, name: str = "tile") -> DataFrame:
    """Adds 1..n by the order (which is unique): as many rows to each, the first ones one more."""
    key = F.struct(*order)
    numbered = prefix_sum(deg.withColumn("__key", key).withColumn("__one", F.lit(1).cast("long")), "__key", "__one", "__row")
    total = numbered.agg(F.count("*").alias("__total"))
    both = numbered.crossJoin(F.broadcast(total))
    size, more = F.floor(F.col("__total") / n), F.col("__total") % n
    tile = F.when(F.col("__row") < more * (size + 1), F.floor(F.col("__row") / (size + 1))).otherwise(more + F.floor((F.col("__row") - more * (size + 1)) / F.greatest(size, F.lit(1))))
    return both.select(*deg.columns, (tile + 1).cast("int").alias(name))


def shares(deg: DataFrame, value: str) -> DataFrame:
    """Adds cume (the share of rows with the value or less) and pct (of other rows with less). Windows run over counts by
    value in ranges, and rows meet the share of their value."""
    counts = prefix_sum(deg.groupBy(value).agg(F.count("*").alias("__n")), value, "__n", "__before")
    total = deg.agg(F.count("*").alias("__total"))
    counts = counts.crossJoin(F.broadcast(total))
    pct = F.when(F.col("__total") > 1, F.col("__before") / (F.col("__total") - 1)).otherwise(F.lit(0.0))
    counts = counts.select(value, ((F.col("__before") + F.col("__n")) / F.col("__total")).alias("cume"), pct.alias("pct"))
    return deg.join(counts, value)


def dense_ids(strings: DataFrame, column: str, name: str = "id") -> DataFrame:
    """Distinct values in binary order, numbered from 0."""
    distinct = strings.select(column).where(F.col(column).isNotNull()).distinct().withColumn("__one", F.lit(1).cast("long"))
    return prefix_sum(distinct, column, "__one", name).drop("__one")
