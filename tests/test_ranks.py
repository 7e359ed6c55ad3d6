"""Running sums and tiles over more rows than the sampling of ranges looks at."""

from pyspark.sql import functions as F

from edgefold.operators import partition, ranks

N = 20_000


def test_prefix_sum_with_columns_beside_the_sum(spark):
    rows = spark.range(N, numPartitions=4).select("id", (F.col("id") % 7).alias("other"), F.lit(1).cast("long").alias("one"))
    got = ranks.prefix_sum(rows, "id", "one", "before")
    assert got.where("id <> before").count() == 0 and got.count() == N


def test_tiles_of_many_rows(spark):
    got = ranks.tiles(spark.range(N, numPartitions=4).select(F.col("id").alias("u"), (F.col("id") % 3).alias("deg")), ["deg", "u"], 4)
    want = {u: k * 4 // N + 1 for k, u in enumerate(sorted(range(N), key=lambda u: (u % 3, u)))}
    assert {r["u"]: r["tile"] for r in got.collect()} == want


def test_equal_row_parts_of_many_rows(spark):
    parts = partition.equal_row_parts(spark.range(N, numPartitions=4).select(F.col("id").alias("u"), F.col("id").alias("v"), F.lit(1.0).alias("a")), 16)
    assert {r["u"]: r["part"] for r in parts.collect()} == {u: 16 * u // N for u in range(N)}


def test_load_of_equal_row_parts(spark):
    """Row u has u % 5 + 1 edges."""
    rows = spark.range(N, numPartitions=4).select(F.col("id").alias("u"), F.explode(F.sequence(F.lit(0), F.col("id") % 5)).alias("v")).withColumn("a", F.lit(1.0))
    load = [0] * 16
    for u in range(N):
        load[16 * u // N] += u % 5 + 1
    got = partition.imbalance(partition.equal_row_parts(rows, 16), 16).first()
    assert (got["nnz"], got["most"]) == (sum(load), max(load))
