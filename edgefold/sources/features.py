"""Vertex features from rules on integers, from the embeddings, and in three layouts."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgefold.sources import tables

#: The rule of hashed features: ((id * 7919 + i * 104729 + seed) mod 1000) / 1000 - 0.5.
ID_FACTOR, DIM_FACTOR, STEPS = 7919, 104729, 1000


def hashed(ids: DataFrame, d: int, seed: int = 0) -> DataFrame:
    """(id, x): multiples of a thousandth, the same in every engine."""
    parts = [((F.col("id") * ID_FACTOR + F.lit(i * DIM_FACTOR + seed)) % STEPS) / float(STEPS) - 0.5 for i in range(d)]
    return ids.select("id", F.array(*parts).alias("x"))


def hashed_sql(ids: str, d: int, seed: int = 0) -> str:
    return f"SELECT ids.id, i, ((ids.id * {ID_FACTOR} + i * {DIM_FACTOR} + {seed}) % {STEPS})::DOUBLE / {float(STEPS)}::DOUBLE - 0.5::DOUBLE AS val FROM ({ids}) ids, (SELECT range::INTEGER AS i FROM range({d}))"


def digest(ids: DataFrame, d: int, seed: int = 0) -> DataFrame:
    """(id, x) from the first 8 hex digits of md5(seed:id:i), scaled to -0.5..0.5."""

    def one(i: int):
        head = F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("id").cast("string"), F.lit(str(i)))), 1, 8)
        return F.conv(head, 16, 10).cast("double") / float(1 << 32) - 0.5

    return ids.select("id", F.array(*[one(i) for i in range(d)]).alias("x"))


def digest_sql(ids: str, d: int, seed: int = 0) -> str:
    return f"SELECT ids.id, i, ('0x' || substr(md5('{seed}:' || ids.id || ':' || i), 1, 8))::BIGINT::DOUBLE / 4294967296.0::DOUBLE - 0.5::DOUBLE AS val FROM ({ids}) ids, (SELECT range::INTEGER AS i FROM range({d}))"


def real(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, x) of the embeddings, in double precision."""
    e = tables.load(spark, sf_dir, "embeddings")
    return e.select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("x"))


def to_layout(features: DataFrame, kind: str, d: int, dtype: str = "double") -> DataFrame:
    """array (id, x), wide (id, x0...), long (id, i, val), from any of them."""
    columns = set(features.columns)
    if {"i", "val"} <= columns:
        rows = features.groupBy("id").agg(F.array_sort(F.collect_list(F.struct("i", "val"))).alias("s"))
        arrays = rows.select("id", F.col("s.val").alias("x"))
    elif "x0" in columns:
        arrays = features.select("id", F.array(*[f"x{i}" for i in range(d)]).alias("x"))
    else:
        arrays = features.select("id", "x")
    arrays = arrays.select("id", F.col("x").cast(f"array<{dtype}>").alias("x"))
    if kind == "array":
        return arrays
    if kind == "wide":
        return arrays.select("id", *[F.col("x").getItem(i).alias(f"x{i}") for i in range(d)])
    if kind == "long":
        return arrays.select("id", F.posexplode("x").alias("i", "val"))
    raise ValueError(f"unknown layout {kind}")


def pivot_features(long: DataFrame, d: int) -> DataFrame:
    out = long.groupBy("id").pivot("i", list(range(d))).agg(F.first("val"))
    return out.select("id", *[F.col(str(i)).alias(f"x{i}") for i in range(d)])
