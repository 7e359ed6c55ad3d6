"""Packed rows of the adjacency: a target, its neighbours in order and their weights."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Neighbours in a packed row at most; targets with more are in pieces.
ROW_EDGES = 65_536


def pack(edges: DataFrame) -> DataFrame:
    """(u, deg, vs, ws), neighbours ascending."""
    row = edges.groupBy("u").agg(F.array_sort(F.collect_list(F.struct("v", "a"))).alias("s"))
    return row.select("u", F.size("s").alias("deg"), F.col("s.v").alias("vs"), F.col("s.a").alias("ws"))


def unpack(rows: DataFrame) -> DataFrame:
    return rows.select("u", F.explode(F.arrays_zip("vs", "ws")).alias("e")).select("u", F.col("e.vs").alias("v"), F.col("e.ws").alias("a"))


def hubs(edges: DataFrame, most: int = ROW_EDGES) -> DataFrame:
    """(hub, chunks): targets with more than `most` edges."""
    found = edges.groupBy("u").agg(F.count("*").alias("d")).where(F.col("d") > most)
    return found.select(F.col("u").alias("hub"), F.ceil(F.col("d") / most).cast("int").alias("chunks"))


def chunk_rows(edges: DataFrame, most: int = ROW_EDGES) -> DataFrame:
    """(u, chunk, chunks, deg, vs, ws): packed rows with about `most` neighbours at most, hubs in pieces by a hash of v.

    Whether there are hubs is asked first, by a count for each target; without any, edges are shuffled just once.
    """
    large = hubs(edges, most)
    if large.isEmpty():
        return pack(edges).select("u", F.lit(0).alias("chunk"), F.lit(1).alias("chunks"), "deg", "vs", "ws")
    dealt = edges.join(large, edges["u"] == large["hub"], "left")
    chunks = F.coalesce("chunks", F.lit(1))
    dealt = dealt.select("u", "v", "a", chunks.alias("chunks"), F.pmod(F.xxhash64("v"), chunks).cast("int").alias("chunk"))
    row = dealt.groupBy("u", "chunk", "chunks").agg(F.array_sort(F.collect_list(F.struct("v", "a"))).alias("s"))
    return row.select("u", "chunk", "chunks", F.size("s").alias("deg"), F.col("s.v").alias("vs"), F.col("s.a").alias("ws"))
