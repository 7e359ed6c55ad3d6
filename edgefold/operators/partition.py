"""Row partitions of a graph: balanced by edges, by rows, by hash."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from edgefold.operators.ranks import prefix_sum


def degrees(edges: DataFrame) -> DataFrame:
    return edges.groupBy("u").agg(F.count("*").alias("deg"))


def balanced_parts(edges: DataFrame, t: int) -> DataFrame:
    """(u, deg, part): rows in order of u, cut where the running number of edges passes each t-th of the total.

    A part then has at most a t-th of the edges and one row more. The running sum is taken in two levels, so no task
    holds all rows.
    """
    deg = prefix_sum(degrees(edges), "u", "deg", "before")
    total = deg.agg(F.coalesce(F.sum("deg"), F.lit(0)).alias("nnz"))
    cut = F.floor(F.lit(t).cast("long") * F.col("before") / F.col("nnz")).cast("int")
    return deg.crossJoin(F.broadcast(total)).select("u", "deg", F.least(cut, F.lit(t - 1)).alias("part"))


def _last_not_above(values: list[int], u: Column) -> Column:
    """Index of the last of the ascending values that is not above u; 0 if all are. Halving, in the plan."""
    steps, n = [], 1
    while n < len(values):
        n *= 2
        steps.insert(0, n // 2)
    held = F.array(*[F.lit(v).cast("long") for v in values])
    if not steps:
        return F.lit(0)
    fits = lambda i, s: (i + s < len(values)) & (F.get(held, i + s) <= u)
    return F.aggregate(F.array(*map(F.lit, steps)), F.lit(0), lambda i, s: F.when(fits(i, s), i + s).otherwise(i))


@dataclass(frozen=True)
class Bounds:
    """Where balanced parts begin. Hubs have more edges than a part: theirs are dealt over the parts that they reach.

    lows: the least target and its part, for each part that has one; hubs: target, edges before it, and its edges. Both
    have at most as many entries as there are parts.
    """

    parts: int
    nnz: int
    lows: tuple[tuple[int, int], ...]
    hubs: tuple[tuple[int, int, int], ...]

    def _part(self, before: Column) -> Column:
        return F.least(F.floor(before * self.parts / F.lit(max(1, self.nnz))), F.lit(self.parts - 1)).cast("int")

    def _plain(self, u: Column) -> Column:
        if not self.lows:
            return F.lit(0)
        return F.get(F.array(*[F.lit(p) for _, p in self.lows]), _last_not_above([u0 for u0, _ in self.lows], u))

    def _hub(self, u: Column) -> tuple[Column, Column, Column]:
        """Whether u is a hub, the edges before it, and its edges."""
        i = _last_not_above([h[0] for h in self.hubs], u)
        held = [F.get(F.array(*[F.lit(h[k]).cast("long") for h in self.hubs]), i) for k in range(3)]
        return held[0] == u, held[1], held[2]

    def part_of(self, u: Column, v: Column) -> Column:
        """The part of an edge."""
        if not self.hubs:
            return self._plain(u)
        hub, before, deg = self._hub(u)
        return F.when(hub, self._part(before + F.pmod(F.xxhash64(v), deg))).otherwise(self._plain(u))

    def parts_of(self, u: Column) -> Column:
        """All parts that hold edges of a target."""
        if not self.hubs:
            return F.array(self._plain(u))
        hub, before, deg = self._hub(u)
        return F.when(hub, F.sequence(self._part(before), self._part(before + deg - 1))).otherwise(F.array(self._plain(u)))


def bounds(edges: DataFrame, t: int) -> Bounds:
    """Bounds of the parts of `balanced_parts`, with hubs split: no part has more than twice its share, but for chance
    in the dealing of a hub's edges by a hash of v. Two jobs: degrees are counted, and at most 2 t rows come back."""
    deg = prefix_sum(degrees(edges), "u", "deg", "before").persist()
    try:
        nnz = deg.agg(F.coalesce(F.sum("deg"), F.lit(0)).alias("nnz")).first()["nnz"]
        hub = F.col("deg") * t > F.lit(nnz)
        part = F.least(F.floor(F.col("before") * t / F.lit(max(1, nnz))), F.lit(t - 1)).cast("int")
        lows = deg.groupBy(part.alias("part")).agg(F.min("u").alias("low")).orderBy("low").collect()
        hubs = deg.where(hub).orderBy("u").collect()
    finally:
        deg.unpersist()
    return Bounds(t, nnz, tuple((r["low"], r["part"]) for r in lows), tuple((r["u"], r["before"], r["deg"]) for r in hubs))


def equal_row_parts(edges: DataFrame, t: int) -> DataFrame:
    """The straw man: as many rows to each part, whatever their edges."""
    ranked = prefix_sum(degrees(edges).withColumn("one", F.lit(1).cast("long")), "u", "one", "rank")
    total = ranked.agg(F.count("*").alias("m"))
    return ranked.crossJoin(F.broadcast(total)).select("u", "deg", F.floor(F.lit(t).cast("long") * F.col("rank") / F.col("m")).cast("int").alias("part"))


def hash_parts(edges: DataFrame, t: int) -> DataFrame:
    return degrees(edges).select("u", "deg", F.pmod(F.col("u"), F.lit(t)).cast("int").alias("part"))


def imbalance(parts: DataFrame, t: int) -> DataFrame:
    """parts, edges, most and the load factor: the largest part over the mean."""
    by = parts.groupBy("part").agg(F.sum("deg").alias("nnz"))
    out = by.agg(F.sum("nnz").cast("long").alias("nnz"), F.max("nnz").cast("long").alias("most"))
    return out.select("nnz", "most", (F.col("most") / (F.col("nnz") / F.lit(t))).alias("factor"))


def place(edges: DataFrame, parts: DataFrame, t: int) -> DataFrame:
    """Edges with part k on partition k, each row's edges together and in order of v."""
    placed = edges.join(parts.select("u", "part"), "u")
    return placed.repartitionById(t, F.col("part")).sortWithinPartitions("u", "v")


def part_bounds(parts: DataFrame) -> DataFrame:
    return parts.groupBy("part").agg(F.min("u").alias("low"), F.max("u").alias("high"))
