"""Edge lists: cleaning, slices, symmetry, similarity and co-occurrence graphs, joins in time, sampling, sets."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def clean(edges: DataFrame, loops: bool = False) -> DataFrame:
    """Without zeros, nulls, NaN and, unless asked for, self edges."""
    out = edges.where("u IS NOT NULL AND v IS NOT NULL AND a IS NOT NULL AND NOT isnan(a) AND a <> 0")
    return out if loops else out.where("u <> v")


def merge_parallel(edges: DataFrame) -> DataFrame:
    return edges.groupBy("u", "v").agg(F.sum("a").alias("a"))


def threshold(similar: DataFrame, tau: float) -> DataFrame:
    return similar.where(F.col("a") >= tau)


def min_degree(edges: DataFrame, k: int) -> DataFrame:
    keep = edges.groupBy("u").agg(F.count("*").alias("n")).where(F.col("n") >= k).select("u")
    return edges.join(keep, "u", "left_semi")


def transpose(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("v").alias("u"), F.col("u").alias("v"), "a")


def symmetrise(edges: DataFrame) -> DataFrame:
    """Both directions; weights of what meets are summed."""
    return merge_parallel(edges.unionByName(transpose(edges)))


def with_self_loops(edges: DataFrame, ids: DataFrame, weight: float = 1.0) -> DataFrame:
    return edges.unionByName(ids.select(F.col("u"), F.col("u").alias("v"), F.lit(weight).alias("a")))


def unweight(edges: DataFrame) -> DataFrame:
    return edges.select("u", "v", F.lit(1.0).alias("a"))


def row_normalise(edges: DataFrame) -> DataFrame:
    total = edges.groupBy("u").agg(F.sum("a").alias("total"))
    return edges.join(total, "u").select("u", "v", (F.col("a") / F.col("total")).alias("a"))


def symmetric_normalise(edges: DataFrame) -> DataFrame:
    """a over the square root of both ends' weighted degrees; a symmetric graph."""
    deg = edges.groupBy("u").agg(F.sum("a").alias("d"))
    both = edges.join(deg.select("u", F.col("d").alias("du")), "u").join(deg.select(F.col("u").alias("v"), F.col("d").alias("dv")), "v")
    return both.select("u", "v", (F.col("a") / F.sqrt(F.col("du") * F.col("dv"))).alias("a"))


def slice_rows(edges: DataFrame, targets: DataFrame) -> DataFrame:
    """The rows of a batch of targets: a rectangular slice."""
    return edges.join(targets.select("u"), "u", "left_semi")


def batches(targets: DataFrame, size: int, seed: int = 0) -> DataFrame:
    """(u, batch): targets dealt into batches of about `size`, by hash."""
    n = max(1, -(-targets.count() // size))
    return targets.select("u", F.pmod(F.xxhash64("u", F.lit(seed)), F.lit(n)).cast("int").alias("batch"))


def isolated(ids: DataFrame, edges: DataFrame) -> DataFrame:
    return ids.join(edges.select("u"), "u", "left_anti")


def similar_pairs(x: DataFrame, tau: float, block: int | None = None) -> DataFrame:
    """(u, v, a), u < v: pairs of vectors with a dot product of tau or more. Exact, every vector against every block of them."""
    import numpy as np
    import pyarrow as pa

    from edgefold.operators.products import blockwise

    def solve(own, rows, ids, matrix):
        s = rows @ matrix.T
        i, j = np.nonzero((s >= tau) & (own[:, None] < ids[None, :]))
        return pa.RecordBatch.from_arrays([pa.array(own[i]), pa.array(ids[j]), pa.array(s[i, j])], ["u", "v", "a"])

    return blockwise(x, solve, block)[0]


def assign_parts(prefix: DataFrame, bounds: DataFrame, width: int | None = None) -> DataFrame:
    """(u, part): rows into the part whose interval of running edges [low, high) they start in.

    Intervals of one width that start at its multiples may be many: they are joined by their number.
    """
    within = (F.col("before") >= F.col("low")) & (F.col("before") < F.col("high"))
    if width is None:
        return prefix.join(F.broadcast(bounds), within).select("u", "part")
    return prefix.join(bounds, (F.floor(F.col("before") / width) == F.floor(F.col("low") / width)) & within).select("u", "part")


def asof_features(events: DataFrame, versions: DataFrame, key: str, at: str, since: str) -> DataFrame:
    """Each event with the latest version of its key at its time or before (null if none). One window over both sides."""
    extra = [c for c in events.columns if c not in (key, at)]
    values = [c for c in versions.columns if c not in (key, since)]
    kinds = [df.select(F.struct(*c).alias("s")).schema["s"].dataType for df, c in ((events, extra), (versions, values))]
    left = events.select(key, F.col(at).alias("__t"), F.lit(1).alias("__side"), F.struct(*extra).alias("__e"), F.lit(None).cast(kinds[1]).alias("__v"))
    right = versions.select(key, F.col(since).alias("__t"), F.lit(0).alias("__side"), F.lit(None).cast(kinds[0]).alias("__e"), F.struct(*values).alias("__v"))
    window = Window.partitionBy(key).orderBy("__t", "__side").rowsBetween(Window.unboundedPreceding, 0)
    both = left.unionByName(right).withColumn("__v", F.last("__v", ignorenulls=True).over(window)).where("__side = 1")
    return both.select(key, F.col("__t").alias(at), *[F.col(f"__e.{c}").alias(c) for c in extra], *[F.col(f"__v.{c}").alias(c) for c in values])


def interval_edges(left: DataFrame, right: DataFrame, seconds: int, salts: int = 8) -> DataFrame:
    """(u, v, a): users of left and right events at most `seconds` apart, counted. Times (t) in seconds.

    Events of one user and second count once, with a number, before they meet; they meet in buckets of time, which are
    split: those of the left side are dealt into `salts` places, those of the right side go to each.
    """
    lo = left.groupBy(F.col("user_id").alias("u"), F.col("t").alias("t1")).agg(F.count("*").alias("n1"))
    hi = right.groupBy(F.col("user_id").alias("v"), F.col("t").alias("t2")).agg(F.count("*").alias("n2"))
    lo = lo.select("*", F.floor(F.col("t1") / seconds).alias("bucket"), F.pmod(F.xxhash64("u", "t1"), F.lit(salts)).cast("int").alias("salt"))
    hi = hi.select("*", F.explode(F.array(*[F.floor(F.col("t2") / seconds) + k for k in (-1, 0, 1)])).alias("bucket"))
    hi = hi.select("*", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"))
    near = lo.join(hi, ["bucket", "salt"]).where((F.abs(F.col("t1") - F.col("t2")) <= seconds) & (F.col("u") != F.col("v")))
    return near.groupBy("u", "v").agg(F.sum(F.col("n1") * F.col("n2")).alias("a"))


def rank_neighbours(edges: DataFrame) -> DataFrame:
    w = Window.partitionBy("u").orderBy(F.desc("a"), "v")
    ties = Window.partitionBy("u").orderBy(F.desc("a"))
    return edges.select("u", "v", "a", F.row_number().over(w).alias("place"), F.rank().over(ties).alias("rank"), F.dense_rank().over(ties).alias("dense"))


def strongest(edges: DataFrame) -> DataFrame:
    """(u, v, a): the heaviest neighbour, the least id among equals."""
    best = edges.groupBy("u").agg(F.max(F.struct("a", (-F.col("v")).alias("n"))).alias("b"))
    return best.select("u", (-F.col("b.n")).alias("v"), F.col("b.a").alias("a"))


def _draw(seed: int, *columns: str):
    return F.md5(F.concat_ws(":", F.lit(str(seed)), *[F.col(c).cast("string") for c in columns]))


def drawn(seed: int, *columns: str):
    """32 bits of a digest of the seed and the columns, the same in every engine."""
    return F.conv(F.substring(_draw(seed, *columns), 1, 8), 16, 10).cast("long")


def sample_neighbours(edges: DataFrame, k: int, seed: int = 0) -> DataFrame:
    """k neighbours of each target, by the order of a digest: the same whenever and wherever it is run."""
    w = Window.partitionBy("u").orderBy(_draw(seed, "u", "v"), "v")
    return edges.withColumn("place", F.row_number().over(w)).where(F.col("place") <= k).select("u", "v", "a")


def negatives(ids: DataFrame, n: int, k: int, seed: int = 0) -> DataFrame:
    """(u, v): k vertices for each of ids, drawn with replacement from 0..n-1 by a digest."""
    each = ids.select("u", F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias("j"))
    return each.select("u", F.pmod(drawn(seed, "u", "j"), F.lit(n)).alias("v"))


def edge_set(one: DataFrame, other: DataFrame, kind: str, all: bool = False) -> DataFrame:
    """union, intersect or except of two edge lists."""
    if kind == "union":
        both = one.unionByName(other)
        return both if all else both.distinct()
    if kind == "intersect":
        return one.intersectAll(other) if all else one.intersect(other)
    if kind == "except":
        return one.exceptAll(other) if all else one.subtract(other)
    raise ValueError(f"unknown kind {kind}")
