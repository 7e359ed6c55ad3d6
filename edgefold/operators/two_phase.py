"""The baselines: messages stored between two phases, tensor operations, a packed sparse product, a dense product."""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgefold.functions import steps as S
from edgefold.operators.fused import _reduction, _start, _wide_message, array_message, complete, gather, ship
from edgefold.operators.packed import chunk_rows
from edgefold.plans.program import Program, check


def store(df: DataFrame, path: str | None = None) -> DataFrame:
    """The barrier: write to storage and read again, else the optimiser would fuse what stands before and after."""
    spark = df.sparkSession
    place = path or f"{_shared(spark)}/messages-{uuid.uuid4().hex}"
    df.write.mode("overwrite").parquet(place)
    return spark.read.parquet(place)


def _shared(spark) -> str:
    """The session's checkpoint folder, or the one that spark.checkpoint.dir names; on a single machine, without either, a temporary one."""
    context = spark.sparkContext
    if not context.getCheckpointDir():
        named = context.getConf().get("spark.checkpoint.dir", "")
        if not named and not context.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        if not named:
            import tempfile

            named = tempfile.mkdtemp(prefix="edgefold-")
        context.setCheckpointDir(named)
    return context.getCheckpointDir()


def edge_dot(edges: DataFrame, x: DataFrame, y: DataFrame, d: int, *, weighted: bool = True) -> DataFrame:
    """(u, v, h): the product of X and Y transposed at the places of A, times A."""
    both = gather(gather(edges, y, "v", "y"), x, "u", "x")
    dot = sum((F.col("x").getItem(i) * F.col("y").getItem(i) for i in range(d)), F.lit(0.0))
    return both.select("u", "v", (dot * F.col("a") if weighted else dot).alias("h"))


def edge_messages(edges: DataFrame, x: DataFrame, y: DataFrame, program: Program, d: int) -> DataFrame:
    """(u, v, a, h, p): the message of each edge, a number or an array, and the pair vector where weigh needs it."""
    check(program)
    both = gather(edges.where("a <> 0"), y, "v", "y")
    both = gather(both, x, "u", "x") if "x" in program.reads else both.withColumn("x", F.col("y"))
    if program.pair.vector is not None:
        p = F.array(*program.pair.vector.wide([F.col("x").getItem(i) for i in range(d)], [F.col("y").getItem(i) for i in range(d)]))
        h = F.transform(p, lambda v: program.scale.element(S.ColumnOps, v, F.col("a"))) if program.scale else p
    else:
        h, p = array_message(program, F.col("x"), F.col("y"), F.col("a"))
    keep = [p.alias("p")] if program.weigh.operand == "pair" else []
    return both.select("u", "v", "a", h.alias("h"), *keep)


def aggregate_messages(messages: DataFrame, y: DataFrame, program: Program, d: int) -> DataFrame:
    """(u, z) from stored messages: neighbour features are read a second time."""
    scalar = messages.schema["h"].dataType.typeName() != "array"
    both = gather(messages, y, "v", "y") if program.weigh.operand == "neighbour" else messages
    h = (lambda i: F.col("h")) if scalar else (lambda i: F.col("h").getItem(i))
    o = {"neighbour": lambda i: F.col("y").getItem(i), "edge": lambda i: F.col("a"), "pair": lambda i: F.col("p").getItem(i)}[program.weigh.operand]
    reduce = _reduction(program)
    z = both.groupBy("u").agg(*[reduce(program.weigh.element(S.ColumnOps, h(i), o(i))).alias(f"z{i}") for i in range(d)])
    return z.select("u", F.array(*[_start(program, F.col(f"z{i}")) for i in range(d)]).alias("z"))


def two_phase(edges: DataFrame, x: DataFrame, y: DataFrame, program: Program, *, d: int, targets: DataFrame | None = None, path: str | None = None) -> DataFrame:
    z = aggregate_messages(store(edge_messages(edges, x, y, program, d), path), y, program, d)
    return complete(z, targets, d) if targets is not None else z


def two_phase_packed(rows: DataFrame, x: DataFrame | None, y: DataFrame, program: Program, *, d: int, targets: DataFrame | None = None, path: str | None = None) -> DataFrame:
    """Both phases as kernels on packed rows (see `pack`) with shipped neighbours; messages are stored between them.

    The first phase gives the scaled message of each edge, a number or a vector; the second reads it, and the neighbours
    again, weighs and reduces. Programs whose weigh step needs the pair vector store that too, as their message.
    """
    check(program)
    shipped, reads_x, pairs = ship(y), "x" in program.reads, program.weigh.operand == "pair"
    ops, width = S.ArrayOps, 1 if program.fold is not None and not pairs else d

    def sides(b):
        ids, matrix = shipped.value
        sizes = np.diff(b.column("vs").offsets.to_numpy())
        return sizes, matrix[np.searchsorted(ids, b.column("vs").flatten().to_numpy(zero_copy_only=False))], np.asarray(b.column("ws").flatten(), dtype=np.float64)[:, None]

    def first(batches):
        for b in batches:
            sizes, ys, a = sides(b)
            xs = np.repeat(np.asarray(b.column("xu").flatten(), dtype=np.float64).reshape(-1, d), sizes, axis=0) if reads_x else ys
            p = program.pair.vector.matrix(xs, ys) if program.pair.vector is not None else program.pair.element(ops, xs, ys, a)
            h = S.matrix_fold(program.fold, p, xs, ys) if program.fold else p
            h = program.scale.element(ops, h, a) if program.scale else h
            h = program.weigh.element(ops, h, p) if pairs else np.broadcast_to(h, (len(ys), width))
            cuts = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32) * width
            yield pa.RecordBatch.from_arrays([b.column("u"), b.column("vs"), b.column("ws"), pa.ListArray.from_arrays(pa.array(cuts), pa.array(np.ascontiguousarray(h).reshape(-1)))], ["u", "vs", "ws", "h"])

    def second(batches):
        reduce = {"sum": np.add, "mean": np.add, "max": np.maximum, "min": np.minimum}[program.collect.reduce]
        for b in batches:
            if not b.num_rows:
                continue
            sizes, ys, a = sides(b)
            h = np.asarray(b.column("h").flatten(), dtype=np.float64).reshape(-1, width)
            w = h if pairs else program.weigh.element(ops, h, ys if program.weigh.operand == "neighbour" else a)
            z = reduce.reduceat(np.ascontiguousarray(np.broadcast_to(w, ys.shape)), np.cumsum(sizes) - sizes, axis=0)
            z = z / sizes[:, None] if program.collect.reduce == "mean" else z
            yield pa.RecordBatch.from_arrays([b.column("u"), pa.ListArray.from_arrays(pa.array(np.arange(0, z.size + 1, d, dtype=np.int32)), pa.array(z.reshape(-1)))], ["u", "z"])

    rows = rows.select("u", "vs", "ws")
    if reads_x:
        rows = rows.join(x.select(F.col("id").alias("u"), F.col("x").alias("xu")), "u")
    stored = store(rows.mapInArrow(first, "u long, vs array<long>, ws array<double>, h array<double>"), path)
    z = stored.mapInArrow(second, "u long, z array<double>").select("u", F.transform("z", lambda e: _start(program, e)).alias("z"))
    return complete(z, targets, d) if targets is not None else z


def tensor_operations(edges: DataFrame, x: DataFrame, y: DataFrame, program: Program, *, d: int, targets: DataFrame | None = None) -> DataFrame:
    """As generic tensor operations do it: both ends gathered for every edge, each step a stored tensor, then a scatter-add."""
    gathered = store(gather(gather(edges.where("a <> 0"), y, "v", "y"), x, "u", "x"))
    h, p = array_message(program, F.col("x"), F.col("y"), F.col("a"))
    pairs = store(gathered.select("u", "y", "a", p.alias("p"), h.alias("h")))
    ops = S.ColumnOps
    operand = {"neighbour": F.col("y"), "pair": F.col("p")}.get(program.weigh.operand)
    if operand is None:
        w = F.transform("h", lambda e: program.weigh.element(ops, e, F.col("a")))
    elif program.fold is not None:
        w = F.transform(operand, lambda e: program.weigh.element(ops, F.col("h"), e))
    else:
        w = F.zip_with("h", operand, lambda e, o: program.weigh.element(ops, e, o))
    weighed = store(pairs.select("u", w.alias("w")))
    reduce = _reduction(program)
    z = weighed.groupBy("u").agg(F.array(*[_start(program, reduce(F.col("w").getItem(i))) for i in range(d)]).alias("z"))
    return complete(z, targets, d) if targets is not None else z


def sparse_product(rows: DataFrame, y: DataFrame, d: int) -> DataFrame:
    """A times Y from packed rows (see chunk_rows): the tuned library kernel that knows this product alone."""
    shipped = ship(y)

    def run(batches):
        ids, matrix = shipped.value
        for b in batches:
            sizes = np.diff(b.column("vs").offsets.to_numpy())
            index = np.searchsorted(ids, b.column("vs").flatten().to_numpy(zero_copy_only=False))
            a = np.asarray(b.column("ws").flatten(), dtype=np.float64)
            starts = np.concatenate([[0], np.cumsum(sizes)[:-1]])
            z = np.add.reduceat(matrix[index] * a[:, None], starts, axis=0)
            yield pa.RecordBatch.from_arrays([b.column("u"), pa.ListArray.from_arrays(pa.array(np.arange(0, z.size + 1, d, dtype=np.int32)), pa.array(z.reshape(-1)))], ["u", "z"])

    part = rows.mapInArrow(run, "u long, z array<double>")
    return part.groupBy("u").agg(F.array(*[F.sum(F.col("z").getItem(i)) for i in range(d)]).alias("z"))


def vendor_product(edges: DataFrame, y: DataFrame, d: int) -> DataFrame:
    """Inspection (packing) included."""
    return sparse_product(chunk_rows(edges), y, d)


def block_matrix_product(edges: DataFrame, y: DataFrame, m: int, n: int, d: int, block: int = 1024):
    """A times Y by the distributed block matrices of Spark's library, as an independent check. Returns (u, z)."""
    from pyspark.mllib.linalg.distributed import CoordinateMatrix, MatrixEntry

    spark = edges.sparkSession
    a = CoordinateMatrix(edges.rdd.map(lambda r: MatrixEntry(r["u"], r["v"], r["a"])), m, n).toBlockMatrix(block, block)
    b = CoordinateMatrix(y.rdd.flatMap(lambda r: [MatrixEntry(r["id"], i, v) for i, v in enumerate(r["x"])]), n, d).toBlockMatrix(block, block)
    rows = a.multiply(b).toIndexedRowMatrix().rows.map(lambda r: (int(r.index), [float(v) for v in r.vector.toArray()]))
    return spark.createDataFrame(rows, "u long, z array<double>")


def dense_reference(edges: DataFrame, x: DataFrame, y: DataFrame, program: Program, *, d: int, targets: DataFrame | None = None) -> DataFrame:
    """The messages of all pairs of a target and a neighbour, then the mask of the edges. For tiny graphs alone.

    The mask is an outer join and a condition inside the reduction: a filter would let the optimiser join the edges first.
    """
    pairs = x.select(F.col("id").alias("u"), "x").crossJoin(y.select(F.col("id").alias("v"), F.col("x").alias("y")))
    masked = pairs.join(edges.where("a <> 0").select("u", "v", F.col("a").alias("mask")), ["u", "v"], "left")
    a = F.coalesce("mask", F.lit(0.0))
    h, operand, _ = _wide_message(program, [F.col("x").getItem(i) for i in range(d)], [F.col("y").getItem(i) for i in range(d)], a)
    w = [F.when(F.col("mask").isNotNull(), program.weigh.element(S.ColumnOps, hi, oi)) for hi, oi in zip(h, operand, strict=True)]
    reduce = _reduction(program)
    z = masked.groupBy("u").agg(F.count("mask").alias("n"), *[reduce(wi).alias(f"z{i}") for i, wi in enumerate(w)]).where("n > 0")
    z = z.select("u", F.array(*[_start(program, F.col(f"z{i}")) for i in range(d)]).alias("z"))
    return complete(z, targets, d) if targets is not None else z


def attention(edges: DataFrame, x: DataFrame, y: DataFrame, d: int) -> DataFrame:
    """Softmax over a target's scores: messages are needed twice, so this stays unfused."""
    scores = store(edge_dot(edges, x, y, d, weighted=False))
    top = scores.groupBy("u").agg(F.max("h").alias("top"))
    weight = scores.join(top, "u").select("u", "v", F.exp(F.col("h") - F.col("top")).alias("e"))
    total = weight.groupBy("u").agg(F.sum("e").alias("total"))
    return weight.join(total, "u").select("u", "v", (F.col("e") / F.col("total")).alias("a"))


def max_abs_diff(one: DataFrame, other: DataFrame) -> DataFrame:
    """n, and the largest difference of two results (u, z); a target in one alone counts as infinite."""
    both = one.select("u", F.col("z").alias("z1")).join(other.select("u", F.col("z").alias("z2")), "u", "full_outer")
    gap = F.when(F.col("z1").isNull() | F.col("z2").isNull(), F.lit(float("inf"))).otherwise(F.array_max(F.zip_with("z1", "z2", lambda p, q: F.abs(p - q))))
    return both.agg(F.count("*").alias("n"), F.max(gap).alias("gap"))
