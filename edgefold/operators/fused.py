"""The fused fold: messages and their reduction in one pass, with no table of messages.

Its ways, with one answer:

relational  edges join the features they need, the message is a projection, and a partial aggregation follows in the
            same stage. All in generated code: many dimensions are reduced in blocks, of which the message is worked out
            once. With `specialise=False` each step makes an array by higher-order functions and the result is unpacked
            by dimension: the unoptimised general form. For features that can be broadcast.
packed      targets' edges go through Arrow to kernels on arrays; neighbour features are a matrix that every executor
            holds once; each target's features are read once and its result written once. Edges come from packed rows,
            or, with `parts`, straight from a partition into parts with equally many edges, in which hubs are split.
tiled       when the neighbours' features are too large to ship: edges are dealt into tiles of a block of targets and a
            block of neighbours. A tile gets the features of both blocks once, never for each edge, and what it gives
            are partial results that are merged by target. Legal if the reduction does not depend on order.

Defined cases: null ids and null or zero weights are no edges; edges that repeat (u, v) count each; an edge without the features its
program reads is an error, or dropped, whatever the strategy (`on_missing`); ids that repeat in a feature table are the
caller's error; without edges there are no rows, or zeros for all targets; other columns are ignored.
"""

from __future__ import annotations

import weakref

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from edgefold.functions import steps as S
from edgefold.operators import partition
from edgefold.operators.kernels import REDUCE, Blocking, generate, matrix_message  # noqa: F401
from edgefold.operators.packed import chunk_rows, hubs, pack
from edgefold.plans import planner
from edgefold.plans.program import Program, check, check_tiled, recognise

BROADCAST_BYTES = 256 << 20
#: Dimensions that are reduced side by side in generated code; more are reduced in blocks of as many.
WIDE = 32
#: Edges that a kernel gets at a time.
KERNEL_EDGES = 1 << 16


def _wide_message(program: Program, x: list[Column], y: list[Column], a: Column) -> list[Column]:
    ops = S.ColumnOps
    if program.pair.vector is not None:
        p = program.pair.vector.wide(x, y)
    else:
        p = [program.pair.element(ops, xi, yi, a) for xi, yi in zip(x, y, strict=True)]
    s = S.wide_fold(program.fold, p, x, y) if program.fold else p
    if program.scale:
        s = program.scale.element(ops, s, a) if isinstance(s, Column) else [program.scale.element(ops, v, a) for v in s]
    operand = {"neighbour": y, "edge": [a] * len(y), "pair": p}[program.weigh.operand]
    h = [s] * len(y) if isinstance(s, Column) else s
    return h, operand, isinstance(s, Column)


def _reduction(program: Program):
    if program.collect.reduce == "user":
        if program.collect.aggregate is None:
            raise ValueError("this collect reduces matrices: use strategy='packed'")
        return program.collect.aggregate
    return {"sum": F.sum, "mean": F.avg, "max": F.max, "min": F.min}[program.collect.reduce]


def _uses_batch(program: Program) -> bool:
    if program.collect.batch is not None and program.collect.aggregate is None:
        return True
    return any(s is not None and s.batch is not None for s in (program.pair, program.fold, program.scale, program.weigh))


def _start(program: Program, z: Column) -> Column:
    """What the accumulator's start adds: a maximum that starts from zero is never negative."""
    if program.collect.init == "zero" and program.collect.reduce == "max":
        return F.greatest(z, F.lit(0.0))
    if program.collect.init == "zero" and program.collect.reduce == "min":
        return F.least(z, F.lit(0.0))
    return z


def _present(df: DataFrame, name: str, missing: str, key: str) -> DataFrame:
    """After an outer join: stop where the features are null, if missing is an error.

    A filter, so that the features themselves stay plain columns, and not a deterministic one: the optimiser would try a
    deterministic one on a row of nulls.
    """
    if missing != "error":
        return df
    lost = F.col(name).isNull() & (F.spark_partition_id() >= 0)
    stop = F.raise_error(F.concat(F.lit(f"an edge's {key} has no features: "), F.col(key).cast("string")))
    return df.where(F.when(lost, stop.cast("boolean")).otherwise(F.lit(True)))


def gather(edges: DataFrame, features: DataFrame, key: str, name: str, how: str = "auto", missing: str = "drop") -> DataFrame:
    """Edges with the features of one end. how: auto, broadcast, merge, hash. missing: drop such edges, or error."""
    side = features.select(F.col("id").alias(key), F.col("x").alias(name))
    if how != "auto":
        side = side.hint({"broadcast": "broadcast", "merge": "merge", "hash": "shuffle_hash"}[how])
    return _present(edges.join(side, key, "left" if missing == "error" else "inner"), name, missing, key)


def salted_gather(edges: DataFrame, features: DataFrame, salts: int, missing: str = "drop") -> DataFrame:
    """Edges with neighbour features where a few neighbours have very many edges: their features go to `salts` places."""
    many = features.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    dealt = edges.withColumn("salt", F.pmod(F.xxhash64("u", "v"), F.lit(salts)).cast("int"))
    side = many.select(F.col("id").alias("v"), "salt", F.col("x").alias("y"))
    return _present(dealt.join(side, ["v", "salt"], "left" if missing == "error" else "inner").drop("salt"), "y", missing, "v")


def complete(z: DataFrame, targets: DataFrame, d: int) -> DataFrame:
    """A row for each target; zeros for those without edges."""
    zeros = F.array(*[F.lit(0.0)] * d)
    return targets.select("u").join(z, "u", "left").select("u", F.coalesce("z", zeros).alias("z"))


def _relational(edges, x, y, program, d, how, missing="drop", salts=1):
    reads = program.reads
    both = edges
    if "y" in reads:
        both = salted_gather(both, y, salts, missing) if salts > 1 else gather(both, y, "v", "y", how, missing)
    if "x" in reads:
        both = gather(both, x, "u", "x", how, missing)
    xs = [F.col("x").getItem(i) for i in range(d)] if "x" in reads else [F.lit(0.0)] * d
    ys = [F.col("y").getItem(i) for i in range(d)] if "y" in reads else [F.lit(0.0)] * d
    h, operand, scalar = _wide_message(program, xs, ys, F.col("a"))
    if scalar:  # worked out once, not once for each dimension
        keep = [c for c in ("x", "y") if c in reads]
        both = both.select("u", "a", *keep, h[0].alias("h"))
        h = [F.col("h")] * d
        _, operand, _ = _wide_message(program, xs, ys, F.col("a"))
    w = [program.weigh.element(S.ColumnOps, hi, oi) for hi, oi in zip(h, operand, strict=True)]
    reduce = _reduction(program)
    if d <= WIDE:
        z = both.groupBy("u").agg(*[reduce(wi).alias(f"z{i}") for i, wi in enumerate(w)])
        return z.select("u", F.array(*[_start(program, F.col(f"z{i}")) for i in range(d)]).alias("z"))
    # More reductions side by side would leave generated code: a row for each block of dimensions instead.
    w += [F.lit(0.0)] * (-d % WIDE)
    blocks = F.array(*[F.struct(F.lit(b).alias("block"), *[w[b * WIDE + i].alias(f"w{i}") for i in range(WIDE)]) for b in range(len(w) // WIDE)])
    cut = both.select("u", F.explode(blocks).alias("b")).select("u", "b.*")
    z = cut.groupBy("u", "block").agg(*[reduce(f"w{i}").alias(f"z{i}") for i in range(WIDE)])
    part = F.struct("block", F.array(*[_start(program, F.col(f"z{i}")) for i in range(WIDE)]).alias("z"))
    z = z.groupBy("u").agg(F.array_sort(F.collect_list(part)).alias("parts"))
    return z.select("u", F.slice(F.flatten("parts.z"), 1, d).alias("z"))


def array_message(program: Program, x: Column, y: Column, a: Column) -> tuple[Column, Column]:
    """The message (scalar or array) and the pair vector, by higher-order functions."""
    ops = S.ColumnOps
    if program.pair.vector is not None:
        raise ValueError("a network message has no array form")
    if "x" not in program.pair.reads:
        p = F.transform(y, lambda v: program.pair.element(ops, v, v, a))
    elif "y" not in program.pair.reads:
        p = F.transform(x, lambda v: program.pair.element(ops, v, v, a))
    else:
        p = F.zip_with(x, y, lambda xi, yi: program.pair.element(ops, xi, yi, a))
    s = S.array_fold(program.fold, p, x, y) if program.fold else p
    if program.scale:
        s = program.scale.element(ops, s, a) if program.fold else F.transform(s, lambda v: program.scale.element(ops, v, a))
    return s, p


def _array(edges, x, y, program, d, how, missing="drop"):
    if program.pair.vector is not None:
        return _relational(edges, x, y, program, d, how, missing)
    reads, none = program.reads, F.array(*[F.lit(0.0)] * d)
    both = gather(edges, y, "v", "y", how, missing) if "y" in reads else edges.withColumn("y", none)
    both = gather(both, x, "u", "x", how, missing) if "x" in reads else both.withColumn("x", none)
    h, p = array_message(program, F.col("x"), F.col("y"), F.col("a"))
    both = both.select("u", "y", "a", p.alias("p"), h.alias("h"))
    weigh = lambda hi, oi: program.weigh.element(S.ColumnOps, hi, oi)
    operand = {"neighbour": F.col("y"), "pair": F.col("p"), "edge": None}[program.weigh.operand]
    if program.fold is not None:
        w = F.transform(operand, lambda v: weigh(F.col("h"), v)) if operand is not None else F.transform("y", lambda v: weigh(F.col("h"), F.col("a")))
    elif operand is None:
        w = F.transform("h", lambda v: weigh(v, F.col("a")))
    else:
        w = F.zip_with("h", operand, weigh)
    long = both.select("u", F.posexplode(w).alias("i", "w")).groupBy("u", "i").agg(_reduction(program)("w").alias("w"))
    z = long.groupBy("u").agg(F.array_sort(F.collect_list(F.struct("i", "w"))).alias("s"))
    return z.select("u", F.transform("s", lambda e: _start(program, e["w"])).alias("z"))


_SHIPPED: weakref.WeakKeyDictionary = weakref.WeakKeyDictionary()


def ship(y: DataFrame, limit: int = BROADCAST_BYTES, dtype: str = "double"):
    """Ids in order and the matrix of neighbour features, as a broadcast, made once for a DataFrame; refused above the limit.

    No more rows than the limit allows are asked for before it is known to hold.
    """
    if dtype in _SHIPPED.get(y, {}):
        return _SHIPPED[y][dtype]
    size = 4 if dtype == "float" else 8
    first = y.select(F.size("x").alias("d")).first()
    d = first["d"] if first else 0
    most = limit // (size * d + 8)
    got = y.select("id", "x").limit(most + 1).toArrow()
    if got.num_rows > most:
        raise ValueError(f"more than {most} rows of {d} features pass the broadcast limit of {limit} bytes; use strategy='tiled'")
    ids = got["id"].to_numpy()
    flat = got["x"].combine_chunks()
    flat = flat if not isinstance(flat, pa.ChunkedArray) else pa.concat_arrays(flat.chunks)
    matrix = np.asarray(flat.flatten()).astype(np.float32 if dtype == "float" else np.float64, copy=False).reshape(len(ids), d)
    order = np.argsort(ids)
    _SHIPPED.setdefault(y, {})[dtype] = y.sparkSession.sparkContext.broadcast((ids[order], matrix[order]))
    return _SHIPPED[y][dtype]


def _places(ids: np.ndarray, wanted: np.ndarray, error: bool, what: str) -> tuple[np.ndarray, np.ndarray]:
    """Where the wanted ids stand among ids in order, and which do; those that do not are an error, if asked."""
    index = np.searchsorted(ids, wanted)
    known = index < len(ids)
    known[known] = ids[index[known]] == wanted[known]
    if error and not known.all():
        raise ValueError(f"an edge's {what} has no features: {wanted[~known][0]}")
    return index, known


def _numbers(column, kind=np.float64) -> np.ndarray:
    return np.asarray(column.flatten()).astype(kind, copy=False)


def _rows_of(u, z: np.ndarray, n: np.ndarray) -> pa.RecordBatch:
    lists = pa.ListArray.from_arrays(pa.array(np.arange(0, z.size + 1, z.shape[1], dtype=np.int32)), pa.array(z.astype(np.float64, copy=False).reshape(-1)))
    return pa.RecordBatch.from_arrays([u if isinstance(u, pa.Array) else pa.array(u), lists, pa.array(n.astype(np.int64))], ["u", "z", "n"])


_PARTIAL = "u long, z array<double>, n long"


def _merged(part: DataFrame, program: Program, d: int) -> DataFrame:
    """Partial results (u, z, n) of a target added up; n: its edges."""
    reduce = {"sum": F.sum, "mean": F.sum, "max": F.max, "min": F.min}[program.collect.reduce]
    if d <= WIDE:
        return part.groupBy("u").agg(F.array(*[reduce(F.col("z").getItem(i)) for i in range(d)]).alias("z"), F.sum("n").alias("n"))
    blocks = F.array(*[F.struct(F.lit(b).alias("block"), F.slice("z", b * WIDE + 1, WIDE).alias("z")) for b in range(-(-d // WIDE))])
    cut = part.select("u", "n", F.explode(blocks).alias("b")).select("u", "n", "b.*")
    z = cut.groupBy("u", "block").agg(F.array(*[reduce(F.get("z", F.lit(i))) for i in range(WIDE)]).alias("z"), F.sum("n").alias("n"))
    z = z.groupBy("u").agg(F.array_sort(F.collect_list(F.struct("block", "z"))).alias("parts"), F.max("n").alias("n"))
    return z.select("u", F.slice(F.flatten("parts.z"), 1, d).alias("z"), "n")


def _ended(z: DataFrame, program: Program) -> DataFrame:
    of = (lambda e: e / F.col("n")) if program.collect.reduce == "mean" else (lambda e: e)
    return z.select("u", F.transform("z", lambda e: _start(program, of(e))).alias("z"))


def _packed(edges, x, y, program, d, *, specialise=True, block=None, dtype="double", limit=BROADCAST_BYTES, rows=None, missing="drop"):
    shipped = ship(y, limit, dtype)
    pattern = recognise(program) if specialise or program.collect.reduce == "user" else "general"
    if pattern == "user" and program.collect.batch is None:
        raise ValueError("this collect reduces columns: use strategy='relational'")
    kernel, reads_x = generate(pattern, d, block, dtype), "x" in program.reads
    kind, error = np.float32 if dtype == "float" else np.float64, missing == "error"
    # a user's reduction sees all messages of a target, so its rows are whole
    whole = rows is None and (pattern == "user" or hubs(edges).isEmpty())
    if rows is None:
        rows = pack(edges) if whole else chunk_rows(edges)
    if reads_x:
        side = x.select(F.col("id").alias("u"), F.col("x").alias("xu"))
        rows = _present(rows.join(side, "u", "left" if error else "inner"), "xu", missing, "u")

    def run(batches):
        ids, matrix = shipped.value
        for b in batches:
            if not b.num_rows:
                continue
            vs, weights = b.column("vs"), b.column("ws")
            sizes = np.diff(vs.offsets.to_numpy())
            a = _numbers(weights, kind)
            index, known = _places(ids, vs.flatten().to_numpy(zero_copy_only=False), error, "v")
            if not known.all():
                sizes = np.bincount(np.repeat(np.arange(len(sizes)), sizes)[known], minlength=len(sizes))
                index, a = index[known], a[known]
            starts = np.cumsum(sizes) - sizes
            xs = _numbers(b.column("xu"), kind).reshape(b.num_rows, d) if reads_x else None
            z = kernel(program, xs, matrix, index, a, sizes, starts)
            some = sizes > 0
            yield _rows_of(b.column("u").filter(pa.array(some)), z[some], sizes[some])

    part = rows.mapInArrow(run, _PARTIAL)
    # a target that is in one piece has nothing to merge
    return _ended(part if whole or "chunks" not in rows.columns else _merged(part, program, d), program)


class _Stream:
    """Edges of one task in order of their targets, in batches that cut targets anywhere; results of whole targets."""

    def __init__(self, kernel, program: Program, d: int, kind):
        self.kernel, self.program, self.d, self.kind = kernel, program, d, kind
        self.open = None  # u, z and n of the target that may go on

    def results(self, u, index, a, matrix, x_of) -> pa.RecordBatch | None:
        """Of the targets that end in these edges. x_of: features of given targets, or None."""
        heads = np.flatnonzero(np.concatenate([[True], u[1:] != u[:-1]]))
        sizes = np.diff(np.append(heads, len(u)))
        targets, n = u[heads], sizes.astype(np.int64)
        z = self.kernel(self.program, x_of(targets) if x_of else None, matrix, index, a, sizes, heads)
        if self.open is not None:
            u0, z0, n0 = self.open
            if u0 == targets[0]:
                z[0], n[0] = REDUCE[self.program.collect.reduce](z[0], z0), n[0] + n0
            else:
                targets, z, n = np.concatenate([[u0], targets]), np.concatenate([z0[None], z]), np.concatenate([[n0], n])
        self.open = (targets[-1], z[-1], n[-1])
        return _rows_of(targets[:-1], z[:-1], n[:-1]) if len(targets) > 1 else None

    def end(self):
        if self.open is not None:
            u, z, n = self.open
            yield _rows_of(np.asarray([u]), z[None], np.asarray([n]))


def _x_rows(x: DataFrame) -> DataFrame:
    """Features of targets as rows of a stream of edges."""
    none = F.lit(None)
    return x.select(F.col("id").alias("u"), none.cast("long").alias("v"), none.cast("double").alias("a"), F.col("x").cast("array<double>").alias("x"))


def placed(edges: DataFrame, x: DataFrame | None, parts: int) -> tuple[DataFrame, bool]:
    """Edges (u, v, a, x null) in `parts` partitions with equally many of them, in order of u, and whether hubs are split.

    With x, each target's features stand as a row (v null) before its edges, in every part that has some.
    """
    bounds = partition.bounds(edges, parts)
    part = bounds.part_of(F.col("u"), F.col("v"))
    rows = edges.select("u", "v", "a", F.lit(None).cast("array<double>").alias("x"), part.alias("part"))
    if x is not None:
        rows = rows.unionByName(_x_rows(x).withColumn("part", F.explode(bounds.parts_of(F.col("u")))))
    return rows.repartitionById(parts, F.col("part")).sortWithinPartitions("u", "v").drop("part"), bool(bounds.hubs)


def _placed(edges, x, y, program, d, *, parts, specialise=True, block=None, dtype="double", limit=BROADCAST_BYTES, missing="drop"):
    shipped = ship(y, limit, dtype)
    pattern = recognise(program) if specialise else "general"
    kernel, reads_x = generate(pattern, d, block, dtype), "x" in program.reads
    kind, error = np.float32 if dtype == "float" else np.float64, missing == "error"
    rows, split = placed(edges, x if reads_x else None, parts)

    def run(batches):
        ids, matrix = shipped.value
        stream = _Stream(kernel, program, d, kind)
        held, size = [], 0
        known_u, known_x = np.zeros(0, dtype=np.int64), np.zeros((0, d), dtype=kind)

        def work():
            nonlocal known_u, known_x
            u, v, a = (np.concatenate([h[k] for h in held]) for k in range(3))
            index, known = _places(ids, v, error, "v")
            x_of = None
            if reads_x:
                known_u, known_x = np.concatenate([known_u, *[h[3] for h in held]]), np.concatenate([known_x, *[h[4] for h in held]])
                known &= _places(known_u, u, error, "u")[1]
                of_u, of_x = known_u, known_x
                x_of = lambda targets: of_x[np.searchsorted(of_u, targets)]
                known_u, known_x = known_u[-1:], known_x[-1:]  # the last target may go on
            if known.any():
                return stream.results(u[known], index[known], a[known], matrix, x_of)
            return None

        for b in batches:
            edge = b.column("v").is_valid()
            e, rest = b.filter(edge), b.filter(pc.invert(edge))
            xs = _numbers(rest.column("x"), kind).reshape(rest.num_rows, d) if reads_x else None
            held.append((e.column("u").to_numpy(), e.column("v").to_numpy(), e.column("a").to_numpy().astype(kind, copy=False), rest.column("u").to_numpy(), xs))
            size += b.num_rows
            if size >= KERNEL_EDGES:
                if (out := work()) is not None:
                    yield out
                held, size = [], 0
        if size and (out := work()) is not None:
            yield out
        yield from stream.end()

    part = rows.mapInArrow(run, _PARTIAL)
    return _ended(_merged(part, program, d) if split else part, program)


def _tiled(edges, x, y, program, d, tiles, *, specialise=True, block=None, dtype="double", missing="drop"):
    """Edges in tiles (block of u, block of v); each tile gets the features of its blocks once and gives partial results."""
    check_tiled(program)
    across, down = tiles if isinstance(tiles, tuple) else planner.grid(tiles, "x" in program.reads)
    reads_x, reads_y = "x" in program.reads, "y" in program.reads
    pattern = recognise(program) if specialise else "general"
    kernel = generate(pattern, d, block, dtype)
    kind, error = np.float32 if dtype == "float" else np.float64, missing == "error"
    none, wide = F.lit(None), f"array<{'float' if dtype == 'float' else 'double'}>"
    row_of = lambda c: F.pmod(F.xxhash64(c), F.lit(down)).cast("int")
    column_of = lambda c: F.pmod(F.xxhash64(c), F.lit(across)).cast("int")

    def copies(n):
        return F.explode(F.sequence(F.lit(0), F.lit(n - 1)))

    dealt = edges.select((row_of("u") * across + column_of("v")).alias("tile"), F.lit(2).alias("what"), "u", "v", "a", none.cast(wide).alias("x"))
    if reads_y:
        ys = y.select("id", "x", copies(down).alias("k"))
        ys = ys.select((F.col("k") * across + column_of("id")).alias("tile"), F.lit(0).alias("what"), F.col("id").alias("u"), none.cast("long").alias("v"), none.cast("double").alias("a"), F.col("x").cast(wide).alias("x"))
        dealt = dealt.unionByName(ys)
    if reads_x:
        xs = x.select("id", "x", copies(across).alias("k"))
        xs = xs.select((row_of("id") * across + F.col("k")).alias("tile"), F.lit(1).alias("what"), F.col("id").alias("u"), none.cast("long").alias("v"), none.cast("double").alias("a"), F.col("x").cast(wide).alias("x"))
        dealt = dealt.unionByName(xs)
    dealt = dealt.repartitionById(across * down, F.col("tile")).sortWithinPartitions("what", "u", "v").drop("tile")

    def run(batches):
        stream, features = _Stream(kernel, program, d, kind), {0: [], 1: []}
        sides = None

        def side(k):
            got = features.pop(k)
            ids = np.concatenate([np.zeros(0, dtype=np.int64), *[i for i, _ in got]])
            return ids, np.concatenate([np.zeros((0, d), dtype=kind), *[m for _, m in got]])

        for b in batches:
            what = b.column("what").to_numpy()
            if sides is None:
                for k in (0, 1):
                    part = b.filter(pa.array(what == k))
                    if part.num_rows:
                        features[k].append((part.column("u").to_numpy(), _numbers(part.column("x"), kind).reshape(part.num_rows, d)))
            if not (what == 2).any():
                continue
            sides = sides or (side(0), side(1))
            (y_ids, matrix), (x_ids, x_all) = sides
            e = b.filter(pa.array(what == 2))
            u, v, a = e.column("u").to_numpy(), e.column("v").to_numpy(), e.column("a").to_numpy().astype(kind, copy=False)
            index, known = _places(y_ids, v, error, "v") if reads_y else (np.zeros(len(u), dtype=np.int64), np.ones(len(u), dtype=bool))
            if reads_x:
                known = known & _places(x_ids, u, error, "u")[1]
            if known.any():
                held = matrix if reads_y else np.zeros((1, d), dtype=kind)
                x_of = (lambda targets: x_all[np.searchsorted(x_ids, targets)]) if reads_x else None
                out = stream.results(u[known], index[known], a[known], held, x_of)
                if out is not None:
                    yield out
        yield from stream.end()

    return _ended(_merged(dealt.mapInArrow(run, _PARTIAL), program, d), program)


def _edges_only(edges, program):
    return edges.select("u", "v", "a").where("a <> 0 AND u IS NOT NULL AND v IS NOT NULL")


def validate(features: DataFrame, d: int) -> DataFrame:
    """Features whose rows have d numbers, none null or NaN; a row that does not stops the job."""
    fine = (F.size("x") == d) & F.forall("x", lambda v: v.isNotNull() & ~F.isnan(v))
    stop = F.raise_error(F.lit("a feature row is null, has NaN or the wrong length"))
    return features.select("id", F.when(F.coalesce(fine, F.lit(False)), F.col("x")).otherwise(stop.cast(features.schema["x"].dataType)).alias("x"))


def fused_fold(
    edges: DataFrame,
    x: DataFrame | None,
    y: DataFrame,
    program: Program,
    *,
    d: int,
    targets: DataFrame | None = None,
    strategy: str = "auto",
    specialise: bool = True,
    how: str = "auto",
    block: Blocking | int | None = None,
    dtype: str = "double",
    tiles: int | tuple[int, int] = 16,
    parts: int | None = None,
    salts: int = 1,
    checked: bool = False,
    on_missing: str = "error",
    rows: DataFrame | None = None,
    tuned: str | None = None,
) -> DataFrame:
    """(u, z): the fold of all edges (u, v, a) with a <> 0, over target features x and neighbour features y (id, x).

    Edges that repeat (u, v) count each. With targets (u), each gets a row. strategy: relational, array, packed, tiled,
    or auto, which asks the planner. checked: stop on malformed features. on_missing: stop with an error where an edge
    lacks features that the program reads, or drop it. block: a Blocking, or bytes of gathered neighbours at a time.
    rows: for packed, rows of `pack` or `chunk_rows` that were made before. parts: for packed, so many parts with
    equally many edges, without packed rows. tiles: for tiled, how many, or (blocks of v, blocks of u). salts: for
    relational, places of each neighbour's features. tuned: a file of plans that `planner.tune` has kept, for auto.
    """
    check(program)
    if on_missing not in ("error", "drop"):
        raise ValueError("on_missing is error or drop")
    block = Blocking(limit=block) if isinstance(block, int) else block
    if checked:
        y = validate(y, d)
        x = validate(x, d) if x is not None else None
    edges = _edges_only(edges, program)
    if strategy == "auto":
        plan = planner.choose(edges, y, d, program, batch=_uses_batch(program), tuned=tuned)
        strategy, tiles, salts, parts = plan.strategy, plan.tiles or tiles, max(salts, plan.salts), parts or plan.parts
        block = block or (Blocking(limit=plan.block) if plan.block else None)
    if _uses_batch(program) and strategy not in ("packed", "tiled"):
        raise ValueError("steps on matrices need strategy='packed' or 'tiled'")
    if strategy == "packed" and parts and rows is None and program.collect.reduce != "user":
        z = _placed(edges, x, y, program, d, parts=parts, specialise=specialise, block=block, dtype=dtype, missing=on_missing)
    elif strategy == "packed":
        z = _packed(edges, x, y, program, d, specialise=specialise, block=block, dtype=dtype, rows=rows, missing=on_missing)
    elif strategy == "tiled":
        z = _tiled(edges, x, y, program, d, tiles, specialise=specialise, block=block, dtype=dtype, missing=on_missing)
    elif strategy == "array" or not specialise:
        z = _array(edges, x, y, program, d, how, on_missing)
    elif strategy == "relational":
        z = _relational(edges, x, y, program, d, how, on_missing, salts)
    else:
        raise ValueError(f"unknown strategy {strategy}")
    return complete(z, targets, d) if targets is not None else z


def to_long(z: DataFrame, digits: int | None = 6) -> DataFrame:
    """(u, i, z) with rounded values, for comparison."""
    out = z.select("u", F.posexplode("z").alias("i", "z"))
    return out.select("u", "i", (F.round("z", digits) if digits is not None else F.col("z")).alias("z"))
