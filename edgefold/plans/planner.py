"""Choice of a strategy from sizes, and tuning on a sample.

What a choice asks of the data is bounded: whether a table has more rows than a limit, which Spark stops counting at. The
bytes that each strategy moves are compared only where features are too many to ship, and all tables are counted then.
"""

from __future__ import annotations

import json
import math
import os
import platform
import time
from dataclasses import asdict, dataclass
from pathlib import Path

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgefold.plans import cost
from edgefold.plans.program import ASSOCIATIVE, Program

#: Multiplications from which Python workers pay.
PACKED_WORK = 2_000_000
BROADCAST_BYTES = 256 << 20
#: Edges from which parts with equally many of them pay for the jobs that find their bounds.
BALANCED_EDGES = 50_000_000
#: Edges of one neighbour, as a share of all, from which its features go to several places.
HUB_SHARE = 0.01


@dataclass(frozen=True)
class Plan:
    """tiles: (blocks of v, blocks of u). block: bytes of gathered neighbours at a time. seconds: where it was timed."""

    strategy: str
    tiles: tuple[int, int] | None = None
    parts: int | None = None
    salts: int = 1
    block: int | None = None
    seconds: float | None = None


def grid(tiles: int, reads_x: bool) -> tuple[int, int]:
    """Blocks of neighbours and of targets that make about so many tiles; one block of targets where x is not read."""
    if not reads_x:
        return max(1, tiles), 1
    across = max(1, math.isqrt(max(1, tiles)))
    return across, max(1, tiles // across)


def more_than(df: DataFrame, n: int) -> bool:
    """Whether there are more than n rows; no more than that are counted."""
    return df.select(F.lit(1)).limit(n + 1).count() > n


def resources(spark) -> tuple[int, int]:
    """Executors (or cores of a single machine), and bytes of memory of one that a fold may use."""
    context = spark.sparkContext
    executors = max(1, context._jsc.sc().getExecutorMemoryStatus().size() - 1)
    memory = context._conf.get("spark.executor.memory", "1g").lower().rstrip("b")
    size = float(memory[:-1]) * {"k": 1 << 10, "m": 1 << 20, "g": 1 << 30, "t": 1 << 40}.get(memory[-1], 1) if memory[-1] in "kmgt" else float(memory)
    return max(executors, context.defaultParallelism), int(size * 0.2)


def choose(edges: DataFrame, y: DataFrame, d: int, program: Program, *, batch: bool = False, limit: int = BROADCAST_BYTES, tuned: str | None = None) -> Plan:
    """relational for little work, packed while neighbour features fit every executor, and beyond that tiled or relational,
    whichever moves less, with salted neighbours if some are hubs. A plan that `tune` has kept in the file `tuned` for
    this program, size and machine goes first."""
    if tuned and (known := _kept(tuned).get(_key(program, d, _size(edges)))):
        return known
    if more_than(y, limit // (8 * d + 8)):
        return _at_scale(edges, y, d, program, batch)
    if batch or (d > 8 and more_than(edges, PACKED_WORK // d)):
        many = more_than(edges, BALANCED_EDGES)
        return Plan("packed", parts=2 * edges.sparkSession.sparkContext.defaultParallelism if many else None)
    return Plan("relational")


def _at_scale(edges: DataFrame, y: DataFrame, d: int, program: Program, batch: bool) -> Plan:
    n, got = y.count(), edges.groupBy("u").agg(F.count("*").alias("deg")).agg(F.count("*").alias("m"), F.sum("deg").alias("nnz")).first()
    m, nnz = got["m"], got["nnz"] or 0
    executors, memory = resources(edges.sparkSession)
    best = choose_by_bytes(m, n, nnz, d, executors=executors, memory=memory, reads_x="x" in program.reads)
    if program.collect.reduce in ASSOCIATIVE and (batch or best["strategy"] != "edge_join"):
        return Plan("tiled", tiles=best["tiles"])
    top = edges.groupBy("v").agg(F.count("*").alias("c")).agg(F.max("c")).first()[0] or 0
    return Plan("relational", salts=min(64, math.ceil(top / (HUB_SHARE * nnz))) if top > HUB_SHARE * nnz else 1)


def choose_by_bytes(m: int, n: int, nnz: int, d: int, *, executors: int, memory: int, reads_x: bool = True) -> dict:
    """At scale: the least moved of broadcast, row- and source-stationary, tiles of both, and a join that carries features
    with each edge; with the blocks (of v, of u) that memory asks for, and at least a tile for each executor."""
    across, down = max(1, -(-n * d * 8 // memory)), max(1, -(-m * d * 16 // memory)) if reads_x else 1
    while across * down < executors:
        across, down = (across * 2, down) if not reads_x or across * m <= down * n else (across, down * 2)
    rows = max(1, -(-m * d * 16 // (executors * memory)), executors)
    columns = max(1, -(-n * d * 8 // memory))
    source = cost.moved_bytes("source_stationary", m, n, nnz, d, executors, columns)
    options = {
        "row_stationary": cost.moved_bytes("row_stationary", m, n, nnz, d, executors, rows),
        "source_stationary": source if reads_x else source / 2,
        "tiled": down * n * d * 8 + (across * m * d * 8 if reads_x else 0) + min(nnz, across * m) * d * 8,
        "edge_join": cost.moved_bytes("edge_join", m, n, nnz, d, executors, 1) * (2 if reads_x else 1),
    }
    if n * d * 8 <= memory // 4:
        options["broadcast"] = cost.moved_bytes("broadcast", m, n, nnz, d, executors, 1)
    best = min(options, key=options.get)
    tiles = {"row_stationary": (1, rows), "source_stationary": (columns, 1)}.get(best, (across, down))
    return {"strategy": best, "tiles": tiles, "bytes": options}


def _size(edges: DataFrame) -> int:
    """Bits of the number of edges."""
    return edges.count().bit_length()


def machine() -> str:
    return f"{platform.machine()}-{os.cpu_count()}"


def _key(program: Program, d: int, size: int) -> str:
    return f"{program.name}-{d}-{size}-{machine()}"


def _kept(path: str) -> dict[str, Plan]:
    if not Path(path).exists():
        return {}
    return {k: Plan(**{**v, "tiles": tuple(v["tiles"]) if v["tiles"] else None}) for k, v in json.loads(Path(path).read_text()).items()}


def tune(edges: DataFrame, x, y, program: Program, d: int, candidates, *, budget_s: float = 60, rows: float = 0.2, repeats: int = 3, cache: str | None = None) -> Plan:
    """Time candidates (Plan) on a share of the targets, several times each in turn; keep the best by its least time.

    cache: a file, of the driver, of plans by program, d, bits of the number of edges, and machine; `fused_fold` reads it
    (`tuned`). The answer never depends on it.
    """
    from edgefold.operators.fused import fused_fold

    edges = edges.where("a <> 0 AND u IS NOT NULL AND v IS NOT NULL")
    key = _key(program, d, _size(edges))
    known = _kept(cache) if cache else {}
    if key in known:
        return known[key]
    sample = edges.where(F.pmod(F.xxhash64("u"), F.lit(1000)) < int(rows * 1000)).persist()
    sample.count()
    times, began = {}, time.time()
    for turn in range(repeats + 1):
        for plan in candidates:
            if times and time.time() - began > budget_s:
                break
            t = time.time()
            options = {"tiles": plan.tiles or 16, "parts": plan.parts, "salts": plan.salts, "block": plan.block}
            fused_fold(sample, x, y, program, d=d, strategy=plan.strategy, **options).write.format("noop").mode("overwrite").save()
            if turn or plan not in times:  # the first turn warms up
                times[plan] = min(times.get(plan, math.inf) if turn > 1 else math.inf, time.time() - t)
    sample.unpersist()
    best = min(times, key=times.get)
    best = Plan(**{**asdict(best), "seconds": times[best]})
    if cache:
        Path(cache).write_text(json.dumps({k: asdict(p) for k, p in (known | {key: best}).items()}))
    return best
