"""Products of all vectors with all vectors, exhaustive by definition, in blocks that fit a task."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Vectors in a block of the matrix side, and of the query side at a time.
BLOCK, QUERIES = 1 << 18, 256


def blockwise(x: DataFrame, solve, block: int | None = None) -> tuple[DataFrame, int]:
    """(u, v, a) of solve(query ids, query rows, ids, matrix) for each group of queries and each block of vectors.

    x: (id, x), rows of one length. A task holds one block of vectors and takes queries from a stream; with b blocks each
    vector is sent b times as a query and as many times as a block has tasks. Returns the number of blocks as well.
    """
    blocks = max(1, math.ceil(x.count() / (block or BLOCK)))
    tasks = max(1, min(blocks, x.sparkSession.sparkContext.defaultParallelism)) if blocks > 1 else x.sparkSession.sparkContext.defaultParallelism
    side = F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int")
    turn = F.pmod(F.xxhash64("id", F.lit(1)), F.lit(tasks)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    held = x.select("id", "x", side.alias("b"), every(tasks).alias("t")).withColumn("asks", F.lit(False))
    asked = x.select("id", "x", every(blocks).alias("b"), turn.alias("t")).withColumn("asks", F.lit(True))
    both = held.unionByName(asked).repartitionById(blocks * tasks, F.col("b") * tasks + F.col("t")).sortWithinPartitions("asks", "id")

    def rows_of(part):
        return part.column("id").to_numpy(), np.asarray(part.column("x").flatten(), dtype=np.float64).reshape(part.num_rows, -1)

    def run(batches):
        parts, matrix = [], None
        for b in batches:
            asks = b.column("asks").to_numpy(zero_copy_only=False)
            mine = b.filter(pa.array(~asks))
            if mine.num_rows:
                parts.append(rows_of(mine))
            rest = b.filter(pa.array(asks))
            if not rest.num_rows or not parts:
                continue
            if matrix is None:
                ids, matrix = np.concatenate([i for i, _ in parts]), np.concatenate([m for _, m in parts])
            for at in range(0, rest.num_rows, QUERIES):
                yield solve(*rows_of(rest.slice(at, QUERIES)), ids, matrix)

    return both.mapInArrow(run, "u long, v long, a double"), blocks
