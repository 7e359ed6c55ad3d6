"""Connected components of links that may be too many for one machine.

Each round contracts: every node points at the least of itself and its neighbours, pointers are doubled until they reach
nodes that point at themselves, links are renamed by them, and links within a name go. A node that is not the least
among its neighbours disappears, so at least half of the nodes that still have links go in a round. The least name by node is a partial aggregation, so a hub is no hot task, and the
renaming joins read settled tables, which Spark can split where one key is hot. Once so few links are left that a
bounded array holds them, one task finishes with union-find.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgefold.llm.shared import settle

#: Links that one task may finish: 16 bytes each in memory.
TASK_LINKS = 1 << 18


def union_find(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Nodes of the links, and the least node of the component of each. Vectorised hooking and pointer jumping."""
    nodes, index = np.unique(np.concatenate([a, b]), return_inverse=True)
    parent, x, y = np.arange(len(nodes)), index[: len(a)], index[len(a) :]
    while len(x):
        low, high = np.minimum(parent[x], parent[y]), np.maximum(parent[x], parent[y])
        np.minimum.at(parent, high, low)
        while (up := parent[parent] != parent).any():
            parent[up] = parent[parent[up]]
        apart = parent[x] != parent[y]
        x, y = x[apart], y[apart]
    return nodes, nodes[parent]


def _finish(links: DataFrame) -> DataFrame:
    def run(batches):
        got = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches]
        if got:
            nodes, least = union_find(np.concatenate([x for x, _ in got]), np.concatenate([x for _, x in got]))
            yield pa.RecordBatch.from_arrays([pa.array(nodes), pa.array(least)], ["node", "least"])

    return links.coalesce(1).mapInArrow(run, "node long, least long")


def _to_roots(step: DataFrame) -> DataFrame:
    while True:
        further = step.select(F.col("node").alias("least"), F.col("least").alias("root"))
        jumped = settle(step.join(further, "least").select("node", F.col("root").alias("least"), (F.col("root") != F.col("least")).alias("moved")))
        step = jumped.select("node", "least")
        if jumped.where("moved").isEmpty():
            return step


def components(links: DataFrame, *, task_links: int = TASK_LINKS) -> DataFrame:
    """(node, component) for each node of the links (a, b): the least node reachable. Nodes without links are left out.

    Null ends and self links are ignored; repeated links count once; no links give no rows.
    """
    left = links.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    left = settle(left.where("a IS NOT NULL AND b IS NOT NULL AND a < b").distinct())
    names: DataFrame | None = None
    while True:
        n = left.count()
        if n <= task_links:
            step = settle(_finish(left))
        else:
            both = left.unionByName(left.select(F.col("b").alias("a"), F.col("a").alias("b")))
            step = settle(both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("b")).select("node", F.least("node", "b").alias("least")))
            step = _to_roots(step)
            ends = [step.select(F.col("node").alias(x), F.col("least").alias(f"least_{x}")) for x in ("a", "b")]
            renamed = left.join(ends[0], "a").join(ends[1], "b")
            renamed = renamed.select(F.least("least_a", "least_b").alias("a"), F.greatest("least_a", "least_b").alias("b"))
            left = settle(renamed.where("a < b").distinct())
        if names is None:
            names = step.select("node", F.col("least").alias("component"))
        else:
            later = step.select(F.col("node").alias("component"), "least")
            names = settle(names.join(later, "component", "left").select("node", F.coalesce("least", "component").alias("component")))
        if n <= task_links:
            return names
