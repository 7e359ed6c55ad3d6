"""Minibatch training of node embeddings by fused folds, and classification on what is learned.

Where no rule is given for the update and its negatives, these are ours: edges pull by (1 - sigmoid(x.y)) y, drawn
pairs push by sigmoid(x.y) y, and a vertex moves by the learning rate times the difference.
"""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgefold.operators import edges as E
from edgefold.operators.fused import fused_fold
from edgefold.operators.two_phase import tensor_operations, two_phase
from edgefold.plans.program import embedding_pull, sigmoid_embedding
from edgefold.sources import features


#: How an epoch's folds are done: the fused one, messages stored between two phases, or generic tensor operations.
METHODS = {"fused": fused_fold, "two_phase": two_phase, "tensor": tensor_operations}


def _move(x: DataFrame, pull: DataFrame, push: DataFrame, lr: float) -> DataFrame:
    p, n = pull.select(F.col("u").alias("id"), F.col("z").alias("pull")), push.select(F.col("u").alias("id"), F.col("z").alias("push"))
    both = x.join(p, "id", "left").join(n, "id", "left")
    zero = F.transform("x", lambda v: v * 0.0)
    step = F.zip_with(F.coalesce("pull", zero), F.coalesce("push", zero), lambda a, b: (a - b) * lr)
    return both.select("id", F.zip_with("x", step, lambda v, s: v + s).alias("x"))


def epoch(edges: DataFrame, x: DataFrame, *, n: int, d: int, batches: int, lr: float, negatives: int, seed: int, checkpoint_every: int = 1, method: str = "fused", strategy: str = "relational") -> DataFrame:
    """One pass over all targets, in batches by a digest of the id; returns the new features (id, x).

    n: ids are 0..n-1. The features are checkpointed after every `checkpoint_every` batches: each batch reads them five times, so an uncut
    lineage would grow fivefold with each.
    """
    fold = METHODS[method]
    options = {"strategy": strategy} if method == "fused" else {}
    ids = x.select(F.col("id").alias("u"))
    for k in range(batches):
        mine = ids.where(E.drawn(seed, "u") % batches == k)
        near = E.slice_rows(edges, mine)
        far = E.negatives(mine, n, negatives, seed * 1000 + k).where("u <> v").withColumn("a", F.lit(1.0))
        pull = fold(near, x, x, embedding_pull(), d=d, **options)
        push = fold(far, x, x, sigmoid_embedding(), d=d, **options)
        x = _move(x, pull, push, lr)
        if (k + 1) % checkpoint_every == 0 or k + 1 == batches:
            x = x.checkpoint()
    return x


def train_embedding(edges: DataFrame, ids: DataFrame, *, d: int = 32, batches: int = 1, epochs: int = 1, lr: float = 0.05, negatives: int = 5, seed: int = 1, checkpoint_every: int = 1, method: str = "fused", strategy: str = "relational"):
    """(features, seconds of each epoch). ids: (u), which run from 0 to n - 1."""
    from edgefold.operators.two_phase import _shared

    _shared(edges.sparkSession)
    n, x, seconds = ids.count(), features.digest(ids.withColumnRenamed("u", "id"), d, seed).checkpoint(), []
    edges = edges.persist()
    for e in range(epochs):
        t = time.time()
        x = epoch(edges, x, n=n, d=d, batches=batches, lr=lr, negatives=negatives, seed=seed + e, checkpoint_every=checkpoint_every, method=method, strategy=strategy)
        seconds.append(time.time() - t)
    edges.unpersist()
    return x, seconds


def loss(edges: DataFrame, x: DataFrame) -> float:
    """Mean of -log sigmoid(x.y) over the edges."""
    from edgefold.functions.vectors import dot

    both = edges.join(x.select(F.col("id").alias("u"), "x"), "u").join(x.select(F.col("id").alias("v"), F.col("x").alias("y")), "v")
    return both.select(F.avg(F.log1p(F.exp(-dot("x", "y"))))).first()[0]


def centroids(x: DataFrame, labels: DataFrame, d: int) -> DataFrame:
    both = x.join(labels, "id")
    return both.groupBy("label").agg(F.array(*[F.avg(F.col("x").getItem(i)) for i in range(d)]).alias("c"))


def classify(x: DataFrame, train: DataFrame, d: int) -> DataFrame:
    """(id, pred): the label with the most alike centroid (cosine), the least label among equals."""
    from edgefold.functions.vectors import cosine

    c = F.broadcast(centroids(x, train, d))  # one row for each label
    scored = x.crossJoin(c).select("id", F.struct(F.round(cosine("x", "c"), 9).alias("s"), (-F.col("label")).alias("n")).alias("k"))
    return scored.groupBy("id").agg((-F.max("k")["n"]).cast("int").alias("pred"))


def f1_micro(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """n, f1: true positives over these and half the false ones, over all classes; accuracy, as each has one label."""
    both = pred.join(truth, "id")
    hit = F.sum((F.col("pred") == F.col("label")).cast("double"))
    miss = F.sum((F.col("pred") != F.col("label")).cast("double"))
    return both.agg(F.count("*").alias("n"), F.round(hit / (hit + 0.5 * (miss + miss)), 9).alias("f1"))
