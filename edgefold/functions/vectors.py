"""Vector functions on array columns, activations, sparse vectors."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _sum(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda acc, v: acc + v)


def dot(x, y) -> Column:
    return _sum(F.zip_with(x, y, lambda a, b: a * b))


def norm(x, p: float = 2) -> Column:
    if p == 1:
        return _sum(F.transform(x, F.abs))
    if p == 2:
        return F.sqrt(_sum(F.transform(x, lambda v: v * v)))
    return F.array_max(F.transform(x, F.abs))


def cosine(x, y) -> Column:
    return dot(x, y) / (norm(x) * norm(y))


def dist(x, y) -> Column:
    return norm(F.zip_with(x, y, lambda a, b: a - b))


def axpy(alpha: float, x, y) -> Column:
    return F.zip_with(x, y, lambda a, b: a * float(alpha) + b)


def hadamard(x, y) -> Column:
    return F.zip_with(x, y, lambda a, b: a * b)


def normalise(x) -> Column:
    n = norm(x)
    return F.transform(x, lambda v: v / n)


def matvec(x, weights: list[list[float]]) -> Column:
    """x times a matrix that has a row for each of x's elements."""
    x = F.col(x) if isinstance(x, str) else x
    return F.array(*[sum((x.getItem(k) * float(row[j]) for k, row in enumerate(weights)), F.lit(0.0)) for j in range(len(weights[0]))])


ACTIVATIONS = {
    "identity": lambda v: v,
    "sigmoid": lambda v: 1.0 / (1.0 + F.exp(-v)),
    "tanh": F.tanh,
    "relu": lambda v: F.greatest(v, F.lit(0.0)),
    "leaky": lambda v: F.when(v > 0, v).otherwise(v * 0.01),
    "softplus": lambda v: F.greatest(v, F.lit(0.0)) + F.log1p(F.exp(-F.abs(v))),
}


def dense(z: DataFrame, weights: list[list[float]], bias: list[float], activation: str = "relu") -> DataFrame:
    """(u, z): a layer on each row. Weights are constants of the plan, fit for layers of a few thousand weights."""
    act = ACTIVATIONS[activation]
    product = matvec("z", weights)
    out = F.transform(F.zip_with(product, F.array(*[F.lit(float(b)) for b in bias]), lambda a, b: a + b), lambda v: act(v))
    return z.select("u", out.alias("z"))


def sparse_vector(tokens: DataFrame) -> DataFrame:
    """(doc_id, terms map): counts by token."""
    return tokens.groupBy("doc_id").agg(F.map_from_entries(F.collect_list(F.struct("token", "a"))).alias("terms"))


def sparse_dot(x, y) -> Column:
    both = F.map_zip_with(x, y, lambda k, a, b: F.coalesce(a, F.lit(0)) * F.coalesce(b, F.lit(0)))
    return F.aggregate(F.map_values(both), F.lit(0).cast("long"), lambda acc, v: acc + v)
