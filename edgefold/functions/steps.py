"""The replaceable steps of a fold.

A step is written once, on elements, against a namespace of functions; columns and NumPy arrays both provide one. It then
runs on lists of columns (one for each dimension, inside generated code), on array columns (higher-order functions) and
on matrices of edges by dimensions.
"""

from __future__ import annotations

import functools
from collections.abc import Callable
from dataclasses import dataclass, field
from typing import Any

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


class ColumnOps:
    exp, sqrt, abs, greatest, least, tanh, log1p = map(staticmethod, (F.exp, F.sqrt, F.abs, F.greatest, F.least, F.tanh, F.log1p))

    @staticmethod
    def where(test, a, b):
        return F.when(test, a).otherwise(b)

    @staticmethod
    def const(v):
        return F.lit(float(v))


class ArrayOps:
    sqrt, abs, greatest, least, tanh, log1p = map(staticmethod, (np.sqrt, np.abs, np.maximum, np.minimum, np.tanh, np.log1p))

    @staticmethod
    def exp(x):
        return np.exp(np.clip(x, -700, 700))

    @staticmethod
    def where(test, a, b):
        return np.where(test, a, b)

    @staticmethod
    def const(v):
        return float(v)


@dataclass(frozen=True)
class Step:
    """kind: pair, fold, scale, weigh or collect. reads: which of x, y, a it needs.

    element: of a pair (ops, x, y, a), a scale (ops, s, a), a weigh (ops, h, operand).
    A fold maps elements, combines them from a start and finishes; a collect names the reduction over the neighbours.
    A fold of the two ends (rather than of the pair vector) maps x and y (`ends`); the pair vector stays for weigh.
    A user's collect has a reduction of columns (`aggregate`), or of one target's messages as a matrix (`batch`).
    sql: the same on element names, for SQL engines.
    """

    kind: str
    name: str
    element: Callable[..., Any] | None = None
    reads: frozenset[str] = frozenset()
    sql: str = ""
    fold_map: Callable[..., Any] = field(default=lambda ops, v: v)
    fold_join: Callable[..., Any] | None = None
    fold_start: float = 0.0
    fold_end: Callable[..., Any] = field(default=lambda ops, v: v)
    operand: str = "neighbour"
    reduce: str = "sum"
    init: str = "zero"
    params: tuple = ()
    vector: Any = None
    batch: Callable[..., Any] | None = None
    ends: Callable[..., Any] | None = None
    aggregate: Callable[..., Any] | None = None


NOOP = None


def _pair(name, f, reads, sql):
    return Step("pair", name, f, frozenset(reads), sql)


def add():
    return _pair("ADD", lambda o, x, y, a: x + y, "xy", "xv + yv")


def mul():
    return _pair("MUL", lambda o, x, y, a: x * y, "xy", "xv * yv")


def sel2nd():
    return _pair("SEL2ND", lambda o, x, y, a: y, "y", "yv")


def sel1st():
    return _pair("SEL1ST", lambda o, x, y, a: x, "x", "xv")


def sub():
    """From the target to the neighbour."""
    return _pair("SUB", lambda o, x, y, a: y - x, "xy", "yv - xv")


def pair_min():
    return _pair("PMIN", lambda o, x, y, a: o.least(x, y), "xy", "least(xv, yv)")


def pair_max():
    return _pair("PMAX", lambda o, x, y, a: o.greatest(x, y), "xy", "greatest(xv, yv)")


@dataclass(frozen=True)
class Mlp:
    """relu(concat(x, y) W1 + b1) W2 + b2, with hidden units and weights as given (rows of tuples)."""

    w1: tuple[tuple[float, ...], ...]
    b1: tuple[float, ...]
    w2: tuple[tuple[float, ...], ...]
    b2: tuple[float, ...]

    def wide(self, x: list[Column], y: list[Column]) -> list[Column]:
        both = [*x, *y]
        hidden = [F.greatest(sum((F.lit(w) * v for w, v in zip(row, both, strict=True)), F.lit(b)), F.lit(0.0)) for row, b in zip(zip(*self.w1, strict=True), self.b1, strict=True)]
        return [sum((F.lit(w) * h for w, h in zip(row, hidden, strict=True)), F.lit(b)) for row, b in zip(zip(*self.w2, strict=True), self.b2, strict=True)]

    def matrix(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        hidden = np.maximum(np.hstack([x, y]) @ np.asarray(self.w1) + np.asarray(self.b1), 0.0)
        return hidden @ np.asarray(self.w2) + np.asarray(self.b2)


def weights_by_rule(d: int, hidden: int = 4) -> Mlp:
    """Small weights from a rule on integers, the same in every engine."""
    w1 = tuple(tuple(((k * 31 + j * 17) % 13 - 6) / 10 for j in range(hidden)) for k in range(2 * d))
    w2 = tuple(tuple(((j * 29 + i * 7) % 11 - 5) / 10 for i in range(d)) for j in range(hidden))
    return Mlp(w1, tuple((j % 3 - 1) / 10 for j in range(hidden)), w2, tuple((i % 5 - 2) / 10 for i in range(d)))


def mlp(weights: Mlp):
    return Step("pair", "MLP", None, frozenset("xy"), "", vector=weights)


def rsum():
    return Step("fold", "RSUM", fold_join=lambda o, p, q: p + q, sql="sum({})")


def rmul():
    return Step("fold", "RMUL", fold_join=lambda o, p, q: p * q, fold_start=1.0, sql="product({})")


def norm(p: float = 2):
    """A vector norm: 1, 2 or infinity."""
    if p == 1:
        return Step("fold", "NORM", fold_map=lambda o, v: o.abs(v), fold_join=lambda o, a, b: a + b, sql="sum(abs({}))", params=(p,))
    if p == 2:
        return Step("fold", "NORM", fold_map=lambda o, v: v * v, fold_join=lambda o, a, b: a + b, fold_end=lambda o, v: o.sqrt(v), sql="sqrt(sum(({0}) * ({0})))", params=(p,))
    if p == float("inf"):
        return Step("fold", "NORM", fold_map=lambda o, v: o.abs(v), fold_join=lambda o, a, b: o.greatest(a, b), sql="max(abs({}))", params=(p,))
    raise ValueError("p is 1, 2 or infinity")


def self_dot():
    return Step("fold", "SELFDOT", fold_map=lambda o, v: v * v, fold_join=lambda o, a, b: a + b, sql="sum(({0}) * ({0}))")


def fold_max():
    return Step("fold", "FMAX", fold_join=lambda o, a, b: o.greatest(a, b), fold_start=float("-inf"), sql="max({})")


def _of_ends(name, f, reads, sql):
    return Step("fold", name, reads=frozenset(reads), fold_join=lambda o, p, q: p + q, sql=sql, ends=f)


def dot_ends():
    """The dot product of both ends, whatever the pair vector is."""
    return _of_ends("DOT", lambda o, x, y: x * y, "xy", "sum(xv * yv)")


def sum_left():
    return _of_ends("LSUM", lambda o, x, y: x, "x", "sum(xv)")


def sum_right():
    return _of_ends("NSUM", lambda o, x, y: y, "y", "sum(yv)")


def _scale(name, f, sql, reads="", params=()):
    return Step("scale", name, f, frozenset(reads), sql, params=params)


def sigmoid():
    return _scale("SIGMOID", lambda o, s, a: 1.0 / (1.0 + o.exp(-s)), "1.0 / (1.0 + exp(-({0})))")


def scal(alpha: float):
    return _scale("SCAL", lambda o, s, a: s * float(alpha), f"({{0}}) * {float(alpha)}", params=(alpha,))


def inverse_tail():
    """1 / (1 + s): forces that fall off with squared distance."""
    return _scale("TAIL", lambda o, s, a: 1.0 / (1.0 + s), "1.0 / (1.0 + ({0}))")


def one_minus_sigmoid():
    return _scale("PULL", lambda o, s, a: 1.0 / (1.0 + o.exp(s)), "1.0 / (1.0 + exp({0}))")


def edge_scale():
    """The edge's weight, whatever came before."""
    return _scale("EDGE", lambda o, s, a: a, "a", reads="a")


def scale_by(name: str, f, sql: str = ""):
    return _scale(name, f, sql)


def weigh_mul(operand: str = "neighbour"):
    return Step("weigh", "MUL", lambda o, h, v: h * v, sql="({h}) * ({o})", operand=operand)


def weigh_add(operand: str = "neighbour"):
    return Step("weigh", "ADD", lambda o, h, v: h + v, sql="({h}) + ({o})", operand=operand)


def weigh_sel2nd(operand: str = "neighbour"):
    return Step("weigh", "SEL2ND", lambda o, h, v: v + h * 0.0, sql="({o})", operand=operand)


def weigh_min(operand: str = "edge"):
    return Step("weigh", "MIN", lambda o, h, v: o.least(h, v), sql="least({h}, {o})", operand=operand)


def weigh_sigmoid(operand: str = "neighbour"):
    """The sigmoid of the message, times the operand."""
    return Step("weigh", "SIGMUL", lambda o, h, v: v / (1.0 + o.exp(-h)), sql="({o}) / (1.0 + exp(-({h})))", operand=operand)


def _collect(name, reduce, init="zero"):
    if init not in ("zero", "identity"):
        raise ValueError("init is zero or identity")
    return Step("collect", name, reduce=reduce, init=init)


def asum():
    return _collect("ASUM", "sum")


def amax(init: str = "zero"):
    return _collect("AMAX", "max", init)


def amin(init: str = "identity"):
    return _collect("AMIN", "min", init)


def amean():
    return _collect("AMEAN", "mean")


def step(kind: str, expr=None, batch=None, *, reads: str = "xy", name: str = "USER", operand: str = "neighbour", sql: str = "") -> Step:
    """A user's step. expr: on elements (ops, ...), for columns and matrices; batch: on matrices alone.

    What a pair gets is x, y and a; a scale s and a; a weigh h and its operand; a fold the matrix, and gives one column.
    For a collect, expr makes an aggregate of a column of messages, for the relational strategies, and batch reduces the
    matrix of one target's messages to a row, for the packed one; either or both.
    """
    if kind == "collect":
        if expr is None and batch is None:
            raise ValueError("a collect needs expr or batch")
        return Step(kind, name, reduce="user", init="identity", aggregate=expr, batch=batch, sql=sql)
    if (expr is None) == (batch is None):
        raise ValueError("give one of expr and batch")
    if kind not in ("pair", "fold", "scale", "weigh"):
        raise ValueError(f"no user steps of kind {kind}")
    if kind == "fold" and expr is not None:
        raise ValueError("a fold is given as batch, or built from RSUM and the like")
    return Step(kind, name, expr, frozenset(reads), sql, operand=operand, batch=batch)


def wide_fold(f: Step, values: list[Column], x: list[Column], y: list[Column]) -> Column:
    mapped = [f.fold_map(ColumnOps, v) for v in values] if f.ends is None else [f.ends(ColumnOps, a, b) for a, b in zip(x, y, strict=True)]
    return f.fold_end(ColumnOps, functools.reduce(functools.partial(f.fold_join, ColumnOps), mapped))


def array_fold(f: Step, values: Column, x: Column, y: Column) -> Column:
    if f.ends is not None:
        values = F.zip_with(x, y, lambda a, b: f.ends(ColumnOps, a, b))
    joined = F.aggregate(values, F.lit(f.fold_start), lambda acc, v: f.fold_join(ColumnOps, acc, f.fold_map(ColumnOps, v)))
    return f.fold_end(ColumnOps, joined)


def matrix_fold(f: Step, values: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    if f.batch is not None:
        return np.asarray(f.batch(values)).reshape(len(values), 1)
    mapped = f.fold_map(ArrayOps, values) if f.ends is None else f.ends(ArrayOps, x, y)
    out = functools.reduce(functools.partial(f.fold_join, ArrayOps), [mapped[:, i] for i in range(mapped.shape[1])])
    return f.fold_end(ArrayOps, out)[:, None]
