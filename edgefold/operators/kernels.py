"""Kernels in workers: from a target's features and those of its neighbours to its result, on arrays.

A specialised kernel knows its program: targets with as many neighbours each form one stack, so that a target's features
are read once, its result is written once, and no pair vector or weighed message is ever stored. Gathered neighbour
features stay in cache between the two halves, as only so many edges are worked on at a time.
"""

from __future__ import annotations

import functools
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np

from edgefold.functions import steps as S
from edgefold.plans.program import Program

REDUCE = {"sum": np.add, "mean": np.add, "max": np.maximum, "min": np.minimum}


@dataclass(frozen=True)
class Blocking:
    """What is held in place.

    vectors: x (a target's features, read once for all its edges), y (a gathered neighbour, for both halves of the
    message) and z (the result, written once); what is not named is fetched or written for each edge. dims: dimensions
    of the result worked out at a time (None: all). limit: bytes of gathered neighbours at a time.
    """

    vectors: tuple[str, ...] = ("x", "y", "z")
    dims: int | None = None
    limit: int = 1 << 20


#: Blocking by the greatest d of a range: narrow rows fit a cache many at a time, wide ones are cut.
RANGES = ((32, Blocking(limit=1 << 19)), (128, Blocking(limit=1 << 20)), (512, Blocking(limit=1 << 20)))


def blocking_for(d: int) -> Blocking:
    return next((b for most, b in RANGES if d <= most), Blocking(dims=256, limit=1 << 21))


def matrix_message(program: Program, x: np.ndarray, y: np.ndarray, a: np.ndarray) -> np.ndarray:
    """Weighed messages of edges by dimensions. a is a column."""
    ops = S.ArrayOps

    def run(s, *args):
        return s.batch(*args) if s.batch is not None else s.element(ops, *args)

    p = program.pair.vector.matrix(x, y) if program.pair.vector is not None else run(program.pair, x, y, a)
    h = S.matrix_fold(program.fold, p, x, y) if program.fold else p
    h = run(program.scale, h, a) if program.scale else h
    operand = {"neighbour": y, "edge": a, "pair": p}[program.weigh.operand]
    return np.broadcast_to(run(program.weigh, h, operand), y.shape)


# What a specialised kernel gives for a stack: h (targets by neighbours), and the operand (targets by neighbours by d).


def _dot(program: Program, x, y, a):
    s = np.matmul(y, x[:, :, None])[:, :, 0]
    return program.scale.element(S.ArrayOps, s, a), y


def _force(program: Program, x, y, a):
    p = y + x[:, None, :] if program.pair.name == "ADD" else y - x[:, None, :]
    s = np.einsum("rkd,rkd->rk", p, p)
    s = np.sqrt(s) if program.fold.name == "NORM" else s
    return program.scale.element(S.ArrayOps, s, a), p if program.weigh.operand == "pair" else y


def _sum(program: Program, x, y, a):
    return a, y


KERNELS: dict[str, Callable] = {"sigmoid_dot": _dot, "norm_force": _force, "neighbour_sum": _sum}


def stacks(sizes: np.ndarray, starts: np.ndarray, most: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Targets with equally many edges, and the positions of these edges (targets by edges), at most `most` at a time.

    A target with more than `most` edges comes several times.
    """
    order = np.argsort(sizes, kind="stable")
    cuts = np.flatnonzero(np.diff(sizes[order], prepend=-1))
    for a, e in zip(cuts.tolist(), [*cuts[1:].tolist(), len(order)], strict=True):
        k = int(sizes[order[a]])
        if not k:
            continue
        step = max(1, most // k)
        for low in range(a, e, step):
            rows = order[low : min(e, low + step)]
            for at in range(0, k, most):
                yield rows, starts[rows][:, None] + np.arange(at, min(k, at + most))


def _specialised(pattern: str, d: int, blocking: Blocking, kind):
    first, size = KERNELS[pattern], np.dtype(kind).itemsize
    most = max(16, blocking.limit // (size * d))
    step = blocking.dims or d

    def run(program, x, y_all, index, a, sizes, starts):
        out = np.zeros((len(sizes), d), dtype=kind)
        for rows, at in stacks(sizes, starts, most):
            y = y_all[index[at]]
            h, operand = first(program, x[rows] if x is not None else None, y, a[at])
            if "y" not in blocking.vectors and operand is y:
                operand = y_all[index[at]]
            for low in range(0, d, step):
                out[rows, low : low + step] += np.matmul(h[:, None, :], operand[:, :, low : low + step])[:, 0]
        return out

    return run


def _unblocked(pattern: str, d: int, blocking: Blocking, kind):
    """Specialised, but with targets' features gathered or results written edge by edge."""
    first, size = KERNELS[pattern], np.dtype(kind).itemsize
    most = max(16, blocking.limit // (size * d))

    def run(program, x, y_all, index, a, sizes, starts):
        of = np.repeat(np.arange(len(sizes)), sizes)
        out = np.zeros((len(sizes), d), dtype=kind)
        for low in range(0, len(of), most):
            part = slice(low, low + most)
            y = y_all[index[part]][:, None, :]
            h, operand = first(program, x[of[part]] if x is not None else None, y, a[part, None])
            weighed = (h[:, :, None] * operand)[:, 0]
            if "z" in blocking.vectors:
                head = np.flatnonzero(np.diff(of[part], prepend=-1))
                out[of[part][head]] += np.add.reduceat(weighed, head, axis=0)
            else:
                np.add.at(out, of[part], weighed)
        return out

    return run


def _general(d: int, blocking: Blocking, kind):
    """Any program: step by step, each a matrix of edges."""
    most = max(16, blocking.limit // (np.dtype(kind).itemsize * d))

    def run(program, x, y_all, index, a, sizes, starts):
        reduce = REDUCE[program.collect.reduce]
        unit = {np.add: 0.0, np.maximum: -np.inf, np.minimum: np.inf}[reduce]
        of = np.repeat(np.arange(len(sizes)), sizes)
        out = np.full((len(sizes), d), unit, dtype=kind)
        for low in range(0, len(of), most):
            part = slice(low, low + most)
            y, targets = y_all[index[part]], of[part]
            xs = x[targets] if x is not None else np.zeros_like(y)
            message = np.ascontiguousarray(matrix_message(program, xs, y, a[part, None]), dtype=kind)
            head = np.flatnonzero(np.diff(targets, prepend=-1))
            out[targets[head]] = reduce(out[targets[head]], reduce.reduceat(message, head, axis=0))
        return out

    return run


def _user(d: int, kind):
    """A user's reduction: all messages of a target at once."""

    def run(program, x, y_all, index, a, sizes, starts):
        out = np.zeros((len(sizes), d), dtype=kind)
        for i, (k, at) in enumerate(zip(sizes.tolist(), starts.tolist(), strict=True)):
            if k:
                y = y_all[index[at : at + k]]
                xs = np.repeat(x[i : i + 1], k, axis=0) if x is not None else np.zeros_like(y)
                out[i] = program.collect.batch(matrix_message(program, xs, y, a[at : at + k, None]))
        return out

    return run


@functools.lru_cache(maxsize=256)
def generate(pattern: str, d: int, blocking: Blocking | None = None, dtype: str = "double"):
    """The kernel of a pattern: run(program, x, y_all, index, a, sizes, starts) gives a row for each target.

    x: a row for each target, or None. index: rows of y_all, one for each edge; the edges of target i are sizes[i] from
    starts[i] on. Made once for each pattern, d, blocking and type. Programs without a pattern get the general kernel.
    """
    kind, blocking = np.float32 if dtype == "float" else np.float64, blocking or blocking_for(d)
    if pattern == "user":
        return _user(d, kind)
    if pattern not in KERNELS:
        return _general(d, blocking, kind)
    held = {"x", "z"} <= set(blocking.vectors)
    return (_specialised if held else _unblocked)(pattern, d, blocking, kind)
