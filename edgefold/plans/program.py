"""Five-step programs: checks, recognition of known patterns, applications and semirings."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from edgefold.functions import steps as S
from edgefold.functions.steps import Step


@dataclass(frozen=True)
class Program:
    """pair makes a vector from x, y and a; fold makes it a scalar; scale changes it; weigh joins it with an operand;
    collect reduces over the neighbours. fold and scale may be left out (None)."""

    pair: Step
    fold: Step | None
    scale: Step | None
    weigh: Step
    collect: Step
    name: str = "program"

    @property
    def reads(self) -> frozenset[str]:
        """Which of x, y, a any step needs. A pair whose result nothing uses is not read."""
        out = set(self.pair.reads)
        for s in (self.fold, self.scale):
            out |= set(s.reads) if s else set()
        out |= {"neighbour": {"y"}, "edge": {"a"}, "pair": set()}[self.weigh.operand]
        return frozenset(out)

    @property
    def scalar_message(self) -> bool:
        return self.fold is not None or (self.scale is not None and self.scale.name == "EDGE")


def check(program: Program) -> Program:
    for part, kind in zip((program.pair, program.fold, program.scale, program.weigh, program.collect), ("pair", "fold", "scale", "weigh", "collect"), strict=True):
        if part is None and kind in ("fold", "scale"):
            continue
        if not isinstance(part, Step) or part.kind != kind:
            raise ValueError(f"{kind} step expected, got {getattr(part, 'kind', part)!r}")
    if program.weigh.operand not in ("neighbour", "edge", "pair"):
        raise ValueError(f"unknown operand {program.weigh.operand}")
    _probe(program)
    return program


def _probe(program: Program, edges: int = 3, d: int = 2) -> None:
    """Run the user's steps on a few made numbers: each must take what its kind gets and give what its kind gives."""
    steps = (program.pair, program.fold, program.scale, program.weigh, program.collect)
    if not any(s is not None and s.name == "USER" for s in steps) or program.pair.vector is not None:
        return
    x, a = np.linspace(0.1, 0.9, edges * d).reshape(edges, d), np.ones((edges, 1))

    def shaped(part, kind, shapes, *args):
        f = part.batch if part.batch is not None else part.element
        try:
            got = np.asarray(f(*args) if part.batch is not None else f(S.ArrayOps, *args))
        except TypeError as e:
            raise ValueError(f"the {kind} step takes {len(args)} arguments: {e}") from e
        if got.shape not in shapes:
            raise ValueError(f"the {kind} step gives shape {got.shape}, expected one of {shapes}")
        return got

    p = shaped(program.pair, "pair", [(edges, d)], x, x[::-1], a)
    h = p
    if program.fold is not None and program.fold.batch is not None:
        h = shaped(program.fold, "fold", [(edges, 1), (edges,)], p).reshape(edges, 1)
    elif program.fold is not None:
        h = S.matrix_fold(program.fold, p, x, x[::-1])
    if program.scale is not None:
        h = shaped(program.scale, "scale", [h.shape, (edges, 1)], h, a)
    w = shaped(program.weigh, "weigh", [(edges, d), h.shape, (edges, 1)], h, {"neighbour": x, "edge": a, "pair": p}[program.weigh.operand])
    if program.collect.batch is not None:
        shaped(program.collect, "collect", [(d,)], np.broadcast_to(w, (edges, d)))


ASSOCIATIVE = {"sum", "max", "min", "mean"}


def check_tiled(program: Program) -> None:
    """Partial results of tiles can be merged if the order of the neighbours does not matter; a mean goes as sum and count."""
    if program.collect.reduce not in ASSOCIATIVE:
        raise ValueError(f"{program.collect.name} can't be merged from tiles")


def check_feature_split(program: Program) -> None:
    """Dimensions can be worked out apart only if no step mixes them: a fold does, unless all that follows is linear."""
    if program.pair.vector is not None or (program.pair.batch is not None):
        raise ValueError("the pair step mixes dimensions")
    if program.fold is not None and not (program.fold.name == "RSUM" and (program.scale is None or program.scale.name == "SCAL")):
        raise ValueError("a scalar from all dimensions passes through a non-linear step")


def recognise(program: Program) -> str:
    """Name of a pattern that has a kernel of its own, or general."""
    pair, fold, scale, weigh = program.pair, program.fold, program.scale, program.weigh
    names = tuple(s.name if s else "NOOP" for s in (pair, fold, scale, weigh))
    plain = all(s is None or (s.batch is None and s.vector is None) for s in (pair, fold, scale, weigh))
    if program.collect.reduce == "user":
        return "user"
    if not plain or weigh.name != "MUL" or program.collect.reduce not in ("sum", "mean"):
        return "general"
    if names[:2] == ("MUL", "RSUM") and scale is not None and weigh.operand == "neighbour":
        return "sigmoid_dot"
    if pair.name in ("ADD", "SUB") and names[1] in ("NORM", "SELFDOT") and scale is not None and fold.params in ((2,), ()) and weigh.operand in ("neighbour", "pair"):
        return "norm_force"
    if names[:3] == ("SEL2ND", "NOOP", "NOOP") and weigh.operand == "edge":
        return "neighbour_sum"
    return "general"


def layout_literal(alpha: float = 0.5) -> Program:
    return Program(S.add(), S.norm(), S.scal(alpha), S.weigh_mul("neighbour"), S.asum(), "layout_literal")


def layout_displacement(k: float = 2.0) -> Program:
    return Program(S.sub(), S.norm(), S.scal(1.0 / k), S.weigh_mul("pair"), S.asum(), "layout_displacement")


def heavy_tail() -> Program:
    return Program(S.sub(), S.self_dot(), S.inverse_tail(), S.weigh_mul("pair"), S.asum(), "heavy_tail")


def sigmoid_embedding() -> Program:
    return Program(S.mul(), S.rsum(), S.sigmoid(), S.weigh_mul("neighbour"), S.asum(), "sigmoid_embedding")


def embedding_pull() -> Program:
    """Neighbours attract in as far as they are not yet alike."""
    return Program(S.mul(), S.rsum(), S.one_minus_sigmoid(), S.weigh_mul("neighbour"), S.asum(), "embedding_pull")


def graph_conv(pool: str = "sum") -> Program:
    collect = {"sum": S.asum, "mean": S.amean, "max": lambda: S.amax("identity"), "min": lambda: S.amin("identity")}[pool]()
    return Program(S.sel2nd(), None, None, S.weigh_mul("edge"), collect, f"graph_conv_{pool}")


def mlp_gnn(weights: S.Mlp, init: str = "zero") -> Program:
    return Program(S.mlp(weights), None, S.sigmoid(), S.weigh_mul("neighbour"), S.amax(init), f"mlp_gnn_{init}")


#: Semirings (addition, multiplication), for neighbour products over them: reduction, and the step that joins h and a.
SEMIRINGS = {
    "plus_times": ("sum", S.weigh_mul),
    "max_times": ("max", S.weigh_mul),
    "min_plus": ("min", S.weigh_add),
    "max_plus": ("max", S.weigh_add),
    "max_min": ("max", S.weigh_min),
    "or_and": ("max", S.weigh_min),
}


def semiring_product(name: str) -> Program:
    """z_u = sum over v of a_uv times y_v, in the semiring. or_and works on values 0 and 1."""
    reduce, weigh = SEMIRINGS[name]
    collect = {"sum": S.asum(), "max": S.amax("identity"), "min": S.amin("identity")}[reduce]
    return Program(S.sel2nd(), None, None, weigh("edge"), collect, f"semiring_{name}")
