"""SQL of a fold in the long layout, for an engine that knows nothing of this library."""

from __future__ import annotations

from edgefold.functions.steps import Mlp
from edgefold.plans.program import Program
from edgefold.sources import features, graphs


def _number(v: float) -> str:
    return f"({v!r})::DOUBLE"


def _mlp_sql(m: Mlp) -> str:
    """Pair values (u, v, a, i, xv, yv, p) of a network, its weights given as a table of constants."""
    h, d = len(m.b1), len(m.b2)
    w1 = ", ".join(f"({k}, {j}, {_number(m.w1[k][j])})" for k in range(2 * d) for j in range(h))
    w2 = ", ".join(f"({j}, {i}, {_number(m.w2[j][i])})" for j in range(h) for i in range(d))
    b1 = ", ".join(f"({j}, {_number(b)})" for j, b in enumerate(m.b1))
    b2 = ", ".join(f"({i}, {_number(b)})" for i, b in enumerate(m.b2))
    return f""",
    w1(k, j, w) AS (VALUES {w1}), w2(j, i, w) AS (VALUES {w2}), b1(j, b) AS (VALUES {b1}), b2(i, b) AS (VALUES {b2}),
    hidden AS (SELECT u, v, j, greatest(sum(t) + any_value(b), 0) AS h FROM (
        SELECT e.u, e.v, w1.j, e.xv * w1.w AS t FROM pairs e JOIN w1 ON w1.k = e.i
        UNION ALL SELECT e.u, e.v, w1.j, e.yv * w1.w FROM pairs e JOIN w1 ON w1.k = e.i + {d}) JOIN b1 USING (j) GROUP BY u, v, j),
    p AS (SELECT e.u, e.v, e.a, e.i, e.xv, e.yv, o.p FROM pairs e JOIN (
        SELECT hidden.u, hidden.v, w2.i, sum(hidden.h * w2.w) + any_value(b2.b) AS p FROM hidden JOIN w2 USING (j) JOIN b2 ON b2.i = w2.i GROUP BY 1, 2, 3) o USING (u, v, i))"""


def fold_sql(program: Program, edges: str, targets: str, x: str, y: str, d: int, digits: int = 6) -> str:
    """edges: (u, v, a), one for each pair; x and y: (id, i, val)."""
    pair = _mlp_sql(program.pair.vector) if program.pair.vector is not None else f", p AS (SELECT u, v, a, i, xv, yv, {program.pair.sql} AS p FROM pairs)"
    if program.fold is not None:
        s = program.fold.sql.format("p")
        h = program.scale.sql.format(s) if program.scale else s
        if program.scale is not None and program.scale.name == "EDGE":
            h = "any_value(a)"
        messages = f", h AS (SELECT u, v, {h} AS h FROM p GROUP BY u, v), m AS (SELECT p.*, h.h FROM p JOIN h USING (u, v))"
    else:
        messages = f", m AS (SELECT *, {program.scale.sql.format('p') if program.scale else 'p'} AS h FROM p)"
    operand = {"neighbour": "yv", "edge": "a", "pair": "p"}[program.weigh.operand]
    w = program.weigh.sql.format(h="h", o=operand)
    reduce = {"sum": "sum", "mean": "avg", "max": "max", "min": "min"}[program.collect.reduce]
    start = "greatest(z, 0)" if (program.collect.reduce, program.collect.init) == ("max", "zero") else "z"
    return f"""WITH edges AS ({edges}), x AS ({x}), y AS ({y}),
    pairs AS (SELECT e.u, e.v, e.a, y.i, x.val AS xv, y.val AS yv FROM edges e JOIN y ON y.id = e.v JOIN x ON x.id = e.u AND x.i = y.i WHERE e.a <> 0){pair}{messages},
    z AS (SELECT u, i, {reduce}({w}) AS z FROM m GROUP BY u, i)
    SELECT t.u, t.i, round(coalesce({start}, 0), {digits}) + 0::DOUBLE AS z FROM (SELECT u, range::INTEGER AS i FROM ({targets}), range({d})) t LEFT JOIN z ON z.u = t.u AND z.i = t.i"""


def graph_fold_sql(graph: str, program: Program, d: int = 8, digits: int = 6, seeds: tuple[int, int] = (0, 0)) -> str:
    """The fold of a graph on the tables with hashed features."""
    targets, sources = graphs.targets_sql(graph), graphs.sources_sql(graph)
    x = features.hashed_sql(f"SELECT u AS id FROM ({targets})", d, seeds[0])
    return fold_sql(program, graphs.SQL[graph], targets, x, features.hashed_sql(sources, d, seeds[1]), d, digits)
