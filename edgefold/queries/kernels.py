"""Queries of methods, steps, applications, baselines and measures."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgefold.functions import steps as S
from edgefold.operators import partition, two_phase
from edgefold.operators.fused import fused_fold, to_long
from edgefold.plans import cost, program as P
from edgefold.queries.oracle import fold_sql, graph_fold_sql
from edgefold.sources import features, graphs

D = 8
QUERIES: dict = {}
ORACLE: dict[str, str] = {}


def inputs(spark, sf_dir, graph, d=D):
    """edges, x, y, targets with hashed features."""
    t = graphs.targets(spark, sf_dir, graph)
    x = features.hashed(t.withColumnRenamed("u", "id"), d)
    return graphs.edges(spark, sf_dir, graph), x, features.hashed(graphs.sources(spark, sf_dir, graph), d), t


def fold_query(name, graph, program, *, d=D, digits=6, run=fused_fold, **options):
    def query(spark, sf_dir) -> DataFrame:
        e, x, y, t = inputs(spark, sf_dir, graph, d)
        return to_long(run(e, x, y, program, d=d, targets=t, **options), digits)

    QUERIES[name] = query
    ORACLE[name] = graph_fold_sql(graph, program, d, digits)


# The core method in its strategies.
fold_query("fused_general_g1", "g1", P.sigmoid_embedding(), strategy="array", specialise=False)
fold_query("sigmoid_embedding_g1", "g1", P.sigmoid_embedding(), strategy="relational")
fold_query("sigmoid_embedding_g2", "g2", P.sigmoid_embedding())
fold_query("sigmoid_embedding_g3", "g3", P.sigmoid_embedding())
fold_query("fused_packed_g1", "g1", P.sigmoid_embedding(), strategy="packed")
fold_query("fused_packed_general_g1", "g1", P.sigmoid_embedding(), strategy="packed", specialise=False)
fold_query("fused_blocked_g1", "g1", P.sigmoid_embedding(), strategy="packed", block=512)
fold_query("fused_tiled_g1", "g1", P.sigmoid_embedding(), strategy="tiled")
fold_query("fused_tiled_mean_g4", "g4", P.graph_conv("mean"), digits=10, strategy="tiled")
fold_query("fused_d64_g4", "g4", P.sigmoid_embedding(), d=64, strategy="packed")
# Applications.
fold_query("layout_literal_g4", "g4", P.layout_literal())
fold_query("layout_literal_g7", "g7", P.layout_literal())
fold_query("layout_displacement_g4", "g4", P.layout_displacement(), d=2)
fold_query("layout_packed_g4", "g4", P.layout_displacement(), strategy="packed")
fold_query("heavy_tail_g4", "g4", P.heavy_tail(), strategy="packed")
for pool in ("sum", "mean", "max", "min"):
    fold_query(f"graph_conv_{pool}_g1", "g1", P.graph_conv(pool), digits=10 if pool == "mean" else 6)
fold_query("graph_conv_sum_g6", "g6", P.graph_conv("sum"))
fold_query("graph_conv_sum_g9", "g9", P.graph_conv("sum"))
fold_query("graph_conv_sum_g11", "g11", P.graph_conv("sum"))
fold_query("graph_conv_sum_g12", "g12", P.graph_conv("sum"))
fold_query("graph_conv_packed_g3", "g3", P.graph_conv("sum"), strategy="packed")
for init in ("zero", "identity"):
    fold_query(f"mlp_gnn_g4_{init}", "g4", P.mlp_gnn(S.weights_by_rule(D), init))
fold_query("mlp_gnn_packed_g4", "g4", P.mlp_gnn(S.weights_by_rule(D), "zero"), strategy="packed")
# Baselines.
fold_query("two_phase_sigmoid_g1", "g1", P.sigmoid_embedding(), run=two_phase.two_phase)
fold_query("two_phase_layout_g4", "g4", P.layout_displacement(), run=two_phase.two_phase)
fold_query("two_phase_graph_conv_g1", "g1", P.graph_conv("sum"), run=two_phase.two_phase)
fold_query("two_phase_mlp_g4", "g4", P.mlp_gnn(S.weights_by_rule(D)), run=two_phase.two_phase)
fold_query("tensor_sigmoid_g4", "g4", P.sigmoid_embedding(), run=two_phase.tensor_operations)
fold_query("dense_reference_g10", "g10", P.sigmoid_embedding(), run=two_phase.dense_reference)
fold_query("vendor_product_g3", "g3", P.graph_conv("sum"), run=lambda e, x, y, p, d, targets: two_phase.complete(two_phase.vendor_product(e, y, d), targets, d))

# Steps, one at a time, on the hand-sized graph.
_BASE = {"pair": S.mul(), "fold": S.rsum(), "scale": S.sigmoid(), "weigh": S.weigh_mul(), "collect": S.asum()}


def step_program(**changes):
    return P.Program(**(_BASE | changes))


_STEPS = {
    "step_add": {"pair": S.add()}, "step_mul": {}, "step_sel2nd": {"pair": S.sel2nd()}, "step_sel1st": {"pair": S.sel1st()}, "step_sub": {"pair": S.sub()},
    "step_pair_min": {"pair": S.pair_min()}, "step_pair_max": {"pair": S.pair_max()}, "step_mlp": {"pair": S.mlp(S.weights_by_rule(D)), "fold": None},
    "step_rsum": {"scale": None}, "step_rmul": {"fold": S.rmul(), "scale": S.scal(1000.0)}, "step_norm": {"pair": S.add(), "fold": S.norm(), "scale": None},
    "step_norm1": {"pair": S.add(), "fold": S.norm(1), "scale": None}, "step_norm_inf": {"pair": S.add(), "fold": S.norm(float("inf")), "scale": None},
    "step_selfdot": {"pair": S.sub(), "fold": S.self_dot(), "scale": None}, "step_dot_ends": {"pair": S.sub(), "fold": S.dot_ends(), "weigh": S.weigh_mul("pair")},
    "step_sum_left": {"pair": S.sub(), "fold": S.sum_left(), "weigh": S.weigh_mul("pair")},
    "step_sum_right": {"pair": S.add(), "fold": S.sum_right(), "weigh": S.weigh_mul("pair")},
    "step_fold_max": {"fold": S.fold_max(), "scale": None},
    "step_sigmoid": {"fold": None}, "step_scal": {"scale": S.scal(0.25)}, "step_tail": {"pair": S.sub(), "fold": S.self_dot(), "scale": S.inverse_tail()},
    "step_edge_scale": {"scale": S.edge_scale()}, "step_noop": {"fold": None, "scale": None},
    "step_weigh_edge": {"weigh": S.weigh_mul("edge")}, "step_weigh_pair": {"weigh": S.weigh_mul("pair")}, "step_weigh_add": {"weigh": S.weigh_add()},
    "step_weigh_sel2nd": {"weigh": S.weigh_sel2nd()}, "step_weigh_sigmoid": {"scale": None, "weigh": S.weigh_sigmoid()},
    "step_asum": {"scale": S.scal(-0.5)}, "step_amax_zero": {"collect": S.amax("zero")}, "step_amax_identity": {"collect": S.amax("identity")},
    "step_amin": {"collect": S.amin()}, "step_min_pool": {"pair": S.sel2nd(), "fold": None, "scale": None, "weigh": S.weigh_mul("edge"), "collect": S.amin()},
    "step_mean_pool": {"collect": S.amean()},
}
for _name, _changes in _STEPS.items():
    fold_query(_name, "g10", step_program(**_changes), strategy="relational", digits=9)
for _name in P.SEMIRINGS:
    fold_query(f"semiring_{_name}_g4", "g4", P.semiring_product(_name), strategy="relational", digits=9)
# User steps: an expression in the plan, and functions on matrices in workers.
_USER = step_program(pair=S.step("pair", expr=lambda o, x, y, a: o.abs(x - y), sql="abs(xv - yv)"), scale=S.step("scale", expr=lambda o, s, a: 1.0 / (1.0 + s * s), reads="", sql="1.0 / (1.0 + ({0}) * ({0}))"))
fold_query("udf_step_column", "g10", _USER, strategy="relational", digits=9)
fold_query("udf_step_matrix", "g10", _USER, strategy="packed", specialise=False, digits=9)


def _batch_steps():
    import numpy as np

    pair = S.step("pair", batch=lambda x, y, a: np.abs(x - y), sql="abs(xv - yv)")
    scale = S.step("scale", batch=lambda s, a: 1.0 / (1.0 + s * s), reads="", sql="1.0 / (1.0 + ({0}) * ({0}))")
    return step_program(pair=pair, scale=scale)


fold_query("udf_step_batch", "g10", _batch_steps(), strategy="packed", specialise=False, digits=9)


def _plain(name, sql):
    def register(f):
        QUERIES[name] = f
        ORACLE[name] = sql
        return f

    return register


def _real(name, program):
    def query(spark, sf_dir):
        x = features.real(spark, sf_dir)
        return to_long(fused_fold(graphs.edges(spark, sf_dir, "g5"), x, x, program, d=64, targets=graphs.targets(spark, sf_dir, "g5")))

    QUERIES[name] = query
    side = "SELECT vec_id AS id, (s - 1)::INTEGER AS i, embedding[s]::DOUBLE AS val FROM embeddings, (SELECT range AS s FROM range(1, 65))"
    ORACLE[name] = fold_sql(program, graphs.SQL["g5"], graphs.targets_sql("g5"), side, side, 64)


_real("sigmoid_embedding_g5", P.sigmoid_embedding())
_real("heavy_tail_g5", P.heavy_tail())
_real("graph_conv_mean_g5", P.graph_conv("mean"))


@_plain("minibatch_slice", f"SELECT u, v, a FROM ({graphs.SQL['g1']}) WHERE u % 7 = 0")
def minibatch_slice(spark, sf_dir):
    from edgefold.operators.edges import slice_rows

    return slice_rows(graphs.edges(spark, sf_dir, "g1"), graphs.targets(spark, sf_dir, "g1").where("u % 7 = 0"))


_CONV_Y = features.hashed_sql(graphs.sources_sql("g1"), D)
# Targets and neighbours of two kinds, each with a table of features of its own, both read.
fold_query("bipartite_g1", "g1", P.layout_displacement())


@_plain("edge_messages_g1",
    f"WITH y AS ({_CONV_Y}), x AS ({features.hashed_sql('SELECT u AS id FROM (' + graphs.targets_sql('g1') + ')', D)}) "
    f"SELECT e.u, e.v, round(sum(x.val * y.val) * any_value(e.a), 6) + 0::DOUBLE AS h FROM ({graphs.SQL['g1']}) e "
    f"JOIN x ON x.id = e.u JOIN y ON y.id = e.v AND y.i = x.i GROUP BY e.u, e.v")
def edge_messages_g1(spark, sf_dir):
    e, x, y, _ = inputs(spark, sf_dir, "g1")
    return two_phase.edge_dot(e, x, y, D).select("u", "v", F.round("h", 6).alias("h"))


@_plain("aggregate_messages_g1",
    f"WITH y AS ({_CONV_Y}), x AS ({features.hashed_sql('SELECT u AS id FROM (' + graphs.targets_sql('g1') + ')', D)}), "
    f"h AS (SELECT e.u, e.v, sum(x.val * y.val) * any_value(e.a) AS h FROM ({graphs.SQL['g1']}) e "
    f"JOIN x ON x.id = e.u JOIN y ON y.id = e.v AND y.i = x.i GROUP BY e.u, e.v) "
    f"SELECT h.u, y.i, round(sum(h.h * y.val), 9) + 0::DOUBLE AS z FROM h JOIN y ON y.id = h.v GROUP BY 1, 2")
def aggregate_messages_g1(spark, sf_dir):
    e, x, y, _ = inputs(spark, sf_dir, "g1")
    h = two_phase.store(two_phase.edge_dot(e, x, y, D).withColumn("a", F.lit(1.0)))
    return to_long(two_phase.aggregate_messages(h, y, P.Program(S.sel2nd(), None, None, S.weigh_mul(), S.asum()), D), 9)


@_plain("attention_unfused_g5",
    f"WITH e AS ({graphs.SQL['g5']}), f AS (SELECT vec_id AS id, (s - 1)::INTEGER AS i, embedding[s]::DOUBLE AS val "
    f"FROM embeddings, (SELECT range AS s "
    f"FROM range(1, 65))), w AS (SELECT u, v, exp(a - max(a) OVER (PARTITION BY u)) AS w "
    f"FROM e), n AS (SELECT u, v, w / sum(w) OVER (PARTITION BY u) AS a FROM w) "
    f"SELECT u, i, round(sum(n.a * f.val), 6) + 0::DOUBLE AS z FROM n JOIN f ON f.id = n.v GROUP BY 1, 2")
def attention_unfused_g5(spark, sf_dir):
    x = features.real(spark, sf_dir)
    weights = two_phase.attention(graphs.edges(spark, sf_dir, "g5"), x, x, 64)
    return to_long(fused_fold(weights, None, x, P.graph_conv("sum"), d=64, strategy="relational"))


@_plain("graph_conv_symnorm_g7",
    f"WITH e AS ({graphs.SQL['g7']}), deg AS (SELECT u, sum(a) AS d FROM e "
    f"GROUP BY u), n AS (SELECT e.u, e.v, e.a / sqrt(p.d * q.d) AS a FROM e JOIN deg p ON p.u = e.u "
    f"JOIN deg q ON q.u = e.v), y AS ({features.hashed_sql(graphs.sources_sql('g7'), D)}) "
    f"SELECT n.u, y.i, round(sum(n.a * y.val), 6) + 0::DOUBLE AS z FROM n JOIN y ON y.id = n.v GROUP BY 1, 2")
def graph_conv_symnorm_g7(spark, sf_dir):
    from edgefold.operators.edges import symmetric_normalise

    e, _, y, _ = inputs(spark, sf_dir, "g7")
    return to_long(fused_fold(symmetric_normalise(e), None, y, P.graph_conv("sum"), d=D, strategy="relational"))


def _weights(rows, columns):
    return [[((k * 13 + j * 5) % 17 - 8) / 8.0 for j in range(columns)] for k in range(rows)]


_W = ", ".join(f"({k}, {j}, {w}::DOUBLE)" for k, row in enumerate(_weights(64, 4)) for j, w in enumerate(row))


@_plain("gcn_layer_g5",
    f"WITH e AS ({graphs.SQL['g5']}), f AS (SELECT vec_id AS id, (s - 1)::INTEGER AS i, embedding[s]::DOUBLE AS val "
    f"FROM embeddings, (SELECT range AS s "
    f"FROM range(1, 65))), w(k, j, w) AS (VALUES {_W}), z AS (SELECT e.u, f.i, avg(e.a * f.val) AS z FROM e "
    f"JOIN f ON f.id = e.v GROUP BY 1, 2) "
    f"SELECT u, j::INTEGER AS i, round(greatest(sum(z.z * w.w) + 0.1, 0), 9) + 0::DOUBLE AS z FROM z "
    f"JOIN w ON w.k = z.i GROUP BY u, j")
def gcn_layer_g5(spark, sf_dir):
    from edgefold.functions.vectors import dense

    x = features.real(spark, sf_dir)
    pooled = fused_fold(graphs.edges(spark, sf_dir, "g5"), None, x, P.graph_conv("mean"), d=64, strategy="relational")
    return to_long(dense(pooled, _weights(64, 4), [0.1] * 4, "relu"), 9)


for _name, _graph, _program in (("sigmoid", "g1", P.sigmoid_embedding()), ("layout", "g4", P.layout_displacement()), ("graph_conv", "g3", P.graph_conv("sum"))):

    def _equal(spark, sf_dir, graph=_graph, program=_program):
        e, x, y, t = inputs(spark, sf_dir, graph)
        one = fused_fold(e, x, y, program, d=D, targets=t, strategy="packed")
        other = two_phase.two_phase(e, x, y, program, d=D, targets=t)
        return two_phase.max_abs_diff(one, other).select("n", (F.col("gap") < 1e-9).alias("equal"))

    QUERIES[f"fused_vs_two_phase_{_name}"] = _equal
    ORACLE[f"fused_vs_two_phase_{_name}"] = f"SELECT count(*) AS n, true AS equal FROM ({graphs.targets_sql(_graph)})"

_DEG = "SELECT u, count(*) AS deg FROM ({}) GROUP BY u"
_PREFIX = f"SELECT u, deg, (sum(deg) OVER (ORDER BY u) - deg)::BIGINT AS before FROM ({_DEG})"


@_plain("balanced_parts_g6", f"SELECT u, deg, least((16 * before) // (SELECT count(*) FROM ({graphs.SQL['g6']})), 15)::INTEGER AS part FROM ({_PREFIX.format(graphs.SQL['g6'])})")
def balanced_parts_g6(spark, sf_dir):
    return partition.balanced_parts(graphs.edges(spark, sf_dir, "g6"), 16)


@_plain("equal_row_parts_g6", f"SELECT u, deg, ((16 * (row_number() OVER (ORDER BY u) - 1)) // count(*) OVER ())::INTEGER AS part FROM ({_DEG.format(graphs.SQL['g6'])})")
def equal_row_parts_g6(spark, sf_dir):
    return partition.equal_row_parts(graphs.edges(spark, sf_dir, "g6"), 16)


_BALANCE = "SELECT {0!r} AS method, sum(n)::BIGINT AS nnz, max(n)::BIGINT AS most, round(max(n) / (sum(n) / 16), 9) AS factor FROM (SELECT part, sum(deg) AS n FROM ({1}) GROUP BY part)"


@_plain("balance_report", " UNION ALL ".join([_BALANCE.format("balanced", ORACLE["balanced_parts_g6"]), _BALANCE.format("equal_rows", ORACLE["equal_row_parts_g6"]), _BALANCE.format("hashed", f"SELECT u % 16 AS part, deg FROM ({_DEG.format(graphs.SQL['g6'])})")]))
def balance_report(spark, sf_dir):
    e, out = graphs.edges(spark, sf_dir, "g6"), None
    for name, f in (("balanced", partition.balanced_parts), ("equal_rows", partition.equal_row_parts), ("hashed", partition.hash_parts)):
        row = partition.imbalance(f(e, 16), 16).select(F.lit(name).alias("method"), "nnz", "most", F.round("factor", 9).alias("factor"))
        out = row if out is None else out.unionByName(row)
    return out


def _profile_sql(graph):
    return (
        f"SELECT (SELECT count(*) FROM ({graphs.targets_sql(graph)})) AS m, (SELECT count(*) "
        f"FROM ({graphs.sources_sql(graph)})) AS n, count(*) AS nnz, max(c)::BIGINT AS max_degree "
        f"FROM (SELECT *, count(*) OVER (PARTITION BY u) AS c FROM ({graphs.SQL[graph]}))"
)


def profile(spark, sf_dir, graph):
    deg = partition.degrees(graphs.edges(spark, sf_dir, graph)).agg(F.sum("deg").cast("long").alias("nnz"), F.max("deg").cast("long").alias("max_degree"))
    m = graphs.targets(spark, sf_dir, graph).agg(F.count("*").alias("m"))
    n = graphs.sources(spark, sf_dir, graph).agg(F.count("*").alias("n"))
    return m.crossJoin(n).crossJoin(deg)


for _graph in graphs.EDGES:
    _sql = _profile_sql(_graph)
    QUERIES[f"graph_profile_{_graph}"] = lambda spark, sf_dir, g=_graph: profile(spark, sf_dir, g).select("m", "n", "nnz", "max_degree", F.round(F.col("nnz") / F.col("m"), 9).alias("mean_degree"))
    ORACLE[f"graph_profile_{_graph}"] = f"SELECT m, n, nnz, max_degree, round(nnz / m, 9) AS mean_degree FROM ({_sql})"
_RMAT = graphs.event_rmat_sql(10)


@_plain("graph_profile_g8",
    f"SELECT count(DISTINCT u) AS m, count(DISTINCT v) AS n, count(*) "
    f"AS nnz, max(c)::BIGINT AS max_degree, sum(a)::BIGINT AS edges "
    f"FROM (SELECT *, count(*) OVER (PARTITION BY u) AS c FROM ({_RMAT}))")
def graph_profile_g8(spark, sf_dir):
    e = graphs.event_rmat(spark, sf_dir, 10)
    deg = e.groupBy("u").agg(F.count("*").alias("c"), F.sum("a").alias("a")).agg(F.count("*").alias("m"), F.sum("c").cast("long").alias("nnz"), F.max("c").alias("max_degree"), F.sum("a").cast("long").alias("edges"))
    return deg.crossJoin(e.agg(F.count_distinct("v").alias("n")))


_COSTS = " UNION ALL ".join(f"SELECT '{g}' AS graph, m, n, nnz FROM ({_profile_sql(g)})" for g in ("g1", "g2", "g3", "g4", "g5", "g7"))


@_plain("cost_model",
    f"SELECT graph, m, n, nnz, 4 * 64 * nnz AS flops, 8 * m * 64 + 4 "
    f"* n * 64 + 12 * nnz AS fused_bytes, 12 * nnz * 64 AS message_bytes, "
    f"m * 64 AS held_loads, nnz * 64 AS edge_loads, round(nnz / m / "
    f"(3.0 * (nnz / m) / 64 + 2.0 + nnz / m), 9) AS intensity FROM ({_COSTS})")
def cost_model(spark, sf_dir):
    out = None
    for g in ("g1", "g2", "g3", "g4", "g5", "g7"):
        row = profile(spark, sf_dir, g).select(F.lit(g).alias("graph"), "m", "n", "nnz")
        out = row if out is None else out.unionByName(row)
    m, n, nnz = F.col("m"), F.col("n"), F.col("nnz")
    held, each, _ = cost.access_counts(m, n, nnz, 64)
    return out.select("graph", "m", "n", "nnz", cost.flops(nnz, 64).alias("flops"), cost.fused_bytes(m, n, nnz, 64).alias("fused_bytes"), cost.message_bytes(nnz, 64).alias("message_bytes"), held.alias("held_loads"), each.alias("edge_loads"), F.round(cost.intensity(nnz / m, 64), 9).alias("intensity"))
