"""Queries of blocked and balanced kernels, tuning, checks, files, measures from formulas, and training."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from edgefold.functions import steps as S
from edgefold.operators import partition, training, two_phase
from edgefold.operators.fused import fused_fold, placed, to_long
from edgefold.operators.kernels import Blocking
from edgefold.operators.packed import pack
from edgefold.plans import cost, planner
from edgefold.plans import program as P
from edgefold.queries import kernels as K
from edgefold.queries.kernels import _profile_sql, inputs, profile
from edgefold.sources import edge_files, features, graphs

QUERIES: dict = {}
ORACLE: dict[str, str] = {}
G4, G6, G10 = graphs.SQL["g4"], graphs.SQL["g6"], graphs.SQL["g10"]


def q(name, sql):
    def register(f):
        QUERIES[name] = f
        ORACLE[name] = sql
        return f

    return register


def fold_query(name, graph, program, **options):
    """As there, registered here."""
    K.fold_query(name, graph, program, **options)
    QUERIES[name], ORACLE[name] = K.QUERIES.pop(name), K.ORACLE.pop(name)


# Kernels: by range of dimensions, by what is held in place, for each pattern; parts with equally many edges.
for _d in (24, 96, 160):
    fold_query(f"kernel_d{_d}_g4", "g4", P.sigmoid_embedding(), d=_d, strategy="packed")
    fold_query(f"relational_d{_d}_g4", "g4", P.sigmoid_embedding(), d=_d, strategy="relational")
fold_query("kernel_force_literal_g4", "g4", P.layout_literal(), strategy="packed")
fold_query("kernel_force_heavy_tail_g10", "g10", P.heavy_tail(), strategy="packed", digits=9)
fold_query("kernel_sum_mean_g4", "g4", P.graph_conv("mean"), strategy="packed", digits=10)
fold_query("blocked_dims_g4", "g4", P.sigmoid_embedding(), d=40, strategy="packed", block=Blocking(dims=16, limit=1 << 14))
fold_query("blocked_x_only_g4", "g4", P.layout_displacement(), strategy="packed", block=Blocking(vectors=("x",)))
fold_query("blocked_z_only_g4", "g4", P.sigmoid_embedding(), strategy="packed", block=Blocking(vectors=("z",)))
fold_query("balanced_fold_g6", "g6", P.sigmoid_embedding(), strategy="packed", parts=16)
fold_query("balanced_fold_mean_g10", "g10", P.graph_conv("mean"), strategy="packed", parts=40, digits=10)
fold_query("tiled_layout_g4", "g4", P.layout_literal(), strategy="tiled", tiles=(3, 2))
fold_query("tiled_max_g6", "g6", P.graph_conv("max"), strategy="tiled", tiles=8)
fold_query("tiled_mlp_g4", "g4", P.mlp_gnn(S.weights_by_rule(8)), strategy="tiled", tiles=(2, 3))
fold_query("relational_salted_g6", "g6", P.sigmoid_embedding(), strategy="relational", salts=4)
fold_query("block_matrix_g10", "g10", P.graph_conv("sum"), run=lambda e, x, y, p, d, targets: two_phase.complete(two_phase.block_matrix_product(e, y, 25, 5, d), targets, d))
fold_query("dense_layout_g10", "g10", P.layout_literal(), run=two_phase.dense_reference, digits=9)
fold_query("tensor_layout_g4", "g4", P.layout_displacement(), run=two_phase.tensor_operations)
fold_query("tensor_graph_conv_g4", "g4", P.graph_conv("sum"), run=two_phase.tensor_operations)

for _name, _program in (("sigmoid", P.sigmoid_embedding()), ("layout", P.layout_displacement()), ("mlp", P.mlp_gnn(S.weights_by_rule(8)))):
    fold_query(f"two_phase_packed_{_name}_g4", "g4", _program, run=lambda e, x, y, p, d, targets: two_phase.two_phase_packed(pack(e), x, y, p, d=d, targets=targets))


def _spread(aggregate=None, batch=None):
    """A user's collect: the population deviation of a target's messages."""
    return P.Program(S.sel2nd(), None, None, S.weigh_mul("edge"), S.step("collect", expr=aggregate, batch=batch))


_SPREAD = (
    f"WITH e AS ({graphs.SQL['g4']}), y AS ({features.hashed_sql(graphs.sources_sql('g4'), 8)}) "
    "SELECT e.u, y.i, round(stddev_pop(e.a * y.val), 8) + 0::DOUBLE AS z FROM e JOIN y ON y.id = e.v GROUP BY 1, 2"
)


@q("udf_collect_column", _SPREAD)
def udf_collect_column(spark, sf_dir):
    e, x, y, t = inputs(spark, sf_dir, "g4")
    return to_long(fused_fold(e, x, y, _spread(aggregate=F.stddev_pop), d=8, strategy="relational"), 8)


@q("udf_collect_matrix", _SPREAD)
def udf_collect_matrix(spark, sf_dir):
    e, x, y, t = inputs(spark, sf_dir, "g4")
    return to_long(fused_fold(e, x, y, _spread(batch=lambda m: m.std(axis=0)), d=8), 8)


_G8 = graphs.rmat_sql(10, 8000)
_G8_DEG = f"SELECT u, count(*) AS deg FROM ({_G8}) GROUP BY u"


@q("balanced_places_g8", f"SELECT true AS whole, true AS within, count(*) AS nnz FROM ({_G8})")
def balanced_places_g8(spark, sf_dir, t=16):
    """Whether each edge of a skewed graph is in one part of 16, and no part holds over twice its share (and a tenth, as
    a hub's edges are dealt by hash)."""
    e = graphs.rmat(spark, 10, 8000)
    rows, _ = placed(e, None, t)
    by = rows.withColumn("part", F.spark_partition_id()).groupBy("part").agg(F.count("*").alias("n"))
    got = by.agg(F.sum("n").alias("nnz"), F.max("n").alias("most"))
    both = got.crossJoin(F.broadcast(e.agg(F.count("*").alias("all"))))
    return both.select((F.col("nnz") == F.col("all")).alias("whole"), (F.col("most") <= F.col("nnz") / t * 2.1).alias("within"), F.col("nnz").cast("long").alias("nnz"))


@q("tuned_fold_g4", K.graph_fold_sql("g4", P.graph_conv("sum"), 8))
def tuned_fold_g4(spark, sf_dir):
    """The fold by the best of some plans, timed on all targets."""
    e, x, y, t = inputs(spark, sf_dir, "g4")
    plans = [planner.Plan("relational"), planner.Plan("packed"), planner.Plan("packed", parts=4, block=1 << 18)]
    best = planner.tune(e, x, y, P.graph_conv("sum"), 8, plans, rows=1.0, repeats=1)
    return to_long(fused_fold(e, x, y, P.graph_conv("sum"), d=8, targets=t, strategy=best.strategy, parts=best.parts, block=best.block))


_PROGRAMS = {
    "sigmoid_embedding": (P.sigmoid_embedding(), "sigmoid_dot", False),
    "embedding_pull": (P.embedding_pull(), "sigmoid_dot", False),
    "layout_literal": (P.layout_literal(), "norm_force", False),
    "layout_displacement": (P.layout_displacement(), "norm_force", False),
    "heavy_tail": (P.heavy_tail(), "norm_force", False),
    "graph_conv_sum": (P.graph_conv("sum"), "neighbour_sum", True),
    "graph_conv_max": (P.graph_conv("max"), "general", True),
    "mlp_gnn": (P.mlp_gnn(S.weights_by_rule(4)), "general", False),
    "dot_products": (P.Program(S.mul(), S.rsum(), S.scal(2.0), S.weigh_mul(), S.asum()), "sigmoid_dot", True),
}
_CHECKS = " UNION ALL ".join(
    f"SELECT '{n}' AS program, '{pattern}' AS pattern, {str(split).lower()} AS splits, round(avg(z), 6) + 0::DOUBLE AS mean FROM ({K.graph_fold_sql('g10', program, 4, 9)})"
    for n, (program, pattern, split) in _PROGRAMS.items()
)


@q("program_checks", _CHECKS)
def program_checks(spark, sf_dir):
    """Pattern of each program, whether its dimensions may be worked out apart, and the mean of its fold over customers'
    nations and segments by the pattern's kernel."""

    def splits(program):
        try:
            P.check_feature_split(program)
        except ValueError:
            return False
        return True

    e, x, y, t = inputs(spark, sf_dir, "g10", 4)
    out = None
    for n, (p, _, _) in _PROGRAMS.items():
        z = to_long(fused_fold(e, x, y, p, d=4, targets=t, strategy="packed"), 9).agg((F.round(F.avg("z"), 6) + 0.0).alias("mean"))
        row = z.select(F.lit(n).alias("program"), F.lit(P.recognise(p)).alias("pattern"), F.lit(splits(p)).alias("splits"), "mean")
        out = row if out is None else out.unionByName(row)
    return out


# Files: out and in again.
def _place(spark, kind):
    return f"{two_phase._shared(spark)}/{kind}-{uuid.uuid4().hex}"


for _format in ("csv", "json"):

    @q(f"edge_list_{_format}", G4)
    def _edge_list(spark, sf_dir, fmt=_format):
        path = _place(spark, "edges")
        edge_files.write(graphs.edges(spark, sf_dir, "g4").select("u", "v", "a"), fmt, path)
        return edge_files.edge_list(spark, path, fmt)


@q("edge_list_text", f"SELECT u, v, sum(a) AS a FROM (SELECT u, v, a FROM ({G4}) UNION ALL SELECT v, u, a FROM ({G4})) GROUP BY 1, 2")
def edge_list_text(spark, sf_dir):
    """Fields between white space, ids from 1, made symmetric."""
    path = _place(spark, "text")
    line = F.format_string("%d\t%d %s", F.col("u") + 1, F.col("v") + 1, F.col("a").cast("string"))
    graphs.edges(spark, sf_dir, "g4").select(line.alias("value")).write.text(path)
    return edge_files.edge_list(spark, path, "text", base=1, symmetric=True)


@q("triplets_text", G10)
def triplets_text(spark, sf_dir):
    path = _place(spark, "triplets")
    e = graphs.edges(spark, sf_dir, "g10")
    entry = F.format_string("%d %d %s", F.col("u") + 1, F.col("v") + 1, F.col("a").cast("string"))
    head = spark.createDataFrame([(0, "%%MatrixMarket matrix coordinate real general"), (1, "25 5 125")], "n int, value string")
    head.unionByName(e.select(F.lit(2).alias("n"), entry.alias("value"))).coalesce(1).sortWithinPartitions("n").select("value").write.text(path)
    return edge_files.triplets(spark, path)


@q("clustered_store", f"SELECT u, v, a FROM ({G4}) WHERE u BETWEEN 20 AND 60")
def clustered_store(spark, sf_dir):
    path = _place(spark, "clustered")
    edge_files.write_clustered(graphs.edges(spark, sf_dir, "g4"), path, 4)
    return spark.read.parquet(path).where("u BETWEEN 20 AND 60").select("u", "v", "a")


@q("parquet_sink", G4)
def parquet_sink(spark, sf_dir):
    path = _place(spark, "sink")
    edge_files.write(graphs.edges(spark, sf_dir, "g4"), "parquet", path)
    return spark.read.parquet(path).select("u", "v", "a")


# Measures from formulas, on the sizes of graphs. Bytes stand for times.
_SPED = ("g1", "g2", "g3", "g4")
_SIZES = " UNION ALL ".join(f"SELECT {k} AS k, m, n, nnz FROM ({_profile_sql(g)})" for k, g in enumerate(_SPED))


@q("speedups",
    f"SELECT k, round((m * 64 * 8 + n * 64 * 4 + nnz * 12 + 2 * nnz * 64 * 12) / fused, 6) AS over_two_phase, "
    f"round((nnz * 64 * 12 + nnz * 12) / fused, 6) AS over_general, NULL::DOUBLE AS unfinished "
    f"FROM (SELECT *, (m * 64 * 8 + n * 64 * 4 + nnz * 12)::DOUBLE AS fused FROM ({_SIZES}))")
def speedups(spark, sf_dir, d=64):
    """Modelled speedups of the fused fold of each graph: over two phases, which write messages and read them again, and
    over the form that fetches both vectors and moves the result for each edge."""
    rows = []
    for k, g in enumerate(_SPED):
        r = profile(spark, sf_dir, g).first()
        fused = cost.fused_bytes(r["m"], r["n"], r["nnz"], d)
        two = fused + 2 * cost.message_bytes(r["nnz"], d)
        general = cost.fused_bytes(r["nnz"], r["nnz"], r["nnz"], d)
        rows.append((k, round(cost.speedup(two, fused), 6), round(cost.speedup(general, fused), 6), cost.speedup(None, fused)))
    return spark.createDataFrame(rows, "k int, over_two_phase double, over_general double, unfinished double")


_GRAPHS = ("g1", "g2", "g3", "g4", "g5", "g7")
_INTENSITY = " UNION ALL ".join(f"SELECT '{g}' AS graph, m, nnz FROM ({_profile_sql(g)})" for g in _GRAPHS)


@q("roofline_model",
    f"SELECT graph, round(ai, 9) AS intensity, round(least(80.0::DOUBLE, "
    f"ai * 100), 9) AS attainable, round(4 * 128 * nnz / 0.25 / 1e9, 9) AS achieved "
    f"FROM (SELECT graph, nnz, nnz / m / (3.0 * (nnz / m) / 128 + 2.0 + nnz / m) AS ai FROM ({_INTENSITY}))")
def roofline_model(spark, sf_dir):
    """Bounds for d = 128, 100e9 bytes and 80e9 operations a second; and the rate of a fold that takes a quarter of a second."""
    rows = []
    for g in _GRAPHS:
        r = profile(spark, sf_dir, g).first()
        ai = cost.intensity(r["nnz"] / r["m"], 128)
        rows.append((g, round(ai, 9), round(cost.roofline(ai, 100.0, 80.0), 9), round(cost.achieved(r["nnz"], 128, 0.25), 9)))
    return spark.createDataFrame(rows, "graph string, intensity double, attainable double, achieved double")


_MOVED = {"broadcast": "40 * n * 64 * 8", "row_stationary": "least(nnz, 20 * n) * 64 * 8", "source_stationary": "least(nnz, 4 * m) * 64 * 16", "edge_join": "nnz * 64 * 8"}


@q("moved_bytes", f"WITH p AS ({_profile_sql('g2')}) " + " UNION ALL ".join(f"SELECT '{k}' AS strategy, ({b})::DOUBLE AS bytes FROM p" for k, b in _MOVED.items()))
def moved_bytes(spark, sf_dir):
    """Suppliers and parts, d = 64, 40 executors; 20 groups of rows and 4 of columns; doubles."""
    r = profile(spark, sf_dir, "g2").first()
    groups = {"broadcast": 1, "row_stationary": 20, "source_stationary": 4, "edge_join": 1}
    rows = [(k, float(cost.moved_bytes(k, r["m"], r["n"], r["nnz"], 64, 40, g))) for k, g in groups.items()]
    return spark.createDataFrame(rows, "strategy string, bytes double")


# Training: every update in SQL.
def _dealt(expr, n):
    return f"(('0x' || substr(md5({expr}), 1, 8))::BIGINT % {n})"


def training_sql(edges: str, ids: str, n: int, *, d: int, batches: int, epochs: int, lr: float = 0.05, negatives: int = 5, seed: int = 1) -> tuple[str, str]:
    """CTEs of all updates in turn, and the name of the last."""
    out, x = [f"e AS ({edges})", f"ids AS ({ids})", f"x0 AS ({features.digest_sql('SELECT u AS id FROM ids', d, seed)})"], "x0"
    step = 0
    for epoch in range(epochs):
        s = seed + epoch
        for k in range(batches):
            step += 1
            far = _dealt(f"'{s * 1000 + k}:' || mine.u || ':' || j", n)
            out += [
                f"m{step} AS (SELECT u FROM ids WHERE {_dealt(repr(f'{s}:') + ' || u', batches)} = {k})",
                f"n{step} AS (SELECT mine.u, {far} AS v FROM m{step} mine, (SELECT range AS j FROM range({negatives})))",
                f"p{step} AS (SELECT u, v, 1 AS sign FROM e SEMI JOIN m{step} USING (u) UNION ALL SELECT u, v, -1 FROM n{step} WHERE u <> v)",
                # repeats of a drawn pair count each: pairs get numbers
                f"q{step} AS (SELECT *, row_number() OVER () AS k FROM p{step})",

                    f"h{step} AS (SELECT q.k, any_value(q.u) AS u, any_value(q.v) AS "
                    f"v, any_value(q.sign) AS sign, sum(a.val * b.val) AS s FROM q{step} q JOIN {x} a ON a.id = q.u "
                    f"JOIN {x} b ON b.id = q.v AND b.i = a.i GROUP BY q.k)",
                f"z{step} AS (SELECT h.u, b.i, sum(CASE WHEN sign = 1 THEN b.val / (1 + exp(s)) ELSE -b.val / (1 + exp(-s)) END) AS z FROM h{step} h JOIN {x} b ON b.id = h.v GROUP BY 1, 2)",
                f"x{step} AS (SELECT a.id, a.i, a.val + {lr}::DOUBLE * coalesce(z.z, 0) AS val FROM {x} a LEFT JOIN z{step} z ON z.u = a.id AND z.i = a.i)",
            ]
            x = f"x{step}"
    return ", ".join(out), x


def _trained(name, graph, method, *, d=8, batches=2, epochs=1, ids_from=None):
    ids = graphs.targets_sql(graph)
    n = f"(SELECT count(*) FROM ({ids}))"
    ctes, last = training_sql(graphs.SQL[graph], ids, n, d=d, batches=batches, epochs=epochs)

    @q(name, f"WITH {ctes} SELECT id AS u, i, round(val, 6) + 0::DOUBLE AS z FROM {last}")
    def train(spark, sf_dir):
        x, _ = training.train_embedding(graphs.edges(spark, sf_dir, graph), graphs.targets(spark, sf_dir, graph), d=d, batches=batches, epochs=epochs, method=method)
        return to_long(x.select(F.col("id").alias("u"), F.col("x").alias("z")))


_trained("train_embedding_g5", "g5", "fused")
_trained("train_two_phase_g5", "g5", "two_phase", batches=1)
_trained("train_tensor_g5", "g5", "tensor", batches=1)

#: Two communities: 120 vertices, a tenth of all pairs within one and a fiftieth of those across, by a digest.
_PLANTED = (
    "SELECT u, v, 1.0::DOUBLE AS a FROM (SELECT p.range AS u, r.range AS v FROM range(120) p, range(120) r) "
    "WHERE u <> v AND "
) + _dealt("'planted:' || u || ':' || v", 1000) + " < CASE WHEN u % 2 = v % 2 THEN 200 ELSE 20 END"


def planted(spark):
    pairs = spark.range(120).select(F.col("id").alias("u")).crossJoin(spark.range(120).select(F.col("id").alias("v")))
    draw = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit("planted"), F.col("u").cast("string"), F.col("v").cast("string"))), 1, 8), 16, 10).cast("long") % 1000
    within = F.when(F.col("u") % 2 == F.col("v") % 2, 200).otherwise(20)
    return pairs.where((F.col("u") != F.col("v")) & (draw < within)).withColumn("a", F.lit(1.0))


_CTES, _LAST = training_sql(_PLANTED, "SELECT range AS u FROM range(120)", 120, d=8, batches=1, epochs=4, lr=0.2)
_F1 = f"""WITH {_CTES}, l AS (SELECT range AS id, (range % 2)::INTEGER AS label FROM range(120)),
  c AS (SELECT label, i, avg(val) AS val FROM {_LAST} JOIN l USING (id) WHERE id % 5 <> 0 GROUP BY 1, 2),
  s AS (SELECT z.id, c.label, round(sum(z.val * c.val) / (sqrt(sum(z.val * z.val)) * sqrt(sum(c.val * c.val))), 9) AS s
    FROM {_LAST} z JOIN c USING (i) WHERE z.id % 5 = 0 GROUP BY 1, 2),
  p AS (SELECT id, label AS pred FROM (SELECT *, row_number() OVER (PARTITION BY id ORDER BY s DESC, label) AS r FROM s) WHERE r = 1)
  SELECT count(*) AS n, round(avg((pred = label)::INTEGER), 9) AS f1 FROM p JOIN l USING (id)"""


def f1_trained(spark, method):
    """F1 of the community of held-out vertices, on vectors trained on a planted graph."""
    x, _ = training.train_embedding(planted(spark), spark.range(120).select(F.col("id").alias("u")), d=8, batches=1, epochs=4, lr=0.2, method=method)
    labels = x.select("id", (F.col("id") % 2).cast("int").alias("label"))
    pred = training.classify(x, labels.where("id % 5 <> 0"), 8)
    return training.f1_micro(pred.where("id % 5 = 0"), labels)


q("f1_micro_trained", _F1)(lambda s, d: f1_trained(s, "fused"))
q("f1_micro_trained_two_phase", _F1)(lambda s, d: f1_trained(s, "two_phase"))
