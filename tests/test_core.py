"""The hand-checked fixture, equality of all strategies, partitions, costs, contracts and plans."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from edgefold.functions import steps as S
from edgefold.operators import edges as E
from edgefold.operators import packed, partition, two_phase
from edgefold.operators.fused import fused_fold
from edgefold.operators.kernels import Blocking, generate, stacks
from edgefold.plans import cost, planner
from edgefold.plans import program as P

X1 = [0.5, -1.0, 0.25, 2.0]
Y = {2: [1.0, 0.0, -2.0, 0.5], 4: [-0.5, 1.5, 1.0, 0.0], 8: [0.0, -1.0, 4.0, -1.0]}
WANT = {
    "embedding": (P.sigmoid_embedding(), [0.639846, -0.226362, 0.720308, -0.134471]),
    "identity": (P.Program(S.mul(), S.rsum(), None, S.weigh_mul(), S.asum()), [1.75, -2.25, -3.5, 0.5]),
    "conv_sum": (P.graph_conv("sum"), [1.5, 1, -1, 0.5]),
    "conv_mean": (P.graph_conv("mean"), [0.5, 1 / 3, -1 / 3, 1 / 6]),
    "conv_max": (P.graph_conv("max"), [2, 1.5, 2, 1]),
    "conv_min": (P.graph_conv("min"), [-0.5, -0.5, -4, -0.5]),
    "layout": (P.layout_literal(0.5), [1.169453, -0.605966, 7.317699, -1.528061]),
    "displacement": (P.layout_displacement(2), [-2.193998, 5.759252, 7.049969, -12.874016]),
    "tail": (P.heavy_tail(), [-0.046327, 0.299697, -0.022516, -0.436354]),
    "min_plus": (P.semiring_product("min_plus"), [0.5, -0.5, 0, -0.5]),
}


@pytest.fixture(scope="module")
def fixture(spark):
    e = spark.createDataFrame([(1, 2, 2.0), (1, 4, 1.0), (1, 8, 0.5), (1, 2, 0.0)], "u long, v long, a double").persist()
    x = spark.createDataFrame([(1, X1), (9, X1)], "id long, x array<double>").persist()
    y = spark.createDataFrame(list(Y.items()), "id long, x array<double>").persist()
    return e, x, y, spark.createDataFrame([(1,), (9,)], "u long").persist()


def rows(z):
    return {r["u"]: list(r["z"]) for r in z.collect()}


@pytest.mark.parametrize("name", WANT)
@pytest.mark.parametrize("strategy", ["relational", "array", "packed", "tiled"])
def test_hand_checked(fixture, name, strategy):
    e, x, y, t = fixture
    program, want = WANT[name]
    got = rows(fused_fold(e, x, y, program, d=4, targets=t, strategy=strategy))
    assert got[1] == pytest.approx(want, abs=1e-6) and got[9] == [0, 0, 0, 0]


@pytest.mark.parametrize("name", ["embedding", "conv_mean", "displacement", "layout"])
def test_baselines_agree(fixture, name):
    e, x, y, t = fixture
    program, want = WANT[name]
    for run in (two_phase.two_phase, two_phase.tensor_operations, two_phase.dense_reference):
        assert rows(run(e, x, y, program, d=4, targets=t))[1] == pytest.approx(want, abs=1e-6)
    if name == "conv_mean":
        assert rows(two_phase.vendor_product(e.where("a <> 0"), y, 4))[1] == pytest.approx([1.5, 1, -1, 0.5])
        assert rows(two_phase.block_matrix_product(e.where("a <> 0"), y, 10, 10, 4))[1] == pytest.approx([1.5, 1, -1, 0.5])


def test_maximum_starts_from_zero_or_identity(fixture, spark):
    _, x, y, _ = fixture
    one = spark.createDataFrame([(1, 2, 1.0)], "u long, v long, a double")
    for init, want in (("zero", [0, 0, 0, 0]), ("identity", [-1, 0, -2, -0.5])):
        program = P.Program(S.step("pair", expr=lambda o, x, y, a: -o.abs(y), reads="y"), None, None, S.weigh_mul("edge"), S.amax(init))
        for strategy in ("relational", "packed"):
            assert rows(fused_fold(one, x, y, program, d=4, strategy=strategy))[1] == want


def test_saturation_float_and_blocks(spark):
    e = spark.createDataFrame([(0, v, 1.0) for v in range(50)] + [(1, 3, 1.0)], "u long, v long, a double")
    y = spark.createDataFrame([(i, [1000.0 * (-1) ** i, float(i)]) for i in range(50)], "id long, x array<double>")
    x = spark.createDataFrame([(0, [1.0, 0.0]), (1, [1.0, 0.0])], "id long, x array<double>")
    want = rows(fused_fold(e, x, y, P.sigmoid_embedding(), d=2, strategy="relational"))
    for options in ({"block": 700}, {"block": None}, {"dtype": "float"}, {"specialise": False}, {"parts": 3}, {"block": Blocking(dims=1)}):
        got = rows(fused_fold(e, x, y, P.sigmoid_embedding(), d=2, strategy="packed", **options))
        assert got[0] == pytest.approx(want[0], rel=1e-5) and got[1] == pytest.approx(want[1])


def test_hubs_go_in_pieces(spark):
    e = spark.createDataFrame([(1, v, 1.0) for v in range(300)] + [(2, 5, 2.0)], "u long, v long, a double")
    y = spark.createDataFrame([(i, [float(i)]) for i in range(300)], "id long, x array<double>")
    pieces = packed.chunk_rows(e, 50)
    assert pieces.where("u = 1").count() > 3 and pieces.agg(F.sum("deg")).first()[0] == 301
    from edgefold.operators.fused import _packed

    for pool, want in (("sum", 44850.0), ("mean", 149.5), ("max", 299.0)):
        assert rows(_packed(e, None, y, P.graph_conv(pool), 1, rows=pieces))[1] == pytest.approx([want])


def test_contracts(fixture, spark):
    e, x, y, _ = fixture
    with pytest.raises(ValueError):
        P.check(P.Program(S.rsum(), None, None, S.weigh_mul(), S.asum()))
    with pytest.raises(ValueError):
        P.check_feature_split(P.sigmoid_embedding())
    P.check_feature_split(P.graph_conv())
    with pytest.raises(ValueError):
        S.amax("other")
    bad = y.unionByName(spark.createDataFrame([(8, [1.0, float("nan"), 0.0, 0.0])], "id long, x array<double>"))
    with pytest.raises(Exception, match="NaN"):
        fused_fold(e, x, bad, P.graph_conv(), d=4, strategy="relational", checked=True).collect()
    empty = e.limit(0)
    for options in WAYS:
        assert rows(fused_fold(empty, x, y, P.graph_conv(), d=4, **options)) == {}


WAYS = [{"strategy": "relational"}, {"strategy": "relational", "salts": 3}, {"strategy": "array"}, {"strategy": "packed"}, {"strategy": "packed", "parts": 3}, {"strategy": "tiled", "tiles": (2, 2)}, {"strategy": "auto"}]


@pytest.mark.parametrize("options", WAYS, ids=str)
def test_missing_features_are_one_rule(spark, options):
    """An edge without features that the program reads is an error in every strategy, or is dropped in every one."""
    e = spark.createDataFrame([(1, 10, 1.0), (1, 11, 2.0), (2, 10, 1.0), (3, 10, 4.0), (4, 12, 1.0)], "u long, v long, a double")
    x = spark.createDataFrame([(u, [1.0, 2.0]) for u in (1, 2, 4)], "id long, x array<double>")
    y = spark.createDataFrame([(10, [1.0, 0.5]), (12, [0.0, -1.0])], "id long, x array<double>")
    for program, fx, fy in ((P.sigmoid_embedding(), x, y), (P.sigmoid_embedding(), x.unionByName(x.limit(1).selectExpr("3L AS id", "x")), y), (P.graph_conv(), None, y)):
        with pytest.raises(Exception, match="no features"):
            fused_fold(e, fx, fy, program, d=2, **options).collect()
    whole_y = y.unionByName(spark.createDataFrame([(11, [1.0, 1.0])], "id long, x array<double>"))
    with pytest.raises(Exception, match="no features"):
        fused_fold(e, x, whole_y, P.sigmoid_embedding(), d=2, **options).collect()
    got = rows(fused_fold(e, x, y, P.sigmoid_embedding(), d=2, on_missing="drop", **options))
    h1, h2 = 1 / (1 + np.exp(-2.0)), 1 / (1 + np.exp(2.0))
    assert got.keys() == {1, 2, 4} and got[1] == pytest.approx([h1, h1 / 2]) and got[4] == pytest.approx([0.0, -h2])
    # features that the program does not read may be missing
    assert rows(fused_fold(e, None, whole_y, P.graph_conv(), d=2, **options))[3] == pytest.approx([4.0, 2.0])
    nulls = e.unionByName(spark.createDataFrame([(None, 10, 1.0), (1, None, 1.0), (2, 12, None), (2, 12, 0.0)], "u long, v long, a double"))
    assert rows(fused_fold(nulls, x, y, P.sigmoid_embedding(), d=2, on_missing="drop", **options)) == {u: pytest.approx(z) for u, z in got.items()}
    with pytest.raises(ValueError):
        fused_fold(e, x, y, P.sigmoid_embedding(), d=2, on_missing="ignore", **options)


def test_contracts_of_user_steps(fixture):
    e, x, y, _ = fixture
    bad = {
        "pair": [{"batch": lambda x, y: x}, {"batch": lambda x, y, a: x[:, 0]}],
        "scale": [{"batch": lambda s: s}, {"batch": lambda s, a: np.hstack([s, s, s])}],
        "weigh": [{"batch": lambda h: h}, {"batch": lambda h, o: (h * o).sum()}],
        "fold": [{"batch": lambda m: m}, {"batch": lambda m, k: m[:, 0]}],
        "collect": [{"batch": lambda m: m}, {"batch": lambda m, k: m[0]}],
    }
    parts = {"pair": S.mul(), "fold": S.rsum(), "scale": S.sigmoid(), "weigh": S.weigh_mul(), "collect": S.asum()}
    for kind, options in bad.items():
        for option in options:
            with pytest.raises(ValueError, match=kind):
                P.check(P.Program(**(parts | {kind: S.step(kind, **option)})))
    P.check(P.Program(**(parts | {"fold": S.step("fold", batch=lambda m: m.max(axis=1))})))
    middle = P.Program(S.sel2nd(), None, None, S.weigh_mul("edge"), S.step("collect", batch=lambda m: np.median(m, axis=0)))
    assert rows(fused_fold(e, x, y, middle, d=4))[1] == pytest.approx([0, 0, 1, 0])
    for strategy in ("relational", "tiled"):
        with pytest.raises(ValueError):
            fused_fold(e, x, y, middle, d=4, strategy=strategy)


@pytest.mark.parametrize("fold", [S.dot_ends(), S.sum_left(), S.sum_right()], ids=lambda f: f.name)
def test_folds_of_both_ends(fixture, fold):
    e, x, y, _ = fixture
    program = P.Program(S.sub(), fold, S.scal(0.5), S.weigh_mul("pair"), S.asum())
    x1, want = np.asarray(X1), np.zeros(4)
    for v, yv in Y.items():
        yv = np.asarray(yv)
        want += 0.5 * {"DOT": x1 @ yv, "LSUM": x1.sum(), "NSUM": yv.sum()}[fold.name] * (yv - x1)
    for strategy in ("relational", "array", "packed", "tiled"):
        assert rows(fused_fold(e, x, y, program, d=4, strategy=strategy))[1] == pytest.approx(want.tolist())
    assert rows(two_phase.two_phase(e, x, y, program, d=4))[1] == pytest.approx(want.tolist())


def test_recognition_and_kernels():
    assert P.recognise(P.sigmoid_embedding()) == "sigmoid_dot" and P.recognise(P.graph_conv()) == "neighbour_sum"
    assert P.recognise(P.layout_literal()) == "norm_force" and P.recognise(P.heavy_tail()) == "norm_force"
    assert P.recognise(P.graph_conv("max")) == "general" and P.graph_conv().reads == {"y", "a"}
    assert generate("sigmoid_dot", 8, Blocking(limit=64), "float") is generate("sigmoid_dot", 8, Blocking(limit=64), "float")


@pytest.mark.parametrize("program", [P.sigmoid_embedding(), P.embedding_pull(), P.layout_literal(), P.layout_displacement(), P.heavy_tail(), P.graph_conv(), P.graph_conv("mean")], ids=lambda p: p.name)
def test_specialised_kernels_agree_with_the_general_one(program):
    draw, d = np.random.default_rng(0), 20
    sizes = np.asarray([3, 0, 7, 3, 1, 90, 3, 0])
    starts, n = np.cumsum(sizes) - sizes, int(sizes.sum())
    x, y, index, a = draw.normal(size=(8, d)), draw.normal(size=(30, d)), draw.integers(0, 30, n), draw.normal(size=n)
    want = generate("general", d)(program, x, y, index, a, sizes, starts)
    pattern = P.recognise(program)
    assert pattern != "general"
    for block in (None, Blocking(limit=1 << 8), Blocking(dims=7), Blocking(vectors=("x", "z")), Blocking(vectors=("x",)), Blocking(vectors=("z",), limit=1 << 9), Blocking(vectors=())):
        assert np.allclose(generate(pattern, d, block)(program, x, y, index, a, sizes, starts), want)
        assert np.allclose(generate("general", d, block)(program, x, y, index, a, sizes, starts), want)
    single = [generate(k, d, None, "float")(program, x.astype("f4"), y.astype("f4"), index, a.astype("f4"), sizes, starts) for k in (pattern, "general")]
    assert single[0].dtype == np.float32 and all(np.allclose(z, want, rtol=1e-3, atol=1e-4) for z in single)
    seen = np.concatenate([at.ravel() for _, at in stacks(sizes, starts, 16)])
    assert sorted(seen.tolist()) == list(range(n))


def test_fused_plan_has_no_exchange_between_message_and_partial_sum(fixture):
    e, x, y, _ = fixture
    plan = fused_fold(e, x, y, P.sigmoid_embedding(), d=4, strategy="relational", how="broadcast")._jdf.queryExecution().executedPlan().toString()
    after = plan[plan.rindex("partial_sum") :]
    assert after.index("Project") < after.index("Join") and "Exchange hashpartitioning" not in after[: after.index("Project")]
    conv = fused_fold(e, x, y, P.graph_conv(), d=4, strategy="relational")._jdf.queryExecution().executedPlan().toString()
    assert conv.count("Join") == 1


def test_balanced_parts(spark):
    degrees = (5, 1, 1, 1, 4, 4, 2, 6)
    e = spark.createDataFrame([(u, v, 1.0) for u, k in enumerate(degrees) for v in range(k)], "u long, v long, a double")
    parts = partition.balanced_parts(e, 3)
    assert [r["part"] for r in parts.orderBy("u").collect()] == [0, 0, 0, 0, 1, 1, 2, 2]
    assert partition.imbalance(parts, 3).first()["factor"] == 1
    placed = partition.place(e, parts, 3).withColumn("at", F.spark_partition_id())
    assert placed.where("at <> part").isEmpty() and placed.count() == 24
    assert partition.imbalance(partition.equal_row_parts(e, 4), 4).first()["nnz"] == 24


def test_parts_of_a_skewed_graph_are_even(spark, sf):
    """Edges of each task, on the graph of tokens and on a random graph with hubs; rows as without parts."""
    from edgefold.operators.fused import placed
    from edgefold.sources import features, graphs

    hub = spark.range(2000).select(F.lit(7).cast("long").alias("u"), F.col("id").alias("v"), F.lit(1.0).alias("a"))
    for e in (graphs.edges(spark, sf, "g6"), graphs.rmat(spark, 9, 6000), graphs.rmat(spark, 9, 3000).where("u <> 7").unionByName(hub)):
        e, t = e.persist(), 12
        ids = e.select(F.col("u").alias("id")).union(e.select("v")).distinct()
        x = features.hashed(ids, 4)
        parts, split = placed(e, x, t)
        by = parts.where("v IS NOT NULL").groupBy(F.spark_partition_id().alias("k")).count().collect()
        n = e.count()
        biggest = max(r["deg"] for r in partition.degrees(e).collect())
        assert sum(r["count"] for r in by) == n and max(r["count"] for r in by) <= 1.1 * (n / t + min(biggest, n / t)) and split == (biggest > n / t)
        want = rows(fused_fold(e, x, x, P.layout_literal(), d=4, strategy="relational"))
        got = rows(fused_fold(e, x, x, P.layout_literal(), d=4, strategy="packed", parts=t))
        assert got.keys() == want.keys() and all(np.allclose(got[u], want[u]) for u in want)


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_tiles_carry_no_features_with_edges(fixture):
    """What is shuffled are rows of features, rows of edges without any, and partial results."""
    e, x, y, _ = fixture
    z = fused_fold(e, x, y, P.sigmoid_embedding(), d=4, strategy="tiled", tiles=(3, 2))
    plan = plan_of(z)
    assert "Join" not in plan and plan.count("Exchange") == 2
    tiles = plan[plan.index("Union") :]
    assert tiles.count("Exchange") == 0 and tiles.count("Generate explode") == 2


def test_wide_results_stay_in_generated_code(spark):
    from edgefold.sources import features

    ids = spark.range(20).select("id")
    e = spark.range(60).select((F.col("id") % 6).alias("u"), (F.col("id") % 20).alias("v"), F.lit(1.0).alias("a"))
    x = features.hashed(ids, 80)
    z = fused_fold(e, x, x, P.sigmoid_embedding(), d=80, strategy="relational", how="broadcast")
    got, want = rows(z), rows(fused_fold(e, x, x, P.sigmoid_embedding(), d=80, strategy="packed"))
    assert got.keys() == want.keys() and all(np.allclose(z0, want[u]) for u, z0 in got.items())
    partial = [line for line in plan_of(z).split("Initial Plan")[0].splitlines() if "partial_sum" in line]
    assert partial and all(line.count("partial_sum") <= 32 and "*(" in line for line in partial)


def test_dense_reference_makes_all_products(fixture):
    e, x, y, _ = fixture
    z = two_phase.dense_reference(e, x, y, P.layout_literal(), d=4)
    plan = plan_of(z)
    assert ("CartesianProduct" in plan or "BroadcastNestedLoopJoin" in plan) and "SortMergeJoin" in plan or "BroadcastHashJoin" in plan
    assert plan.index("OuterJoin" if "OuterJoin" in plan else "LeftOuter") >= 0
    want = rows(fused_fold(e, x, y, P.layout_literal(), d=4, strategy="relational"))
    assert {u: pytest.approx(v) for u, v in want.items()} == rows(z)


def test_products_in_blocks_are_exact(spark, sf):
    from edgefold.sources import features, graphs

    x = features.real(spark, sf).limit(300).persist()
    key = lambda df: sorted((r["u"], r["v"], round(r["a"], 9)) for r in df.collect())
    assert key(graphs.knn(x, 5, block=70)) == key(graphs.knn(x, 5)) and graphs.knn(x, 5).count() == 1500
    assert key(E.similar_pairs(x, 0.2, block=70)) == key(E.similar_pairs(x, 0.2)) != []
    assert E.similar_pairs(x.limit(0), 0.2, block=70).collect() == []


def test_costs():
    assert cost.roofline(cost.intensity(76.28, 128), 100) == pytest.approx(95.27, abs=0.01)
    assert cost.intensity(1, 1) == pytest.approx(1 / 6)
    assert (cost.fused_bytes(1500, 2000, 59391, 64), cost.message_bytes(59391, 64), cost.flops(59391, 64)) == (1992692, 45612288, 15204096)
    assert cost.speedup(2.0, None) is None and cost.achieved(1000, 10, 1e-6) == pytest.approx(40)
    assert planner.choose_by_bytes(10**4, 10**4, 10**6, 64, executors=1, memory=1 << 33)["strategy"] in ("broadcast", "row_stationary", "source_stationary")
    assert planner.choose_by_bytes(5 * 10**10, 5 * 10**10, 2 * 10**12, 128, executors=1000, memory=1 << 37)["strategy"] != "broadcast"


def test_invariants(spark, sf):
    from edgefold.queries.kernels import inputs

    e, x, y, t = inputs(spark, sf, "g4")
    e, x, y = e.persist(), x.persist(), y.persist()
    twice = rows(fused_fold(E.transpose(E.transpose(e)), x, y, P.graph_conv(), d=8))
    doubled = rows(fused_fold(e.withColumn("a", F.col("a") * 2), x, y, P.graph_conv(), d=8))
    once = rows(fused_fold(e, x, y, P.graph_conv(), d=8))
    assert twice.keys() == once.keys() and all(np.allclose(once[u], twice[u], rtol=1e-9, atol=1e-12) for u in once)
    assert all(np.allclose(np.asarray(once[u]) * 2, doubled[u]) for u in once)
    assert two_phase.max_abs_diff(fused_fold(e, x, y, P.heavy_tail(), d=8, strategy="packed"), two_phase.two_phase(e, x, y, P.heavy_tail(), d=8)).first()["gap"] < 1e-9


def test_tuning_keeps_the_answer(fixture, tmp_path):
    e, x, y, _ = fixture
    cache = str(tmp_path / "plans.json")
    plans = [planner.Plan("relational"), planner.Plan("packed", parts=2, block=1 << 10), planner.Plan("tiled", tiles=(2, 2))]
    best = planner.tune(e, x, y, P.graph_conv(), 4, plans, rows=1.0, repeats=1, cache=cache)
    assert best.strategy in ("relational", "packed", "tiled") and planner.tune(e, x, y, P.graph_conv(), 4, [], cache=cache) == best
    assert planner.choose(E.clean(e), y, 4, P.graph_conv(), tuned=cache) == best and planner.machine() in open(cache).read()
    want = rows(fused_fold(e, x, y, P.graph_conv(), d=4, strategy="relational"))
    assert {u: pytest.approx(z) for u, z in want.items()} == rows(fused_fold(e, x, y, P.graph_conv(), d=4, tuned=cache))


def test_plans_by_size(fixture, spark):
    e, x, y, _ = fixture
    assert planner.choose(e, y, 4, P.graph_conv()).strategy == "relational"
    assert planner.choose(e, y, 4, P.graph_conv(), batch=True).strategy == "packed"
    small = planner.choose(e, y, 4, P.graph_conv(), limit=1)
    assert small.strategy in ("tiled", "relational")
    big = planner.choose_by_bytes(5 * 10**10, 5 * 10**10, 2 * 10**12, 128, executors=1000, memory=1 << 37)
    assert big["strategy"] != "edge_join" and all(k >= 1 for k in big["tiles"])
    assert planner.grid(16, True) == (4, 4) and planner.grid(7, False) == (7, 1)


def test_measures(spark, fixture):
    from edgefold.plans import measure

    e, x, y, _ = fixture
    make = lambda: fused_fold(e, x, y, P.graph_conv(), d=4, strategy="relational")

    def fails():
        raise MemoryError

    times = measure.time_kernels({"fused": make, "broken": fails}, n=2)
    assert times["fused"] > 0 and times["broken"] is None
    swept = measure.sweep([1, 2], lambda k: {"fused": make, "two_phase": lambda: two_phase.two_phase(e, x, y, P.graph_conv(), d=4)}, n=1)
    assert set(swept) == {1, 2} and swept[1]["speedup"] > 0
    with measure.Moved(spark) as moved:
        two_phase.two_phase(e, x, y, P.graph_conv(), d=4).collect()
    assert moved.bytes["outputBytes"] > 0 and measure.peak_memory(spark, make)["stored_mb"] >= 0
    assert measure.bandwidth(8, 1) > 0 and measure.rates(1000, 8, 10, 0.1, 10.0)["achieved"] > 0
    assert measure.scaling("import json, os; print(json.dumps({'p': int(os.environ['CORES'])}))", [1, 2]) == {1: {"p": 1}, 2: {"p": 2}}


def test_edge_files(spark, tmp_path):
    from edgefold.sources import edge_files as files

    (tmp_path / "a.csv").write_text("1,2,0.5\n1,3\n2,1,4\n")
    (tmp_path / "a.txt").write_text("# nodes\n1 2\n\n3\t1 2.5\n")
    (tmp_path / "a.mtx").write_text("%%MatrixMarket\n% c\n3 3 2\n1 2 5.0\n3 3 1\n")
    got = {(r["u"], r["v"]): r["a"] for r in files.edge_list(spark, str(tmp_path / "a.csv"), base=1).collect()}
    assert got == {(0, 1): 0.5, (0, 2): 1.0, (1, 0): 4.0}
    assert files.edge_list(spark, str(tmp_path / "a.txt"), "text", symmetric=True).count() == 4
    assert {(r["u"], r["v"], r["a"]) for r in files.triplets(spark, str(tmp_path / "a.mtx")).collect()} == {(0, 1, 5.0), (2, 2, 1.0)}
    e = spark.createDataFrame([(u, v, 1.0) for u in range(40) for v in range(3)], "u long, v long, a double")
    files.write_clustered(e, str(tmp_path / "c"), 4)
    assert len(list((tmp_path / "c").glob("part=*"))) == 4 and spark.read.parquet(str(tmp_path / "c")).count() == 120
    for kind in ("parquet", "csv", "json", "noop"):
        files.write(e, kind, str(tmp_path / kind))
    assert files.write(e, "memory").num_rows == 120


def test_training_lowers_the_loss_and_is_the_same_for_both_methods(spark):
    from edgefold.operators import training
    from edgefold.sources import features

    e = spark.createDataFrame([(u, v, 1.0) for b in (0, 6) for u in range(b, b + 6) for v in range(b, b + 6) if u != v], "u long, v long, a double").persist()
    ids = spark.range(12).select(F.col("id").alias("u"))
    start = training.loss(e, features.digest(ids.withColumnRenamed("u", "id"), 8, 1))
    one, seconds = training.train_embedding(e, ids, d=8, batches=1, epochs=2, lr=0.5, negatives=2)
    assert training.loss(e, one) < start and len(seconds) == 2
    other, _ = training.train_embedding(e, ids, d=8, batches=1, epochs=2, lr=0.5, negatives=2, method="two_phase")
    a, b = ({r["id"]: r["x"] for r in f.collect()} for f in (one, other))
    assert all(np.allclose(a[k], b[k]) for k in a)
