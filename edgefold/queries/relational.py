"""Queries of the operators around the fold."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from edgefold.functions import vectors
from edgefold.operators import edges as E
from edgefold.operators import packed, partition, ranks
from edgefold.operators.fused import fused_fold, gather, salted_gather, to_long
from edgefold.operators.ranks import prefix_sum
from edgefold.plans import program as P
from edgefold.queries.kernels import D, inputs
from edgefold.sources import features, graphs, tables

QUERIES: dict = {}
ORACLE: dict[str, str] = {}
G = graphs.SQL
G1, G4, G5, G7, G10 = G["g1"], G["g4"], G["g5"], G["g7"], G["g10"]


def q(name, sql=None):
    def register(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLE[name] = sql
        return f

    return register


def edges(graph):
    return lambda spark, sf_dir: graphs.edges(spark, sf_dir, graph)


for _table in tables.KEYS:
    QUERIES[f"scan_{_table}"] = lambda spark, sf_dir, t=_table: tables.checksums(tables.load(spark, sf_dir, t), t)
    ORACLE[f"scan_{_table}"] = tables.checksums_sql(_table)

# Layouts, cleaning, shape.
_LONG = f"SELECT id, i, val FROM ({features.hashed_sql(graphs.sources_sql('g1'), 4, 3)})"


@q("layout_roundtrip", _LONG)
def layout_roundtrip(spark, sf_dir):
    x = features.hashed(graphs.sources(spark, sf_dir, "g1"), 4, 3)
    for kind in ("wide", "long", "array", "long"):
        x = features.to_layout(x, kind, 4)
    return x


@q("feature_slice", f"SELECT id, val FROM ({_LONG}) WHERE i = 2")
def feature_slice(spark, sf_dir):
    x = features.hashed(graphs.sources(spark, sf_dir, "g1"), 4, 3)
    return x.select("id", F.slice("x", 3, 1).getItem(0).alias("val"))


@q("feature_digest", f"SELECT id, i, val FROM ({features.digest_sql(graphs.sources_sql('g1'), 4, 5)})")
def feature_digest(spark, sf_dir):
    return features.to_layout(features.digest(graphs.sources(spark, sf_dir, "g1"), 4, 5), "long", 4)


@q("pivot_features", "SELECT id, max(val) FILTER (i = 0) AS x0, max(val) FILTER (i = 1) AS x1, max(val) FILTER (i = 2) AS x2, max(val) FILTER (i = 3) AS x3 FROM (" + _LONG + ") GROUP BY id")
def pivot_features(spark, sf_dir):
    return features.pivot_features(features.to_layout(features.hashed(graphs.sources(spark, sf_dir, "g1"), 4, 3), "long", 4), 4)


@q("clean_edges",
    f"SELECT u, v, a FROM (SELECT l_suppkey AS u, l_partkey AS v, CASE "
    f"WHEN l_partkey % 11 = 0 THEN 0 WHEN l_partkey % 13 = 0 THEN NULL ELSE l_quantity END AS a FROM lineitem) "
    f"WHERE a IS NOT NULL AND a <> 0 AND u <> v")
def clean_edges(spark, sf_dir):
    weight = F.when(F.col("l_partkey") % 11 == 0, 0.0).when(F.col("l_partkey") % 13 == 0, None).otherwise(F.col("l_quantity"))
    return E.clean(tables.load(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("u"), F.col("l_partkey").alias("v"), weight.alias("a")))


@q("threshold_graph", f"SELECT u, v, round(a, 9) AS a FROM ({G5}) WHERE a >= 0.3")
def threshold_graph(spark, sf_dir):
    return E.threshold(graphs.edges(spark, sf_dir, "g5"), 0.3).select("u", "v", F.round("a", 9).alias("a"))


@q("min_degree", f"SELECT u, v, a FROM (SELECT *, count(*) OVER (PARTITION BY u) AS n FROM ({G4})) WHERE n >= 55")
def min_degree(spark, sf_dir):
    return E.min_degree(graphs.edges(spark, sf_dir, "g4"), 55)


q("transpose", f"SELECT v AS u, u AS v, a FROM ({G4})")(lambda s, d: E.transpose(graphs.edges(s, d, "g4")))
q("symmetrise", f"SELECT u, v, sum(a) AS a FROM (SELECT u, v, a FROM ({G4}) UNION ALL SELECT v, u, a FROM ({G4})) GROUP BY 1, 2")(lambda s, d: E.symmetrise(graphs.edges(s, d, "g4")))
q("self_loops", f"SELECT u, v, a FROM ({G4}) UNION ALL SELECT u, u, 1.0::DOUBLE FROM ({graphs.targets_sql('g4')})")(lambda s, d: E.with_self_loops(graphs.edges(s, d, "g4"), graphs.targets(s, d, "g4")))
q("unweighted_g1", f"SELECT u, v, 1.0::DOUBLE AS a FROM ({G1})")(lambda s, d: E.unweight(graphs.edges(s, d, "g1")))
q("packed_roundtrip", G4)(lambda s, d: packed.unpack(packed.pack(graphs.edges(s, d, "g4"))))
q("packed_rows", f"SELECT u, count(*)::INTEGER AS deg, min(v) AS first_v, sum(a) AS total FROM ({G4}) GROUP BY u")(lambda s, d: packed.pack(graphs.edges(s, d, "g4")).select("u", "deg", F.col("vs").getItem(0).alias("first_v"), F.aggregate("ws", F.lit(0.0), lambda a, x: a + x).alias("total")))

# Joins.
_Y = features.hashed_sql(graphs.sources_sql("g1"), 4)
_JOIN = f"WITH y AS ({_Y}) SELECT e.u, round(sum(e.a * y.val), 6) + 0::DOUBLE AS s FROM ({G1}) e JOIN y ON y.id = e.v AND y.i = 1 GROUP BY e.u"
for _how in ("broadcast", "merge", "hash"):

    def _join(spark, sf_dir, how=_how):
        y = features.hashed(graphs.sources(spark, sf_dir, "g1"), 4)
        both = gather(graphs.edges(spark, sf_dir, "g1"), y, "v", "y", how)
        return both.groupBy("u").agg(F.round(F.sum(F.col("a") * F.col("y").getItem(1)), 6).alias("s"))

    q(f"join_{_how}", _JOIN)(_join)


@q("salted_join", _JOIN)
def salted_join(spark, sf_dir):
    y = features.hashed(graphs.sources(spark, sf_dir, "g1"), 4)
    both = salted_gather(graphs.edges(spark, sf_dir, "g1"), y, 4)
    return both.groupBy("u").agg(F.round(F.sum(F.col("a") * F.col("y").getItem(1)), 6).alias("s"))


@q("join_x",
    f"WITH x AS ({features.hashed_sql('SELECT u AS id FROM (' + graphs.targets_sql('g1') + ')', 4)}) "
    f"SELECT e.u, round(sum(e.a) * any_value(x.val), 6) + 0::DOUBLE AS s FROM ({G1}) e "
    f"JOIN x ON x.id = e.u AND x.i = 0 GROUP BY e.u")
def join_x(spark, sf_dir):
    x = features.hashed(graphs.targets(spark, sf_dir, "g1").withColumnRenamed("u", "id"), 4)
    # sums first, so that one row for each target meets its features
    sums = graphs.edges(spark, sf_dir, "g1").groupBy("u").agg(F.sum("a").alias("a"))
    return gather(sums, x, "u", "x").select("u", F.round(F.col("a") * F.col("x").getItem(0), 6).alias("s"))


q("semi_targets", f"SELECT u, v, a FROM ({G1}) WHERE u IN (SELECT c_custkey FROM customer WHERE c_mktsegment = 'BUILDING')")(lambda s, d: E.slice_rows(graphs.edges(s, d, "g1"), tables.load(s, d, "customer").where("c_mktsegment = 'BUILDING'").select(F.col("c_custkey").alias("u"))))
q("anti_isolated", f"SELECT p_partkey AS u FROM part WHERE p_partkey NOT IN (SELECT u FROM ({G7}))")(lambda s, d: E.isolated(graphs.targets(s, d, "g7"), graphs.edges(s, d, "g7")))
q("outer_zero_rows",
    f"SELECT t.u, coalesce(sum(e.a), 0)::DOUBLE AS s FROM ({graphs.targets_sql('g3')}) t LEFT "
    f"JOIN ({G['g3']}) e USING (u) GROUP BY t.u"
    )(lambda s, d: graphs.targets(s, d, "g3").join(graphs.edges(s, d, "g3"), "u", "left").groupBy("u").agg(F.coalesce(F.sum("a"), F.lit(0.0)).alias("s")))


@q("full_outer_degree",
    f"SELECT coalesce(p.u, q.u) AS u, coalesce(p.n, 0)::BIGINT AS as_target, coalesce(q.n, 0)::BIGINT AS as_source "
    f"FROM (SELECT u, count(*) AS n FROM ({G1}) GROUP BY u) p FULL JOIN (SELECT v AS u, count(*) AS n FROM ({G1}) "
    f"GROUP BY v) q ON p.u = q.u")
def full_outer_degree(spark, sf_dir):
    e = graphs.edges(spark, sf_dir, "g1")
    out = e.groupBy("u").agg(F.count("*").alias("p")).join(e.groupBy(F.col("v").alias("u")).agg(F.count("*").alias("q")), "u", "full_outer")
    return out.select("u", F.coalesce("p", F.lit(0)).cast("long").alias("as_target"), F.coalesce("q", F.lit(0)).cast("long").alias("as_source"))


q("right_outer_sources", f"SELECT p_partkey AS v, count(e.u) AS n FROM ({G1}) e RIGHT JOIN part ON p_partkey = e.v GROUP BY p_partkey")(lambda s, d: graphs.edges(s, d, "g1").join(tables.load(s, d, "part").select(F.col("p_partkey").alias("v")), "v", "right").groupBy("v").agg(F.count("u").alias("n")))
q("cross_small", "SELECT n_nationkey AS u, r_regionkey AS v, (n_regionkey = r_regionkey) AS own FROM nation, region")(lambda s, d: tables.load(s, d, "nation").crossJoin(tables.load(s, d, "region")).select(F.col("n_nationkey").alias("u"), F.col("r_regionkey").alias("v"), (F.col("n_regionkey") == F.col("r_regionkey")).alias("own")))
q("copurchase_pairs", G7)(edges("g7"))
q("theta_similar",
    "SELECT p.vec_id AS u, q.vec_id AS v, round(list_dot_product(p.embedding::DOUBLE[], "
    "q.embedding::DOUBLE[]), 9) AS a FROM embeddings p "
    "JOIN embeddings q ON p.vec_id < q.vec_id AND list_dot_product(p.embedding::DOUBLE[], q.embedding::DOUBLE[]) >= 0.35"
    )(lambda s, d: E.similar_pairs(features.real(s, d), 0.35).select("u", "v", F.round("a", 9).alias("a")))
_DEG = "SELECT u, count(*) AS deg FROM ({}) GROUP BY u"
_PRE = f"SELECT u, deg, (sum(deg) OVER (ORDER BY u) - deg)::BIGINT AS before FROM ({_DEG.format(G4)})"


@q("part_range_join",
    f"WITH p AS ({_PRE}), b AS (SELECT k::INTEGER AS part, k * 1000 AS low, (k + 1) * 1000 AS high "
    f"FROM (SELECT unnest(range((SELECT max(before) // 1000 + 1 FROM p))) AS k)) SELECT u, part FROM p "
    f"JOIN b ON before >= low AND before < high")
def part_range_join(spark, sf_dir):
    prefix = prefix_sum(partition.degrees(graphs.edges(spark, sf_dir, "g4")), "u", "deg", "before")
    last = prefix.agg(F.max("before")).first()[0]  # intervals as far as the running counts go
    bounds = spark.range(0 if last is None else last // 1000 + 1).select(F.col("id").cast("int").alias("part"), (F.col("id") * 1000).alias("low"), ((F.col("id") + 1) * 1000).alias("high"))
    return E.assign_parts(prefix, bounds, 1000)


q("prefix_nnz", _PRE)(lambda s, d: prefix_sum(partition.degrees(graphs.edges(s, d, "g4")), "u", "deg", "before"))


@q("asof_event",
    "SELECT e.event_id, e.user_id, max_by(v.value, (v.ts, v.event_id)) AS version FROM (SELECT * FROM events "
    "WHERE event_type <> 'purchase') e LEFT JOIN (SELECT * FROM events "
    "WHERE event_type = 'purchase') v ON v.user_id = e.user_id AND v.ts <= e.ts GROUP BY 1, 2")
def asof_event(spark, sf_dir):
    e = tables.load(spark, sf_dir, "events")
    versions = e.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("since"), F.col("value").alias("version"))
    asked = e.where("event_type <> 'purchase'").select("user_id", "ts", "event_id")
    return E.asof_features(asked, versions, "user_id", "ts", "since").select("event_id", "user_id", "version")


@q("interval_edges",
    "SELECT p.user_id AS u, q.user_id AS v, count(*) AS a FROM events p "
    "JOIN events q ON p.user_id <> q.user_id AND abs(epoch_us(p.ts) // 1000000 - epoch_us(q.ts) // 1000000) <= 300 "
    "WHERE p.event_type = 'click' AND q.event_type = 'view' GROUP BY 1, 2")
def interval_edges(spark, sf_dir):
    e = tables.load(spark, sf_dir, "events").withColumn("t", F.unix_timestamp(F.col("ts").cast("timestamp")))
    return E.interval_edges(e.where("event_type = 'click'"), e.where("event_type = 'view'"), 300)


# Aggregations.
@q("ordered_fold", f"SELECT u, list_reduce(list(a ORDER BY v), lambda s, x: s * 0.5 + x) AS s FROM ({G10}) GROUP BY u")
def ordered_fold(spark, sf_dir):
    rows = packed.pack(graphs.edges(spark, sf_dir, "g10"))
    return rows.select("u", F.aggregate(F.slice("ws", 2, 1 << 30), F.col("ws").getItem(0), lambda s, x: s * 0.5 + x).alias("s"))


q("degree_distinct", "SELECT l_suppkey AS u, count(DISTINCT l_partkey) AS deg FROM lineitem GROUP BY 1")(lambda s, d: tables.load(s, d, "lineitem").groupBy(F.col("l_suppkey").alias("u")).agg(F.count_distinct("l_partkey").alias("deg")))
@q("degree_approximate", "SELECT l_suppkey AS u, count(DISTINCT l_partkey) AS deg, true AS counted, true AS sketched FROM lineitem GROUP BY 1")
def degree_approximate(spark, sf_dir):
    """Distinct neighbours, and whether an approximate count and a sketch come within a fifth of them."""
    li = tables.load(spark, sf_dir, "lineitem").groupBy(F.col("l_suppkey").alias("u"))
    got = li.agg(F.count_distinct("l_partkey").alias("deg"), F.approx_count_distinct("l_partkey").alias("c"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("s"))
    near = lambda c: F.abs(F.col(c) - F.col("deg")) <= F.col("deg") * 0.2 + 1
    return got.select("u", "deg", near("c").alias("counted"), near("s").alias("sketched"))


_DIMS = "(SELECT l_returnflag, l_linestatus, l_quantity FROM lineitem)"
for _name, _group in (("rollup_weight", "ROLLUP (l_returnflag, l_linestatus)"), ("cube_weight", "CUBE (l_returnflag, l_linestatus)"), ("gsets_weight", "GROUPING SETS ((l_returnflag), (l_linestatus), ())")):

    def _grouped(spark, sf_dir, group=_group):
        tables.load(spark, sf_dir, "lineitem").createOrReplaceTempView("__lineitem")
        return spark.sql(f"SELECT l_returnflag, l_linestatus, grouping_id(l_returnflag, l_linestatus) AS g, sum(l_quantity) AS weight FROM __lineitem GROUP BY {group}")

    q(_name, f"SELECT l_returnflag, l_linestatus, grouping_id(l_returnflag, l_linestatus)::BIGINT AS g, sum(l_quantity) AS weight FROM {_DIMS} GROUP BY {_group}")(_grouped)


@q("centroids_by_label", "SELECT label, (s - 1)::INTEGER AS i, round(avg(embedding[s]::DOUBLE), 9) + 0::DOUBLE AS mean FROM embeddings, (SELECT range AS s FROM range(1, 65)) GROUP BY 1, 2")
def centroids_by_label(spark, sf_dir):
    e = tables.load(spark, sf_dir, "embeddings")
    means = e.groupBy("label").agg(F.array(*[F.avg(F.col("embedding").getItem(i).cast("double")) for i in range(64)]).alias("m"))
    return means.select("label", F.posexplode("m").alias("i", "mean")).select("label", "i", F.round("mean", 9).alias("mean"))


q("degree_hist", f"SELECT (deg // 5)::BIGINT AS bin, count(*) AS n FROM ({_DEG.format(G4)}) GROUP BY 1")(lambda s, d: partition.degrees(graphs.edges(s, d, "g4")).groupBy(F.floor(F.col("deg") / 5).alias("bin")).agg(F.count("*").alias("n")))
q("degree_quantiles",
    f"SELECT quantile_cont(deg, 0.25)::DOUBLE AS q1, quantile_cont(deg, "
    f"0.5)::DOUBLE AS q2, quantile_cont(deg, 0.75)::DOUBLE AS q3 FROM ({_DEG.format(G4)})"
    )(lambda s, d: partition.degrees(graphs.edges(s, d, "g4")).agg(*[F.percentile("deg", F.lit(p)).alias(n) for p, n in ((0.25, "q1"), (0.5, "q2"), (0.75, "q3"))]))
@q("degree_quantiles_approximate", f"SELECT true AS counted, true AS sketched, count(*) AS n FROM ({_DEG.format(G4)})")
def degree_quantiles_approximate(spark, sf_dir):
    """Whether an approximate median and a sketch's have between 45 and 55 per cent of the degrees below or at them."""
    deg = partition.degrees(graphs.edges(spark, sf_dir, "g4"))
    kll = F.kll_sketch_get_quantile_bigint(F.kll_sketch_agg_bigint("deg"), F.lit(0.5))
    medians = deg.agg(F.percentile_approx("deg", F.lit(0.5)).alias("q"), kll.alias("k"))
    both = deg.crossJoin(F.broadcast(medians))

    def near(c):
        return (F.avg((F.col("deg") < F.col(c)).cast("double")) <= 0.55) & (F.avg((F.col("deg") <= F.col(c)).cast("double")) >= 0.45)

    return both.agg(near("q").alias("counted"), near("k").alias("sketched"), F.count("*").alias("n"))


q("strongest_neighbour", f"SELECT u, v, a FROM (SELECT *, row_number() OVER (PARTITION BY u ORDER BY a DESC, v) AS r FROM ({G1})) WHERE r = 1")(lambda s, d: E.strongest(graphs.edges(s, d, "g1")))
q("filtered_weight",
    "SELECT l_suppkey AS u, sum(l_quantity) FILTER (WHERE l_returnflag "
    "= 'R') AS returned, sum(CASE WHEN l_linestatus = 'F' THEN l_quantity ELSE 0 END) AS done FROM lineitem "
    "GROUP BY 1"
    )(lambda s, d: tables.load(s, d, "lineitem").groupBy(F.col("l_suppkey").alias("u")).agg(F.expr("sum(l_quantity) FILTER (WHERE l_returnflag = 'R')").alias("returned"), F.sum(F.when(F.col("l_linestatus") == "F", F.col("l_quantity")).otherwise(0)).alias("done")))

# Windows.
q("rank_neighbours",
    f"SELECT u, v, a, row_number() OVER (PARTITION BY u "
    f"ORDER BY a DESC, v)::INTEGER AS place, rank() OVER (PARTITION BY u "
    f"ORDER BY a DESC)::INTEGER AS rank, dense_rank() OVER (PARTITION BY u ORDER BY a DESC)::INTEGER AS dense FROM ({G4})")(lambda s, d: E.rank_neighbours(graphs.edges(s, d, "g4")))
q("degree_ntile", f"SELECT u, deg, ntile(4) OVER (ORDER BY deg, u)::INTEGER AS tile FROM ({_DEG.format(G4)})")(lambda s, d: ranks.tiles(partition.degrees(graphs.edges(s, d, "g4")), ["deg", "u"], 4))
q("degree_cume",
    f"SELECT u, deg, round(cume_dist() OVER (ORDER BY deg), 9) AS cume, "
    f"round(percent_rank() OVER (ORDER BY deg), 9) AS pct FROM ({_DEG.format(G4)})"
    )(lambda s, d: ranks.shares(partition.degrees(graphs.edges(s, d, "g4")), "deg").select("u", "deg", F.round("cume", 9).alias("cume"), F.round("pct", 9).alias("pct")))
q("successor_edges", G4)(edges("g4"))
q("turn_edges", G["g11"])(edges("g11"))
_T = "epoch_us(ts) // 1000000 AS t"


@q("rolling_rows",
    "SELECT event_id, first_value(value) OVER w AS first, last_value(value) "
    "OVER w AS last, nth_value(value, 2) OVER w AS second, max(value) OVER w AS top FROM events "
    "WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)")
def rolling_rows(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)
    return tables.load(spark, sf_dir, "events").select("event_id", F.first("value").over(w).alias("first"), F.last("value").over(w).alias("last"), F.nth_value("value", 2).over(w).alias("second"), F.max("value").over(w).alias("top"))


@q("rolling_range",
    f"SELECT event_id, count(*) OVER w AS n, max(value) OVER w AS top FROM (SELECT *, {_T} FROM events) "
    f"WINDOW w AS (PARTITION BY user_id ORDER BY t RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW)")
def rolling_range(spark, sf_dir):
    e = tables.load(spark, sf_dir, "events").withColumn("t", F.unix_timestamp(F.col("ts").cast("timestamp")))
    w = Window.partitionBy("user_id").orderBy("t").rangeBetween(-3600, 0)
    return e.select("event_id", F.count("*").over(w).alias("n"), F.max("value").over(w).alias("top"))


q("row_normalise", f"SELECT u, v, round(a / sum(a) OVER (PARTITION BY u), 9) AS a FROM ({G4})")(lambda s, d: E.row_normalise(graphs.edges(s, d, "g4")).select("u", "v", F.round("a", 9).alias("a")))

# Sorts, limits, sets, sampling.
q("sorted_edges", G4)(lambda s, d: graphs.edges(s, d, "g4").orderBy("u", "v"))
_NORM = f"SELECT id AS u, round(sqrt(sum(val * val)), 9) AS norm FROM ({features.hashed_sql(graphs.sources_sql('g1'), 4)}) GROUP BY id"


def _norms(spark, sf_dir):
    return features.hashed(graphs.sources(spark, sf_dir, "g1"), 4).select(F.col("id").alias("u"), F.round(vectors.norm("x"), 9).alias("norm"))


q("topk_norm", f"{_NORM} ORDER BY norm DESC, u LIMIT 20")(lambda s, d: _norms(s, d).orderBy(F.desc("norm"), "u").limit(20))
q("limit_offset", f"{_NORM} ORDER BY norm DESC, u LIMIT 20 OFFSET 7")(lambda s, d: _norms(s, d).orderBy(F.desc("norm"), "u").offset(7).limit(20))
q("knn_g5", f"SELECT u, v, round(a, 9) AS a FROM ({G5})")(lambda s, d: graphs.edges(s, d, "g5").select("u", "v", F.round("a", 9).alias("a")))
q("sample_neighbours",
    f"SELECT u, v, a FROM (SELECT *, row_number() OVER (PARTITION BY u ORDER BY md5('9:' || u || ':' || v), v) AS r "
    f"FROM ({G4})) WHERE r <= 5"
    )(lambda s, d: E.sample_neighbours(graphs.edges(s, d, "g4"), 5, 9))
q("negative_pairs",
    f"SELECT u, ('0x' || substr(md5('2:' || u || ':' || j), 1, 8))::BIGINT % 1000 AS v "
    f"FROM ({graphs.targets_sql('g4')}), (SELECT range AS j FROM range(4))"
    )(lambda s, d: E.negatives(graphs.targets(s, d, "g4"), 1000, 4, 2))
_A, _B = "SELECT l_suppkey AS u, l_partkey AS v FROM lineitem WHERE l_returnflag = 'R'", "SELECT l_suppkey AS u, l_partkey AS v FROM lineitem WHERE l_linestatus = 'F'"
for _kind in ("union", "intersect", "except"):
    for _all in (False, True):

        def _set(spark, sf_dir, kind=_kind, every=_all):
            li = tables.load(spark, sf_dir, "lineitem")
            pick = lambda test: li.where(test).select(F.col("l_suppkey").alias("u"), F.col("l_partkey").alias("v"))
            return E.edge_set(pick("l_returnflag = 'R'"), pick("l_linestatus = 'F'"), kind, every)

        q(f"edges_{_kind}{'_all' if _all else ''}", f"{_A} {_kind.upper()} {'ALL ' if _all else ''}{_B}")(_set)

# Functions.
_VAL = features.hashed_sql(graphs.sources_sql("g1"), 4)
_ACT = {"sigmoid": "1.0 / (1.0 + exp(-val))", "tanh": "tanh(val)", "relu": "greatest(val, 0)", "softplus": "greatest(val, 0) + ln(1 + exp(-abs(val)))", "leaky": "CASE WHEN val > 0 THEN val ELSE val * 0.01 END", "identity": "val"}
for _name, _sql in _ACT.items():
    q(f"act_{_name}", f"SELECT id, i, round({_sql}, 9) + 0::DOUBLE AS z FROM ({_VAL})")(lambda s, d, n=_name: features.hashed(graphs.sources(s, d, "g1"), 4).select("id", F.posexplode(F.transform("x", vectors.ACTIVATIONS[n])).alias("i", "z")).select("id", "i", F.round("z", 9).alias("z")))


@q("math_functions",
    f"SELECT id, i, round(exp(val), 9) AS e, round(ln(1 + abs(val)), "
    f"9) AS l, round(sqrt(abs(val)), 9) AS r, round(pow(val, 3), 9) "
    f"+ 0::DOUBLE AS p, sign(val)::DOUBLE AS s, floor(val * 7)::BIGINT AS f FROM ({_VAL})")
def math_functions(spark, sf_dir):
    x = features.to_layout(features.hashed(graphs.sources(spark, sf_dir, "g1"), 4), "long", 4)
    v = F.col("val")
    return x.select("id", "i", F.round(F.exp(v), 9).alias("e"), F.round(F.log1p(F.abs(v)), 9).alias("l"), F.round(F.sqrt(F.abs(v)), 9).alias("r"), F.round(F.pow(v, 3), 9).alias("p"), F.signum(v).alias("s"), F.floor(v * 7).alias("f"))


_ARR = f"SELECT id, list(val ORDER BY i) AS x FROM ({_VAL}) GROUP BY id"
_PAIR = f"SELECT p.id, p.x, q.x AS y FROM ({_ARR}) p JOIN (SELECT id, list(val ORDER BY i) AS x FROM ({features.hashed_sql(graphs.sources_sql('g1'), 4, 77)}) GROUP BY id) q USING (id)"


def _two(spark, sf_dir):
    ids = graphs.sources(spark, sf_dir, "g1")
    return features.hashed(ids, 4).join(features.hashed(ids, 4, 77).withColumnRenamed("x", "y"), "id")


_VEC = {
    "vec_dot": (lambda: vectors.dot("x", "y"), "list_dot_product(x, y)"),
    "vec_cosine": (lambda: vectors.cosine("x", "y"), "list_dot_product(x, y) / (sqrt(list_dot_product(x, x)) * sqrt(list_dot_product(y, y)))"),
    "vec_norm": (lambda: vectors.norm("x"), "sqrt(list_dot_product(x, x))"),
    "vec_dist": (lambda: vectors.dist("x", "y"), "sqrt(list_sum(list_transform(list_zip(x, y), lambda p: (p[1] - p[2]) * (p[1] - p[2]))))"),
    "vec_axpy": (lambda: vectors.axpy(0.5, "x", "y").getItem(2), "0.5::DOUBLE * x[3] + y[3]"),
    "vec_hadamard": (lambda: vectors.hadamard("x", "y").getItem(1), "x[2] * y[2]"),
    "vec_normalise": (lambda: vectors.normalise("x").getItem(3), "x[4] / sqrt(list_dot_product(x, x))"),
    "vec_matvec": (lambda: vectors.matvec("x", [[1.0, 0.5], [2.0, -1.0], [0.25, 3.0], [-2.0, 1.0]]).getItem(1), "x[1] * 0.5::DOUBLE - x[2] + x[3] * 3::DOUBLE + x[4]"),
    "array_sum": (lambda: F.aggregate("x", F.lit(0.0), lambda a, v: a + v), "list_sum(x)"),
    "array_zip": (lambda: F.arrays_zip("x", "y").getItem(1)["y"], "y[2]"),
    "array_slice": (lambda: F.array_max(F.slice("x", 2, 2)), "greatest(x[2], x[3])"),
    "array_sort": (lambda: F.array_sort("x").getItem(0), "list_min(x)"),
    "array_size": (lambda: F.size(F.filter("x", lambda v: v > 0)).cast("double"), "len(list_filter(x, lambda v: v > 0))::DOUBLE"),
}
for _name, (_f, _sql) in _VEC.items():
    q(_name, f"SELECT id, round({_sql}, 8) + 0::DOUBLE AS z FROM ({_PAIR})")(lambda s, d, f=_f: _two(s, d).select("id", F.round(f(), 8).alias("z")))


@q("sparse_dot",
    "SELECT p.u, q.u AS v, sum(p.n * q.n)::BIGINT AS s FROM (SELECT item_id AS u, token, count(*) AS n "
    "FROM (SELECT item_id, unnest(regexp_split_to_array(lower(text), '[^a-zà-ÿ]+')) AS token FROM benchmark) "
    "WHERE token <> '' GROUP BY 1, 2) p JOIN (SELECT item_id AS u, token, count(*) AS n "
    "FROM (SELECT item_id, unnest(regexp_split_to_array(lower(text), '[^a-zà-ÿ]+')) AS token FROM benchmark) "
    "WHERE token <> '' GROUP BY 1, 2) q ON p.token = q.token AND p.u < q.u GROUP BY 1, 2")
def sparse_dot(spark, sf_dir):
    b = tables.load(spark, sf_dir, "benchmark")
    words = b.select(F.col("item_id").alias("doc_id"), F.explode(F.split(F.lower("text"), graphs.TOKEN)).alias("token")).where("token <> ''")
    x = vectors.sparse_vector(words.groupBy("doc_id", "token").agg(F.count("*").alias("a")))
    # only items that share a token meet
    tokens = words.distinct()
    pairs = tokens.join(tokens.select(F.col("doc_id").alias("v"), "token"), "token").where("doc_id < v").select("doc_id", "v").distinct()
    both = pairs.join(x, "doc_id").join(x.select(F.col("doc_id").alias("v"), F.col("terms").alias("other")), "v")
    return both.select(F.col("doc_id").alias("u"), "v", vectors.sparse_dot("terms", "other").alias("s"))


q("json_weight", "SELECT user_id AS u, sum((props ->> '$.k')::BIGINT)::BIGINT AS s FROM events GROUP BY 1")(lambda s, d: tables.load(s, d, "events").groupBy(F.col("user_id").alias("u")).agg(F.sum(F.get_json_object("props", "$.k").cast("long")).alias("s")))
q("tokens_g6",
    "SELECT doc_id, token, count(*) AS a "
    "FROM (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '[^a-zà-ÿ]+')) AS token FROM documents) "
    "WHERE token <> '' GROUP BY 1, 2")(lambda s, d: graphs.tokens(s, d))
q("time_edges",
    "SELECT user_id AS u, (epoch(date_trunc('hour', ts)) // 3600)::BIGINT "
    "AS v, count(*)::DOUBLE AS a, max(dayofweek(ts))::INTEGER AS dow FROM events GROUP BY 1, 2"
    )(lambda s, d: tables.load(s, d, "events").withColumn("h", F.date_trunc("hour", F.col("ts").cast("timestamp"))).groupBy(F.col("user_id").alias("u"), F.floor(F.unix_timestamp("h") / 3600).alias("v")).agg(F.count("*").cast("double").alias("a"), (F.max(F.dayofweek("h")) - 1).alias("dow")))
q("time_slice_weight",
    "SELECT event_type, sum(value) FILTER (WHERE ts < TIMESTAMP '2024-01-01' "
    "+ INTERVAL 7 DAY) IS NOT NULL AS early, count(*) FILTER (WHERE "
    "date_diff('day', DATE '2024-01-01', ts::DATE) >= 7) AS late FROM events GROUP BY 1"
    )(lambda s, d: tables.load(s, d, "events").groupBy("event_type").agg(F.expr("sum(value) FILTER (WHERE ts < TIMESTAMP_NTZ '2024-01-01' + INTERVAL 7 DAY) IS NOT NULL").alias("early"), F.expr("count(*) FILTER (WHERE date_diff(cast(ts AS date), DATE '2024-01-01') >= 7)").alias("late")))


@q("udf_arrow_step", f"SELECT id, i, round(val / (1 + abs(val)), 9) + 0::DOUBLE AS z FROM ({_VAL})")
def udf_arrow_step(spark, sf_dir):
    @F.pandas_udf("double")
    def softsign(v):
        return v / (1 + v.abs())

    x = features.to_layout(features.hashed(graphs.sources(spark, sf_dir, "g1"), 4), "long", 4)
    return x.select("id", "i", F.round(softsign("val"), 9).alias("z"))


@q("udaf_vector_sum", f"SELECT id % 10 AS u, i, round(sum(val), 6) + 0::DOUBLE AS z FROM ({_VAL}) GROUP BY 1, 2")
def udaf_vector_sum(spark, sf_dir):
    import numpy as np
    import pyarrow as pa

    def run(group):
        m = np.asarray(group["x"].combine_chunks().flatten()).reshape(group.num_rows, -1)
        return pa.table({"u": group["u"][:1], "z": pa.array([m.sum(axis=0).tolist()])})

    x = features.hashed(graphs.sources(spark, sf_dir, "g1"), 4).select((F.col("id") % 10).alias("u"), "x")
    return to_long(x.groupBy("u").applyInArrow(run, "u long, z array<double>"))


@q("udtf_unpack", G4)
def udtf_unpack(spark, sf_dir):
    @F.udtf(returnType="v bigint, a double")
    class Unpack:
        def eval(self, vs, ws):
            yield from zip(vs, ws, strict=True)

    spark.udtf.register("edgefold_unpack", Unpack)
    packed.pack(graphs.edges(spark, sf_dir, "g4")).createOrReplaceTempView("__packed")
    return spark.sql("SELECT u, e.v, e.a FROM __packed, LATERAL edgefold_unpack(vs, ws) e")


def _views(spark, sf_dir):
    e, x, y, _ = inputs(spark, sf_dir, "g4")
    e.createOrReplaceTempView("__edges")
    features.to_layout(x, "long", D).createOrReplaceTempView("__x")
    features.to_layout(y, "long", D).createOrReplaceTempView("__y")


_XL, _YL = features.hashed_sql(f"SELECT u AS id FROM ({graphs.targets_sql('g4')})", D), features.hashed_sql(graphs.sources_sql("g4"), D)
_SIG = (
    "WITH s AS (SELECT e.u, e.v, 1 / (1 + exp(-sum(x.val * y.val))) AS h FROM {e} e JOIN {x} x ON x.id = e.u "
    "JOIN {y} y ON y.id = e.v AND y.i = x.i GROUP BY e.u, e.v) SELECT s.u, y.i, round(sum(s.h * y.val), 6) AS z "
    "FROM s JOIN {y} y ON y.id = s.v GROUP BY s.u, y.i"
)


@q("sql_sigmoid_embedding", _SIG.format(e=f"({G4})", x=f"({_XL})", y=f"({_YL})").replace("AS z FROM", "+ 0::DOUBLE AS z FROM"))
def sql_sigmoid_embedding(spark, sf_dir):
    _views(spark, sf_dir)
    return spark.sql(_SIG.format(e="__edges", x="__x", y="__y"))


@q("sql_graph_conv", f"SELECT e.u, y.i, round(sum(e.a * y.val), 6) + 0::DOUBLE AS z FROM ({G4}) e JOIN ({_YL}) y ON y.id = e.v WHERE e.a >= 2 GROUP BY e.u, y.i")
def sql_graph_conv(spark, sf_dir):
    _views(spark, sf_dir)
    return spark.sql("SELECT e.u, y.i, round(sum(e.a * y.val), 6) AS z FROM __edges e JOIN __y y ON y.id = e.v WHERE e.a >= :least GROUP BY e.u, y.i", args={"least": 2})
