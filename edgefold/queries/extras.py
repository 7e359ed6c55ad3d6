"""Queries of training, accuracy, generated graphs and streams."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from edgefold.functions import steps as S
from edgefold.operators import training
from edgefold.operators.fused import fused_fold, to_long
from edgefold.operators.two_phase import _shared, two_phase
from edgefold.plans import program as P
from edgefold.queries.oracle import fold_sql
from edgefold.sources import features, graphs, tables
from edgefold.streaming import folds

QUERIES: dict = {}
ORACLE: dict[str, str] = {}
LANGS = ("de", "en", "es", "fr")


def q(name, sql=None):
    def register(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLE[name] = sql
        return f

    return register


_RMAT = graphs.event_rmat_sql(10)
_RT, _RS = f"SELECT DISTINCT u FROM ({_RMAT})", f"SELECT DISTINCT v AS id FROM ({_RMAT})"


@q("sigmoid_embedding_g8", fold_sql(P.sigmoid_embedding(), _RMAT, _RT, features.hashed_sql(f"SELECT u AS id FROM ({_RT})", 8), features.hashed_sql(_RS, 8), 8))
def sigmoid_embedding_g8(spark, sf_dir):
    _shared(spark)
    e = graphs.event_rmat(spark, sf_dir, 10).checkpoint()  # read for edges, targets and neighbours
    ids = e.select(F.col("u").alias("id")).distinct()
    return to_long(fused_fold(e, features.hashed(ids, 8), features.hashed(e.select(F.col("v").alias("id")).distinct(), 8), P.sigmoid_embedding(), d=8, strategy="packed"))


@q("rmat_g8", _RMAT)
def rmat_g8(spark, sf_dir):
    return graphs.event_rmat(spark, sf_dir, 10)


_X5 = features.digest_sql(graphs.targets_sql("g4").replace("AS u", "AS id"), 8, 1)


@q("embedding_step", f"""WITH e AS ({graphs.SQL['g4']}), x AS ({_X5}),
  h AS (SELECT e.u, e.v, sum(p.val * r.val) AS s FROM e JOIN x p ON p.id = e.u JOIN x r ON r.id = e.v AND r.i = p.i GROUP BY 1, 2),
  z AS (SELECT h.u, r.i, sum(r.val / (1 + exp(h.s))) AS z FROM h JOIN x r ON r.id = h.v GROUP BY 1, 2)
  SELECT x.id AS u, x.i, round(x.val + 0.05::DOUBLE * coalesce(z.z, 0), 9) + 0::DOUBLE AS z FROM x LEFT JOIN z ON z.u = x.id AND z.i = x.i""")
def embedding_step(spark, sf_dir):
    """One pull of all vertices, without negatives."""
    x = features.digest(graphs.targets(spark, sf_dir, "g4").withColumnRenamed("u", "id"), 8, 1)
    pull = fused_fold(graphs.edges(spark, sf_dir, "g4"), x, x, P.embedding_pull(), d=8, strategy="relational")
    moved = training._move(x, pull, pull.select("u", F.transform("z", lambda v: v * 0.0).alias("z")), 0.05)
    return to_long(moved.select(F.col("id").alias("u"), F.col("x").alias("z")), 9)


def _language(spark, sf_dir, fold, **options):
    d = 32
    e = graphs.edges(spark, sf_dir, "g6")
    y = features.digest(graphs.sources(spark, sf_dir, "g6"), d, 1)
    docs = tables.load(spark, sf_dir, "documents")
    z = fold(e, None if fold is fused_fold else y, y, P.graph_conv("mean"), d=d, **options)
    label = (F.array_position(F.array(*[F.lit(x) for x in LANGS]), F.col("lang")) - 1).cast("int")
    labels = docs.select(F.col("doc_id").alias("id"), label.alias("label"))
    pred = training.classify(z.select(F.col("u").alias("id"), F.col("z").alias("x")), labels.where("id % 5 <> 0"), d)
    return training.f1_micro(pred.where("id % 5 = 0"), labels)


_F1 = f"""WITH e AS ({graphs.SQL['g6']}), y AS ({features.digest_sql('SELECT DISTINCT v AS id FROM e', 32, 1)}),
  z AS (SELECT e.u AS id, y.i, avg(e.a * y.val) AS val FROM e JOIN y ON y.id = e.v GROUP BY 1, 2),
  l AS (SELECT doc_id AS id, list_position(['de', 'en', 'es', 'fr'], lang) - 1 AS label FROM documents),
  c AS (SELECT label, i, avg(val) AS val FROM z JOIN l USING (id) WHERE id % 5 <> 0 GROUP BY 1, 2),
  s AS (SELECT z.id, c.label, round(sum(z.val * c.val) / (sqrt(sum(z.val * z.val)) * sqrt(sum(c.val * c.val))), 9) AS s FROM z JOIN c USING (i) WHERE z.id % 5 = 0 GROUP BY 1, 2),
  p AS (SELECT id, label AS pred FROM (SELECT *, row_number() OVER (PARTITION BY id ORDER BY s DESC, label) AS r FROM s) WHERE r = 1)
  SELECT count(*) AS n, round(avg((pred = label)::INTEGER), 9) AS f1 FROM p JOIN l USING (id)"""
q("f1_micro_lang", _F1)(lambda s, d: _language(s, d, fused_fold, strategy="relational"))
q("f1_micro_lang_two_phase", _F1)(lambda s, d: _language(s, d, two_phase))


def _files(spark, sf_dir):
    """The events table in files of the shared folder, for a stream."""
    place = f"{_shared(spark)}/events-{uuid.uuid4().hex}"
    tables.load(spark, sf_dir, "events").repartition(3).write.parquet(place)
    return place


def _stream(spark, sf_dir):
    return folds.as_edges(folds.events(spark, _files(spark, sf_dir)))


def _types(spark):
    return features.hashed(spark.range(1, 6).select("id"), 8)


_KINDS = "list_position(['click', 'error', 'purchase', 'signup', 'view'], event_type)"
_TY = features.hashed_sql("SELECT range AS id FROM range(1, 6)", 8)
for _name, _reduce in (("sum", "sum"), ("max", "max"), ("min", "min"), ("mean", "avg")):

    @q(f"streaming_fold_{_name}", f"SELECT user_id AS u, i, round({_reduce}(val), 9) + 0::DOUBLE AS z FROM events JOIN ({_TY}) y ON y.id = {_KINDS} GROUP BY 1, 2")
    def _fold(spark, sf_dir, pool=_name):
        z = folds.streaming_fold(_stream(spark, sf_dir), None, _types(spark), P.graph_conv(pool), 8)
        return to_long(folds.drain(z, f"fold_{uuid.uuid4().hex}"), 9)


@q("streaming_windows",
    f"SELECT user_id AS u, epoch_us(time_bucket(INTERVAL 1 DAY, ts)) "
    f"// 1000000 AS t, i, round(sum(val), 9) + 0::DOUBLE AS z FROM events JOIN ({_TY}) y ON y.id = {_KINDS} "
    f"GROUP BY 1, 2, 3")
def streaming_windows(spark, sf_dir):
    z = folds.windowed_fold(folds.with_lateness(_stream(spark, sf_dir), "1 day"), _types(spark), P.graph_conv("sum"), 8, "1 day")
    z = folds.drain(z, f"windows_{uuid.uuid4().hex}")
    return z.select("u", F.unix_timestamp("start").alias("t"), F.posexplode("z").alias("i", "z")).select("u", "t", "i", F.round("z", 9).alias("z"))


@q("streaming_state", "SELECT user_id AS u, count(*) AS n FROM events GROUP BY 1")
def streaming_state(spark, sf_dir):
    z = folds.stateful_fold(folds.with_lateness(_stream(spark, sf_dir), "40 days"), _types(spark), 8, 3_600_000)
    return folds.drain(z, f"state_{uuid.uuid4().hex}", "update").groupBy("u").agg(F.max("n").alias("n"))


_DAY = "epoch_us(time_bucket(INTERVAL 1 DAY, ts)) // 1000000"
_SLIDING = f"""SELECT user_id AS u, {_DAY} - k * 86400 AS t, i, round(sum(val), 9) + 0::DOUBLE AS z
  FROM events, (SELECT range AS k FROM range(2)) JOIN ({_TY}) y ON y.id = {_KINDS} GROUP BY 1, 2, 3"""


@q("streaming_sliding", _SLIDING)
def streaming_sliding(spark, sf_dir):
    """Windows of two days, one for each day."""
    stream = folds.with_lateness(_stream(spark, sf_dir), "1 day")
    z = folds.drain(folds.windowed_fold(stream, _types(spark), P.graph_conv("sum"), 8, "2 days", "1 day"), f"sliding_{uuid.uuid4().hex}")
    return z.select("u", F.unix_timestamp("start").alias("t"), F.posexplode("z").alias("i", "z")).select("u", "t", "i", F.round("z", 9).alias("z"))


_SESSIONS = f"""WITH e AS (SELECT user_id AS u, epoch_us(ts) AS t, {_KINDS} AS v FROM events),
  b AS (SELECT *, coalesce(t - lag(t) OVER w > 21600000000, true)::INTEGER AS new FROM e WINDOW w AS (PARTITION BY u ORDER BY t)),
  s AS (SELECT *, sum(new) OVER (PARTITION BY u ORDER BY t) AS k FROM b),
  g AS (SELECT *, min(t) OVER (PARTITION BY u, k) // 1000000 AS start FROM s)
  SELECT u, start AS t, i, round(sum(val), 9) + 0::DOUBLE AS z FROM g JOIN ({_TY}) y ON y.id = g.v GROUP BY 1, 2, 3"""


@q("streaming_sessions", _SESSIONS)
def streaming_sessions(spark, sf_dir):
    """Sessions of a user that end after six hours without an event."""
    stream = folds.with_lateness(_stream(spark, sf_dir), "40 days")
    z = folds.drain(folds.windowed_fold(stream, _types(spark), P.graph_conv("sum"), 8, "1 day", gap="6 hours"), f"sessions_{uuid.uuid4().hex}")
    return z.select("u", F.unix_timestamp("start").alias("t"), F.posexplode("z").alias("i", "z")).select("u", "t", "i", F.round("z", 9).alias("z"))


@q("streaming_join", """SELECT p.user_id AS u, q.user_id AS v, count(*) AS a FROM events p JOIN events q ON p.user_id <> q.user_id
  AND abs(epoch_us(p.ts) - epoch_us(q.ts)) <= 300000000 WHERE p.event_type = 'click' AND q.event_type = 'view' GROUP BY 1, 2""")
def streaming_join(spark, sf_dir):
    """Two streams of events, joined where they are five minutes apart at most."""
    place = _files(spark, sf_dir)
    one, other = (folds.events(spark, place).where(F.col("event_type") == t) for t in ("click", "view"))
    met = folds.drain(folds.joined_edges(one, other, "40 days", 300), f"join_{uuid.uuid4().hex}", "append")
    return met.groupBy("u", "v").agg(F.count("*").alias("a"))


@q("streaming_distinct", "SELECT count(*) AS n, count(DISTINCT event_id) AS events FROM events")
def streaming_distinct(spark, sf_dir):
    """The stream twice over: each event counts once."""
    place = _files(spark, sf_dir)
    tables.load(spark, sf_dir, "events").repartition(2).write.mode("append").parquet(place)
    once = folds.drain(folds.distinct_edges(folds.as_edges(folds.events(spark, place)), "40 days"), f"distinct_{uuid.uuid4().hex}", "append")
    return once.agg(F.count("*").alias("n"), F.count_distinct("event_id").alias("events"))


@q("streaming_refresh", "SELECT user_id AS u, count(*) AS n FROM events GROUP BY 1")
def streaming_refresh(spark, sf_dir):
    """Versions of a feature table, one for each micro-batch, that add up to all events."""
    path = f"{_shared(spark)}/versions-{uuid.uuid4().hex}"
    step = lambda batch, version: batch.groupBy("u").agg(F.count("*").alias("n"))
    folds.refresh(_stream(spark, sf_dir), path, step, f"{path}-log").awaitTermination()
    return spark.read.parquet(path).groupBy("u").agg(F.sum("n").alias("n"))
