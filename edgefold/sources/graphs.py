"""Graphs on the given tables: edges (u, v, a), u the target; targets; and the same as SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from edgefold.operators.ranks import dense_ids
from edgefold.sources import tables

SEGMENTS = ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")
TOKEN = "[^a-zà-ÿ]+"


def _edges(df: DataFrame) -> DataFrame:
    return df.select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v"), F.col("a").cast("double").alias("a"))


def _ids(spark, sf_dir, table, column):
    return tables.load(spark, sf_dir, table).select(F.col(column).cast("long").alias("u"))


def customer_part(spark, sf_dir):
    """G1. Weights are quantities."""
    li, o = tables.load(spark, sf_dir, "lineitem"), tables.load(spark, sf_dir, "orders")
    both = li.join(o, li["l_orderkey"] == o["o_orderkey"])
    return _edges(both.groupBy(F.col("o_custkey").alias("u"), F.col("l_partkey").alias("v")).agg(F.sum("l_quantity").alias("a")))


def supplier_part(spark, sf_dir):
    """G2."""
    li = tables.load(spark, sf_dir, "lineitem")
    return _edges(li.groupBy(F.col("l_suppkey").alias("u"), F.col("l_partkey").alias("v")).agg(F.sum("l_quantity").alias("a")))


def order_part(spark, sf_dir):
    """G3."""
    li = tables.load(spark, sf_dir, "lineitem")
    return _edges(li.groupBy(F.col("l_orderkey").alias("u"), F.col("l_partkey").alias("v")).agg(F.sum("l_quantity").alias("a")))


def successors(events: DataFrame) -> DataFrame:
    """(u, v) of each event and the next in time. Windows are by day; the ends of days are met through one row a day."""
    day = events.withColumn("day", F.to_date("ts"))
    order = Window.partitionBy("day").orderBy("ts", "event_id")
    within = day.select("day", F.col("user_id").alias("u"), F.lead("user_id").over(order).alias("v"))
    firsts = day.groupBy("day").agg(F.min(F.struct("ts", "event_id", "user_id"))["user_id"].alias("first"))
    days = Window.orderBy("day")  # as many rows as days
    nexts = firsts.select("day", F.lead("first").over(days).alias("next"))
    return within.join(F.broadcast(nexts), "day").select("u", F.coalesce("v", "next").alias("v")).where("v IS NOT NULL")


def user_next(spark, sf_dir):
    """G4: a user and the user of the next event, no self edges."""
    pairs = successors(tables.load(spark, sf_dir, "events")).where("u <> v")
    return _edges(pairs.groupBy("u", "v").agg(F.count("*").alias("a")))


def knn(x: DataFrame, k: int, block: int | None = None) -> DataFrame:
    """(u, v, a): the k most alike vectors of each by dot product, ties by id. Exact: every vector meets every block of
    vectors, each block gives its k best, and these are merged. block: vectors in one; a shipped matrix if there is one block."""
    import numpy as np
    import pyarrow as pa

    from edgefold.operators.products import blockwise

    def best(own, rows, ids, matrix):
        s = rows @ matrix.T
        s[own[:, None] == ids[None, :]] = -np.inf
        order = np.lexsort((np.broadcast_to(ids, s.shape), -s), axis=1)[:, :k]
        return pa.RecordBatch.from_arrays([pa.array(np.repeat(own, order.shape[1])), pa.array(ids[order].reshape(-1)), pa.array(np.take_along_axis(s, order, 1).reshape(-1))], ["u", "v", "a"])

    found, blocks = blockwise(x, best, block)
    found = found.where("a > double('-infinity')")
    if blocks == 1:
        return found
    top = F.slice(F.array_sort(F.collect_list(F.struct((-F.col("a")).alias("n"), "v"))), 1, k)
    merged = found.groupBy("u").agg(top.alias("top")).select("u", F.explode("top").alias("t"))
    return merged.select("u", "t.v", (-F.col("t.n")).alias("a"))


def vector_knn(spark, sf_dir, k=10):
    """G5."""
    from edgefold.sources.features import real

    return knn(real(spark, sf_dir), k)


def tokens(spark, sf_dir):
    """(doc_id, token, a): counts of lower-case tokens."""
    d = tables.load(spark, sf_dir, "documents")
    words = d.select("doc_id", F.explode(F.split(F.lower("text"), TOKEN)).alias("token")).where("token <> ''")
    return words.groupBy("doc_id", "token").agg(F.count("*").alias("a"))


def document_token(spark, sf_dir):
    """G6: tokens have dense ids in binary order."""
    t = tokens(spark, sf_dir)
    ids = dense_ids(t, "token", "v")
    return _edges(t.join(ids, "token").select(F.col("doc_id").alias("u"), "v", "a"))


def part_part(spark, sf_dir):
    """G7: parts in one order, both ways; weights are numbers of orders."""
    li = tables.load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    other = li.select("l_orderkey", F.col("l_partkey").alias("v"))
    both = li.withColumnRenamed("l_partkey", "u").join(other, "l_orderkey").where("u <> v")
    return _edges(both.groupBy("u", "v").agg(F.count("*").alias("a")))


def page_link(spark, sf_dir):
    """G9: a page and the words of the paths that it links to."""
    p = tables.load(spark, sf_dir, "pages")
    links = p.select(F.col("page_id").alias("u"), F.explode(F.regexp_extract_all("html", F.lit('href="/([^"]*)"'), 1)).alias("word"))
    counted = links.groupBy("u", "word").agg(F.count("*").alias("a"))
    return _edges(counted.join(dense_ids(counted, "word", "v"), "word"))


def nation_segment(spark, sf_dir):
    """G10: a nation and the market segments of its customers."""
    c = tables.load(spark, sf_dir, "customer")
    segment = F.array_position(F.array(*[F.lit(s) for s in SEGMENTS]), F.col("c_mktsegment")) - 1
    return _edges(c.groupBy(F.col("c_nationkey").alias("u"), segment.alias("v")).agg(F.count("*").alias("a")))


def turn_path(spark, sf_dir):
    """G11: a turn and the one before it; ids are conversation * 1000 + turn."""
    c = tables.load(spark, sf_dir, "conversations")
    before = F.lag("turn").over(Window.partitionBy("conv_id").orderBy("turn"))
    t = c.select("conv_id", "turn", before.alias("before")).where("before IS NOT NULL")
    return _edges(t.select((F.col("conv_id") * 1000 + F.col("turn")).alias("u"), (F.col("conv_id") * 1000 + F.col("before")).alias("v"), F.lit(1.0).alias("a")))


def benchmark_token(spark, sf_dir):
    """G12: benchmark items and tokens, numbered by themselves."""
    b = tables.load(spark, sf_dir, "benchmark")
    words = b.select(F.col("item_id").alias("u"), F.explode(F.split(F.lower("text"), TOKEN)).alias("token")).where("token <> ''")
    counted = words.groupBy("u", "token").agg(F.count("*").alias("a"))
    return _edges(counted.join(dense_ids(counted, "token", "v"), "token"))


def rmat(spark: SparkSession, scale: int, edges: int | DataFrame, probs=(0.57, 0.19, 0.19, 0.05), seed: int = 1) -> DataFrame:
    """G8: each edge falls into a quadrant of the adjacency at each of `scale` levels, by bytes of a digest. Repeats merge.

    edges: how many, or a row (id) for each."""
    a, b, c, _ = (round(p * 65536) for p in probs)
    e = spark.range(edges) if isinstance(edges, int) else edges
    u, v = F.lit(0).cast("long"), F.lit(0).cast("long")
    for level in range(scale):
        head = F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("id").cast("string"), F.lit(str(level)))), 1, 4)
        r = F.conv(head, 16, 10).cast("long")
        u = u * 2 + (r >= a + b).cast("long")
        v = v * 2 + (((r >= a) & (r < a + b)) | (r >= a + b + c)).cast("long")
    return _edges(e.select(u.alias("u"), v.alias("v")).groupBy("u", "v").agg(F.count("*").alias("a")))


def rmat_sql(scale: int, edges: int, probs=(0.57, 0.19, 0.19, 0.05), seed: int = 1) -> str:
    a, b, c, _ = (round(p * 65536) for p in probs)
    return f"""SELECT u, v, count(*)::DOUBLE AS a FROM (
      SELECT id, sum((r >= {a + b})::BIGINT << ({scale - 1} - l))::BIGINT AS u, sum(((r >= {a} AND r < {a + b}) OR r >= {a + b + c})::BIGINT << ({scale - 1} - l))::BIGINT AS v
      FROM (SELECT id, l, ('0x' || substr(md5('{seed}:' || id || ':' || l), 1, 4))::BIGINT AS r FROM (SELECT range AS id FROM range({edges})), (SELECT range AS l FROM range({scale}))) GROUP BY id) GROUP BY u, v"""


def event_rmat(spark: SparkSession, sf_dir: str, scale: int = 10) -> DataFrame:
    """G8 with an edge for each event."""
    return rmat(spark, scale, tables.load(spark, sf_dir, "events").select(F.col("event_id").alias("id")).where("id IS NOT NULL"))


def event_rmat_sql(scale: int = 10, probs=(0.57, 0.19, 0.19, 0.05), seed: int = 1) -> str:
    a, b, c, _ = (round(p * 65536) for p in probs)
    draws = ", ".join(f"('0x' || substr(md5('{seed}:' || event_id || ':{k}'), 1, 4))::BIGINT AS r{k}" for k in range(scale))
    u = " + ".join(f"((r{k} >= {a + b})::BIGINT << {scale - 1 - k})" for k in range(scale))
    v = " + ".join(f"(((r{k} >= {a} AND r{k} < {a + b}) OR r{k} >= {a + b + c})::BIGINT << {scale - 1 - k})" for k in range(scale))
    return f"SELECT {u} AS u, {v} AS v, count(*)::DOUBLE AS a FROM (SELECT {draws} FROM events WHERE event_id IS NOT NULL) GROUP BY 1, 2"


EDGES = {"g1": customer_part, "g2": supplier_part, "g3": order_part, "g4": user_next, "g5": vector_knn, "g6": document_token, "g7": part_part, "g9": page_link, "g10": nation_segment, "g11": turn_path, "g12": benchmark_token}
_SEGMENT_SQL = "list_position([" + ", ".join(f"'{s}'" for s in SEGMENTS) + "], c_mktsegment) - 1"
_TOKENS_SQL = "SELECT {id} AS u, token, count(*)::DOUBLE AS a FROM (SELECT {id}, unnest(regexp_split_to_array(lower(text), '" + TOKEN + "')) AS token FROM {table}) WHERE token <> '' GROUP BY {id}, token"
SQL = {
    "g1": "SELECT o_custkey AS u, l_partkey AS v, sum(l_quantity) AS a FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2",
    "g2": "SELECT l_suppkey AS u, l_partkey AS v, sum(l_quantity) AS a FROM lineitem GROUP BY 1, 2",
    "g3": "SELECT l_orderkey AS u, l_partkey AS v, sum(l_quantity) AS a FROM lineitem GROUP BY 1, 2",
    "g4": "SELECT u, v, count(*)::DOUBLE AS a FROM (SELECT user_id AS u, lead(user_id) OVER (ORDER BY ts, event_id) AS v FROM events) WHERE u <> v GROUP BY 1, 2",
    "g5": "SELECT u, v, a FROM (SELECT u, v, a, row_number() OVER (PARTITION BY u ORDER BY a DESC, v) AS r FROM (SELECT p.vec_id AS u, q.vec_id AS v, list_dot_product(p.embedding::DOUBLE[], q.embedding::DOUBLE[]) AS a FROM embeddings p, embeddings q WHERE p.vec_id <> q.vec_id)) WHERE r <= 10",
    "g6": "SELECT u, dense_rank() OVER (ORDER BY token) - 1 AS v, a FROM (" + _TOKENS_SQL.format(id="doc_id", table="documents") + ")",
    "g7": "SELECT p.l_partkey AS u, q.l_partkey AS v, count(*)::DOUBLE AS a FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) p JOIN (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) q USING (l_orderkey) WHERE p.l_partkey <> q.l_partkey GROUP BY 1, 2",
    "g9": "SELECT u, dense_rank() OVER (ORDER BY word) - 1 AS v, a FROM (SELECT page_id AS u, word, count(*)::DOUBLE AS a FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"/([^\"]*)\"', 1)) AS word FROM pages) GROUP BY 1, 2)",
    "g10": f"SELECT c_nationkey::BIGINT AS u, ({_SEGMENT_SQL})::BIGINT AS v, count(*)::DOUBLE AS a FROM customer GROUP BY 1, 2",
    "g11": "SELECT conv_id * 1000 + turn AS u, conv_id * 1000 + before AS v, 1.0::DOUBLE AS a FROM (SELECT conv_id, turn, lag(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS before FROM conversations) WHERE before IS NOT NULL",
    "g12": "SELECT u, dense_rank() OVER (ORDER BY token) - 1 AS v, a FROM (" + _TOKENS_SQL.format(id="item_id", table="benchmark") + ")",
}
#: Tables and keys of the targets; graphs that are not here have their edges' targets.
_TARGETS = {"g1": ("customer", "c_custkey"), "g2": ("supplier", "s_suppkey"), "g3": ("orders", "o_orderkey"), "g5": ("embeddings", "vec_id"), "g6": ("documents", "doc_id"), "g7": ("part", "p_partkey"), "g10": ("nation", "n_nationkey")}
_SOURCES = {"g1": ("part", "p_partkey"), "g2": ("part", "p_partkey"), "g3": ("part", "p_partkey"), "g5": ("embeddings", "vec_id"), "g7": ("part", "p_partkey")}


def edges(spark: SparkSession, sf_dir: str, graph: str) -> DataFrame:
    return EDGES[graph](spark, sf_dir)


def targets(spark: SparkSession, sf_dir: str, graph: str) -> DataFrame:
    if graph in _TARGETS:
        return _ids(spark, sf_dir, *_TARGETS[graph]).distinct()
    if graph == "g4":
        return _ids(spark, sf_dir, "events", "user_id").distinct()
    return edges(spark, sf_dir, graph).select("u").distinct()


def targets_sql(graph: str) -> str:
    if graph in _TARGETS:
        table, key = _TARGETS[graph]
        return f"SELECT DISTINCT {key}::BIGINT AS u FROM {table}"
    return "SELECT DISTINCT user_id AS u FROM events" if graph == "g4" else f"SELECT DISTINCT u FROM ({SQL[graph]})"


def sources(spark: SparkSession, sf_dir: str, graph: str) -> DataFrame:
    """(id) of all possible neighbours."""
    if graph in _SOURCES:
        return _ids(spark, sf_dir, *_SOURCES[graph]).distinct().withColumnRenamed("u", "id")
    if graph == "g4":
        return targets(spark, sf_dir, graph).withColumnRenamed("u", "id")
    if graph == "g10":
        return spark.range(len(SEGMENTS)).select("id")
    return edges(spark, sf_dir, graph).select(F.col("v").alias("id")).distinct()


def sources_sql(graph: str) -> str:
    if graph in _SOURCES:
        table, key = _SOURCES[graph]
        return f"SELECT DISTINCT {key}::BIGINT AS id FROM {table}"
    return "SELECT DISTINCT user_id AS id FROM events" if graph == "g4" else f"SELECT DISTINCT v AS id FROM ({SQL[graph]})"
