import re
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from edgefold.llm import mixing


def brute_targets(sizes):
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: (1.0, 2.0, 3.0)[i % 3] for i, s in enumerate(names)}
    out, total = dict.fromkeys(names, 0.0), float(sum(sizes.values()))
    free, left = set(names), total
    while free:
        level = left / sum(weight[s] for s in free)
        over = {s for s in free if weight[s] * level > 3 * sizes[s]}
        if not over:
            out |= {s: weight[s] * level for s in free}
            break
        out |= {s: 3.0 * sizes[s] for s in over}
        left -= sum(3.0 * sizes[s] for s in over)
        free -= over
    return out


def test_pivotal_keeps_the_sum_and_is_unbiased():
    draw, p = np.random.default_rng(0), np.asarray([0.3, 0.7, 0.25, 0.5, 0.9, 0.05, 0.8, 0.5])
    seen = np.zeros(len(p))
    for _ in range(4000):
        out, open_at = mixing.pivotal(p, draw.random(len(p)))
        assert abs(out.sum() - p.sum()) < 1e-9 and open_at < 0
        seen += out
    assert np.abs(seen / 4000 - p).max() < 0.03
    out, open_at = mixing.pivotal(np.asarray([0.5, 0.2, 0.0, 1.0]), np.asarray([0.1, 0.9, 0.2, 0.3]))
    assert open_at >= 0 and abs(out[:2].sum() - 0.7) < 1e-12 and out[2:].tolist() == [0.0, 1.0]


@pytest.mark.parametrize("sizes", [{"a": 1, "b": 100, "c": 5, None: 7}, {"a": 0, "b": 10}, {None: 4}, {"x": 5, "y": 5, "z": 5, "zz": 1000}, {"a": 0}])
def test_targets(spark, sizes):
    df = spark.createDataFrame([(s, n, 1) for s, n in sizes.items()], "source string, source_size long, n long")
    got, want = {r["source"]: r["target"] for r in mixing.targets(df).collect()}, brute_targets(sizes)
    assert got == pytest.approx(want)


def test_whole_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = mixing.op5_mixing(spark, sf).collect()
    assert rows and sorted(r["doc_id"] for r in rows) == sorted(r["doc_id"] for r in docs.collect())
    words = {r["doc_id"]: (r["source"], len(re.findall(r"[^\x20\x09-\x0D]+", r["text"]))) for r in docs.collect()}
    sizes = defaultdict(int)
    for s, n in words.values():
        sizes[s] += n
    want, taken = brute_targets(sizes), Counter()
    largest = defaultdict(int)
    for r in rows:
        s, n = words[r["doc_id"]]
        assert r["size"] == n and r["source_size"] == sizes[s] and r["target"] == pytest.approx(want[s]) and r["taken"] <= 3 * n
        taken[s] += r["taken"]
        largest[s] = max(largest[s], n)
    for s in sizes:
        assert abs(taken[s] - want[s]) <= 2 * largest[s]
    assert sorted(r["taken"] for r in mixing.op5_mixing(spark, sf).repartition(3).collect()) == sorted(r["taken"] for r in rows)


def test_mix_and_odd_rows(spark):
    rows = [(1, "a b", "s"), (1, "a b", "s"), (1, None, "t"), (None, "x", None), (None, "y z", None), (4, "", "t"), *((i, "w " * i, "u") for i in range(5, 40))]
    docs = spark.createDataFrame([(*r, "clash", 3) for r in rows], "doc_id long, text string, source string, size string, n int")
    mixed = mixing.mix(docs)
    assert mixed.columns == docs.columns
    got, have = Counter((r["doc_id"], r["text"], r["source"]) for r in mixed.collect()), Counter(rows)
    assert got and all(n <= 3 * have[k] for k, n in got.items())
    assert mixing.mix(docs.where("doc_id < 0")).collect() == []
    tree = spark.createDataFrame([(i, "s" if i % 9 else "r", 10) for i in range(3000)], "doc_id long, source string, size long")
    block, fan = mixing.BLOCK, mixing.FAN_IN
    try:
        mixing.BLOCK, mixing.FAN_IN = 16, 4
        total = {r["source"]: r["n"] for r in mixing.copies(tree).groupBy("source").agg(F.sum(F.col("copies") * 10).alias("n")).collect()}
    finally:
        mixing.BLOCK, mixing.FAN_IN = block, fan
    want = brute_targets({"s": 26660, "r": 3340})
    assert all(abs(total[s] - want[s]) <= 10 for s in want)


def test_hot_ids_are_dealt_apart(spark, monkeypatch):
    """All rows without an id, many of them alike: no block gets more than its share, and reruns agree."""
    monkeypatch.setattr(mixing, "BLOCK", 64)
    df = spark.range(1500).select(F.lit(None).cast("long").alias("doc_id"), F.lit("a").alias("source"), (F.col("id") % 3 + 40).alias("size")).repartition(7)
    df = df.unionByName(spark.range(500).select((F.col("id") % 5).alias("doc_id"), F.lit("b").alias("source"), F.lit(40).cast("long").alias("size")))
    numbered = mixing._numbered(df).persist()
    assert numbered.count() == 2000
    per = {r["doc_id"]: (r["n"], r["low"], r["high"], r["d"]) for r in numbered.groupBy("doc_id").agg(F.count("*").alias("n"), F.min("nth").alias("low"), F.max("nth").alias("high"), F.count_distinct("nth").alias("d")).collect()}
    assert per == {None: (1500, 0, 1499, 1500)} | {k: (100, 0, 99, 100) for k in range(5)}
    blocks = numbered.groupBy(F.pmod(F.xxhash64("doc_id", "nth", F.lit(mixing.SEED)), F.lit(24)).alias("b")).count().collect()
    assert max(r["count"] for r in blocks) < 200
    key = lambda d: sorted(map(str, d.select("doc_id", "source", "size", "copies").collect()))
    assert key(mixing.copies(df)) == key(mixing.copies(df.repartition(3)))
    sums = {r["source"]: (r["s"], r["t"]) for r in mixing.copies(df).groupBy("source").agg(F.sum(F.col("copies") * F.col("size")).alias("s"), F.max("target").alias("t")).collect()}
    assert all(abs(s - t) <= 130 for s, t in sums.values())
