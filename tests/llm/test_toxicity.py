import numpy as np
import pytest
from pyspark.sql import functions as F

from edgefold.llm import toxicity as tx


def test_logistic_finds_the_optimum():
    draw = np.random.default_rng(0)
    x = draw.normal(size=(400, 3)).astype(np.float32)
    y = (draw.random(400) < 1 / (1 + np.exp(-(x @ [2.0, -1.0, 0.0] + 0.5)))).astype(float)
    w = tx.fit_logistic(x, y)
    p = tx.probability(x, w)
    grad = np.append(x.T @ (p - y) + tx.PENALTY * w[:-1], (p - y).sum())
    assert np.abs(grad).max() < 0.05
    assert tx.probability(x, tx.fit_logistic(x, np.ones(400))).min() > 0.99
    assert tx.probability(x[:2], tx.fit_logistic(x[:0], y[:0])).max() < 0.01


def test_chain_feeds_earlier_categories():
    counts = [tx.count_words("alpha beta" if i % 2 else "gamma delta") for i in range(200)]
    labels = np.asarray([[i % 2, i % 2] for i in range(200)], dtype=float)
    chain = tx.fit_chain(list(range(200)), counts, labels, ("one", "two"))
    assert len(chain.models[1]) == len(chain.models[0]) + 1 and chain.models[1][-2] > 0
    assert (np.round(chain.predict(counts)) == labels).all()


def test_held_out_labels(spark):
    sf = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), tx.known_labels(spark.read.parquet(f"{sf}/labels.parquet"))
    chain = tx.train(docs, labels.where("doc_id % 2 = 0"))
    rows = tx.predict(docs.join(labels.where("doc_id % 2 = 1").select("doc_id", F.col("toxic").alias("truth")), "doc_id"), chain)
    got = rows.join(labels.select("doc_id", F.col("toxic").alias("truth")), "doc_id").select("toxic", "truth").toPandas()
    found = (got["toxic"] >= 0.5) & (got["truth"] == 1)
    assert found.sum() / (got["toxic"] >= 0.5).sum() > 0.95 and found.sum() / (got["truth"] == 1).sum() > 0.8


def test_odd_rows(spark):
    docs = spark.createDataFrame([(i, "bad worse " * 3 if i % 3 == 0 else "good day", "x") for i in range(60)] + [(None, None, "x"), (1, "", None), (1, "bad worse bad", "x")], "doc_id long, text string, toxic string")
    labels = spark.createDataFrame([(i, 1, int(i % 3 == 0)) for i in range(60)] + [(3, None, None), (None, 0, 1)], "doc_id long, quality int, toxic int")
    chain = tx.train(docs, tx.known_labels(labels))
    kept = tx.keep_clean(docs, chain)
    assert kept.columns == docs.columns
    assert not [r for r in kept.collect() if "bad" in (r["text"] or "")] and kept.count() == 42
    assert tx.predict(docs, chain).count() == 63
    none = tx.train(docs, tx.known_labels(labels.limit(0)))
    assert tx.keep_clean(docs, none).count() == 63
    assert tx.keep_clean(docs.limit(0), none).collect() == []


def test_whole_table_against_a_plain_chain(spark, sf):
    from test_pipeline import plain_probability

    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), tx.known_labels(spark.read.parquet(f"{sf}/labels.parquet"))
    chain, text = tx.train(docs, labels), {r["doc_id"]: r["text"] for r in docs.collect()}
    rows = tx.op9_toxicity(spark, sf).collect()
    assert sorted(r["doc_id"] for r in rows) == sorted(text)
    for r in rows:
        p = plain_probability(text[r["doc_id"]], chain)
        assert r["p_toxic"] == pytest.approx(p, abs=1e-4) and r["rejected"] == (r["p_toxic"] >= tx.THRESHOLD)


def test_labels_that_disagree(spark):
    docs = spark.createDataFrame([(i, "bad" if i % 2 else "good") for i in range(40)], "doc_id long, text string")
    labels = [(i, 0, 0) for i in range(40)] + [(i, 0, 1) for i in range(40) if i % 2] + [(2, 0, None)]
    df = spark.createDataFrame(labels, "doc_id long, low_quality int, toxic int")
    one, other = (tx.train(docs, df.repartition(n)) for n in (1, 5))
    assert [m.tolist() for m in one.models] == [m.tolist() for m in other.models]
    got = {r["doc_id"]: r["toxic"] >= 0.5 for r in tx.predict(docs, one).collect()}
    assert got == {i: i % 2 == 1 for i in range(40)}
