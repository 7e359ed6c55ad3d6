import random

import numpy as np
import pytest

from edgefold.llm import near_copies, simhash


def jaccard(x, y):
    a, b = (set(simhash.shingle_set(t, 5).tolist()) for t in (x, y))
    return len(a & b) / len(a | b) if a | b else 1.0


def groups(texts):
    """Least index reachable by pairs of similarity 0.8 or more."""
    parent = list(range(len(texts)))
    sets = [simhash.shingle_set(t, 5) for t in texts]

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(texts)):
        for j in range(i):
            both = len(np.intersect1d(sets[i], sets[j]))
            if 5 * both >= 4 * (len(sets[i]) + len(sets[j]) - both):
                a, b = sorted((root(i), root(j)))
                parent[b] = a
    return [root(i) for i in range(len(texts))]


def edited(draw, words, low, high):
    """A copy with words changed one by one until its similarity lies in [low, high)."""
    out = list(words)
    while True:
        out[draw.randrange(len(out))] = f"new{draw.random()}"
        j = jaccard(" ".join(words), " ".join(out))
        if j < low:
            out = list(words)
        elif j < high:
            return " ".join(out)


def corpus(seed=3):
    draw = random.Random(seed)
    texts = []
    for k in range(40):
        words = [f"w{draw.randrange(3000)}" for _ in range(draw.choice([100, 160, 400]))]
        low = (0.8, 0.85, 0.9, 0.95)[k % 4]
        texts += [" ".join(words), edited(draw, words, low, low + 0.05), edited(draw, words, 0.5, 0.78)]
    return texts


def test_stage_finds_edited_copies(spark):
    texts = corpus() + ["one two", "One  two", "", None, "a b c"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    kept = sorted(r["doc_id"] for r in simhash.keep_one(docs).collect())
    assert kept == sorted(set(groups(texts)))
    assert not {3 * k + 1 for k in range(40)} & set(kept)


@pytest.mark.parametrize("leaders, chunk", [(0, 4), (1, 4), (2, 256)])
def test_all_ways_of_comparing_agree(spark, leaders, chunk):
    draw = random.Random(9)
    base = [f"w{k}" for k in range(150)]
    texts = [edited(draw, base, 0.75, 0.95) for _ in range(40)] + corpus(4)[:30]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: r["component_id"] for r in near_copies.cluster(docs, lambda t: simhash.shingle_set(t, 5), leaders=leaders, chunk=chunk).collect()}
    assert [got[k] for k in range(len(texts))] == groups(texts)


def test_ids_and_given_documents(spark, sf):
    odd = spark.createDataFrame([(None, "x y"), (5, None), (3, ""), (9, "x y"), (9, "x y")], "doc_id long, text string")
    assert sorted(r["doc_id"] or 0 for r in simhash.keep_one(odd).collect()) == [0, 3, 9, 9]
    assert simhash.keep_one(odd.limit(0)).collect() == []
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = sorted((r["doc_id"], r["text"]) for r in docs.collect())
    want = sorted({rows[k][0] for k in groups([t for _, t in rows])})
    assert sorted(r["doc_id"] for r in simhash.keep_one(docs).collect()) == want
