import re

import numpy as np
import xxhash
from pyspark.sql import functions as F

from edgefold.llm import components, simhash


def brute(text, size=4):
    words = re.findall(r"[^\x20\x09-\x0D]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or ""))
    if not words:
        return 0
    hs = [xxhash.xxh64_intdigest(" ".join(words[i : i + size]).encode(), 42) for i in range(max(1, len(words) - size + 1))]
    return sum(1 << b for b in range(64) if sum(h >> b & 1 for h in hs) * 2 > len(hs))


def least_reachable(fps, bits=4):
    parent = list(range(len(fps)))

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(fps)):
        for j in range(i):
            if bin(fps[i] ^ fps[j]).count("1") <= bits:
                a, b = sorted((root(i), root(j)))
                parent[b] = a
    return [root(i) for i in range(len(fps))]


def test_fingerprint_is_the_definition():
    for text in [None, "", " \n", "One", "A b\x1cc d", "é È a b x y z", "the cat sat on the mat " * 40]:
        assert simhash.fingerprint(text) == brute(text)
    assert simhash.with_fingerprints is not None


def test_spark_hash_agrees(spark):
    assert spark.sql("SELECT xxhash64('ein zwei é') AS h").first()["h"] % (1 << 64) == xxhash.xxh64_intdigest("ein zwei é".encode(), 42)


def test_sets_cover_every_choice():
    for size in (1, 2, 3, 4):
        sets = simhash.position_sets(4, size)
        from itertools import combinations

        assert all(any(set(s) <= set(x) for s in sets) for x in combinations(range(8), 4))


def test_links_join_all_within_four_bits(spark):
    draw = np.random.default_rng(5)
    base = draw.integers(0, 1 << 63, 40).tolist()
    fps = [0, (1 << 64) - 1]
    for b in base:
        fps.append(b)
        for _ in range(12):
            flips = draw.choice(64, draw.integers(1, 6), replace=False)
            fps.append(fps[-1] ^ sum(1 << int(f) for f in flips))
    hub = base[0]
    fps += [hub ^ (1 << i) ^ (1 << j) for i in range(64) for j in range(0, i, 5)]
    fps = sorted(set(fps))
    want = least_reachable(fps)
    signed = [f - (1 << 64) if f >> 63 else f for f in fps]
    df = spark.createDataFrame(list(zip(signed, range(len(fps)))), "fp long, name long")
    for chunk in (2048, 16):
        got = {r["node"]: r["component"] for r in components.components(simhash.links(df, chunk=chunk)).collect()}
        assert [got.get(i, i) for i in range(len(fps))] == want


def test_components_by_rounds(spark):
    draw = np.random.default_rng(1)
    pairs = [(int(a), int(b)) for a, b in draw.integers(0, 400, (300, 2))] + [(i, i + 1) for i in range(500, 560)] + [(900, 900 + i) for i in range(1, 50)]
    df = spark.createDataFrame([*pairs, (None, 4)], "a long, b long")
    want = {r["node"]: r["component"] for r in components.components(df).collect()}
    got = {r["node"]: r["component"] for r in components.components(df, task_links=3).collect()}
    nodes, least = components.union_find(*np.asarray([p for p in pairs if p[0] != p[1]]).T)
    assert got == want == dict(zip(nodes.tolist(), least.tolist()))
    assert components.components(df.limit(0)).collect() == []


def test_small_tables(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").withColumn("fp", F.lit("clash"))
    rows = simhash.cluster(docs).collect()
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    ids = sorted(texts)
    fps = [brute(texts[i]) for i in ids]
    want = {ids[i]: ids[r] for i, r in enumerate(least_reachable(fps))}
    assert {r["doc_id"]: r["component_id"] for r in rows} == want and len(rows) == len(ids)
    odd = spark.createDataFrame([(None, "x y"), (5, None), (3, ""), (9, "x y"), (9, "x y")], "doc_id long, text string")
    got = sorted(((r["doc_id"] or 0, r["component_id"]) for r in simhash.cluster(odd).collect()))
    assert got == [(0, 9), (3, 3), (5, 3), (9, 9), (9, 9)]
    assert simhash.cluster(odd.limit(0)).collect() == []
