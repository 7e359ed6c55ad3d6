"""Packing against the ids of the whole library, and the planner against brute force."""

import itertools
import random
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from edgefold.llm import packing
from edgefold.llm.vocabulary import WordIds, default_path

ROWS = [(1, "one two three"), (2, None), (3, ""), (3, "same id again, twice."), (4, "w" * 50), (None, "no id"), (5, "go on " * 3000), (6, "go on " * 3000)]


def test_closest_fill_is_the_best_subset():
    draw = random.Random(3)
    for _ in range(60):
        counts = Counter(draw.choices(range(1, 30), k=7))
        room = draw.randint(5, 60)
        items = list(counts.elements())
        best = max(s for k in range(len(items) + 1) for c in itertools.combinations(items, k) if (s := sum(c)) <= room)
        used = packing.closest_fill(dict(counts), room)
        assert sum(x * n for x, n in used.items()) == best and all(n <= counts[x] for x, n in used.items())


@pytest.mark.parametrize("counts", [{2500: 40}, {1: 3}, {4095: 5, 1: 2}, {100: 1000, 333: 77, 4000: 9}, {3000: 13, 1500: 1}])
def test_plan_gives_each_item_a_place_of_its_own(counts):
    places = packing.Places(packing.make_plan(counts))
    filled = defaultdict(list)
    for length, n in counts.items():
        for k in range(n):
            parts = places.pieces(length, k)
            assert sum(p[1] for p in parts) == length
            for _, size, window, offset in parts:
                filled[window].append((offset, size))
    for parts in filled.values():
        at = 0
        for offset, size in sorted(parts):
            assert offset == at
            at += size
        assert at <= 4096
    total = sum(x * n for x, n in counts.items())
    assert len(filled) <= -(-total // 4096) + 1


def test_pieces_hold_each_id_once(spark, sf):
    docs = spark.createDataFrame(ROWS, "doc_id long, text string").unionByName(
        spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").where("doc_id >= 10")
    )
    docs = docs.withColumn("sequence_id", F.lit("clash")).withColumn("part", F.lit(1))
    rows = [r.asDict() for r in packing.pack(docs).collect()]
    library, want = WordIds(default_path()).library, Counter()
    texts = defaultdict(list)
    for r in docs.collect():
        texts[r["doc_id"]].append(library.encode(r["text"] or "", add_special_tokens=False).ids + [2])
    for r in rows:
        assert any(
            len(ids) == r["doc_tokens"]
            and zlib.crc32(np.asarray(ids[r["start"] : r["start"] + r["length"]], "<u4").tobytes()) == r["ids_crc32"]
            for ids in texts[r["doc_id"]]
        )
    for r in rows:
        want[r["sequence_id"]] += r["length"]
    assert max(want.values()) <= 4096
    assert sum(want.values()) == sum(len(x) for v in texts.values() for x in v)
    assert len(want) <= -(-sum(want.values()) // 4096) + 1


def test_empty_table(spark):
    assert packing.pack(spark.createDataFrame([], "doc_id long, text string")).collect() == []
