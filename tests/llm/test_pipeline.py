"""The five stages in sequence, each against a plain version of it, on documents with planted cases."""

import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from edgefold.llm import toxicity
from edgefold.llm.vocabulary import WordIds, default_path
from test_mixing import brute_targets

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


@pytest.fixture(scope="module")
def folder(spark, sf, tmp_path_factory):
    draw = np.random.default_rng(5)
    words = ["".join(chr(97 + c) for c in draw.integers(0, 26, k)) for k in draw.integers(3, 9, 400)]
    say = lambda n: " ".join(draw.choice(words, n))
    base, passage, rows = say(150), say(60), []
    changed = base.split()
    changed[70] = "otherword"
    rows += [(5001, base), (5002, base), (5003, " ".join(changed)), (5004, say(150))]
    rows += [(5010 + i, f"{say(40)} {passage} {say(40)}") for i in range(5)]
    rows += [(5020, None), (5021, ""), (5022, "é" * 300), (5023, say(20_000))]
    made = [(i, t, "en", "planted" if i % 2 else None, len(t or "")) for i, t in rows]
    place = str(tmp_path_factory.mktemp("pipeline"))
    docs = spark.read.parquet(f"{sf}/documents.parquet").select(*COLUMNS)
    docs.unionByName(spark.createDataFrame(made, docs.schema)).repartition(3).write.parquet(f"{place}/documents.parquet")
    spark.read.parquet(f"{sf}/labels.parquet").write.parquet(f"{place}/labels.parquet")
    return place


@pytest.fixture(scope="module")
def stages(spark, folder):
    """What goes into each stage and what comes out, as lists of rows."""
    docs, out = spark.read.parquet(f"{folder}/documents.parquet"), []
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        got = stage(spark, docs, folder)
        got.write.parquet(f"{folder}/out-{k}")
        got = spark.read.parquet(f"{folder}/out-{k}")
        out.append((name, docs.collect(), got.collect(), got.columns))
        docs = got
    return out


def test_stages_are_named_and_keep_columns(stages):
    assert [s[0] for s in stages] == ["toxicity", "simhash", "suffix_array", "mixing", "packing"]
    assert all(s[3] == COLUMNS for s in stages[:-1])


def plain_probability(text, chain):
    """The chain's last probability, word by word."""
    marks = {}
    for w in re.findall(r"[^\W\d_]+", (text or "").lower()):
        for mark in [w, *[f"^{w[:k]}" for k in (4, 5, 6, 7, 8) if len(w) > k]]:
            marks[mark] = marks.get(mark, 0) + 1
    seen = []
    for model in chain.models:
        at = len(chain.words)
        s = model[-1] + sum(model[chain.words[m]] * np.log1p(n) for m, n in marks.items() if m in chain.words)
        s += sum(model[at + i] * p for i, p in enumerate(seen))
        seen.append(1 / (1 + np.exp(-np.clip(s, -30, 30))))
    return seen[chain.categories.index("toxic")]


def test_toxicity_keeps_what_a_plain_chain_keeps(spark, folder, stages):
    _, before, after, _ = stages[0]
    docs, labels = spark.read.parquet(f"{folder}/documents.parquet"), spark.read.parquet(f"{folder}/labels.parquet")
    chain = toxicity.train(docs, toxicity.known_labels(labels))
    p = {r["doc_id"]: plain_probability(r["text"], chain) for r in before}
    sure = {i for i, x in p.items() if abs(x - 0.5) > 1e-3}
    assert {r["doc_id"] for r in after} & sure == {i for i in sure if p[i] < 0.5}
    assert 0 < len(before) - len(after) < len(before) / 2 and {5001, 5004, 5020, 5023} <= {r["doc_id"] for r in after}


def shingles(text):
    words = (text or "").encode().lower().split()
    return {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()


def test_simhash_keeps_one_of_each_group(stages):
    _, before, after, _ = stages[1]
    ids = sorted(r["doc_id"] for r in before)
    sets = {r["doc_id"]: shingles(r["text"]) for r in before}
    least = {i: i for i in ids}

    def root(i):
        while least[i] != i:
            i = least[i]
        return i

    for k, i in enumerate(ids):
        for j in ids[:k]:
            a, b = sets[i], sets[j]
            if 5 * len(a & b) >= 4 * len(a | b):
                p, q = sorted((root(i), root(j)))
                least[q] = p
    assert sorted(r["doc_id"] for r in after) == [i for i in ids if root(i) == i]
    kept = {r["doc_id"] for r in after}
    assert 5001 in kept and not {5002, 5003} & kept and 5004 in kept


def test_repeats_go(stages):
    _, before, after, _ = stages[2]
    seen, want = set(), {}
    for r in sorted(before, key=lambda r: r["doc_id"]):
        raw, gone = (r["text"] or "").encode(), set()
        for p in range(len(raw) - 99):
            w = raw[p : p + 100]
            if w in seen:
                gone.update(range(p, p + 100))
            seen.add(w)
        want[r["doc_id"]] = bytes(c for i, c in enumerate(raw) if i not in gone).decode("utf-8", "ignore")
    got = {r["doc_id"]: r["text"] or "" for r in after}
    assert got == want and sum(map(len, got.values())) < sum(len(r["text"] or "") for r in before)
    assert all(r["n_chars"] == len(r["text"]) for r in after if r["text"] is not None)


def test_mix_meets_its_targets(stages):
    _, before, after, _ = stages[3]
    size = lambda r: len(re.findall(r"[^\x20\x09-\x0D]+", r["text"] or ""))
    have, taken, largest = {}, {}, {}
    for r in before:
        have[r["source"]] = have.get(r["source"], 0) + size(r)
        largest[r["source"]] = max(largest.get(r["source"], 0), size(r))
    for r in after:
        taken[r["source"]] = taken.get(r["source"], 0) + size(r)
    for s, target in brute_targets(have).items():
        assert abs(taken.get(s, 0) - target) <= 3 * largest[s]
    times = {}
    for r in after:
        times[r["doc_id"]] = times.get(r["doc_id"], 0) + 1
    assert max(times.values()) <= 3 and {(r["doc_id"], r["text"]) for r in after} <= {(r["doc_id"], r["text"]) for r in before}


def test_packing_holds_every_token_once(stages):
    _, before, after, _ = stages[4]
    words, want, got = WordIds.opened(default_path()), {}, {}
    end = np.asarray([2], dtype="<u4").tobytes()
    for r in before:
        raw = words.encode([r["text"]])[0] + end
        want.setdefault(r["doc_id"], []).append(len(raw) // 4)
        for p in (p for p in after if p["doc_id"] == r["doc_id"]):
            assert p["ids_crc32"] == zlib.crc32(raw[4 * p["start"] : 4 * (p["start"] + p["length"])])
    for p in after:
        got[p["doc_id"]] = got.get(p["doc_id"], 0) + p["length"]
    assert got == {i: sum(n) for i, n in want.items()}
    at = {}
    for p in sorted(after, key=lambda p: (p["sequence_id"], p["offset"])):
        assert p["offset"] == at.get(p["sequence_id"], 0)
        at[p["sequence_id"]] = p["offset"] + p["length"]
    assert max(at.values()) <= 4096 and sum(at.values()) >= 0.9 * 4096 * (len(at) - 1)


def test_run_is_the_stages_in_sequence(spark, folder, stages):
    got = corpus_pipeline.run(spark, folder)
    key = lambda rows: sorted((r["doc_id"], r["start"], r["length"], r["ids_crc32"]) for r in rows)
    assert key(got.collect()) == key(stages[-1][2])


def test_stages_take_clashing_columns_and_empty_tables(spark, folder):
    docs = spark.read.parquet(f"{folder}/documents.parquet").limit(40)
    names = ["row", "doc", "nth", "gone", "size", "copies", "time", "key", "name", "left", "mixed_size", "__gone", "kept_id", "fp", "component_id", "h"]
    wide = docs.select("*", *[F.lit(f"v{i}").alias(n) for i, n in enumerate(names)])
    for name, stage in corpus_pipeline.STAGES:
        got, none = stage(spark, wide, folder), stage(spark, wide.limit(0), folder)
        assert none.count() == 0
        if name != "packing":
            assert got.columns == wide.columns
            row = got.first()
            assert all(row[n] == f"v{i}" for i, n in enumerate(names))
        else:
            assert got.count() >= 40
