import hashlib
import re
from collections import Counter

import numpy as np
import pytest

from edgefold.llm import weighted_sampling as ws


def jaccard(a, b):
    x, y = (Counter(re.findall(r"[^\x20\x09-\x0D]+", t.lower())) for t in (a, b))
    return sum((x & y).values()) / max(1, sum((x | y).values()))


def test_collision_rate_is_generalised_jaccard():
    sampler, draw = ws.Sampler.made(2048), np.random.default_rng(2)
    base = draw.integers(0, 60, 300)
    for share in (0.1, 0.4, 0.8):
        other = np.where(draw.random(300) < share, draw.integers(40, 200, 300), base)
        a, b = (" ".join(f"w{i}" for i in x) for x in (base, other))
        codes = sampler.signatures([ws.weighted_set(a, {}), ws.weighted_set(b, {})])
        assert (codes[0] == codes[1]).mean() == pytest.approx(jaccard(a, b), abs=0.05)


def plain_signature(text, sampler):
    """Sample by sample and word by word."""
    import xxhash

    f, out = np.float32, []
    words = sorted((xxhash.xxh64_intdigest(w), n) for w, n in Counter((text or "").encode().lower().split()).items())
    for j in range(sampler.samples):
        best = None
        for h, n in words:
            x = h * int(sampler.salt[j]) % 2**64
            x ^= x >> 29
            x = x * 0xBF58476D1CE4E5B9 % 2**64
            x ^= x >> 32
            r, beta, log_c = sampler.rate[x & 0xFFFF], sampler.beta[x >> 16 & 0xFFFF], sampler.log_c[x >> 32 & 0xFFFF]
            up = np.floor(f(np.log(float(n))) / r + beta) if n > 1 else f(0)
            score = log_c - r * (up - beta + f(1)) if n > 1 else log_c - r * (f(1) - beta)
            if best is None or score < best[0]:
                best = (score, max(1, ((h & 0xFFFFFFFF) + 1 + int(up) * 0x9E3779B1) % 2**32))
        out.append(best[1] if best else 0)
    return out


def test_signatures_are_those_of_a_plain_version():
    sampler, draw = ws.Sampler.made(32), np.random.default_rng(3)
    texts = [" ".join(f"w{i}" for i in draw.zipf(1.4, n).clip(max=60)) for n in (1, 5, 40, 300)] + ["", None, "é É e", "a " * 70_000]
    codes = sampler.signatures([ws.weighted_set(t, {}) for t in texts])
    assert codes.tolist() == [plain_signature(t, sampler) for t in texts]


def test_rows_of_one_id_are_in_many_ranges(spark):
    rows = [(None, f"{i:04} a b {i % 7}") for i in range(300)] + [(5, f"z{i % 3} c") for i in range(100)] + [(6, "end")]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    check(ws.likeness_to_next(df).collect(), rows)
    sizes = [r["count"] for r in ws.with_next(df).groupBy("part").count().collect()]
    assert len(sizes) > 2 and max(sizes) < 200


def test_gamma_tables():
    sampler = ws.Sampler.made(8)
    assert sampler.rate.mean() == pytest.approx(2, abs=0.01) and sampler.rate.var() == pytest.approx(2, abs=0.03)


def check(rows, docs):
    ordered = sorted(docs, key=lambda r: (r[0] is not None, r[0] or 0, r[1] is not None, r[1] or ""))
    want = Counter()
    texts = [t or "" for _, t in ordered]
    for i, (d, _) in enumerate(ordered):
        t, f = texts[i], texts[(i + 1) % len(texts)]
        changed = ws.edited(t, f)
        want[d, len(t), hashlib.sha256(changed.encode()).hexdigest()] += 1
    assert Counter((r["doc_id"], r["n_chars"], r["edited_sha256"]) for r in rows) == want
    prints = {}
    for r in rows:
        assert 0 <= r["near_edited"] <= 1 and 0 <= r["near_next"] <= 1
    return prints


def test_whole_table(spark, sf):
    docs = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    rows = ws.op4_fingerprints(spark, sf).collect()
    check(rows, docs)
    by = {r["doc_id"]: r["fingerprint"] for r in rows}
    alone = {r["doc_id"]: r["fingerprint"] for r in ws.fingerprints(spark.read.parquet(f"{sf}/documents.parquet")).collect()}
    assert by == alone
    text_of = dict(docs)
    same = {}
    for d, f in by.items():
        assert same.setdefault(text_of[d], f) == f
    off = [abs(r["near_edited"] - jaccard(text_of[r["doc_id"]], ws.edited(text_of[r["doc_id"]], text_of.get(r["doc_id"] + 1, text_of[0])))) for r in rows]
    assert np.mean(off) < 0.06


@pytest.mark.parametrize("rows", [[], [(3, "a b c d")], [(3, "abcd"), (3, "abcd"), (3, None), (None, "x" * 9), (None, None), (1, "é è"), (9, "")]])
def test_odd_rows(spark, rows):
    df = spark.createDataFrame([(*r, 1, True) for r in rows], "doc_id long, text string, part int, own boolean")
    check(ws.likeness_to_next(df).collect(), rows)
