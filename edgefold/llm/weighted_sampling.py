"""Document fingerprints by consistent weighted sampling.

A document is a weighted set: its words (runs of characters other than ASCII white space, A-Z lowered) with their
counts. For each of D samples every term draws two gamma(2, 1) values and a uniform from its hash and the sample's
number, and the term with the least score is the sample: a term, and the step of its weight. Two documents share a sample
with a probability that equals their generalised Jaccard similarity (sum of minima over sum of maxima).

Draws come from 16 bits of a hash each through tables of quantiles, so scores are the same on every machine and in
every batch, and equal texts have equal fingerprints.

Defined cases: null and empty texts have the fingerprint of zeros and are alike to each other only; rows are ordered by
doc_id, nulls first, and those that repeat an id by the first 64 characters of their texts, a hash of these and the
texts; the next document of the last is the first; a lone document is its own next; an
empty table gives no rows; columns other than doc_id and text are ignored.
"""

from __future__ import annotations

import hashlib
from collections import Counter

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgefold.llm.shared import long_id, partitions, prepare, settle, table

SAMPLES = 64
_LEVELS = 1 << 16


def _gamma_quantiles() -> np.ndarray:
    """x with 1 - (1 + x) exp(-x) = q, for q in the middle of each level; by bisection."""
    q = (np.arange(_LEVELS) + 0.5) / _LEVELS
    low, high = np.zeros(_LEVELS), np.full(_LEVELS, 64.0)
    for _ in range(80):
        mid = (low + high) / 2
        under = 1 - (1 + mid) * np.exp(-mid) < q
        low, high = np.where(under, mid, low), np.where(under, high, mid)
    return high


class Sampler:
    _made: dict[int, Sampler] = {}

    def __init__(self, samples: int):
        quantiles = _gamma_quantiles()
        self.rate = quantiles.astype(np.float32)
        self.log_c = np.log(quantiles).astype(np.float32)
        self.beta = ((np.arange(_LEVELS) + 0.5) / _LEVELS).astype(np.float32)
        self.samples = samples
        self.salt = np.asarray([xxhash.xxh64_intdigest(str(j), 1) | 1 for j in range(samples)], dtype=np.uint64)
        self.log = np.log(np.arange(1, 1 << 16, dtype=np.float64)).astype(np.float32)

    @classmethod
    def made(cls, samples: int) -> Sampler:
        if samples not in cls._made:
            cls._made[samples] = cls(samples)
        return cls._made[samples]

    def _bits(self, terms: np.ndarray) -> np.ndarray:
        x = terms[:, None] * self.salt[None, :]
        x ^= x >> np.uint64(29)
        x *= np.uint64(0xBF58476D1CE4E5B9)
        x ^= x >> np.uint64(32)
        return x

    def signatures(self, sets: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
        """For each set (term hashes, counts): a 32-bit code of each sample; zeros for an empty set."""
        out = np.zeros((len(sets), self.samples), dtype=np.uint32)
        full = [i for i, (t, _) in enumerate(sets) if len(t)]
        if not full:
            return out
        terms = np.concatenate([sets[i][0] for i in full])
        counts = np.concatenate([sets[i][1] for i in full])
        sizes = np.asarray([len(sets[i][0]) for i in full])
        known, index = np.unique(terms, return_inverse=True)
        x = self._bits(known)
        rate = self.rate[(x & np.uint64(0xFFFF)).astype(np.uint16)]
        beta = self.beta[(x >> np.uint64(16) & np.uint64(0xFFFF)).astype(np.uint16)]
        log_c = self.log_c[(x >> np.uint64(32) & np.uint64(0xFFFF)).astype(np.uint16)]
        score = log_c - rate * (1 - beta)  # at weight 1, whose step is 0
        bound = np.concatenate([[0], np.cumsum(sizes)])
        low = (known & np.uint64(0xFFFFFFFF)).astype(np.uint32)
        for k, i in enumerate(full):
            at, n = index[bound[k] : bound[k + 1]], counts[bound[k] : bound[k + 1]]
            s, step = score[at], None
            many = np.flatnonzero(n > 1)
            if len(many):
                m = at[many]
                weight = np.where(n[many] < _LEVELS, self.log[np.minimum(n[many], _LEVELS - 1) - 1], np.log(n[many]).astype(np.float32))
                up = np.floor(weight[:, None] / rate[m] + beta[m])
                s[many] = log_c[m] - rate[m] * (up - beta[m] + 1)
                step = up.astype(np.uint32)
            best = s.argmin(axis=0)
            code = low[at[best]] + np.uint32(1)
            if step is not None:
                steps = np.zeros(len(at), dtype=np.int64)
                steps[many] = np.arange(1, len(many) + 1)
                of = steps[best]
                code = code + np.where(of > 0, step[np.maximum(of - 1, 0), np.arange(self.samples)], 0).astype(np.uint32) * np.uint32(0x9E3779B1)
            out[i] = np.maximum(code, 1)
        return out


def weighted_set(text: str | None, memory: dict[bytes, int]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words of a text, with their counts. memory: hashes of words already met."""
    words = Counter((text or "").encode("utf-8").lower().split())
    digest = xxhash.xxh64_intdigest
    if len(memory) > 300_000:
        memory.clear()
    hashes = []
    for w in words:
        h = memory.get(w)
        if h is None:
            h = memory[w] = digest(w)
        hashes.append(h)
    terms, counts = np.asarray(hashes, dtype=np.uint64), np.fromiter(words.values(), np.int64, len(words))
    order = np.argsort(terms)
    return terms[order], counts[order]


def show(codes: np.ndarray) -> list[str]:
    raw = codes.astype(">u4").tobytes().hex()
    size = codes.shape[1] * 8
    return [raw[i : i + size] for i in range(0, len(raw), size)]


def fingerprints(docs: DataFrame, *, samples: int = SAMPLES) -> DataFrame:
    """doc_id and fingerprint (8 hex digits a sample) of each whole text, without a shuffle."""
    prepare(docs.sparkSession)

    def run(batches):
        sampler, memory = Sampler.made(samples), {}
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                codes = sampler.signatures([weighted_set(t.as_py(), memory) for t in part.column(1)])
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(show(codes))], ["doc_id", "fingerprint"])

    return long_id(docs.select("doc_id", "text"), "doc_id").mapInArrow(run, "doc_id long, fingerprint string")


def with_next(docs: DataFrame) -> DataFrame:
    """doc_id and text in ranges of the order, sorted, one range to a partition, with the first row of the next range last.

    Columns: part, own (false for the row that belongs to the next range), doc_id, text. Range bounds are places that
    exist, from quantiles of the places alone; texts are shuffled once. A row's place is its doc_id; where ids repeat,
    rows are sorted and settled first, in ranges that cut through the rows of one id, and have a place of their own.
    """
    spark = docs.sparkSession
    prepare(spark)
    docs = long_id(docs.select("doc_id", "text"), "doc_id")
    n = partitions(spark)
    if docs.groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1 OR doc_id IS NULL").isEmpty():
        return _with_next(docs.withColumn("place", F.col("doc_id")), n)
    by = ["doc_id", F.substring("text", 1, 64), F.xxhash64("text")]
    tie = docs.withColumn("tie", F.monotonically_increasing_id())
    ranged = tie.repartitionByRange(n, *by, "tie").sortWithinPartitions(*by, "text", "tie")
    return _with_next(settle(ranged).select("doc_id", "text", F.monotonically_increasing_id().alias("place")), n)


def _with_next(docs: DataFrame, n: int) -> DataFrame:
    """docs: doc_id, text, and place, which tells all rows and is never null."""
    share = F.array(*[F.lit((i + 1) / n) for i in range(n - 1)] or [F.lit(0.5)])
    seen = docs.agg(F.percentile_approx("place", share, F.lit(max(1000, 20 * n))).alias("q"), F.min("place").alias("low")).first()
    starts = np.asarray(sorted(set(seen["q"] or []) - {seen["low"]}), dtype=np.int64)
    ranges, low = len(starts) + 1, seen["low"]

    @F.pandas_udf("array<int>")
    def parts(places):
        import pandas as pd

        at = places.to_numpy(dtype=np.int64)
        part = np.searchsorted(starts, at, side="right")
        first = at == low
        if len(starts):
            first |= (part > 0) & (starts[np.maximum(part - 1, 0)] == at)
        return pd.Series([[p] if not f else [p, (p - 1) % ranges] for p, f in zip(part.tolist(), first.tolist(), strict=True)])

    dealt = docs.select("doc_id", "text", "place", F.posexplode(parts("place")).alias("copy", "part"))
    dealt = dealt.select("part", (F.col("copy") == 0).alias("own"), "doc_id", "text", "place")
    dealt = dealt.repartitionById(ranges, F.col("part")).sortWithinPartitions(F.col("own").desc(), "place")
    return dealt.select("part", "own", "doc_id", "text")


def edited(text: str, following: str) -> str:
    """The last quarter of the code points replaced by the first as many of the following text."""
    cut = len(text) // 4
    return text[: len(text) - cut] + following[:cut]


OUT = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def likeness_to_next(docs: DataFrame, *, samples: int = SAMPLES, chunk_chars: int = 1_000_000) -> DataFrame:
    def run(batches):
        sampler, memory = Sampler.made(samples), {}

        def flush(rows, after):
            texts = [t for _, t in rows]
            follow = [*texts[1:], after]
            changed = [edited(t, f) for t, f in zip(texts, follow, strict=True)]
            own = [weighted_set(t, memory) for t in texts]
            codes = sampler.signatures([*own, weighted_set(after, memory), *[weighted_set(t, memory) for t in changed]])
            n = len(rows)
            mine, nxt, new = codes[:n], codes[1 : n + 1], codes[n + 1 :]
            columns = [
                pa.array([d for d, _ in rows], pa.int64()), pa.array([len(t) for t in texts], pa.int64()),
                pa.array([hashlib.sha256(t.encode()).hexdigest() for t in changed]), pa.array(show(mine)), pa.array(show(new)),
                pa.array((mine == new).mean(axis=1)), pa.array((mine == nxt).mean(axis=1)),
            ]
            return pa.RecordBatch.from_arrays(columns, [x.split()[0] for x in OUT.split(", ")])

        held, size, first, ahead = [], 0, None, None
        for b in batches:
            for own, doc, text in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), b.column(3), strict=True):
                text = text.as_py() or ""
                if not own:
                    ahead = text if ahead is None else ahead
                    continue
                if size >= chunk_chars or len(held) >= 512:
                    yield flush(held, text)
                    held, size = [], 0
                first = text if first is None else first
                held.append((doc, text))
                size += len(text)
        if held:
            yield flush(held, first if ahead is None else ahead)

    return with_next(docs).mapInArrow(run, OUT)


def op4_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return likeness_to_next(table(spark, sf_dir, "documents", "doc_id", "text"))
