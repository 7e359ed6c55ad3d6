"""Toxicity by a chain of linear classifiers.

Categories are predicted in a stated order. The first model sees the document's words; each later one also sees the
probabilities of the categories before it. In training those probabilities are out-of-fold predictions (a document's
comes from models that did not see it), so a later model learns how far to trust them; for prediction every model is
fitted on the whole sample. What a model sees are words and beginnings of words, so that inflected and compounded forms
count; the value of each is the log of one plus its count in the whole text.

Fitting takes at most `sample_docs` labelled documents, those with the least hash of doc_id; words and models are chosen
on these alone. Prediction covers every document.

Defined cases: a null text is empty; labels that are null are left out of their category; of several labels of one
document the greatest counts; with no labelled documents, or a category with one value alone, the probability is that of
the value seen (0 with none); repeated rows are predicted each; an empty table gives no rows; columns other than those
named are ignored, and kept by `keep_clean`.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zlib
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgefold.llm.shared import long_id, prepare, table

SAMPLE_DOCS = 4_000
#: Words and beginnings of words that the models see.
WORDS = 1_000
STEMS = (4, 5, 6, 7, 8)
FOLDS = 5
PENALTY = 1.0
#: Categories in the order of the chain; "low_quality" is 1 - quality.
CHAIN = ("low_quality", "toxic")
THRESHOLD = 0.5
_WORD = re.compile(r"[^\W\d_]+")


def count_words(text: str | None) -> Counter:
    return Counter(_WORD.findall((text or "").lower()))


def marks(words: Counter) -> Counter:
    """Counts of words, and of their beginnings (with ^ before them)."""
    out = Counter(words)
    for w, n in words.items():
        for k in STEMS:
            if len(w) > k:
                out["^" + w[:k]] += n
    return out


def fit_logistic(x: np.ndarray, y: np.ndarray, penalty: float = PENALTY, rounds: int = 200) -> np.ndarray:
    """Weights and, last, the intercept, which is not penalised; accelerated gradient descent with a safe step."""
    a = np.hstack([x, np.ones((len(x), 1), dtype=x.dtype)]).astype(np.float32)
    y = y.astype(np.float32)
    if len(y) == 0 or y.min() == y.max():
        w = np.zeros(a.shape[1])
        w[-1] = 30.0 if len(y) and y[0] > 0 else -30.0
        return w
    v = np.ones(a.shape[1], dtype=np.float32)
    for _ in range(20):
        v = a.T @ (a @ v)
        top = np.linalg.norm(v)
        v /= top
    step, ridge = 1.0 / (0.25 * top + penalty), np.full(a.shape[1], penalty, dtype=np.float32)
    ridge[-1] = 0
    step = np.float32(step)
    w = z = np.zeros(a.shape[1], dtype=np.float32)
    for k in range(1, rounds + 1):
        p = 1 / (1 + np.exp(-np.clip(a @ z, -30, 30)))
        new = z - step * (a.T @ (p - y) + ridge * z)
        z = new + np.float32((k - 1) / (k + 2)) * (new - w)
        w = new
    return w


def probability(x: np.ndarray, w: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x @ w[:-1] + w[-1], -30, 30)))


@dataclass
class Chain:
    categories: tuple[str, ...]
    words: dict[str, int]
    models: list[np.ndarray]

    def matrix(self, counts: list[Counter]) -> np.ndarray:
        x = np.zeros((len(counts), len(self.words)), dtype=np.float32)
        for i, c in enumerate(map(marks, counts)):
            for w in c.keys() & self.words.keys():
                x[i, self.words[w]] = math.log1p(c[w])
        return x

    def predict(self, counts: list[Counter]) -> np.ndarray:
        """A column of probabilities for each category."""
        x, out = self.matrix(counts), np.zeros((len(counts), 0))
        for model in self.models:
            out = np.hstack([out, probability(np.hstack([x, out]), model)[:, None]])
        return out


def choose_words(counts: list[Counter], labels: np.ndarray, most: int) -> dict[str, int]:
    """Words whose presence tells most about a category: by the square of the difference over its variance."""
    n, seen = len(counts), Counter()
    by = [Counter() for _ in range(labels.shape[1])]
    for c, row in zip(map(marks, counts), labels, strict=True):
        seen.update(c.keys())
        for k, value in enumerate(row):
            if value == 1:
                by[k].update(c.keys())
    best: dict[str, float] = {}
    for k, with_label in enumerate(by):
        positive = int((labels[:, k] == 1).sum())
        for w, m in seen.items():
            if m >= 5:
                expected = m * positive / max(n, 1)
                best[w] = max(best.get(w, 0.0), (with_label[w] - expected) ** 2 / max(expected, 1e-9))
    return {w: i for i, w in enumerate(sorted(sorted(best, key=lambda w: (-best[w], w))[:most]))}


def fit_chain(ids: list[int], counts: list[Counter], labels: np.ndarray, categories: tuple[str, ...], *, words: int = WORDS, folds: int = FOLDS) -> Chain:
    chain = Chain(categories, choose_words(counts, labels, words), [])
    x = chain.matrix(counts)
    fold = np.asarray([zlib.crc32(str(i).encode()) % folds for i in ids], dtype=int)
    for k in range(len(categories)):
        y, known = labels[:, k], ~np.isnan(labels[:, k])
        chain.models.append(fit_logistic(x[known], y[known]))
        if k + 1 < len(categories):
            unseen = np.zeros((len(ids), 1), dtype=np.float32)
            for f in range(folds):
                held = fold == f
                if held.any():
                    unseen[held, 0] = probability(x[held], fit_logistic(x[known & ~held], y[known & ~held]))
            x = np.hstack([x, unseen])
    return chain


def train(docs: DataFrame, labels: DataFrame, *, categories: tuple[str, ...] = CHAIN, sample_docs: int = SAMPLE_DOCS) -> Chain:
    """labels: doc_id and a 0/1 column for each category. At most `sample_docs` documents' word counts reach the driver."""
    prepare(docs.sparkSession)
    known = long_id(labels.select("doc_id", *categories), "doc_id").where("doc_id IS NOT NULL").groupBy("doc_id").agg(*[F.max(c).alias(c) for c in categories])
    sample = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_docs)
    texts = long_id(docs.select("doc_id", "text"), "doc_id").join(F.broadcast(sample), "doc_id")

    def run(batches):
        for b in batches:
            for at in range(0, b.num_rows, 200):
                part = b.slice(at, 200)
                c = [count_words(t.as_py()) for t in part.column(1)]
                columns = [pa.array([list(x.keys()) for x in c], pa.list_(pa.string())), pa.array([list(x.values()) for x in c], pa.list_(pa.int64()))]
                yield pa.RecordBatch.from_arrays([part.column(0), *part.columns[2:], *columns], ["doc_id", *categories, "words", "counts"])

    kept = texts.select("doc_id", "text", *[F.col(c).cast("double").alias(c) for c in categories])
    schema = "doc_id long, " + ", ".join(f"{c} double" for c in categories) + ", words array<string>, counts array<long>"
    rows = sorted(kept.mapInArrow(run, schema).collect(), key=lambda r: (r["doc_id"], r["words"]))
    counts = [Counter(dict(zip(r["words"], r["counts"], strict=True))) for r in rows]
    values = np.asarray([[np.nan if r[c] is None else r[c] for c in categories] for r in rows], dtype=float).reshape(-1, len(categories))
    return fit_chain([r["doc_id"] for r in rows], counts, values, categories)


def predict(docs: DataFrame, chain: Chain) -> DataFrame:
    """doc_id and a probability for each category, for each document, from its whole text."""
    prepare(docs.sparkSession)
    shipped = docs.sparkSession.sparkContext.broadcast(chain)

    def run(batches):
        own = shipped.value
        for b in batches:
            for at in range(0, b.num_rows, 200):
                part = b.slice(at, 200)
                p = own.predict([count_words(t.as_py()) for t in part.column(1)])
                yield pa.RecordBatch.from_arrays([part.column(0), *[pa.array(p[:, k]) for k in range(p.shape[1])]], ["doc_id", *own.categories])

    schema = "doc_id long, " + ", ".join(f"{c} double" for c in chain.categories)
    return long_id(docs.select("doc_id", "text"), "doc_id").mapInArrow(run, schema)


def known_labels(labels: DataFrame) -> DataFrame:
    return labels.select("doc_id", (1 - F.col("quality")).alias("low_quality"), "toxic")


def keep_clean(docs: DataFrame, chain: Chain, *, category: str = "toxic", threshold: float = THRESHOLD) -> DataFrame:
    """The documents, with all their columns, whose probability of the category is below the threshold."""
    prepare(docs.sparkSession)
    shipped, k = docs.sparkSession.sparkContext.broadcast(chain), chain.categories.index(category)

    @F.pandas_udf("double")
    def likely(texts):
        import pandas as pd

        return pd.Series(np.concatenate([np.zeros(0), *[shipped.value.predict([count_words(t) for t in texts[a : a + 200]])[:, k] for a in range(0, len(texts), 200)]]))

    return docs.where(likely(F.col("text")) < threshold)


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    chain = train(docs, known_labels(table(spark, sf_dir, "labels", "doc_id", "quality", "toxic")))
    out = predict(docs, chain)
    return out.select("doc_id", *[F.col(c).alias(f"p_{c}") for c in chain.categories], (F.col("toxic") >= THRESHOLD).alias("rejected"))
