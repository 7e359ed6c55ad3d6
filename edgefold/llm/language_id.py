"""Language identification by unigram pieces with all segmentations summed.

The pieces are those of a fixed public vocabulary (never trained here), lowered, without their word-start mark. Each
language has a probability for each piece, learned by expectation-maximisation on words of its documents: the forward
pass sums the probability of all ways to cut a word into pieces, the backward pass gives each piece's expected count.
A text's score in a language is the sum over its words of the log of that sum; letters alone make words.

Words are whole, however long, and so are pieces. Sums over long words are kept as logs, so nothing vanishes.

Scoring is by word: each worker keeps the scores of words it has met. Training reads at most `sample_docs` documents of
a language, by hash of doc_id and text, and all words of these; every language that has a document is learned.

Defined cases: a null text, or one without a letter, is `und` with score 0; without any document to learn from every
prediction is `und`; documents without an id are predicted but not learned from; rows that repeat an id are predicted
each, and learned from once if their texts are equal too; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import re
from collections import Counter

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from edgefold.llm.shared import long_id, prepare, settle, table

SAMPLE_DOCS = 1_500
ROUNDS = 4
#: Languages whose numbers of documents are sent to all tasks; more are joined by shuffles.
SHIPPED_LANGUAGES = 100_000
UNDETERMINED = "und"
#: Words with more letters are summed in logs; with more yet, in blocks of letters side by side.
LINEAR_CHARS, BLOCKED_CHARS, BLOCK = 24, 512, 256
#: Letters of a word that are learned from together: longer words are learned from in parts.
TRAIN_CHARS = 1_000
#: Numbers of pieces that a lattice of words of one length holds at a time.
LATTICE = 1 << 22
_WORD = re.compile(r"[^\W\d_]+")


def default_pieces() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def read_pieces(path: str) -> list[str]:
    """Pieces of letters from a sentencepiece model, lowered."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    found = {model.id_to_piece(i).lstrip("▁").lower() for i in range(model.get_piece_size())}
    return sorted(p for p in found if p and p.isalpha())


def words_of(text: str) -> list[str]:
    return _WORD.findall(text.lower())


def _parts(text: str) -> list[str]:
    """Words to learn from, long ones in parts."""
    return [w[a : a + TRAIN_CHARS] for w in words_of(text) if w.isalpha() for a in range(0, len(w), TRAIN_CHARS)]


class Pieces:
    """Piece numbers in words; 0 stands for a letter that is no piece."""

    def __init__(self, pieces: list[str]):
        self.number = {p: i + 1 for i, p in enumerate(pieces)}
        self.longest = max(map(len, pieces), default=1)

    def lattices(self, words: list[str]):
        """For each word length: positions of the words, and the piece that ends at each place with each length (-1: none)."""
        by_length: dict[int, list[int]] = {}
        for i, w in enumerate(words):
            by_length.setdefault(len(w), []).append(i)
        get = self.number.get
        for length, those in by_length.items():
            most = min(length, self.longest)
            if length > BLOCKED_CHARS:
                for i in those:
                    w, ids = words[i], np.full((1, length, most), -1, dtype=np.int32)
                    for k in range(1, most + 1):
                        ids[0, k - 1 :, k - 1] = [get(w[a : a + k], -1) for a in range(length - k + 1)]
                    ids[:, :, 0] = np.maximum(ids[:, :, 0], 0)
                    yield np.asarray([i]), ids
                continue
            spans = [(e - k, e) if e >= k else (0, 0) for e in range(1, length + 1) for k in range(1, most + 1)]
            step = max(1, LATTICE // len(spans))
            for at in (those[a : a + step] for a in range(0, len(those), step)):
                ids = np.asarray([[get(w[a:b], -1) for a, b in spans] for w in (words[i] for i in at)], dtype=np.int32)
                ids = ids.reshape(len(at), length, most)
                ids[:, :, 0] = np.maximum(ids[:, :, 0], 0)
                yield np.asarray(at), ids


def forward(ids: np.ndarray, prob: np.ndarray) -> np.ndarray:
    """Sum over all segmentations of each prefix: (words, length + 1, languages). prob has a last row of zeros for -1."""
    n, length, most = ids.shape
    alpha = np.zeros((n, length + 1, prob.shape[1]))
    alpha[:, 0] = 1
    for e in range(1, length + 1):
        for k in range(1, min(e, most) + 1):
            alpha[:, e] += alpha[:, e - k] * prob[ids[:, e - 1, k - 1]]
    return alpha


def log_sums(ids: np.ndarray, prob: np.ndarray) -> np.ndarray:
    """The log of the sum over all segmentations of each whole word: (words, languages), for words of any length.

    Of the prefixes only the last few, as many as a piece is long, are held, each as the sum over the sum before it.
    """
    n, length, most = ids.shape
    step = max(1, LATTICE // ((LINEAR_CHARS + 1) * max(1, prob.shape[1])))
    if n > step:
        return np.concatenate([log_sums(ids[a : a + step], prob) for a in range(0, n, step)])
    if length <= LINEAR_CHARS:
        return np.log(np.maximum(forward(ids, prob)[:, -1], 1e-300))
    if length > BLOCKED_CHARS:
        return np.stack([_log_sum_in_blocks(word, prob) for word in ids])
    total, last = np.zeros((n, prob.shape[1])), np.ones((most, n, prob.shape[1]))  # last[k - 1]: k letters back
    for e in range(1, length + 1):
        grown = np.zeros_like(total)
        for k in range(1, min(e, most) + 1):
            grown += last[k - 1] * prob[ids[:, e - 1, k - 1]]
        grown = np.maximum(grown, 1e-300)
        total += np.log(grown)
        last[1:] = last[:-1] / grown
        last[0] = 1
    return total


def _log_sum_in_blocks(ids: np.ndarray, prob: np.ndarray) -> np.ndarray:
    """As log_sums, for one long word. The sums of the last few prefixes after a block of letters are linear in those before it:
    the blocks' matrices are worked out side by side and then applied in order."""
    length, most = ids.shape
    languages = prob.shape[1]
    state, total = np.zeros((most, languages)), np.zeros(languages)  # sums of the prefixes 0, 1, ... letters back
    state[0] = 1
    head = length % BLOCK
    for e in range(head):
        state = np.concatenate([(state * prob[ids[e]]).sum(axis=0)[None], state[:-1]])
        top = state.max(axis=0)
        state, total = state / top, total + np.log(top)
    together = max(1, LATTICE // (most * most * max(1, languages)))
    blocks = ids[head:].reshape(-1, BLOCK, most)
    for at in range(0, len(blocks), together):
        some = blocks[at : at + together]
        sums = [np.zeros((len(some), most, languages)) for _ in range(most)]  # by letters back: blocks, start, language
        for j in range(most):
            sums[j][:, j] = 1
        logs = np.zeros((len(some), 1, languages))
        for e in range(BLOCK):
            p = prob[some[:, e]]
            new = sums[0] * p[:, 0, None]
            for k in range(1, most):
                new += sums[k] * p[:, k, None]
            sums = [new, *sums[:-1]]
            if e % 16 == 15:
                top = np.maximum(np.max([s.max(axis=1, keepdims=True) for s in sums], axis=0), 1e-300)
                sums, logs = [s / top for s in sums], logs + np.log(top)
        step = np.stack(sums)
        for b in range(len(some)):
            state = np.einsum("kjl,jl->kl", step[:, b], state)
            top = state.max(axis=0)
            state, total = state / top, total + np.log(top) + logs[b, 0]
    return total + np.log(np.maximum(state[0], 1e-300))


def log_prefixes(ids: np.ndarray, prob: np.ndarray) -> np.ndarray:
    """The log of the sum over all segmentations of each prefix, for one language: (words, length + 1)."""
    n, length, most = ids.shape
    out = np.zeros((n, length + 1))
    for e in range(1, length + 1):
        near = sum(np.exp(out[:, e - k] - out[:, e - 1]) * prob[ids[:, e - 1, k - 1]] for k in range(1, min(e, most) + 1))
        out[:, e] = out[:, e - 1] + np.log(np.maximum(near, 1e-300))
    return out


def _long_counts(ids: np.ndarray, counts: np.ndarray, prob: np.ndarray) -> np.ndarray:
    """Expected counts of pieces in words of any length, by logs of the sums before and after each place."""
    n, length, most = ids.shape
    before, total = log_prefixes(ids, prob), np.zeros(len(prob))
    after = np.full((n, length + 1), -np.inf)
    after[:, length] = 0
    for e in range(length, 0, -1):
        for k in range(1, min(e, most) + 1):
            piece = ids[:, e - 1, k - 1]
            p = prob[piece]
            share = np.exp(before[:, e - k] + after[:, e] - before[:, length]) * p
            total += np.bincount(np.where(piece < 0, len(prob) - 1, piece), share * counts, len(prob))
            with np.errstate(divide="ignore"):
                after[:, e - k] = np.logaddexp(after[:, e - k], after[:, e] + np.log(p))
    return total


def expected_counts(pieces: Pieces, words: list[str], counts: np.ndarray, prob: np.ndarray) -> np.ndarray:
    total = np.zeros(len(prob))
    for at, ids in pieces.lattices(words):
        n, length, most = ids.shape
        if length > LINEAR_CHARS:
            total += _long_counts(ids, counts[at], prob)
            continue
        alpha = forward(ids, prob[:, None])[:, :, 0]
        beta = np.zeros((n, length + 1))
        beta[:, length] = 1
        scale = counts[at] / np.maximum(alpha[:, length], 1e-300)
        for e in range(length, 0, -1):
            for k in range(1, min(e, most) + 1):
                piece = ids[:, e - 1, k - 1]
                p = prob[piece]
                total += np.bincount(np.where(piece < 0, len(prob) - 1, piece), alpha[:, e - k] * p * beta[:, e] * scale, len(prob))
                beta[:, e - k] += p * beta[:, e]
    total[-1] = 0
    return total


def fit(words_by_language: dict[str, tuple[list[str], np.ndarray]], pieces: list[str], rounds: int = ROUNDS) -> tuple[list[str], np.ndarray]:
    """Languages and piece probabilities: a row for each piece, row 0 for other letters, a last row of zeros."""
    lattice, languages = Pieces(pieces), sorted(words_by_language)
    size = len(pieces) + 2
    out = np.zeros((size, len(languages)))
    for column, language in enumerate(languages):
        words, counts = words_by_language[language]
        prob = np.full(size, 1.0 / (size - 1))
        prob[-1] = 0
        for _ in range(rounds):
            total = expected_counts(lattice, words, counts, prob) + 0.1
            total[-1] = 0
            prob = total / total.sum()
        out[:, column] = prob
    return languages, out


class Scorer:
    def __init__(self, pieces: list[str], languages: list[str], prob: np.ndarray):
        self.pieces, self.languages, self.prob = Pieces(pieces), languages, prob
        self.row: dict[str, int] = {}
        self.table = np.zeros((0, len(languages)))

    def _learn(self, words: list[str]) -> None:
        scores = np.zeros((len(words), len(self.languages)))
        for at, ids in self.pieces.lattices(words):
            scores[at] = log_sums(ids, self.prob)
        start = len(self.row)
        self.row.update(zip(words, range(start, start + len(words)), strict=True))
        if start + len(words) > len(self.table):
            grown = np.zeros((max(1 << 16, 2 * (start + len(words))), len(self.languages)))
            grown[:start] = self.table[:start]
            self.table = grown
        self.table[start : start + len(words)] = scores

    def score(self, texts: list[str | None], keep: int = 300_000) -> tuple[list[str], np.ndarray]:
        if len(self.row) > keep:
            self.row, self.table = {}, np.zeros((0, len(self.languages)))
        split = [words_of(t or "") for t in texts]
        met = set()
        for words in split:
            met.update(words)
        if new := [w for w in met if w not in self.row]:
            self._learn(new)
        label, likely = [], np.zeros(len(texts))
        for i, words in enumerate(split):
            if not self.languages or not any(w.isalpha() or any(c.isalpha() for c in w) for w in words):
                label.append(UNDETERMINED)
                continue
            total = self.table[np.fromiter(map(self.row.__getitem__, words), np.int64, len(words))].sum(axis=0)
            best = int(total.argmax())
            label.append(self.languages[best])
            likely[i] = 1 / np.exp(np.minimum(total - total[best], 0)).sum()
        return label, likely


def train(docs: DataFrame, *, pieces: str | None = None, sample_docs: int = SAMPLE_DOCS) -> Scorer:
    """docs: doc_id, text, lang. What reaches the driver are the words of `sample_docs` documents of each language."""
    names = read_pieces(pieces or default_pieces())
    hashed = F.xxhash64("doc_id", "text").alias("h")
    known = docs.where("lang IS NOT NULL AND text IS NOT NULL AND doc_id IS NOT NULL").select("doc_id", "lang", "text", hashed)
    # A bound on the hash that leaves a few times the wanted documents of each language, before ranking these.
    sizes = settle(known.groupBy("lang").agg(F.count("*").alias("n")))
    sizes = F.broadcast(sizes) if sizes.count() <= SHIPPED_LANGUAGES else sizes
    share = F.least(F.lit(1.0), 3.0 * sample_docs / F.col("n")) * 2.0**64 - 2.0**63
    some = known.select("doc_id", "lang", "h").join(sizes, "lang").where(F.col("h").cast("double") <= share)
    rank = F.row_number().over(Window.partitionBy("lang").orderBy("h", "doc_id"))
    chosen = some.select("doc_id", "lang", "h").distinct().withColumn("rank", rank).where(F.col("rank") <= sample_docs).drop("rank")

    def run(batches):
        for b in batches:
            counts: dict[str, Counter] = {}
            for language, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                counts.setdefault(language, Counter()).update(_parts(text.as_py()))
            rows = [(k, w, n) for k, c in counts.items() for w, n in c.items()]
            yield pa.RecordBatch.from_pandas(pd.DataFrame(rows, columns=["lang", "word", "n"]), pa.schema([("lang", pa.string()), ("word", pa.string()), ("n", pa.int64())]))

    texts = known.join(chosen, ["doc_id", "lang", "h"], "left_semi").dropDuplicates(["doc_id", "lang", "h"]).select("lang", "text")
    counted = texts.mapInArrow(run, "lang string, word string, n long").groupBy("lang", "word").agg(F.sum("n").alias("n"))
    rows = counted.orderBy("lang", F.desc("n"), "word").toPandas()
    words = {str(k): (g["word"].tolist(), g["n"].to_numpy(dtype=float)) for k, g in rows.groupby("lang")}
    languages, prob = fit(words, names)
    return Scorer(names, languages, prob)


def predict(docs: DataFrame, scorer: Scorer) -> DataFrame:
    """doc_id, lang_pred, score: a row for each document, from the text alone."""
    shipped = docs.sparkSession.sparkContext.broadcast((list(scorer.pieces.number), scorer.languages, scorer.prob))

    def run(batches):
        own = Scorer(*shipped.value)
        for b in batches:
            for at in range(0, b.num_rows, 200):
                part = b.slice(at, 200)
                label, likely = own.score(part.column(1).to_pylist())
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(label), pa.array(likely)], ["doc_id", "lang_pred", "score"])

    return long_id(docs.select("doc_id", "text"), "doc_id").mapInArrow(run, "doc_id long, lang_pred string, score double")


def held_out(doc_id) -> F.Column:
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % 3 == 1


def op6_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text", "lang")
    scorer = train(docs.where(~held_out(F.col("doc_id"))))
    return predict(docs, scorer).select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")
