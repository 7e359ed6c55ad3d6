import itertools

import numpy as np
import pytest

from edgefold.llm import language_id as li

PIECES = ["ab", "a", "b", "abc", "ca"]


def all_ways(word, prob, number):
    total = 0.0
    for cuts in itertools.product([0, 1], repeat=len(word) - 1):
        at, p = 0, 1.0
        for end in [i + 1 for i, c in enumerate(cuts) if c] + [len(word)]:
            w = word[at:end]
            p *= prob[number[w]] if w in number else prob[0] if len(w) == 1 else 0.0
            at = end
        total += p
    return total


def test_forward_sums_all_segmentations():
    prob = np.asarray([0.05, 0.3, 0.2, 0.1, 0.25, 0.1, 0.0])
    lattice = li.Pieces(PIECES)
    words = ["abcab", "a", "zz", "cabca", "abc"]
    for at, ids in lattice.lattices(words):
        got = li.forward(ids, prob[:, None])[:, -1, 0]
        assert got == pytest.approx([all_ways(words[i], prob, lattice.number) for i in at])


def test_long_words_are_summed_whole(monkeypatch):
    """A word of 60 letters against plain arithmetic with fractions, and short words in logs against the linear pass."""
    from fractions import Fraction

    prob = np.asarray([0.05, 0.3, 0.2, 0.1, 0.25, 0.1, 0.0])
    lattice = li.Pieces(PIECES)
    word = "".join("abczabcab"[i % 9] for i in range(60))
    exact = [Fraction(1)]
    for e in range(1, len(word) + 1):
        ways = [(word[e - k : e], exact[e - k]) for k in range(1, min(e, 3) + 1)]
        exact.append(sum((Fraction(prob[lattice.number.get(w, 0)]) * f for w, f in ways if w in lattice.number or len(w) == 1), Fraction(0)))
    for repeat in (1, 8, 9, 30):
        (_, ids), = lattice.lattices([word * repeat])
        assert ids.shape[1] == 60 * repeat and (repeat < 9 or ids.shape[1] > li.BLOCKED_CHARS)
        got = li.log_sums(ids, prob[:, None])[0, 0]
        assert got == pytest.approx(li.log_prefixes(ids, prob)[0, -1])
        if repeat == 1:
            assert got == pytest.approx(float(np.log(float(exact[-1]))))
    words, counts = ["abcab", "ca", "zz", "cabca"], np.asarray([2.0, 1.0, 3.0, 5.0])
    linear = li.expected_counts(lattice, words, counts, prob)
    monkeypatch.setattr(li, "LINEAR_CHARS", 1)
    assert li.expected_counts(lattice, words, counts, prob) == pytest.approx(linear)
    sizes = np.asarray([1, 2, 1, 1, 3, 2, 0])
    assert (li.expected_counts(lattice, [word * 30], np.ones(1), prob) * sizes).sum() == pytest.approx(1800)


def test_pieces_of_all_lengths():
    assert max(map(len, li.read_pieces(li.default_pieces()))) > 10


def test_many_languages_are_all_learned(spark):
    draw = np.random.default_rng(3)
    letters = {f"l{k:02}": draw.permutation(list("abcdefghijklmnopqrstuvwxyz"))[:9].tolist() for k in range(40)}
    text = {k: [" ".join("".join(draw.choice(v, 5)) for _ in range(60)) for _ in range(8)] for k, v in letters.items()}
    rows = [(i * 40 + n, t, k) for n, (k, ts) in enumerate(text.items()) for i, t in enumerate(ts)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    scorer = li.train(docs.where("doc_id < 240"))
    assert scorer.languages == sorted(text)
    got = {r["doc_id"]: r["lang_pred"] for r in li.predict(docs, scorer).collect()}
    assert np.mean([got[i] == k for i, _, k in rows if i >= 240]) > 0.95


def test_expected_counts_add_up_and_learning_helps():
    lattice, prob = li.Pieces(PIECES), np.asarray([0.05, 0.3, 0.2, 0.1, 0.25, 0.1, 0.0])
    words, counts = ["abcab", "ca"], np.asarray([2.0, 1.0])
    total = li.expected_counts(lattice, words, counts, prob)
    sizes = np.asarray([1, 2, 1, 1, 3, 2, 0])
    assert (total * sizes).sum() == pytest.approx(12)
    likely = []
    for rounds in (1, 6):
        _, fitted = li.fit({"x": (words, counts)}, PIECES, rounds)
        likely.append(sum(n * np.log(all_ways(w, fitted[:, 0], lattice.number)) for w, n in zip(words, counts)))
    assert likely[1] > likely[0]


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.01"
    rows = li.op6_language_id(spark, sf).collect()
    truth = {r["doc_id"]: r["lang"] for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    held = [r for r in rows if r["held_out"]]
    assert len(rows) == len(truth) and len(held) > 200
    assert np.mean([truth[r["doc_id"]] == r["lang_pred"] for r in held]) > 0.97
    assert all(0 <= r["score"] <= 1 for r in rows)


def test_odd_rows(spark):
    docs = spark.createDataFrame([(1, "the cat", "en"), (2, None, "en"), (3, "12 ²!", None), (None, "le chat é" + "x" * 90, "fr"), (1, "", "fr"), (8, "le chat é", "fr")], "doc_id long, text string, lang string")
    got = [(r["doc_id"], r["lang_pred"], r["score"]) for r in li.predict(docs, li.train(docs)).collect()]
    assert [(d, lang) for d, lang, _ in got] == [(1, "en"), (2, "und"), (3, "und"), (None, "fr"), (1, "und"), (8, "fr")]
    assert [s for _, lang, s in got if lang == "und"] == [0, 0, 0]
    assert [r["lang_pred"] for r in li.predict(docs, li.train(docs.where("lang IS NULL"))).collect()] == ["und"] * 6
    assert li.predict(docs.limit(0), li.train(docs.limit(0))).collect() == []
