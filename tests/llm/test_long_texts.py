"""Texts far longer than any batch, and conversations of very many turns."""

import numpy as np
import xxhash
from pyspark.sql import functions as F

from edgefold.llm import chat, language_id, mixing, simhash, toxicity

LONG = " ".join(f"w{i % 977}" for i in range(400_000))


def test_fingerprint_of_a_long_text():
    words = LONG.encode().split()
    once = np.asarray([[xxhash.xxh64_intdigest(b" ".join(words[i : i + 4]), 42) >> b & 1 for b in range(64)] for i in range(977)])
    whole, rest = divmod(len(words) - 3, 977)  # the words repeat
    counts = once.sum(axis=0) * whole + once[:rest].sum(axis=0)
    assert simhash.fingerprint(LONG) == sum(1 << b for b in range(64) if 2 * counts[b] > len(words) - 3)


def test_operators_take_long_texts(spark):
    docs = spark.createDataFrame([(1, LONG, "en", "a"), (2, "the cat " * 100_000, "en", "a"), (3, "le chat", "fr", "b"), (4, "x" * 300_000, "fr", "b")], "doc_id long, text string, lang string, source string")
    sizes = {r["doc_id"]: r["n"] for r in docs.select("doc_id", mixing.word_count("text").alias("n")).collect()}
    assert sizes == {1: 400_000, 2: 200_000, 3: 2, 4: 1}
    got = {r["doc_id"]: r["lang_pred"] for r in language_id.predict(docs, language_id.train(docs)).collect()}
    assert got == {1: "en", 2: "en", 3: "fr", 4: "fr"}
    labels = spark.createDataFrame([(1, 0, 1), (2, 0, 0), (3, 0, 0)], "doc_id long, low_quality int, toxic int")
    assert toxicity.predict(docs, toxicity.train(docs, labels)).count() == 4


def test_long_conversations(spark):
    rows = [(1, i, "user" if i % 2 else "assistant", f"turn {i} \\ </") for i in range(3_000)] + [(2, 0, "assistant", LONG)]
    out = chat.format_conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string"))
    read = out.select("conv_id", F.size(chat.read_turns(F.col("formatted"))).alias("n"), chat.read_trained(F.encode("formatted", "UTF-8"), F.col("loss_spans")).alias("t"))
    got = {r["conv_id"]: (r["n"], r["t"]) for r in read.collect()}
    assert got == {1: (3_000, "".join(f"turn {i} \\ </" for i in range(0, 3_000, 2))), 2: (1, LONG)}
