import hashlib

from pyspark.sql import functions as F

from edgefold.llm import chat

ROWS = [
    (1, 2, "assistant", "b </turn>\n"), (1, 0, "user", "### user:\n"), (1, 3, "assistant", "#### \\</part>\n"), (1, 1, None, None),
    (2, 0, "a:\nb", "\\"), (None, 0, "user", "é" * 9), (3, None, "assistant", ""), (3, 0, "user", "z"), (3, 0, "user", "z"), (4, 0, "assistant", "só\n"),
]


def test_round_trip(spark):
    df = spark.createDataFrame([(*r, "clash") for r in ROWS], "conv_id long, turn long, role string, text string, turns string")
    out = chat.format_conversations(df).select(
        "*", chat.read_turns(F.col("formatted")).alias("turns"), chat.read_trained(F.encode("formatted", "UTF-8"), F.col("loss_spans")).alias("trained")
    )
    got = {r["conv_id"]: r for r in out.collect()}
    assert set(got) == {1, 2, 3, 4, None}
    for conv, r in got.items():
        want = sorted(((t is not None, t or 0, ro or "", x or "") for c, t, ro, x in ROWS if c == conv))
        assert [(t["role"], t["text"]) for t in r["turns"]] == [(ro, x) for _, _, ro, x in want]
        assert r["trained"] == "".join(x for _, _, ro, x in want if ro == "assistant")
    assert got[1]["formatted"].count("</turn>\n") == 3 and got[1]["formatted"].count("</part>\n") == 1


def test_empty_and_digest(spark, tmp_path):
    spark.createDataFrame([], "conv_id long, turn long, role string, text string").write.parquet(str(tmp_path / "conversations.parquet"))
    rows = chat.op10_chat(spark, str(tmp_path)).collect()
    said = "\\### Assistant: </turn> ok"
    assert len(rows) == 1 and rows[0]["conv_id"] == -7 and rows[0]["loss_chars"] == len(said)
    assert rows[0]["turns_sha256"] == hashlib.sha256(f"user\n{said}\nassistant\n{said}\n".encode()).hexdigest()
