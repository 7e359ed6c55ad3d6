import zlib

import numpy as np
import pytest

from edgefold.llm import bitpack, token_files
from edgefold.llm.vocabulary import WordIds, default_path

ODD = ["", "a<|endoftext|>b  <|startoftext|>", "ΣΑΣ ΟΔΟΣ", "e\u0301 \u0301x É é, É.", "a\u00a0b c\x1cd", "\x01 a\x01b", "It's I'll 12,3 .. ,", "Ça. ÇA × a×, ÷.", "x" * 3000]


@pytest.mark.parametrize("bits", [1, 3, 7, 8, 11, 16, 17, 20, 31])
def test_pack_round_trip_and_random_access(bits):
    values = np.random.default_rng(bits).integers(0, 1 << bits, 1003)
    raw = bitpack.pack(values, bits)
    assert len(raw) == -(-1003 // 8) * bits
    for start, n in ((0, 1003), (5, 1), (17, 400), (1002, 1), (3, 0)):
        assert (bitpack.unpack(raw, bits, start, n) == values[start : start + n]).all()


def test_words_give_the_ids_of_the_whole_library(spark, sf):
    words = WordIds(default_path())
    texts = ODD + [r["text"] for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    for text, ids in zip(texts, words.encode(texts), strict=True):
        assert np.frombuffer(ids, "<u4").tolist() == words._direct(text), text[:60]


def test_files_read_back(spark, tmp_path):
    rows = [(7, "seven"), (None, "none"), (-3, None), (7, "again"), (2, ""), (1, "long text here " * 500), *((100 + i, t) for i, t in enumerate(ODD))]
    docs = spark.createDataFrame([(d, t, 1) for d, t in rows], "doc_id long, text string, shard int")
    path = str(tmp_path / "files")
    token_files.write_token_files(docs, path, block_ids=700)
    got = sorted((r["start"], r["doc_id"], r["n_tokens"], r["ids_crc32"]) for r in token_files.read_digest(spark, path).collect())
    library, start, want = WordIds(default_path()).library, 0, []
    for d, t in sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1] is not None, r[1] or "")):
        ids = [*library.encode(t or "", add_special_tokens=False).ids, 2]
        want.append((start, d, len(ids), zlib.crc32(np.asarray(ids, "<u4").tobytes())))
        start += len(ids)
    assert got == want
    one = token_files.read_ids(spark, path, [1]).collect()
    assert one[0]["ids"] == [*library.encode("long text here " * 500, add_special_tokens=False).ids, 2]


def test_empty_table(spark, tmp_path):
    path = str(tmp_path / "none")
    token_files.write_token_files(spark.createDataFrame([], "doc_id long, text string"), path)
    assert token_files.read_digest(spark, path).collect() == []
