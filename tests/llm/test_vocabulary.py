"""Words of letters and punctuation get the library's ids without going through the whole library one by one."""

import random

import numpy as np

from edgefold.llm.vocabulary import WordIds, default_path


def made_words(n, seed=4):
    draw = random.Random(seed)
    letters = "abcdefgh\u00e9\u00e8\u00e0\u00df\u00ffABCDEFGH\u00c9\u00c0\u00de\u00fe\u00d7"
    marks = ["", ",", ".", "%%%", "&&&", "'", "'s", "''", ".'s", "<|", "|>", "$$$", "!?", "()[]{}", "~`^_", "***********", ",&&&", "-", "/", "9", "\u2026", "\u0301", "<"]
    return ["".join(draw.choice(letters) for _ in range(draw.randint(1, 12))) + draw.choice(marks) for _ in range(n)]


def test_letters_and_marks_are_as_the_whole_library_gives_them():
    words = WordIds(default_path())
    for text in (*made_words(4_000), *[" ".join(made_words(30, k)) for k in range(50)], "a", "A,", "\u00c9\u00c9...", "don't", "don'", "D'", "'d", "x" * 500 + "!!"):
        assert np.frombuffer(words.encode([text])[0], "<u4").tolist() == words._direct(text), text


def test_the_library_sees_each_run_of_marks_once(monkeypatch):
    words, seen = WordIds(default_path()), []
    whole = words._direct
    monkeypatch.setattr(words, "_direct", lambda text: seen.append(text) or whole(text))
    words.encode([f"{chr(97 + k % 26) * (1 + k // 26)}{mark} {chr(65 + k % 26)}{mark}" for k in range(500) for mark in ("%%%", ",&&&", ".")])
    assert sorted(seen) == sorted([",&&&", ".", "%%%"])
