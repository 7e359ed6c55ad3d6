"""Token ids of whole texts by a public vocabulary, exactly as the tokenizers library gives them.

The vocabulary splits at white space before anything else, so a text's ids are those of its white-space words in order.
Most words of a corpus are repeats: each worker keeps the ids of words it has met (a bounded cache) and hands only new
words to the library, many at a time.
"""

from __future__ import annotations

import os
import re
import struct

import numpy as np

#: Words held by a worker's cache before its older half goes.
CACHE_WORDS = 300_000
#: One character that no word handed to the library in a joined batch holds.
_MARK = "\x01"
#: Words of unaccented and Latin-1 letters, perhaps with ASCII punctuation after them: lowering them letter by letter is
#: safe, and as the marks are a piece of their own, neither ids depend on the other's.
_PLAIN = re.compile(rb"((?:[A-Za-z]|\xc3[\x80-\x96\x98-\xb6\xb8-\xbf])+)([!-/:-@\[-`{-~]{0,8})\Z")
#: Runs of punctuation whose ids a worker keeps at most.
_ENDS = 100_000


def _byte_letters() -> dict[int, str]:
    """The public byte-level alphabet: printable Latin-1 stands for itself, the rest follow from 256 on."""
    kept = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in kept]
    return {b: chr(b) for b in kept} | {b: chr(256 + i) for i, b in enumerate(rest)}


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class WordIds:
    """Ids of texts as little-endian unsigned 32-bit integers in bytes.

    path: a tokenizers file whose normaliser and pre-tokenizer treat white space as a boundary that leaves no id.
    """

    _open: dict[str, WordIds] = {}

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.size = self.library.get_vocab_size()
        self.young: dict[bytes, bytes] = {}
        self.old: dict[bytes, bytes] = {}
        mark = self._direct(_MARK)
        self.mark = mark[0] if len(mark) == 1 else None
        self.letters = _byte_letters()
        self.ends = {b"": b""}

    @classmethod
    def opened(cls, path: str) -> WordIds:
        """One for each path and worker."""
        if path not in cls._open:
            cls._open[path] = cls(path)
        return cls._open[path]

    def _direct(self, text: str) -> list[int]:
        return self.library.encode(text, add_special_tokens=False).ids

    @staticmethod
    def _pack(ids) -> bytes:
        return np.asarray(ids, dtype="<u4").tobytes()

    def _learn(self, stems: list[bytes], words: list[bytes]) -> None:
        """Put the ids of unmet stems and words into the cache.

        Stems are lower-case plain letters, a single pre-token, so the model gets them at once; words go through the
        whole library, joined by a mark where they do not hold it.
        """
        tokenize, letters, young = self.library.model.tokenize, self.letters, self.young
        for w in stems:
            ids = [x.id for x in tokenize(w.decode() if w.isascii() else w.decode("latin-1").translate(letters))]
            young[w] = struct.pack(f"<{len(ids)}I", *ids)
        joined, alone = [], []
        for w in words:
            (joined if self.mark is not None and _MARK.encode() not in w and b"<|" not in w else alone).append(w)
        for at in range(0, len(joined), 2_000):
            some = joined[at : at + 2_000]
            text = f" {_MARK} ".join([w.decode() for w in some])
            ids = np.asarray(self._direct(text), dtype="<u4")
            cuts = np.flatnonzero(ids == self.mark)
            if len(cuts) != len(some) - 1:
                alone += some
                continue
            raw = ids.tobytes()
            starts, ends = [0, *(cuts * 4 + 4).tolist()], [*(cuts * 4).tolist(), len(raw)]
            young.update(zip(some, [raw[a:b] for a, b in zip(starts, ends, strict=True)], strict=True))
        for w in alone:
            young[w] = self._pack(self._direct(w.decode()))

    def _end(self, marks: bytes) -> bytes:
        ids = self.ends.get(marks)
        if ids is None:
            ids = self._pack(self._direct(marks.decode()))
            if len(self.ends) < _ENDS:
                self.ends[marks] = ids
        return ids

    def _meet(self, words: set[bytes]) -> None:
        """See that every word is in the young half of the cache."""
        if len(self.young) > CACHE_WORDS:
            self.old, self.young = self.young, {}
        young, old, plain = self.young, self.old, _PLAIN.match
        stems, others, made, of, ends = set(), [], [], [], []
        for w in words:
            if w in young:
                continue
            ids = old.get(w)
            if ids is not None:
                young[w] = ids
                continue
            found = plain(w)
            if found is None:
                others.append(w)
                continue
            stem, marks = found.groups()
            stem = stem.lower() if stem.isascii() else stem.decode().lower().encode()
            if stem != w:
                made.append(w)
                of.append(stem)
                ends.append(self._end(marks))
            if stem not in young:
                ids = old.get(stem)
                if ids is None:
                    stems.add(stem)
                else:
                    young[stem] = ids
        self._learn(list(stems), others)
        for w, stem, end in zip(made, of, ends, strict=True):
            young[w] = young[stem] + end

    def encode(self, texts: list[str]) -> list[bytes]:
        """Ids of each whole text. None counts as empty."""
        split = [(t or "").encode("utf-8").split() for t in texts]
        met: set[bytes] = set()
        for words in split:
            met.update(words)
        self._meet(met)
        ids = self.young.__getitem__
        return [b"".join(map(ids, words)) for words in split]
