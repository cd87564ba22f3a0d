"""Public tokenizers behind a bounded memory of words.

Each vocabulary cuts texts at white space in a way that makes the ids of a text the concatenation
of the ids of its words, so a word needs encoding once per worker and not once per occurrence.
"""

from __future__ import annotations

import re
from functools import lru_cache

import numpy as np

from hybridrec.llm.texts import Memo


def vocabulary_path(name: str) -> str:
    """Where a public vocabulary lies on this machine."""
    import public_tokenizers

    return public_tokenizers.path(name)


@lru_cache(1)
def _byte_letters() -> list[str]:
    """The letter by which a byte-level vocabulary writes each byte: printable Latin-1 stands for itself, the rest follows from U+0100."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    out, n = [], 0
    for b in range(256):
        if b in plain:
            out.append(chr(b))
        else:
            out.append(chr(256 + n))
            n += 1
    return out


class WordIds:
    """Ids of a lower-casing BPE with word ends, per white-space word, as little-endian 32-bit bytes."""

    #: Words of these characters are their own normal form but for case.
    PLAIN = re.compile("[!-~À-ÖØ-öø-ÿ]+")
    #: How the vocabulary cuts such a word.
    CUT = re.compile("'s|'t|'re|'ve|'m|'ll|'d|[a-zß-öø-ÿ]+|[0-9]|[^a-zß-öø-ÿ0-9]+")

    def __init__(self, path: str, size: int = 400_000):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.model = self.tokenizer.model
        self.letters = _byte_letters()
        self.memo = Memo(self._encode, size)
        self.cuts: dict[str, tuple] = {}

    def _cut_ids(self, cut: str) -> list[int]:
        shown = cut if cut.isascii() else "".join([self.letters[b] for b in cut.encode()])
        return [t.id for t in self.model.tokenize(shown)]

    def _encode(self, words: list[bytes]) -> list[bytes]:
        out, short = [], self.cuts
        for w in words:
            s = w.decode("utf-8", "replace")
            if self.PLAIN.fullmatch(s) and "<|" not in s:
                ids = []
                for cut in self.CUT.findall(s.lower()):
                    if len(cut) > 4:
                        ids += self._cut_ids(cut)
                    else:
                        got = short.get(cut)
                        if got is None:
                            if len(short) > 100_000:
                                short.clear()
                            got = short[cut] = self._cut_ids(cut)
                        ids += got
            else:
                ids = self.tokenizer.encode(s, add_special_tokens=False).ids
            out.append(np.array(ids, "<u4").tobytes())
        return out

    def ids(self, text: bytes) -> bytes:
        """All ids of a text."""
        words = text.split()
        got = self.memo.load(words)
        return b"".join([got[w] for w in words])


@lru_cache(2)
def word_ids(path: str) -> WordIds:
    return WordIds(path)
