"""Byte-level BPE by pieces.

The vocabulary's own splitting rule never joins what stands before and after a space that follows a character
other than white space: such a space always begins a new unit. A single line feed between two such characters is
a unit of its own, and so is a run of punctuation marks between a letter and the end of its piece. A text is cut
there; each distinct piece is encoded once by the tokenizer, and a text's ids are its pieces' ids, one after the
other. Pieces with one space, at their start, are encoded JOINED at a time: a piece's ids begin where an id's bytes
begin with that space."""

from __future__ import annotations

import os
import re

import numpy as np

KEEP, GROUP, JOINED = 1 << 21, 256, 400
#: Punctuation marks; an apostrophe may begin a unit with the letters behind it.
MARKS = "!\"#$%&()*+,-./:;<=>?@[\\]^_`{|}~"
_CUT = re.compile(r"(?<=\S) ")


class Encoder:
    """ids of whole texts as little-endian unsigned 32-bit integers."""

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.size = self.tokenizer.get_vocab_size()
        self.cache: dict[str, bytes] = {}
        self.begins = np.zeros(self.size, bool)
        for token, i in self.tokenizer.get_vocab().items():
            if token.startswith("\u0120"):  # how this vocabulary writes a space
                self.begins[i] = True

    def _ids(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(e.ids, "<u4") for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _encode(self, pieces: list[str]) -> None:
        simple = [p for p in pieces if p[:1] == " " and len(p) > 1 and p.rfind(" ") == 0 and "<|" not in p and not p[-1].isspace()]
        groups = [simple[i : i + JOINED] for i in range(0, len(simple), JOINED)]
        left = set(pieces).difference(simple) if len(simple) < len(pieces) else set()
        for group, ids in zip(groups, self._ids(["".join(g) for g in groups]), strict=True):
            at = (np.flatnonzero(self.begins[ids]) * 4).tolist()
            if len(at) != len(group):
                left.update(group)
                continue
            data = ids.tobytes()
            self.cache.update(zip(group, [data[a:b] for a, b in zip(at, [*at[1:], len(data)], strict=True)], strict=True))
        alone = list(left)
        self.cache.update(zip(alone, [x.tobytes() for x in self._ids(alone)], strict=True))

    def _learn(self, pieces: list[str]) -> None:
        """Adds pieces to the cache; a word with marks behind it is the word and the marks."""
        cache, plain, marked = self.cache, set(), []
        for p in pieces:
            word = p.rstrip(MARKS)
            if len(word) < len(p) and len(word) > 2 and word[-1] < "ɐ" and word[1:].isalpha():
                marked.append((p, word, p[len(word) :]))
                plain.update(marked[-1][1:])
            else:
                plain.add(p)
        self._encode(list(plain.difference(cache)))
        for p, word, marks in marked:
            cache[p] = cache[word] + cache[marks]

    def pieces(self, text: str) -> list[str]:
        if len(text.split()) != text.count(" ") + text.count("\n") + 1 or "\0" in text:
            # white space of other kinds, at an end, or side by side
            cut = _CUT.split(text)
            return [cut[0], *(" " + p for p in cut[1:])]
        # a space stays with what follows it, a line feed stands alone
        return text.replace("\n", "\0\n\0").replace(" ", "\0 ").split("\0")

    def many(self, texts: list[str | None]):
        """Yields the ids of each text."""
        for at in range(0, len(texts), GROUP):
            cuts = [self.pieces(t or "") for t in texts[at : at + GROUP]]
            if len(self.cache) > KEEP:
                self.cache.clear()
            self._learn(list(set().union(*cuts).difference(self.cache)))
            for cut in cuts:
                yield b"".join(map(self.cache.__getitem__, cut))


_encoders: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    """The encoder of a vocabulary, kept with its pieces for all tasks of a Python worker."""
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    return _encoders[path]
