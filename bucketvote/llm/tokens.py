"""Token ids of whole texts, by the tokenizers library, with a bounded cache of white-space separated chunks, of two generations.

The word vocabulary drops white space and never joins across it, so a text's ids are those of its chunks one after
another. Every chunk is encoded by the library once while it stays in the cache. Other vocabularies, whose ids may
span white space, are encoded whole (``chunked=False``).
"""

from __future__ import annotations

import json
import re
import sys
from array import array

import numpy as np

#: Id appended to each document.
END_ID = 1
#: Latin letters that normalisation keeps, apart from their case; then marks that cannot join the letters.
_PLAIN = re.compile(r"([A-Za-zÀ-ÖØ-öø-ÿ]+)([!-&(-/:-@\[-`{-~]*)").fullmatch


def byte_letters() -> str:
    """The 256 characters by which byte-level vocabularies write bytes: printable ones stand for themselves."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    spare = iter(range(256, 512))
    return "".join(chr(b) if b in set(own) else chr(next(spare)) for b in range(256))


class _Cache(dict):
    """Ids by chunk, made when first asked for. What the generation before holds is taken over when it is asked for again."""

    def __init__(self, make, before: dict | None = None):
        super().__init__()
        self.make = make
        self.before = before or {}

    def __missing__(self, chunk: str) -> bytes:
        out = self.before.get(chunk)
        out = self[chunk] = self.make(chunk) if out is None else out
        return out

    def known(self, chunk: str) -> bytes | None:
        out = self.get(chunk)
        return self.before.get(chunk) if out is None else out

    def next(self) -> "_Cache":
        """A new generation after this one; the one before this goes."""
        self.before = {}
        return _Cache(self.make, self)


class Encoder:
    """Little-endian unsigned 32-bit ids of texts as bytes."""

    def __init__(self, path: str, cache_size: int = 400_000, chunked: bool = True):
        from tokenizers import Tokenizer

        self.whole = Tokenizer.from_file(path)
        model = self.whole.model
        self.tokenize = model.tokenize
        self.letters = byte_letters()
        self.cache = _Cache(self._chunk)
        self.cache_size = cache_size
        with open(path) as f:
            kind = json.load(f)
        #: Plain words go straight to the merge table where the vocabulary is byte-level BPE over single words.
        self.words = chunked and kind["model"]["type"] == "BPE" and kind["model"].get("end_of_word_suffix") == "</w>" and sys.byteorder == "little"
        self.chunked = chunked

    def ids(self, text: str) -> bytes:
        return np.array(self.whole.encode(text, add_special_tokens=False).ids, dtype="<u4").tobytes()

    def _chunk(self, chunk: str) -> bytes:
        """Ids of a chunk that the cache lacks; a plain word and the marks after it are separate to the vocabulary."""
        if self.words and (found := _PLAIN(chunk)):
            word, marks = found.groups()
            if (known := self.cache.known(word)) is None:
                spelled = word.lower()
                if not spelled.isascii():
                    spelled = spelled.encode().decode("latin1").translate(self.letters)
                known = array("I", [t.id for t in self.tokenize(spelled)]).tobytes()
                if marks:
                    self.cache[word] = known
            if marks:
                if (tail := self.cache.known(marks)) is None:
                    tail = self.cache[marks] = self.ids(marks)
                return known + tail
            return known
        return self.ids(chunk)

    def encode(self, text: str) -> bytes:
        if not self.chunked:
            return self.ids(text)
        if len(self.cache) > self.cache_size:
            self.cache = self.cache.next()
        return b"".join(map(self.cache.__getitem__, text.replace("\n", " ").split(" ")))


_encoders: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    """The worker's encoder: Spark reuses Python workers, so later tasks find the cache warm."""
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    return _encoders[path]
