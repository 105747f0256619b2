"""Token ids of whole texts by a given public tokenizer file, with a bounded cache of words."""

from __future__ import annotations

import re
import struct

import numpy as np

#: Words kept by a worker; a full cache is emptied.
CACHE_WORDS = 300_000
#: Characters for which Python's lower() and split() agree with the tokenizer's own steps.
PLAIN = re.compile(r"[\t\n\r\x20-\x7e\xa1-\xb1\xb4-\xb8\xba\xbb\xbf-ɏ]*")
#: The tokenizer's pieces, for plain characters.
PIECES = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[^\W\d_]+|\d|(?:[^\w\s]|_)+")
_OPEN: dict[int, "WordTokenizer"] = {}


class _Words(dict):
    """Ids by word; a word that isn't there yet is learned."""

    def __init__(self, learn):
        super().__init__()
        self.learn = learn

    def __missing__(self, word: str) -> bytes:
        return self.learn(word)


class WordTokenizer:
    """A tokenizer whose pieces never cross white space and that drops it (as word_bpe_49k.json does).

    A text of plain characters is split at white space and every word's ids come from a cache; words
    not in it are cut in pieces that go to the tokenizer's merges. Other texts go through the
    tokenizer as a whole. Ids are the same.
    """

    def __init__(self, definition: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_str(definition)
        self.special = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.dtype = np.dtype("<u2" if self.tokenizer.get_vocab_size() <= 1 << 16 else "<u4")
        self.code = "H" if self.dtype.itemsize == 2 else "I"
        self.words = _Words(self._learn)
        self.model = self.tokenizer.model
        shown = [*range(33, 127), *range(161, 173), *range(174, 256)]  # bytes that stand for themselves; the others follow from 256 on
        self.letters = {b: 256 + i for i, b in enumerate(b for b in range(256) if b not in shown)}

    @classmethod
    def shared(cls, definition: str) -> "WordTokenizer":
        """One per worker process."""
        key = hash(definition)
        if key not in _OPEN:
            _OPEN[key] = cls(definition)
        return _OPEN[key]

    def _whole(self, text: str) -> bytes:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, dtype=self.dtype).tobytes()

    def _learn(self, word: str) -> bytes:
        """Ids of a word of plain characters, piece by piece."""
        pieces = PIECES.findall(word)
        if len(pieces) > 1:
            out = b"".join(map(self.words.__getitem__, pieces))
        else:
            ids = [t.id for t in self.model.tokenize(word if word.isascii() else self._bytes_as_letters(word))]
            out = struct.pack(f"<{len(ids)}{self.code}", *ids)
        self.words[word] = out
        return out

    def _bytes_as_letters(self, piece: str) -> str:
        """The piece as the byte-level step spells it."""
        return piece.encode().decode("latin-1").translate(self.letters)

    def encode(self, text: str) -> bytes:
        """Ids of the whole text as little-endian ``dtype``."""
        if not PLAIN.fullmatch(text) or any(s in text for s in self.special):
            return self._whole(text)
        if len(self.words) > CACHE_WORDS:
            self.words.clear()
        return b"".join(map(self.words.__getitem__, text.lower().split()))
