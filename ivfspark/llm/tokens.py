"""Encoding with a public tokenizer, by pieces between spaces.

The tokenizers used here drop white space before they split, so a text's ids are the ids of its pieces
between spaces, tabs and line ends, one after the other. Each worker keeps the pieces it has met. A new
piece of letters before ASCII signs splits once more: letters and signs are separate words to the tokenizer.
New words of letters are encoded as one text, and cut where a token ends a word; if the cuts do not fit the
words, and for all other pieces, each is encoded by itself. ``split_spaces=False`` encodes whole texts,
for tokenizers where spaces matter.
"""

from __future__ import annotations

import os
import re
from collections.abc import Iterable

import numpy as np

TOKENIZER = "word_bpe_49k.json"
#: Pieces and words kept by a worker; when full the memory starts anew. Words are what costs the tokenizer
#: time, so more of them are kept: about 200 bytes each.
MEMORY_PIECES = 1_200_000
MEMORY_WORDS = 1_000_000
#: Letters, then ASCII signs other than the apostrophe, which the tokenizer may join to letters.
_LETTERS_SIGNS = re.compile(r"([^\W\d_]+)([!-&(-/:-@\[-`{-~]*)\Z")
#: The signs of that pattern.
_SIGNS = frozenset("".join(map(chr, range(33, 127)))) - frozenset("'0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz")
_WORD_END = "</w>"
_encoders: dict[tuple[str, bool], Encoder] = {}


def tokenizer_path(name: str = TOKENIZER) -> str:
    """Place of a public tokenizer file on this machine."""
    import public_tokenizers

    return public_tokenizers.path(name)


class Encoder:
    """Text to little-endian 32-bit ids."""

    def __init__(self, path: str, split_spaces: bool = True):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # tasks already fill the cores
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.split_spaces = split_spaces
        vocabulary = self.tokenizer.get_vocab()
        self.ends = np.zeros(max(vocabulary.values()) + 1, bool)
        self.ends[[i for t, i in vocabulary.items() if t.endswith(_WORD_END)]] = True
        self.known: dict[str, bytes] = {"": b""}
        self.words: dict[str, bytes] = {"": b""}

    def _ids(self, text: str) -> np.ndarray:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, "<u4")

    def _learn_words(self, words: list[str]) -> None:
        """Encode new words of letters together."""
        ids = self._ids(" ".join(words))
        cuts = np.flatnonzero(self.ends[ids]) + 1
        if len(cuts) == len(words) and cuts[-1] == len(ids):
            raw, at = ids.tobytes(), 0
            for word, cut in zip(words, (cuts * 4).tolist(), strict=True):
                self.words[word] = raw[at:cut]
                at = cut
        else:
            for word in words:
                self.words[word] = self._ids(word).tobytes()

    def _learn(self, pieces: list[str]) -> None:
        known, words = self.known, self.words
        split: list[tuple[str, str, str]] = []
        new: dict[str, None] = {}
        for piece in pieces:
            if piece.isalpha():
                letters, signs = piece, ""
            elif piece[-1] in _SIGNS and piece[:-1].isalpha():
                letters, signs = piece[:-1], piece[-1]
            else:
                found = _LETTERS_SIGNS.match(piece)
                letters, signs = found.groups() if found else ("", "")
            word = letters.lower()
            if word.isalpha() and "Σ" not in letters:  # a final sigma's lower case depends on its place
                split.append((piece, word, signs))
                if word not in words:
                    new[word] = None
                if signs not in words:
                    words[signs] = self._ids(signs).tobytes()
            else:
                known[piece] = self._ids(piece).tobytes()
        if new:
            self._learn_words(list(new))
        for piece, word, signs in split:
            known[piece] = words[word] + words[signs]

    def encode(self, text: str | None) -> bytes:
        if not self.split_spaces:
            return self._ids(text or "").tobytes()
        pieces = (text or "").replace("\n", " ").replace("\t", " ").replace("\r", " ").split(" ")
        new = set(pieces).difference(self.known)
        if new:
            if len(self.known) > MEMORY_PIECES:
                self.known = {"": b""}
                new = set(pieces).difference(self.known)
            if len(self.words) > MEMORY_WORDS:
                self.words = {"": b""}
            self._learn(list(new))
        return b"".join(map(self.known.__getitem__, pieces))

    def encode_all(self, texts: Iterable[str | None]) -> list[bytes]:
        return [self.encode(t) for t in texts]


def encoder(path: str, split_spaces: bool = True) -> Encoder:
    """This worker's encoder for a tokenizer file."""
    key = (path, split_spaces)
    if key not in _encoders:
        _encoders[key] = Encoder(path, split_spaces)
    return _encoders[key]
