"""Token ids by the installed tokenizers library, cached word by word.

The vocabulary file word_bpe_49k.json splits texts at white space before its merges, so the ids of a text are those of
its white-space words in a row. Words are encoded once per worker and kept, as the bytes of their ids.
"""

from __future__ import annotations

import re

import numpy as np
import regex

END_ID = 2
#: Words, and pieces of words, that a worker keeps; when there are more it starts anew.
CACHE_WORDS, CACHE_PIECES = 800_000, 400_000
_SPACE = re.compile(r"[ \t\n\r]+")
_SEPARATORS = "\x1c\x1d\x1e\x1f"
#: Words of these characters alone have one NFC form, so they can be lower-cased and split here.
_LATIN = re.compile("[\x21-\x7e\xa1-\u024f]+")


def _pieces() -> re.Pattern:
    """The split pattern in the vocabulary file, for lower-cased words of the characters above: its classes are spelled out."""
    lowered = sorted({x for c in map(chr, (*range(0x21, 0x7F), *range(0xA1, 0x250))) for x in c.lower()})
    letters, numbers = ("".join(x for x in lowered if regex.match(kind, x)) for kind in (r"\p{L}", r"\p{N}"))
    # Fixed value: the pattern's parts and their order.
    return re.compile(rf"'s|'t|'re|'ve|'m|'ll|'d|[{letters}]+|[{numbers}]|[^\s{letters}{numbers}]+")


_PIECES = _pieces()
_SPECIAL = "<|"


def _byte_letters() -> list[str]:
    """The letter that byte-level vocabularies show for each byte: printable ones stand for themselves."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    spare = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


class WordEncoder(dict):
    """Word to little-endian uint32 ids, as bytes. Words are cut into pieces, and each piece is merged once."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        super().__init__()
        self.tokenizer = Tokenizer.from_file(path)
        self.model = self.tokenizer.model
        self.letters = _byte_letters()
        self.pieces: dict[str, bytes] = {}

    def _piece(self, piece: str) -> bytes:
        if (ids := self.pieces.get(piece)) is None:
            shown = piece if piece.isascii() else "".join(self.letters[b] for b in piece.encode())
            ids = b"".join([x.id.to_bytes(4, "little") for x in self.model.tokenize(shown)])
            if len(self.pieces) > CACHE_PIECES:
                self.pieces.clear()
            if len(piece) <= 64:
                self.pieces[piece] = ids
        return ids

    def __missing__(self, word: str) -> bytes:
        if _SPECIAL not in word and _LATIN.fullmatch(word):
            low = word.lower() if word.isascii() else "".join(c.lower() for c in word)
            # letters alone are one piece
            ids = self._piece(low) if low.isalpha() else b"".join(map(self._piece, _PIECES.findall(low)))
        else:
            ids = np.array(self.tokenizer.encode(word, add_special_tokens=False).ids, "<u4").tobytes()
        if len(word) <= 64:
            self[word] = ids
        return ids

    def payload(self, text: str, end: int = END_ID) -> bytes:
        """The ids of text and the end id, as bytes."""
        if len(self) > CACHE_WORDS:
            self.clear()
        if any(c in text for c in _SEPARATORS):  # str.split() cuts there, the vocabulary's white space doesn't
            words = [w for w in _SPACE.split(text) if w]
        else:
            words = text.split()
        return b"".join(map(self.__getitem__, words)) + end.to_bytes(4, "little")


_ENCODERS: dict[str, WordEncoder] = {}


def encoder(path: str) -> WordEncoder:
    if path not in _ENCODERS:
        _ENCODERS[path] = WordEncoder(path)
    return _ENCODERS[path]


def default_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))
