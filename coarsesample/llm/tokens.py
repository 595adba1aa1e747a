"""Token ids of the public ``tokenizers`` vocabularies, encoded once per distinct piece of text.

Both vocabularies treat white space as a hard border, so a text's ids are the ids of its pieces in
order. Each worker keeps the ids of the pieces that it was first to meet twice, among them the frequent
ones, up to a limit of some 40 MB; any other piece goes through the library each time.
Texts with the separators U+001C to U+001F, which Python and the library class differently, are
encoded whole.
"""

from __future__ import annotations

import os
import re
import unicodedata
from array import array
from itertools import islice

from coarsesample.llm import worker

END_ID = 1
_ODD = "\x1c\x1d\x1e\x1f"
_SPACE = re.compile(r"\s")
_CLOSING = ".,!?;:#$%&*|-\"()"
_SPACED = re.compile(r"\s+(?!\S)| ?\S+|\s")


def vocabulary_path(name: str) -> str:
    """Where a public vocabulary file lies; ``name`` may also be a full path."""
    if os.path.isabs(name):
        return name
    import public_tokenizers

    return public_tokenizers.path(name)


def _byte_letters() -> dict[int, str]:
    """The byte-level alphabet: printable Latin-1 signs stand for themselves, other bytes follow from U+0100."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in plain]
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(rest)}


_LETTERS = _byte_letters()
_SPACE_LETTER = _LETTERS[32]
_LATIN_END = "\u0250"


class _Pieces(dict):
    """Piece to its ids as little-endian 32-bit bytes; stops growing at ``limit`` entries.

    A piece is kept when it comes again, so that the many that come once take no entry; ``seen`` has a
    byte for each hash.

    A new piece that is letters and closing punctuation is the ids of both, since every vocabulary
    here cuts between letters and other signs; so the library sees each stem once.
    """

    def __init__(self, tokenizer, limit: int, folds: bool):
        super().__init__()
        self.tokenizer, self.limit, self.folds, self.tokenize = tokenizer, limit, folds, tokenizer.model.tokenize
        self.seen = bytearray(1 << 22)

    def keep(self, piece: str, ids: bytes) -> bytes:
        if len(self) < self.limit and len(piece) < 64:
            at = hash(piece) & 0x3FFFFF
            if self.seen[at]:
                self[piece] = ids
            self.seen[at] = 1
        return ids

    def encode(self, text: str) -> bytes:
        return array("I", self.tokenizer.encode(text, add_special_tokens=False).ids).tobytes()

    def letters(self, word: str, before: str = "") -> bytes:
        """Ids of a word of Latin letters: one pre-token, so the vocabulary's model takes it as it is.

        ``before`` is in the byte-level alphabet, where ASCII letters stand for themselves.
        """
        if self.folds:
            word = word.lower()
        mapped = before + (word if word.isascii() else word.encode().decode("latin-1").translate(_LETTERS))
        return array("I", [t.id for t in self.tokenize(mapped)]).tobytes()

    def __missing__(self, piece: str) -> bytes:
        stem = piece.rstrip(_CLOSING)
        if stem and len(stem) < len(piece) and stem.isalpha() and (not self.folds or unicodedata.normalize("NFC", stem).lower().isalpha()):
            ids = self[stem] + self.tail(piece[len(stem) :])
        elif self.folds and piece.isascii() and piece != piece.lower():
            ids = self[piece.lower()]
        else:
            ids = self.novel(piece)
        return self.keep(piece, ids)

    def tail(self, signs: str) -> bytes:
        return self[signs]

    def novel(self, piece: str) -> bytes:
        if piece.isalpha() and max(piece) < _LATIN_END and (not self.folds or piece.lower().isalpha()):
            return self.letters(piece)
        return self.encode(piece)


class _SpacedPieces(_Pieces):
    """Pieces that follow one space in the text; the space is part of their ids."""

    def __init__(self, tokenizer, limit: int):
        super().__init__(tokenizer, limit, False)
        self.bare = _Pieces(tokenizer, 50_000, False)

    def __missing__(self, piece: str) -> bytes:
        if not (piece.isascii() and piece.isalpha()):
            return super().__missing__(piece)
        return self.keep(piece, array("I", [t.id for t in self.tokenize(_SPACE_LETTER + piece)]).tobytes())

    def tail(self, signs: str) -> bytes:
        return self.bare[signs]

    def novel(self, piece: str) -> bytes:
        if piece.isalpha() and max(piece) < _LATIN_END:
            return self.letters(piece, _SPACE_LETTER)
        if _SPACE.search(piece) or not piece:
            return self.join(_SPACED.findall(" " + piece))
        return self.encode(" " + piece)

    def join(self, parts: list[str]) -> bytes:
        return b"".join(self[p[1:]] if p[0] == " " and len(p) > 1 and not p[1].isspace() else self.bare[p] for p in parts)


class PieceEncoder:
    """Encodes texts to ids. ``spaces`` says whether the vocabulary keeps white space (byte level) or drops it."""

    def __init__(self, vocabulary: str, spaces: bool, limit: int = 200_000):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        tokenizer = Tokenizer.from_file(vocabulary_path(vocabulary))
        tokenizer.encode_special_tokens = True
        self.spaces = spaces
        self._pieces = _SpacedPieces(tokenizer, limit) if spaces else _Pieces(tokenizer, limit, True)

    def ids_bytes(self, text: str | None) -> bytes:
        """Ids of one text as little-endian unsigned 32-bit integers, without an end id."""
        if not text:
            return b""
        pieces = self._pieces
        if any(c in text for c in _ODD):
            return pieces.encode(text)
        if not self.spaces:
            return b"".join(map(pieces.__getitem__, text.split()))
        if text[0] == " " or text[-1] == " " or "  " in text:
            return pieces.join(_SPACED.findall(text))
        words = text.split(" ")
        return pieces.join(_SPACED.findall(words[0])) + b"".join(map(pieces.__getitem__, islice(words, 1, None)))


END_BYTES = array("I", [END_ID]).tobytes()
_encoders: dict[tuple, PieceEncoder] = {}


def encoder(vocabulary: str, spaces: bool) -> PieceEncoder:
    """The worker's encoder for a vocabulary; it lives as long as the Python worker."""
    worker.claim("tokens", _encoders.clear)
    key = (vocabulary, spaces)
    if key not in _encoders:
        _encoders[key] = PieceEncoder(vocabulary, spaces)
    return _encoders[key]
