"""Byte-level BPE ids by a public vocabulary: one regular-expression pass, each distinct piece encoded once per worker.

A byte-level BPE encodes the pieces of its pattern one by one, so remembering the ids of pieces gives the same ids as
encoding the whole text; the tests hold both against each other. The memory is bounded in pieces and
their length (some 200 bytes a piece); what no longer fits is encoded anew.
"""

from __future__ import annotations

import re
from array import array
from functools import lru_cache

VOCABULARY = "byte_bpe_50k.json"


def _byte_letters() -> dict[int, str]:
    """The usual byte alphabet of byte-level BPE: visible Latin-1 characters stand for themselves, the other bytes for the
    characters from 256 on, in order."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in own]
    return {b: chr(b) for b in own} | {b: chr(256 + i) for i, b in enumerate(rest)}


class _Pieces(dict):
    """Piece -> ids. A new piece goes to the tokenizer's model directly, without offsets, masks and pattern."""

    def __init__(self, tokenizer, limit: int, longest: int):
        super().__init__()
        self._model, self._limit, self._longest, self._letters = tokenizer.model, limit, longest, _byte_letters()

    def __missing__(self, piece: str) -> bytes:
        found = self._model.tokenize(piece.encode().decode("latin-1").translate(self._letters))
        ids = array("I", [t.id for t in found]).tobytes()
        if len(self) < self._limit and len(piece) <= self._longest:
            self[piece] = ids
        return ids


#: The classes of the vocabulary's pattern among the code points below 256: letters, numbers, white space.
_L, _N, _S = "A-Za-z\xaa\xb5\xba\xc0-\xd6\xd8-\xf6\xf8-\xff", "0-9\xb2\xb3\xb9\xbc-\xbe", "\t-\r \x85\xa0"


def narrow_pattern() -> re.Pattern:
    """The vocabulary's pattern for texts of Latin-1 characters, with its classes spelled out: the standard library matches
    these about three times as fast as properties. Runs of letters and numbers come first, as nothing else starts like them."""
    parts = (f" ?[{_L}]+", f" ?[{_N}]+", "'(?:s|t|re|ve|m|ll|d)", f" ?[^{_S}{_L}{_N}]+", f"[{_S}]+(?![^{_S}])", f"[{_S}]+")
    return re.compile("|".join(parts))


class ByteBpe:
    def __init__(self, path: str, remember: int = 600_000, longest: int = 48):
        import public_tokenizers
        import regex
        from tokenizers import Tokenizer

        t = Tokenizer.from_file(path)
        t.encode_special_tokens = True  # their strings in a text are ordinary text
        self._find, self._find_narrow = regex.compile(public_tokenizers.PATTERN).findall, narrow_pattern().findall
        self._ids = _Pieces(t, remember, longest).__getitem__

    def encode(self, text: str) -> bytes:
        """Little-endian unsigned 32-bit ids."""
        try:
            text.encode("latin-1")
            find = self._find_narrow
        except UnicodeEncodeError:
            find = self._find
        return b"".join(map(self._ids, find(text)))


@lru_cache(maxsize=2)
def encoder(path: str) -> ByteBpe:
    return ByteBpe(path)


def vocabulary_path(name: str = VOCABULARY) -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))
