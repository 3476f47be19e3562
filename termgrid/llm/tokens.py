"""Encoding of whole texts by a public tokenizer, with the ids of frequent pieces kept."""

from __future__ import annotations

import os
import re
import unicodedata
from array import array

#: White space after which the tokenizers split in any case (fixed values).
_WIDE = "\x85\xa0  -     　"
_WHITE = "\t\n\x0b\x0c\r " + _WIDE
_PIECES = re.compile(f"[{_WHITE}]*[^{_WHITE}]+|[{_WHITE}]+")
_UNUSUAL = re.compile(f"[\t\x0b\x0c\r\0{_WIDE}]")
#: A word with what may stand before and after it: letters are cut from the signs that follow, but for apostrophes (fixed values).
_WORD = re.compile(r"([ \n]?)([^\W\d_]+)([!-&(-/:-@\[-`{-~]*)")
_PROBES = [" ab", "The", "\nZyqxw", " über.", "Éa,", " zyq***", "\nab...", " ñandú"]
#: Pieces kept for each worker, in two generations.
KEPT = 600_000
_encoders: dict[str, Encoder] = {}


def _byte_signs() -> dict[int, str]:
    """Sign that byte-level tokenizers put for each byte: printable Latin-1 stands for itself, the rest counts on from U+0100."""
    shown = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    hidden = [b for b in range(256) if b not in shown]
    return {b: chr(b) if b in shown else chr(0x100 + hidden.index(b)) for b in range(256)}


class Pieces(dict):
    """Piece -> its ids; what is missing comes from the generation before or is encoded."""

    def __init__(self, encode, old: dict[str, bytes]):
        super().__init__()
        self.encode, self.old = encode, old

    def __missing__(self, piece: str) -> bytes:
        ids = self.old.get(piece)
        ids = self[piece] = self.encode(piece) if ids is None else ids
        return ids


class Encoder:
    """Ids of texts as little-endian unsigned 32-bit integers.

    Both kinds of tokenizer cut a text where white space follows other characters before they merge, so the ids of a text
    are those of its pieces, each with its leading white space, in a row; equal pieces are encoded once. They cut between
    letters and signs, too, so a word can go to the tokenizer's model without the passes over texts before it; a tokenizer
    that gives other ids for a few probes gets whole pieces only. The ids are those of the plain library call, strings like
    ``<|endoftext|>`` included.
    """

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.added = tuple({t.content[:2] for t in self.tokenizer.get_added_tokens_decoder().values()})
        self.model = self.tokenizer.model
        self.signs = _byte_signs()
        self.folds = self._whole(" \u00c9Zyq") == self._whole("\n\u00e9zyq") == self._whole("\u00e9zyq")
        self.newline = b"" if self.folds else self._whole("\n")
        self.pieces = Pieces(self._ids, {})
        self.kept = KEPT
        self.direct = True
        self.direct = all(self._ids(p) == self._whole(p) for p in _PROBES)
        self.pieces = Pieces(self._ids, {})

    def _whole(self, piece: str) -> bytes:
        return array("I", self.tokenizer.encode_batch_fast([piece], add_special_tokens=False)[0].ids).tobytes()

    def _ids(self, piece: str) -> bytes:
        """Ids of a piece: of its leading line end, its word and the signs after that."""
        found = _WORD.fullmatch(piece) if self.direct else None
        if not found or not found[2].isalpha():
            return self._whole(piece)
        lead, word, signs = found.groups()
        ascii_ = word.isascii()
        if not ascii_ and not unicodedata.is_normalized("NFKC", word):
            return self._whole(piece)
        if self.folds:
            word = word.lower() if ascii_ else "".join(map(str.lower, word))
            if not ascii_ and not word.isalpha():
                return self._whole(piece)
            lead = ""
        ids = self._word(" " + word if lead == " " else word, ascii_)
        if lead == "\n":
            ids = self.newline + ids
        return ids + self.pieces[signs] if signs else ids

    def _word(self, word: str, ascii_: bool) -> bytes:
        """Ids of letters, or of a space and letters, in the case and form that the model sees."""
        ids = self.pieces.get(word) or self.pieces.old.get(word)
        if ids is None:
            mapped = word.replace(" ", self.signs[32]) if ascii_ else "".join(map(self.signs.__getitem__, word.encode()))
            ids = self.pieces[word] = array("I", [t.id for t in self.model.tokenize(mapped)]).tobytes()
        return ids

    def _cut(self, text: str) -> list[str]:
        if _UNUSUAL.search(text) or "  " in text or "\n\n" in text or " \n" in text or "\n " in text:
            return _PIECES.findall(text)
        return text.replace(" ", "\0 ").replace("\n", "\0\n").split("\0") if text else []

    def encode(self, texts: list[str | None]) -> list[bytes]:
        if len(self.pieces) > self.kept:
            last = self.pieces
            last.old = {}
            self.pieces = Pieces(self._ids, last)
        get = self.pieces.__getitem__
        # strings of added tokens are one id wherever they stand, so texts that may hold one go to the library whole
        return [self._whole(t) if t and any(a in t for a in self.added) else b"".join(map(get, self._cut(t or ""))) for t in texts]


def encoder(path: str, kept: int = KEPT) -> Encoder:
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    _encoders[path].kept = kept
    return _encoders[path]


def in_pieces(texts: list, most: int = 1_000_000):
    """Slices of the list with about so many characters each, a longer text alone."""
    i, size = 0, 0
    for j, t in enumerate(texts):
        if size and size + len(t or "") > most:
            yield i, j
            i, size = j, 0
        size += len(t or "")
    if i < len(texts):
        yield i, len(texts)
