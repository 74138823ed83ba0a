"""Token ids of whole texts with the tokenizers library, at the cost of a dictionary look-up for most words.

A text of Latin-1 characters is cut by the tokenizer's own pre-tokenisation, written out for these characters,
and each piece goes to the library's model; pieces met lately are kept. Where no piece has white space in it, what
stands between white space is kept as well, with the ids of all its pieces, so that most of a text is not cut. A text
with other characters, or with what may be a special token, goes through the library's full encoding. All ways give
the same ids.
"""

from __future__ import annotations

import re
import sys

import numpy as np

_OTHER = re.compile("[^\x00-\xff]")
_PARTING = "\x1c\x1d\x1e\x1f"  # white space to str.split, but not to the tokenizers
# Latin-1 white space, letters and numbers.
_W = "\t-\r \x85\xa0"
_L = "A-Za-z\xaa\xb5\xba\xc0-\xd6\xd8-\xf6\xf8-\xff"
_N = "0-9\xb2\xb3\xb9\xbc-\xbe"
_ENDINGS = "'s|'t|'re|'ve|'m|'ll|'d"
_CUTS = {
    "byte": re.compile(f"{_ENDINGS}| ?[{_L}]+| ?[{_N}]+| ?[^{_W}{_L}{_N}]+|[{_W}]+(?![^{_W}])|[{_W}]+"),
    "word": re.compile(f"[{_L}]+|[{_N}]|{_ENDINGS}|[^{_W}{_L}{_N}]+"),
}


def byte_letters() -> dict[int, str]:
    """The printable character that stands for each byte in the model's vocabulary."""
    printable = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = (b for b in range(256) if b not in printable)
    return {b: chr(b) for b in printable} | {b: chr(256 + i) for i, b in enumerate(rest)}


class IdBytes(dict):
    def __missing__(self, i: int) -> bytes:
        value = self[i] = i.to_bytes(4, "little")
        return value


class Pieces(dict):
    def __init__(self, model, most: int):
        super().__init__()
        self.model, self.most, self.letters, self.bytes_of = model, most, byte_letters(), IdBytes()

    def __missing__(self, piece: str) -> bytes:
        if len(self) >= self.most:
            self.clear()
        value = self[piece] = self.ids(piece)
        return value

    def ids(self, piece: str) -> bytes:
        if not piece.isascii() or not piece.isprintable() or " " in piece:  # else its letters stand for themselves
            piece = piece.encode().decode("latin-1").translate(self.letters)
        return b"".join([self.bytes_of[t.id] for t in self.model.tokenize(piece)])


class Runs(Pieces):
    """The ids of what stands between white space, and of its pieces. When it is half full, what is asked for again moves on."""

    def __init__(self, model, most: int, cut: re.Pattern):
        super().__init__(model, most)
        self.cut, self.before = cut, {}

    def __missing__(self, run: str) -> bytes:
        if 2 * len(self) >= self.most:
            self.before = dict(self)
            self.clear()
        value = self.before.get(run)
        if value is None:
            found = [run] if run.isalpha() else self.cut.findall(run)
            value = self.ids(run) if len(found) == 1 else b"".join(map(self.__getitem__, found))
        self[run] = value
        return value


class TextTokenizer:
    def __init__(self, path: str, most: int = 400_000):
        from tokenizers import Tokenizer

        self.whole = Tokenizer.from_file(path)
        kind = type(self.whole.pre_tokenizer).__name__
        self.lower = kind == "Sequence" and self.whole.normalizer is not None
        self.cut = _CUTS["byte" if kind == "ByteLevel" else "word"] if kind == "ByteLevel" or self.lower else None
        self.pieces = Runs(self.whole.model, 2 * most, self.cut) if self.lower else Pieces(self.whole.model, most)
        self.size = self.whole.get_vocab_size(with_added_tokens=True)

    def ids(self, text: str | None) -> bytes:
        """Little-endian unsigned 32-bit ids."""
        if not text:
            return b""
        if self.cut is None or "<|" in text or not text.isascii() and _OTHER.search(text):
            return np.array(self.whole.encode(text, add_special_tokens=False).ids, "<u4").tobytes()
        if self.lower:
            text = text.lower()
            if not any(x in text for x in _PARTING):
                return b"".join(map(self.pieces.__getitem__, text.split()))
        return b"".join(map(self.pieces.__getitem__, self.cut.findall(text)))


def tokenizer(path: str) -> TextTokenizer:
    """One per worker process and path."""
    kept = sys.__dict__.setdefault("_text_tokenizers", {})
    if path not in kept:
        kept[path] = TextTokenizer(path)
    return kept[path]
