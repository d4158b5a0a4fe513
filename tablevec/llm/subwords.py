"""Subword ids of whole texts by a public tokenizer, with a bounded cache of space-separated chunks."""

from __future__ import annotations

import numpy as np


def byte_letters() -> dict[int, str]:
    """The letters by which byte-level vocabularies write bytes: printable ones as they are, others from U+0100 on."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in plain]
    return {b: chr(b) for b in plain} | {b: chr(0x100 + i) for i, b in enumerate(rest)}


class ChunkCoder(dict):
    """Bytes of little-endian unsigned 32-bit ids for each chunk of a text between single spaces or line feeds.

    Valid for tokenizers that replace runs of white space by one space, drop it and never join across it, so the
    ids of a text are those of its chunks in a row. A chunk that ends in ASCII punctuation after a letter is two
    pre-tokens, and case is folded, so both are looked up in parts. A run of small Latin letters is one pre-token that
    normalisation leaves alone, so it goes to the merge model at once. The cache holds at most `most` chunks of up to
    64 characters; others are encoded each time, which changes the speed only.
    """

    def __init__(self, path: str, most: int = 500_000):
        super().__init__()
        from tokenizers import Tokenizer

        self.most, self.tokenizer = most, Tokenizer.from_file(path)
        self.model = self.tokenizer.model
        letters = byte_letters()
        self.spelled = {c: "".join(letters[b] for b in chr(c).encode()) for c in range(0x80, 0x250)}
        self[""] = b""
        for mark in ",.;:":
            self[mark] = self._encode(mark)

    def _encode(self, chunk: str) -> bytes:
        if chunk.isalpha() and chunk == chunk.lower() and max(chunk) < "ɐ" and len(chunk) <= 64:
            ids = [t.id for t in self.model.tokenize(chunk if chunk.isascii() else chunk.translate(self.spelled))]
        else:
            ids = self.tokenizer.encode(chunk, add_special_tokens=False).ids
        return np.array(ids, dtype="<u4").tobytes()

    def __missing__(self, chunk: str) -> bytes:
        if len(chunk) > 1 and chunk[-1] in ",.;:" and chunk[:-1].isalpha() and chunk.lower()[:-1].isalpha():
            out = self[chunk[:-1]] + self[chunk[-1]]
        elif chunk.isalpha() and chunk != (low := chunk.lower()) and max(chunk) < "ɐ" and "İ" not in chunk:
            out = self[low]
        else:
            out = self._encode(chunk)
        if len(self) < self.most and len(chunk) <= 64:
            self[chunk] = out
        return out

    def ids(self, text: str) -> bytes:
        return b"".join(map(self.__getitem__, text.replace("\n", " ").split(" ")))


_CODERS: dict[tuple[str, int], ChunkCoder] = {}


def coder(path: str, most: int = 500_000) -> ChunkCoder:
    """The worker's own coder for a tokenizer file; it stays for the next tasks."""
    if (path, most) not in _CODERS:
        _CODERS[path, most] = ChunkCoder(path, most)
    return _CODERS[path, most]
