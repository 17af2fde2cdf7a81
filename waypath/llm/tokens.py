"""Ids of a word-level BPE file exactly as its library gives them, mostly from per-chunk tables.

Under this file's rules no token crosses white space, so a text is the chain of its
white-space separated chunks and a chunk's ids can be kept.  Texts with characters
outside ``SAFE``, or with the opening of a special token, go whole to the library.
"""

from __future__ import annotations

import json
import re

import numpy as np
import public_tokenizers
import regex
from tokenizers import Tokenizer

WORD_FILE = "word_bpe_49k.json"
#: Characters for which lower-casing, NFC and white space agree between Python and the library.
SAFE = re.compile("[\t\n\r\x20-\x7e\xa1-įı-ſ‐-―‘-‟•…€]*")
#: A worker keeps at most this many chunks; then it starts over.  Bounds memory only, never results.
KEEP_CHUNKS, KEEP_LENGTH = 500_000, 48

_BYTES = [*range(33, 127), *range(0xA1, 0xAD), *range(0xAE, 0x100)]


def byte_letters() -> list[str]:
    """The letter that stands for each byte in byte-level vocabularies."""
    spare = iter(range(256, 512))
    own = set(_BYTES)
    return [chr(b) if b in own else chr(next(spare)) for b in range(256)]


class _Table(dict):
    def __init__(self, make):
        super().__init__()
        self.make = make

    def __missing__(self, key):
        value = self.make(key)
        if len(key) <= KEEP_LENGTH:
            if len(self) >= KEEP_CHUNKS:
                self.clear()
            self[key] = value
        return value


class WordBpe:
    """encode(text) -> bytes of ids (``dtype``); count(text) -> number of ids."""

    def __init__(self, path: str, whole: frozenset[str] | None = None):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.lib = Tokenizer.from_file(path)
        self.pieces = regex.compile(spec["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"])
        self.dtype = "<u2" if len(spec["model"]["vocab"]) + len(spec["added_tokens"]) < 65536 else "<u4"
        self.letters = byte_letters()
        self.merge = self.lib.model.tokenize
        self.whole = whole or frozenset()
        self._ids = _Table(self._chunk_ids)
        self._piece_ids = _Table(self._merge_ids)
        self._counts = _Table(self._chunk_count)
        self._piece_counts = _Table(self._merge_count)

    def _level(self, piece: str) -> str:
        return piece if piece.isascii() else "".join([self.letters[b] for b in piece.encode()])

    def _merge_ids(self, piece: str) -> bytes:
        return np.array([t.id for t in self.merge(self._level(piece))], self.dtype).tobytes()

    def _chunk_ids(self, chunk: str) -> bytes:
        return b"".join(map(self._piece_ids.__getitem__, self.pieces.findall(chunk)))

    def _merge_count(self, piece: str) -> int:
        return len(self.merge(self._level(piece)))

    def _chunk_count(self, chunk: str) -> int:
        whole, merged = self.whole, self._piece_counts
        return sum([1 if p in whole else merged[p] for p in self.pieces.findall(chunk)])

    @staticmethod
    def plain(text: str) -> bool:
        return "<|" not in text and SAFE.fullmatch(text) is not None

    def encode(self, text: str) -> bytes:
        if self.plain(text):
            return b"".join(map(self._ids.__getitem__, text.lower().split()))
        return np.array(self.lib.encode(text, add_special_tokens=False).ids, self.dtype).tobytes()

    def count(self, text: str) -> int:
        if self.plain(text):
            return sum(map(self._counts.__getitem__, text.lower().split()))
        return len(self.lib.encode(text, add_special_tokens=False).ids)


_LOADED: dict[str, WordBpe] = {}


def loaded(path: str | None = None, whole: frozenset[str] | None = None) -> WordBpe:
    """One encoder per worker process and file."""
    path = path or public_tokenizers.path(WORD_FILE)
    key = f"{path}|{whole is not None}"
    if key not in _LOADED:
        _LOADED[key] = WordBpe(path, whole)
    return _LOADED[key]


def prove_whole_tokens(path: str | None = None) -> frozenset[str]:
    """Vocabulary strings that, standing alone as a pre-token, encode as exactly their own one token.

    Each candidate is decoded from its byte letters, must be a single pre-token under the
    file's pattern, and is run through the library; only those that come back as the one
    expected id are kept.  Nothing is assumed from the vocabulary alone.
    """
    path = path or public_tokenizers.path(WORD_FILE)
    bpe = loaded(path)
    back = {c: b for b, c in enumerate(bpe.letters)}
    end = "</w>"
    cand = {}
    for token, i in bpe.lib.get_vocab(with_added_tokens=False).items():
        if token.endswith(end) and len(token) > len(end) and all(c in back for c in token[:-len(end)]):
            try:
                text = bytes(back[c] for c in token[:-len(end)]).decode()
            except UnicodeDecodeError:
                continue
            if WordBpe.plain(text) and text == text.lower() and bpe.pieces.findall(text) == [text]:
                cand[text] = i
    texts = list(cand)
    found = bpe.lib.encode_batch(texts, add_special_tokens=False)
    return frozenset(t for t, e in zip(texts, found) if e.ids == [cand[t]])
