"""Token ids by a public tokenizer, one chunk of non-space bytes at a time.

The tokenizer of ``word_bpe_49k.json`` never joins text across white space, so the ids of a text are
those of its chunks in order. Each distinct chunk is encoded once per worker process, as long as the
caches hold it, and looked up afterwards.
Chunks of plain Latin letters, digits and signs are cut into the tokenizer's words here, and a new word
goes to its model alone; all other chunks go through the whole tokenizer.
"""

from __future__ import annotations

import re

import numpy as np

from .common import word_codes

VOCABULARY = "word_bpe_49k.json"


def vocabulary_path(name: str = VOCABULARY) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


#: Chunks of visible ASCII and of the Latin-1 letters, for which normalising is lower-casing.
_PLAIN = re.compile(rb"(?:[!-~]|\xc3[\x80-\xbf])+")
_LETTER = r"a-z\xdf-\xf6\xf8-\xff"
#: The tokenizer's words in such chunks, and the line ends between chunks.
_WORDS = re.compile(rf"\n|'s|'t|'re|'ve|'m|'ll|'d|[{_LETTER}]+|[0-9]|[^\n0-9{_LETTER}]+")


def _byte_letters() -> dict[int, int]:
    """The public byte-to-letter rule of byte-level BPE: visible Latin-1 stands for itself, the rest follows 255."""
    visible = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    hidden = [b for b in range(256) if b not in visible]
    return {b: 256 + i for i, b in enumerate(hidden) if b != 10}  # no word holds a line end


_LETTERS = _byte_letters()
_TOKENIZERS: dict = {}


def _tokenizer(path: str):
    """One per worker process, kept from task to task."""
    if path not in _TOKENIZERS:
        from tokenizers import Tokenizer

        _TOKENIZERS[path] = Tokenizer.from_file(path)
    return _TOKENIZERS[path]


class _Store:
    """Sequences of ids under keys, in one flat array."""

    def __init__(self):
        self.place: dict = {}
        self.flat = np.zeros(1 << 16, np.uint16)
        self.starts = np.zeros(1 << 14, np.int64)
        self.sizes = np.zeros(1 << 14, np.int64)
        self.used = 0

    def add(self, keys: list, flat: np.ndarray, sizes: np.ndarray) -> None:
        n, m = len(self.place), len(keys)
        while self.used + len(flat) > len(self.flat):
            self.flat = np.concatenate((self.flat, np.zeros_like(self.flat)))
        while n + m > len(self.starts):
            self.starts, self.sizes = (np.concatenate((a, np.zeros_like(a))) for a in (self.starts, self.sizes))
        self.flat[self.used : self.used + len(flat)] = flat
        self.starts[n : n + m] = self.used + np.cumsum(sizes) - sizes
        self.sizes[n : n + m] = sizes
        self.used += len(flat)
        self.place.update(zip(keys, range(n, n + m), strict=True))

    def missing(self, keys: list) -> list:
        return list(set(keys) - self.place.keys())

    def gather(self, keys: list, codes: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all keys in order, how many each has); with ``codes``, of ``keys[code]`` for each code."""
        at = np.fromiter(map(self.place.__getitem__, keys), np.int64, len(keys))
        at = at if codes is None else at[codes]
        sizes = self.sizes[at]
        before = np.cumsum(sizes) - sizes
        return self.flat[np.repeat(self.starts[at] - before, sizes) + np.arange(sizes.sum())], sizes


class ChunkEncoder:
    """Bounded caches from chunk and word to ids: each starts afresh when it holds ``most``."""

    def __init__(self, path: str, most: int = 300_000):
        self.tokenizer, self.most = _tokenizer(path), most
        self.chunks, self.words = _Store(), _Store()

    def _learn_words(self, fresh: list[str]) -> None:
        spelled = [w if w.isascii() else w.encode("utf-8").decode("latin-1").translate(_LETTERS) for w in fresh]  # visible ASCII stands for itself
        model = self.tokenizer.model
        ids = [[t.id for t in model.tokenize(w)] for w in spelled]
        self.words.add(fresh, np.array([x for e in ids for x in e], np.uint16), np.fromiter(map(len, ids), np.int64, len(ids)))

    def _learn(self, fresh: list[bytes]) -> None:
        match = _PLAIN.fullmatch
        plain = [c for c in fresh if match(c) and b"<|" not in c]
        if plain:
            if len(self.words.place) > self.most:
                self.words = _Store()
            if "\n" not in self.words.place:
                self.words.add(["\n"], np.zeros(0, np.uint16), np.zeros(1, np.int64))
            words = _WORDS.findall(b"\n".join(plain).decode("utf-8").lower())
            if unknown := self.words.missing(words):
                self._learn_words(unknown)
            flat, sizes = self.words.gather(words)
            ends = np.fromiter((w == "\n" for w in words), bool, len(words))
            total = np.cumsum(sizes)
            self.chunks.add(plain, flat, np.diff(np.concatenate(([0], total[ends], total[-1:]))))
        if len(plain) < len(fresh):
            known = set(plain)
            rest = [c for c in fresh if c not in known]
            ids = [self.tokenizer.encode(c.decode("utf-8"), add_special_tokens=False).ids for c in rest]
            self.chunks.add(rest, np.array([x for e in ids for x in e], np.uint16), np.fromiter(map(len, ids), np.int64, len(ids)))

    def encode(self, texts: list[bytes], end: int) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts, each closed by ``end``; offsets of the texts in it)."""
        if len(self.chunks.place) > self.most:
            self.chunks = _Store()
        codes, edge, distinct = word_codes(texts)
        if fresh := [c for c in distinct if c not in self.chunks.place]:
            self._learn(fresh)
        flat, sizes = self.chunks.gather(distinct, codes)
        total = np.concatenate(([0], np.cumsum(sizes)))[edge]
        offsets = total + np.arange(len(edge))
        out = np.full(offsets[-1], end, np.uint16)
        inside = np.ones(offsets[-1], bool)
        inside[offsets[1:] - 1] = False
        out[inside] = flat
        return out, offsets


_ENCODERS: dict = {}


def encoder(path: str) -> ChunkEncoder:
    """One per worker process: what a task has learnt serves the next."""
    if path not in _ENCODERS:
        _ENCODERS[path] = ChunkEncoder(path)
    return _ENCODERS[path]
