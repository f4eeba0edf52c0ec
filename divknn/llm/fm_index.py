"""Removal of repeated passages by a compressed full-text index of each shard.

A shard's texts are kept as the Burrows-Wheeler transform of their words in a wavelet matrix: a few bit
rows with rank counts, beside one byte of common prefix a row with a tree of minima, and the first place
behind each interval of full matches in place of the suffix order. Documents are streamed against it from
the right: a backward search step extends the match by a word, and where it would be empty the match is
shortened on its right end (the parent interval) until it can go on. That gives the matching statistics -
for each place the longest match that starts there - up to the threshold, and its interval; where the
threshold is reached, the interval's first place tells whether the window occurs before. The streamed texts
of a shard are its own, as windows are judged against all others: streaming them against an index of only
a part of the shard gives the same rows but took ten times as long.

Null and empty texts keep their zero words. See ``repeats`` for other awkward cases.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table, text_slices, word_codes
from .repeats import NULL_DOC, Words, covered, repeated_spans


class Bits:
    """A row of bits with counts of the ones before each place."""

    def __init__(self, bit: np.ndarray):
        packed = np.packbits(bit.astype(np.uint8), bitorder="little")
        self.words = np.concatenate((packed, np.zeros(16 - len(packed) % 8, np.uint8))).view(np.uint64)
        self.counts = np.concatenate(([0], np.cumsum(np.bitwise_count(self.words), dtype=np.int64))).astype(np.int32)

    def rank(self, at: np.ndarray) -> np.ndarray:
        word = at >> 6
        return self.counts[word] + np.bitwise_count(self.words[word] & ((np.uint64(1) << (at & 63).astype(np.uint64)) - np.uint64(1)))


class WaveletMatrix:
    """Rank of a symbol before a place, for many places at once."""

    def __init__(self, values: np.ndarray, sigma: int):
        self.levels = max(1, int(sigma - 1).bit_length())
        self.rows, self.zeros = [], []
        for level in reversed(range(self.levels)):
            bit = (values >> level) & 1
            self.rows.append(Bits(bit))
            self.zeros.append(int(len(bit) - bit.sum()))
            values = np.concatenate((values[bit == 0], values[bit == 1]))
        every = np.arange(1 << self.levels)
        self.origin = self._descend(every, np.zeros(len(every), np.int64))

    def _descend(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        for k, level in enumerate(reversed(range(self.levels))):
            ones = self.rows[k].rank(at)
            at = np.where((symbol >> level) & 1, self.zeros[k] + ones, at - ones)
        return at

    def rank(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        return self._descend(symbol, at) - self.origin[symbol]


class Minima:
    """Nearest place with a small value, by minima over aligned blocks of 2, 4, 8, ... values: two bytes a value in all."""

    def __init__(self, values: np.ndarray):
        self.levels = max(1, int(len(values)).bit_length())
        row = np.concatenate((values, np.zeros((1 << self.levels) - len(values), values.dtype)))
        self.rows = [row]
        for _ in range(self.levels):
            row = np.minimum(row[::2], row[1::2])
            self.rows.append(row)

    def _search(self, pos: np.ndarray, least: np.ndarray, back: bool) -> np.ndarray:
        found = np.full(len(pos), self.levels)
        open_ = np.ones(len(pos), bool)
        for k in range(self.levels):  # up, past whole blocks that hold no small value
            there = np.flatnonzero(open_ & ((pos >> k) & 1 == 1))
            block = (pos[there] >> k) - (1 if back else 0)
            whole = self.rows[k][block] >= least[there]
            pos[there[whole]] += -(1 << k) if back else 1 << k
            found[there[~whole]], open_[there[~whole]] = k, False
        for k in reversed(range(self.levels)):  # down, into the half that holds it
            there = np.flatnonzero(found > k)
            block = (pos[there] >> k) - (1 if back else 0)
            there = there[self.rows[k][np.minimum(block, len(self.rows[k]) - 1)] >= least[there]]
            pos[there] += -(1 << k) if back else 1 << k
        return pos

    def before(self, at: np.ndarray, least: np.ndarray) -> np.ndarray:
        """The last place up to ``at`` with a value under ``least``; there is one."""
        return self._search(at + 1, least, True) - 1

    def after(self, at: np.ndarray, least: np.ndarray) -> np.ndarray:
        """The first place from ``at`` on with a value under ``least``; the end has one."""
        return self._search(at.copy(), least, False)


class FMIndex:
    """Index of a text over symbols 1..sigma-1; 0 separates. Matches are followed up to ``cap`` symbols.

    ``value`` has a number for each place; the least of each interval of rows that share ``cap`` symbols is kept.
    """

    def __init__(self, text: np.ndarray, sigma: int, cap: int, value: np.ndarray | None = None):
        value = np.arange(len(text)) if value is None else value
        if not len(text) or text[-1]:
            text, value = np.append(text, 0), np.append(value, np.iinfo(np.int64).max)  # the row of the whole text then has a separator on its left
        self.cap, self.rows, n = cap, len(text), len(text)
        ranks, width, rank = [], 1, text.astype(np.int64)
        while True:  # sort by prefixes of twice the length until they exceed the cap
            ranks.append((width, rank))
            if width > cap:
                break
            nxt = np.zeros(n, np.int64)
            nxt[: max(0, n - width)] = rank[width:] + 1
            rank = np.unique((rank << 32) | nxt, return_inverse=True)[1]
            width *= 2
        order = np.argsort(rank, kind="stable")
        common = np.zeros(n, np.int64)
        a, b = order[:-1], order[1:]
        for width, rank in reversed(ranks[:-1]):
            held = np.concatenate((rank, np.full(2 * cap + 2, -1)))
            at = common[1:]
            at += width * ((held[a + at] == held[b + at]) & (held[a + at] >= 0))
        self.common = np.append(np.minimum(common, cap), 0).astype(np.uint8)  # with the row above; row 0 and the end: 0
        self.minima = Minima(self.common)
        # Where intervals of full matches begin, and those of one symbol less, their parents.
        full, almost = self.common[:n] < cap, self.common[:n] < cap - 1
        full[0] = almost[0] = True
        self.full, self.almost = Bits(full), Bits(almost)
        self.parents = np.append(np.flatnonzero(almost), n).astype(np.int32)
        self.least = np.minimum.reduceat(value[order], np.flatnonzero(full))
        self.wavelet = WaveletMatrix(text[order - 1], sigma)
        self.before = np.concatenate(([0], np.cumsum(np.bincount(text, minlength=1 << self.wavelet.levels))))

    def extend(self, symbol: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Backward search step: rows of ``symbol`` followed by what the rows lo..hi start with."""
        at = self.before[symbol]
        return at + self.wavelet.rank(symbol, lo), at + self.wavelet.rank(symbol, hi)

    def widen(self, lo: np.ndarray, hi: np.ndarray, depth: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """All rows that share ``depth`` symbols with the rows lo..hi."""
        root, depth = depth == 0, np.maximum(depth, 1)
        return np.where(root, 0, self.minima.before(lo, depth)), np.where(root, self.rows, self.minima.after(hi, depth))

    def parent(self, lo: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """All rows that share ``cap - 1`` symbols with the rows ``lo``."""
        at = self.almost.rank(lo + 1)
        return self.parents[at - 1].astype(np.int64), self.parents[at].astype(np.int64)

    def first(self, row: np.ndarray) -> np.ndarray:
        """The least value behind the interval of full matches that holds each row."""
        return self.least[self.full.rank(row + 1) - 1]

    def stream(self, symbols: np.ndarray, ends: np.ndarray, sizes: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        """Matching statistics of many sequences together, from the right.

        ``symbols`` holds them one after another, ``ends`` the place after each, ``sizes`` their lengths.
        Yields (sequence, place in it, match length, first row of the match) for each step.
        """
        who = np.arange(len(ends))
        lo, hi, depth = np.zeros(len(ends), np.int64), np.full(len(ends), self.rows), np.zeros(len(ends), np.int64)
        step = 0
        while True:
            alive = sizes[who] > step
            who, lo, hi, depth = who[alive], lo[alive], hi[alive], depth[alive]
            if not len(who):
                return
            symbol = symbols[ends[who] - 1 - step]
            full = depth == self.cap
            if full.any():
                lo[full], hi[full] = self.parent(lo[full])
                depth[full] -= 1
            new_lo, new_hi = self.extend(symbol, lo, hi)
            stuck = np.flatnonzero((new_lo >= new_hi) & (depth > 0))
            while len(stuck):
                down = np.minimum(depth[stuck] - 1, np.maximum(self.common[lo[stuck]], self.common[hi[stuck]]).astype(np.int64))
                depth[stuck] = down
                lo[stuck], hi[stuck] = self.widen(lo[stuck], hi[stuck], down)
                new_lo[stuck], new_hi[stuck] = self.extend(symbol[stuck], lo[stuck], hi[stuck])
                stuck = stuck[(new_lo[stuck] >= new_hi[stuck]) & (depth[stuck] > 0)]
            found = new_lo < new_hi
            lo, hi = np.where(found, new_lo, 0), np.where(found, new_hi, self.rows)
            depth = np.where(found, depth + 1, 0)
            yield who, sizes[who] - 1 - step, depth, lo
            step += 1


def first_occurrences(bodies: list[bytes], docs: np.ndarray, starts: np.ndarray, window: int):
    """For every window of every body, in order: (number in its body, first document, its position, windows a body)."""
    codes, offsets, distinct = word_codes(bodies)
    sizes = np.diff(offsets)
    count = np.maximum(sizes - window + 1, 0)
    into = np.cumsum(count) - count
    got = np.full(int(count.sum()), np.iinfo(np.int64).max)
    ranked = np.unique(docs, return_inverse=True)[1].astype(np.int64)
    body = np.repeat(np.arange(len(bodies)), sizes + 1)
    inner = np.arange(len(body)) - np.repeat(offsets[:-1] + np.arange(len(bodies)), sizes + 1)
    text = np.zeros(len(body), np.int64)
    text[inner < sizes[body]] = codes + 1
    value = (ranked[body] << 32) | (starts[body] + inner)
    index = FMIndex(text, len(distinct) + 1, window, value)
    for who, at, depth, row in index.stream(codes + 1, offsets[1:], sizes):
        hit = depth >= window
        got[into[who[hit]] + at[hit]] = index.first(row[hit])
    number = np.arange(len(got)) - np.repeat(into, count)
    return number, np.unique(docs)[got >> 32], got & 0xFFFFFFFF, count


_RESULT = "doc_id long, n_words long, n_removed long, kept_sha256 string"


def remove_repeated_passages(docs: DataFrame, most: int | None = None) -> DataFrame:
    """Per document: its words, how many a window that occurs in an earlier document covers, and the rest's digest."""

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            spans, ids = batch.column("spans"), batch.column("doc").to_pylist()
            for a, _, texts in text_slices(batch):
                rows = []
                for i, t in enumerate(texts):
                    words, own = t.split(), spans[a + i].as_py()
                    gone = covered(own, len(words)) if own else np.zeros(len(words), bool)
                    kept = [w for w, g in zip(words, gone.tolist(), strict=True) if not g] if own else words
                    rows.append((None if ids[a + i] == NULL_DOC else ids[a + i], len(words), len(words) - len(kept), hashlib.sha256(b" ".join(kept)).hexdigest()))
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.int64(), pa.string()), strict=True)], names=["doc_id", "n_words", "n_removed", "kept_sha256"])

    found = repeated_spans(docs, Words, first_occurrences, most)
    return found.select("doc", "text", F.col("spans")).mapInArrow(finish, _RESULT)


def op1_fm_index_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeated_passages(table(spark, sf_dir, "documents"))
