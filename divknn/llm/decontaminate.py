"""Benchmark decontamination under edit distance.

A benchmark item of n words is found where some stretch of a document is within k = n // 5 word edits of
it. Windows as long as the item are embedded by a random walk: a walk reads the window with a pointer
that advances or waits by a random bit of (step, word read), so that an edit lets the walks of item and
window part only for a short time, and edit distance becomes Hamming distance. Each repetition samples a
few places of the embedding as a key; windows with an item's key in any repetition are candidates, and
an alignment decides exactly.

Of k + 1 pieces of an item one survives k edits, so windows are taken only where the first words of a
piece stand, each place giving the windows around it in which the piece has its own offset. That
loses nothing. The recall of the keys is measured in the tests.

Items are held in blocks of ``BLOCK_WORDS`` words at most; more items take more passes. Null and empty
texts and items match nothing; repeated rows are searched each; other columns are not read.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import FOLD, HashSet, _mix, gram_hashes, table, text_slices, word_hashes

BLOCK_WORDS, REPETITIONS, SAMPLES = 1_000_000, 16, 3
_MATCHES = "doc_id long, item_id long, start_word int, end_word int, edits int"


def allowed(n: int) -> int:
    return n // 5


def _walk(words: np.ndarray) -> np.ndarray:
    """(repetitions, rows) keys of sequences: the embedding's symbols at the sampled steps, hashed. words: (rows, n) hashes.

    The walks of all repetitions go side by side.
    """
    rows, n = words.shape
    picks = np.random.default_rng(n).integers(0, 3 * n, (REPETITIONS, SAMPLES))
    held = np.concatenate((words, np.zeros((rows, 1), np.uint64)), axis=1).ravel()
    start = np.arange(rows) * (n + 1)
    at = np.tile(start, (REPETITIONS, 1))
    last, key = start + n, np.zeros((REPETITIONS, rows), np.uint64)
    salt = np.arange(REPETITIONS, dtype=np.uint64)[:, None] * np.uint64(1_000_003)
    for step in range(int(picks.max()) + 1):
        mixed = _mix(held[at] + (salt + np.uint64(step)) * np.uint64(0x9E3779B97F4A7C15))
        for rep, _ in np.argwhere(picks == step):
            key[rep] = _mix(key[rep] + mixed[rep])
        at = np.minimum(at + (mixed & np.uint64(1)).astype(np.int64), last)
    return key


def _distances(item: list[int], text: list[int], anchored: bool) -> Iterator[int]:
    """Edits between ``item`` and the best stretch that ends at each word of ``text`` (or all of text so far, if anchored).

    The columns of the alignment table are bit vectors of their steps up and down.
    """
    n = len(item)
    full, top, where = (1 << n) - 1, 1 << (n - 1), defaultdict(int)
    for i, w in enumerate(item):
        where[w] |= 1 << i
    up, down, score = full, 0, n
    for w in text:
        same = where.get(w, 0)
        x = same | down
        h = (((same & up) + up) ^ up) | same
        right, left = down | (full & ~(h | up)), up & h
        score += bool(right & top) - bool(left & top)
        right, left = (right << 1 | anchored) & full, left << 1 & full
        up, down = left | (full & ~(x | right)), right & x
        yield score


def edit_place(item: np.ndarray, text: np.ndarray) -> tuple[int, int, int]:
    """(fewest edits between ``item`` and a stretch of ``text``, where it begins, where it ends)."""
    own, words = item.tolist(), text.tolist()
    best, end = len(own), 0
    for j, d in enumerate(_distances(own, words, False), 1):
        if d < best:
            best, end = d, j
    back = _distances(own[::-1], words[:end][::-1], True)
    return best, end - next((t for t, d in enumerate(back, 1) if d == best), 0), end


class ItemIndex:
    def __init__(self, items: list[tuple[int, bytes]]):
        h, offsets, _, _ = word_hashes([t.translate(FOLD) for _, t in items])
        self.ids = [k for k, _ in items]
        self.words = [h[a:b] for a, b in zip(offsets[:-1], offsets[1:], strict=True)]
        seeds: dict[int, dict[int, list[tuple[int, int]]]] = defaultdict(lambda: defaultdict(list))
        self.keys: dict[int, list[dict[int, list[int]]]] = {}
        alike: dict[int, list[int]] = {}
        for i, w in enumerate(self.words):
            n = len(w)
            if not n:
                continue
            parts = allowed(n) + 1
            gram = min(3, n // parts)
            for p in range(parts):
                o = p * n // parts
                seeds[gram][int(gram_hashes(w[o : o + gram], gram)[0])].append((i, o))
            self.keys.setdefault(n, [defaultdict(list) for _ in range(REPETITIONS)])
            alike.setdefault(n, []).append(i)
        for n, own in alike.items():
            for rep, keys in enumerate(_walk(np.stack([self.words[i] for i in own])).tolist()):
                for i, key in zip(own, keys, strict=True):
                    self.keys[n][rep][key].append(i)
        self.seeds = {g: (HashSet(np.array(list(s), np.uint64)), dict(s)) for g, s in seeds.items()}
        self.keys = {n: [dict(x) for x in v] for n, v in self.keys.items()}

    def candidates(self, h: np.ndarray, offsets: np.ndarray) -> dict[int, np.ndarray]:
        """{item length: first words of windows to embed}: (place, text) pairs."""
        found: dict[int, list[np.ndarray]] = defaultdict(list)
        for gram, (held, where) in self.seeds.items():
            grams = gram_hashes(h, gram)
            hits = held.where(grams)
            owner = np.searchsorted(offsets, hits, "right") - 1
            inside = hits + gram <= offsets[owner + 1]
            hits, owner = hits[inside], owner[inside]
            values, which = np.unique(grams[hits], return_inverse=True)
            order = np.argsort(which, kind="stable")
            edge = np.searchsorted(which[order], np.arange(len(values) + 1))
            for v, value in enumerate(values.tolist()):
                own = order[edge[v] : edge[v + 1]]
                for n, o in {(len(self.words[i]), o) for i, o in where[value]}:
                    found[n].append(np.stack((hits[own] - o, owner[own])))
        return {n: np.unique(np.concatenate(x, axis=1), axis=1) for n, x in found.items()}

    def search(self, h: np.ndarray, offsets: np.ndarray) -> list[tuple[int, int, int, int, int]]:
        """(text, item, first word, word after, edits) for the words of several texts."""
        near: dict[tuple[int, int], list[int]] = defaultdict(list)
        for n, (place, owner) in self.candidates(h, offsets).items():
            begin, end = offsets[owner], offsets[owner + 1]
            for lo in range(0, len(place), 20_000):
                s, b, e, o = (x[lo : lo + 20_000] for x in (place, begin, end, owner))
                at = s[:, None] + np.arange(n)
                words = np.where((at >= b[:, None]) & (at < e[:, None]), h[np.clip(at, 0, len(h) - 1)], np.uint64(0))
                for index, keys in zip(self.keys[n], _walk(words), strict=True):
                    for j in np.flatnonzero(np.isin(keys, np.fromiter(index, np.uint64, len(index)))):
                        for i in index[int(keys[j])]:
                            near[int(o[j]), i].append(int(s[j]))
        out = []
        for (text, i), places in near.items():
            n = len(self.words[i])
            k, at = allowed(n), -1
            for s in sorted(set(places)):
                if s + k < at:  # inside what is found
                    continue
                lo, hi = max(int(offsets[text]), s - k), min(int(offsets[text + 1]), s + n + k)
                edits, a, b = edit_place(self.words[i], h[lo:hi])
                if edits <= k and lo + a >= at:
                    out.append((text, i, lo + a - int(offsets[text]), lo + b - int(offsets[text]), edits))
                    at = lo + b
        return out


def _blocks(benchmark: DataFrame) -> list[ItemIndex]:
    """Items in blocks of bounded size, each an index for one pass."""
    blocks, held, size = [], [], 0
    for item, text in benchmark.where("text is not null").select(F.col("item_id").cast("long"), "text").toLocalIterator():
        raw = text.encode()
        if held and size + len(raw) // 2 > BLOCK_WORDS:
            blocks.append(ItemIndex(held))
            held, size = [], 0
        held.append((item, raw))
        size += len(raw) // 2
    return [*blocks, ItemIndex(held)] if held else blocks


def _passes(docs: DataFrame, benchmark: DataFrame, work, schema) -> DataFrame | None:
    out = None
    for index in _blocks(benchmark):
        found = docs.mapInArrow(work(index), schema)
        out = found if out is None else out.unionByName(found)
    return out


def benchmark_matches(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """One row per place of an item in a document."""

    def work(index: ItemIndex):
        def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                ids = batch.column("doc_id").to_pylist()
                for a, _, texts in text_slices(batch):
                    h, offsets, _, _ = word_hashes([t.translate(FOLD) for t in texts])
                    if rows := [(ids[a + t], index.ids[i], s, e, d) for t, i, s, e, d in index.search(h, offsets)]:
                        kinds = (pa.int64(), pa.int64(), *[pa.int32()] * 3)
                        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=[x.split()[0] for x in _MATCHES.split(", ")])

        return search

    found = _passes(docs.select(F.col("doc_id").cast("long"), "text"), benchmark, work, _MATCHES)
    return found if found is not None else docs.sparkSession.createDataFrame([], _MATCHES)


def drop_contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The rows of ``docs`` in which no item is found; nothing is shuffled."""
    for index in _blocks(benchmark):

        def clean(batches: Iterator[pa.RecordBatch], index=index) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for a, b, texts in text_slices(batch):
                    keep = np.ones(b - a, bool)
                    h, offsets, _, _ = word_hashes([t.translate(FOLD) for t in texts])
                    keep[[x[0] for x in index.search(h, offsets)]] = False
                    yield batch.slice(a, b - a).filter(pa.array(keep))

        docs = docs.mapInArrow(clean, docs.schema)
    return docs


def op9_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return benchmark_matches(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
