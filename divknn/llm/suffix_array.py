"""Removal of repeated byte strings by a suffix array of each shard, sorted in two stages.

Suffixes smaller than their successors are sorted directly; all others follow from them: scanning the
buckets of equal first bytes in order, the suffix one place to the left of each scanned one, where it is
larger than its successor, goes to the next free place at the front of its own bucket. Suffixes matter up
to the window length only. Adjacent common prefixes then cut the array into groups of equal windows.

Null and empty texts keep their zero bytes. See ``repeats`` for other awkward cases.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import runs_of, table, text_slices
from .repeats import NULL_DOC, Bytes, covered, powers, repeated_spans


def _eight(text: np.ndarray) -> np.ndarray:
    """The eight bytes from each place on, as one number in their order; zeros after the end."""
    held = np.concatenate((text, np.zeros(8, np.uint8))).astype(np.uint64)
    out = held[: len(text)].copy()
    for i in range(1, 8):
        out = (out << np.uint64(8)) | held[i : i + len(text)]
    return out


def smaller_than_next(text: np.ndarray) -> np.ndarray:
    """Mask of suffixes smaller than their successor; within equal bytes the next different one decides, the end is least."""
    n = len(text)
    change = np.flatnonzero(text[1:] != text[:-1])
    up = text[change + 1] > text[change]
    where = np.searchsorted(change, np.arange(n))
    return np.append(up, False)[where]


def sort_directly(text: np.ndarray, which: np.ndarray, depth: int) -> np.ndarray:
    """Starts ``which`` ordered by their first ``depth`` bytes, eight at a time; only ties go on."""
    words = _eight(text)
    held = np.concatenate((words, np.zeros(depth + 8, np.uint64)))
    up, down = powers(len(text) + 1)
    sums = np.concatenate((np.zeros(1, np.uint64), np.cumsum(Bytes._table[text] * up[: len(text)], dtype=np.uint64)))
    end = np.minimum(which + depth, len(text))
    print_ = (sums[end] - sums[which]) * down[which] + (end - which).astype(np.uint64)  # of what is compared
    order = np.argsort(held[which])
    key = held[which[order]]
    group = np.concatenate(([0], np.cumsum(key[1:] != key[:-1])))
    for at in range(8, depth, 8):
        mark = print_[order]
        mixed = np.zeros(int(group[-1]) + 1 if len(group) else 0, bool)
        mixed[group[1:][(group[1:] == group[:-1]) & (mark[1:] != mark[:-1])]] = True
        open_ = np.flatnonzero(mixed[group]) if len(group) else group
        if not len(open_):
            break
        own, key = group[open_], held[which[order[open_]] + at]
        inner = np.lexsort((key, own))
        order[open_] = order[open_][inner]
        key, new = key[inner], np.zeros(len(order), np.int64)
        cut = np.zeros(len(open_), bool)
        cut[1:] = (own[1:] == own[:-1]) & (key[1:] != key[:-1])
        new[open_] = cut
        group = group + np.cumsum(new)
    return which[order]


def suffix_order(text: np.ndarray, depth: int) -> np.ndarray:
    """All starts of ``text`` ordered by their first ``depth`` bytes."""
    n = len(text)
    small = smaller_than_next(text)
    direct = sort_directly(text, np.flatnonzero(small), depth)
    sizes = np.bincount(text, minlength=256)
    head = np.cumsum(sizes) - sizes
    out = np.full(n, -1, np.int64)
    many = np.bincount(text[direct], minlength=256)
    tail = head + sizes - many
    at = tail[text[direct]] + np.arange(len(direct)) - (np.cumsum(many) - many)[text[direct]]
    out[at] = direct
    free = head.copy()

    def induce(starts: np.ndarray) -> np.ndarray:
        """Place the left neighbours that are larger than these; returns those in the same bucket."""
        left = starts[starts > 0] - 1
        left = left[~small[left]]
        byte = text[left]
        order = np.argsort(byte, kind="stable")
        left, byte = left[order], byte[order]
        own = np.bincount(byte, minlength=256)
        out[free[byte] + np.arange(len(left)) - (np.cumsum(own) - own)[byte]] = left
        free[:] += own
        return left

    if n and not small[n - 1]:  # the last suffix is followed by the empty one
        out[free[text[n - 1]]] = n - 1
        free[text[n - 1]] += 1
    for c in np.flatnonzero(sizes):
        done = head[c]
        while done < free[c]:  # larger suffixes of this bucket may bring more of it
            fresh = out[done : free[c]].copy()
            done = free[c]
            induce(fresh)
        induce(out[tail[c] : head[c] + sizes[c]])
    return out


def common_prefixes(text: np.ndarray, order: np.ndarray, depth: int) -> np.ndarray:
    """Whether each row shares ``depth`` bytes with the row before it."""
    words = np.concatenate((_eight(text), np.zeros(depth + 8, np.uint64)))
    same = np.zeros(len(order), bool)
    left = np.arange(1, len(order))
    for at in [*range(0, depth - 8, 8), depth - 8]:
        left = left[words[order[left] + at] == words[order[left - 1] + at]]
    same[left] = True
    return same


def first_occurrences(bodies: list[bytes], docs: np.ndarray, starts: np.ndarray, window: int):
    """For every window of every body, in order: (number in its body, first document, its position, windows a body)."""
    raw = np.frombuffer(b"\0".join(bodies) + b"\0", np.uint8)
    sizes = np.array([len(b) for b in bodies], np.int64)
    owner = np.repeat(np.arange(len(bodies)), sizes + 1)
    inner = np.arange(len(raw)) - np.repeat(np.cumsum(sizes + 1) - sizes - 1, sizes + 1)
    whole = inner + window <= sizes[owner]
    order = suffix_order(raw, window)
    order = order[whole[order]]  # equal windows stay neighbours without the others
    group = np.cumsum(~common_prefixes(raw, order, window)) - 1
    ranked, ids = np.unique(docs, return_inverse=True)[1].astype(np.int64), np.unique(docs)
    value = (ranked[owner[order]] << 32) | (starts[owner[order]] + inner[order])
    got = np.zeros(len(raw), np.int64)
    if len(order):
        got[order] = np.minimum.reduceat(value, np.flatnonzero(np.append(True, group[1:] != group[:-1])))[group]
    got, number = got[whole], inner[whole]
    return number, ids[got >> 32], got & 0xFFFFFFFF, np.maximum(sizes - window + 1, 0)


_RESULT = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"


def remove_repeated_strings(docs: DataFrame, most: int | None = None) -> DataFrame:
    """Per document: its bytes, how many a window that starts earlier covers, in how many runs, and the rest's digest."""

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            spans, ids = batch.column("spans"), batch.column("doc").to_pylist()
            for a, _, texts in text_slices(batch):
                rows = []
                for i, t in enumerate(texts):
                    own, digest, at, gone = spans[a + i].as_py(), hashlib.sha256(), 0, 0
                    begin, end = runs_of(covered(own, len(t))) if own else ((), ())
                    for s, e in zip(begin, end, strict=True):
                        digest.update(t[at:s])
                        at, gone = e, gone + int(e - s)
                    digest.update(t[at:])
                    rows.append((None if ids[a + i] == NULL_DOC else ids[a + i], len(t), gone, len(begin), digest.hexdigest()))
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(),) * 4 + (pa.string(),), strict=True)], names=[x.split()[0] for x in _RESULT.split(", ")])

    found = repeated_spans(docs, Bytes, first_occurrences, most)
    return found.select("doc", "text", F.col("spans")).mapInArrow(finish, _RESULT)


def op4_suffix_array_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeated_strings(table(spark, sf_dir, "documents"))
