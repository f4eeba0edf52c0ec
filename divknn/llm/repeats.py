"""Finding passages that occur before, whatever index then decides: the distributed frame.

A document is a sequence of symbols (words or bytes). Windows of W symbols are grouped by their smallest
k-gram hash, the anchor: equal windows have equal anchors, and neighbouring windows mostly share one gram,
so a run of windows with one anchor - a segment - is handled as a whole. Anchors that occur once in the
corpus are counted away first. What is left is reduced to distinct segment contents with their first
occurrence, dealt to shards by anchor, and each shard's index tells for every window of every content
where it occurs first. All occurrences then learn what of them is a repeat.

An anchor with more contents than a shard holds (a passage in ever new surroundings) is split: its windows
are told apart by where in them the anchor lies, in blocks of places, and by all that the windows of a block
must have in common, the core. Equal windows have equal blocks and cores, so each such group can go to a
shard of its own; a core that one content alone has is counted away. Blocks become smaller until every
group fits; blocks of one place have the window itself as core.

Rows that repeat are judged each against smaller ``doc_id`` values; a null ``doc_id`` ranks last.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SPACE, _mix, runs_of, saved, text_slices, word_hashes

NULL_DOC = (1 << 63) - 1
#: Places in a block are fewer by this factor in each round of splitting.
FINER = 4
_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)


class Words:
    """Words as symbols."""

    window, gram, within, shard_symbols, slice_bytes = 50, 6, False, 100_000, 1 << 20

    @staticmethod
    def symbols(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        h, offsets, _, _ = word_hashes(texts)
        return h, offsets

    @staticmethod
    def cutter(text: bytes) -> Callable[[int, int], bytes]:
        words = text.split()
        return lambda a, b: b" ".join(words[a:b])


class Bytes:
    """UTF-8 bytes as symbols; a place counts as earlier within a document too."""

    window, gram, within, shard_symbols, slice_bytes = 100, 24, True, 500_000, 256 << 10
    _table = _mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(_BASE))

    @classmethod
    def symbols(cls, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        raw = np.frombuffer(b"".join(texts), np.uint8)
        return cls._table[raw], np.concatenate(([0], np.cumsum([len(t) for t in texts]))).astype(np.int64)

    @staticmethod
    def cutter(text: bytes) -> Callable[[int, int], bytes]:
        return lambda a, b: text[a:b]


_POWERS: list[np.ndarray] = []


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the hash base and of its inverse, modulo 2**64."""
    if not _POWERS or len(_POWERS[0]) < n:
        m = max(n, 1 << 16)
        _POWERS[:] = [np.concatenate((np.ones(1, np.uint64), np.cumprod(np.full(m - 1, b, np.uint64)))) for b in (_BASE, _INVERSE)]
    return _POWERS[0][:n], _POWERS[1][:n]


def sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    done = 1
    while done * 2 <= width:
        x = np.minimum(x[:-done], x[done:])
        done *= 2
    return np.minimum(x[: len(x) - (width - done)], x[width - done :]) if width > done else x


def segments(h: np.ndarray, offsets: np.ndarray, window: int, gram: int, contents: bool = True):
    """(owner, start in its text, symbols, anchor, content hash) of every segment; windows never cross texts."""
    n = len(h)
    nothing = np.zeros(0, np.int64)
    if n < window:
        return nothing, nothing, nothing, nothing, nothing
    up, down = powers(n + 1)
    prefix = np.concatenate((np.zeros(1, np.uint64), np.cumsum(h * up[:n], dtype=np.uint64)))
    grams = _mix((prefix[gram:] - prefix[:-gram]) * down[: n - gram + 1])
    least = sliding_min(grams, window - gram + 1)
    owner = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))
    valid = owner[: len(least)] == owner[window - 1 :]
    change = np.ones(len(least), bool)
    # A window keeps the place of its first smallest gram until that gram leaves it or a smaller one comes.
    change[1:] = (least[1:] != least[:-1]) | (grams[: len(least) - 1] == least[:-1]) | (valid[1:] != valid[:-1]) | (owner[1 : len(least)] != owner[: len(least) - 1])
    begin = np.flatnonzero(change)
    last = np.append(begin[1:], len(least))
    keep = valid[begin]
    begin, last = begin[keep], last[keep]
    end = last + window - 1
    content = _mix((prefix[end] - prefix[begin]) * down[begin] + (end - begin).astype(np.uint64)).view(np.int64) if contents else nothing
    return owner[begin], begin - offsets[owner[begin]], end - begin, least[begin].view(np.int64), content


def _ranked(docs: DataFrame) -> DataFrame:
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NULL_DOC)).alias("doc"), F.xxhash64(text).alias("key"), F.hash(text).alias("key2"), text.alias("text"))


def _live_segments(ranked: DataFrame, kind) -> DataFrame:
    """Occurrences of the anchors that occur twice or more: (anchor, content, doc, key, key2, start, size)."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, _, texts in text_slices(batch, limit=kind.slice_bytes):
                anchors, n = np.unique(segments(*kind.symbols(texts), kind.window, kind.gram, False)[3], return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(anchors), pa.array(np.minimum(n, 2).astype(np.int16))], names=["anchor", "n"])

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            docs, keys, keys2 = (batch.column(c).to_numpy() for c in ("doc", "key", "key2"))
            for a, _, texts in text_slices(batch, limit=kind.slice_bytes):
                owner, start, size, anchor, content = segments(*kind.symbols(texts), kind.window, kind.gram)
                cols = [anchor, content, docs[a + owner], keys[a + owner], keys2[a + owner], start.astype(np.int32), size.astype(np.int32)]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=["anchor", "content", "doc", "key", "key2", "start", "size"])

    again = saved(ranked.select("text").mapInArrow(count, "anchor long, n short").groupBy("anchor").agg(F.sum("n").alias("n")).where("n > 1").select("anchor"))  # apart, so that a hot anchor can be split in the join
    every = ranked.mapInArrow(place, "anchor long, content long, doc long, key long, key2 int, start int, size int")
    return saved(every.join(again, "anchor"))


_FETCHED = "anchor long, content long, doc long, start long, size long, large boolean, body binary"
_RUNS = "anchor long, content long, runs array<struct<from:int,to:int,doc:long,base:long>>"


def _fetch(kind):
    def fetch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            asked = batch.column("asked").to_pylist()
            docs = batch.column("doc").to_pylist()
            for a, _, texts in text_slices(batch, limit=kind.slice_bytes):
                rows = []
                for i, t in enumerate(texts):
                    cut = kind.cutter(t)
                    rows += [(q["anchor"], q["content"], docs[a + i], q["start"], q["size"], q["large"], cut(q["start"], q["start"] + q["size"])) for q in asked[a + i]]
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(),) * 5 + (pa.bool_(), pa.binary()), strict=True)], names=[x.split()[0] for x in _FETCHED.split(", ")])

    return fetch


def window_runs(at: np.ndarray, doc: np.ndarray, pos: np.ndarray, count: np.ndarray) -> pa.Array:
    """For each body, the runs of its windows whose first occurrence moves along with them.

    ``at`` numbers the windows of each body from 0; ``count`` has how many each has.
    """
    base = pos - at
    cut = at == 0
    cut[1:] |= (doc[1:] != doc[:-1]) | (base[1:] != base[:-1])
    first = np.flatnonzero(cut)
    last = np.append(first[1:], len(at)) - 1
    runs = pa.StructArray.from_arrays([pa.array(at[first].astype(np.int32)), pa.array((at[last] + 1).astype(np.int32)), pa.array(doc[first]), pa.array(base[first])], names=["from", "to", "doc", "base"])
    edge = np.searchsorted(first, np.concatenate(([0], np.cumsum(count))))
    return pa.ListArray.from_arrays(pa.array(edge.astype(np.int32)), runs)


def _resolver(kind, index):
    """index(bodies, docs, starts, window) -> per window of each body: (its number, first doc, first position); and how many a body."""

    def resolve(shard: pa.Table) -> pa.Table:
        shard = shard.sort_by([("doc", "ascending"), ("start", "ascending")])
        runs = window_runs(*index(shard.column("body").to_pylist(), shard.column("doc").to_numpy(), shard.column("start").to_numpy(), kind.window))
        return pa.table({"anchor": shard.column("anchor"), "content": shard.column("content"), "runs": runs})

    return resolve


_PARTS = "panchor long, pcontent long, at int, anchor long, content long, doc long, start long, size long, place int, body binary"


def _parts(large: DataFrame, kind, block: int) -> DataFrame:
    """Contents cut where the anchor's place in their windows enters another block; the new anchor is block and core."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, bodies in text_slices(batch, "body", kind.slice_bytes):
                h, offsets = kind.symbols(bodies)
                up, down = powers(len(h) + 1)
                prefix = np.concatenate((np.zeros(1, np.uint64), np.cumsum(h * up[: len(h)], dtype=np.uint64)))
                anchor = batch.column("anchor").to_numpy()[a:b]
                place = batch.column("place").to_numpy(zero_copy_only=False)[a:b]
                if batch.column("place").null_count:
                    place = _places(prefix, down, offsets, anchor, kind.gram)
                place, count = place.astype(np.int64), np.diff(offsets) - kind.window + 1
                blocks = place // block - (place - count + 1) // block + 1
                who = np.repeat(np.arange(b - a), blocks)
                own = place[who] // block - (np.arange(len(who)) - np.repeat(np.cumsum(blocks) - blocks, blocks))
                first = place[who] - np.minimum(place[who], own * block + block - 1)
                last = place[who] - np.maximum(place[who] - count[who] + 1, own * block)
                begin, end = offsets[who] + first, offsets[who] + last + kind.window
                core = offsets[who] + place[who] - own * block, offsets[who] + place[who] - np.minimum(own * block + block - 1, kind.window - kind.gram) + kind.window
                digest = lambda x, y: _mix((prefix[y] - prefix[x]) * down[x] + (y - x).astype(np.uint64))
                with np.errstate(over="ignore"):
                    key = _mix(digest(*core) + _mix(anchor.view(np.uint64)[who] + _mix(own.astype(np.uint64))))
                cuts: list[bytes] = []
                for i, t in enumerate(bodies):
                    piece = kind.cutter(t)
                    cuts += [piece(int(first[j]), int(last[j]) + kind.window) for j in range(*np.searchsorted(who, [i, i + 1]))]
                cols = [anchor[who], batch.column("content").to_numpy()[a:b][who], first.astype(np.int32), key.view(np.int64), digest(begin, end).view(np.int64)]
                cols += [batch.column("doc").to_numpy()[a:b][who], batch.column("start").to_numpy()[a:b][who] + first, end - begin, (place[who] - first).astype(np.int32), pa.array(cuts, pa.binary())]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=[x.split()[0] for x in _PARTS.split(", ")])

    return large.select("anchor", "content", "doc", "start", "place", "body").mapInArrow(cut, _PARTS)


def _places(prefix: np.ndarray, down: np.ndarray, offsets: np.ndarray, anchor: np.ndarray, gram: int) -> np.ndarray:
    """Where the anchor is first in each body; all windows of a body hold it there."""
    grams = _mix((prefix[gram:] - prefix[:-gram]) * down[: len(prefix) - gram]).view(np.int64)
    owner = np.repeat(np.arange(len(anchor)), np.diff(offsets))[: len(grams)]
    at = np.flatnonzero(grams == anchor[owner])
    who, first = np.unique(owner[at], return_index=True)
    assert len(who) == len(anchor)
    return at[first] - offsets[:-1]


def _resolved(level: DataFrame, kind, index, shards: int) -> DataFrame:
    dealt = level.select("anchor", "content", "doc", "start", "body").withColumn("shard", F.pmod(F.xxhash64("anchor"), F.lit(shards)))
    return dealt.groupBy("shard").applyInArrow(_resolver(kind, index), _RUNS)


def _split(large: DataFrame, kind, index, block: int, most: int) -> DataFrame:
    """Runs (anchor, content, runs) of contents whose anchors have more than a shard holds."""
    parts = saved(_parts(large, kind, block))
    firsts = parts.groupBy("anchor", "content").agg(F.min(F.struct("doc", "start")).alias("f"), F.first("size").alias("size"), F.first("place").alias("place"), F.first("body").alias("body"))
    firsts = saved(firsts.select("anchor", "content", "f.*", "size", "place", "body"))
    sums = saved(firsts.groupBy("anchor").agg(F.count("*").alias("contents"), F.sum("size").alias("symbols")))
    level = firsts.join(sums, "anchor")
    whole = F.struct(F.lit(0).alias("from"), (F.col("size") - kind.window + 1).cast("int").alias("to"), "doc", F.col("start").alias("base"))
    runs = level.where("contents = 1").select("anchor", "content", F.array(whole).alias("runs"))
    shared = level.where("contents > 1")
    total = sums.where(f"contents > 1 and symbols <= {most}").agg(F.sum("symbols").alias("n")).first()["n"] or 0
    runs = runs.unionByName(_resolved(shared.where(F.col("symbols") <= most), kind, index, max(1, -(-total // kind.shard_symbols))))
    if block > 1 and sums.where(f"contents > 1 and symbols > {most}").limit(1).count():
        runs = runs.unionByName(_split(shared.where(F.col("symbols") > most), kind, index, max(1, block // FINER), most))
    moved = lambda r: F.struct((r["from"] + F.col("at")).alias("from"), (r["to"] + F.col("at")).alias("to"), r["doc"].alias("doc"), (r["base"] - F.col("at")).alias("base"))
    back = parts.select("panchor", "pcontent", "at", "anchor", "content").join(saved(runs), ["anchor", "content"]).select("panchor", "pcontent", F.transform("runs", moved).alias("runs"))
    return back.groupBy(F.col("panchor").alias("anchor"), F.col("pcontent").alias("content")).agg(F.flatten(F.collect_list("runs")).alias("runs"))


def repeated_spans(docs: DataFrame, kind, index, most: int | None = None) -> DataFrame:
    """``docs``' (doc, key, key2, text) with ``spans`` (from, to in symbols, may overlap) that occur before; null if none.

    ``most``: symbols of an anchor's contents that go to one shard unsplit, those of a shard unless told.
    """
    most = kind.shard_symbols if most is None else most
    row = ["doc", "key", "key2"]
    ranked = _ranked(docs)
    live = _live_segments(ranked, kind)
    first = live.groupBy("anchor", "content").agg(F.min(F.struct("doc", "start", "key", "key2", "size")).alias("f"))
    first = saved(first.select("anchor", "content", "f.*"))
    sums = first.groupBy("anchor").agg(F.sum("size").alias("symbols"))
    large = saved(sums.where(F.col("symbols") > most).select("anchor", F.lit(True).alias("many")))
    total = first.agg(F.sum("size").alias("symbols")).first()["symbols"] or 0
    any_large = large.limit(1).count() > 0
    asked = first.join(large, "anchor", "left").withColumn("large", F.coalesce("many", F.lit(False))) if any_large else first.withColumn("large", F.lit(False))
    asked = asked.groupBy(row).agg(F.collect_list(F.struct("anchor", "content", "start", "size", "large")).alias("asked"))
    # Each part is written as it is done, so that the shuffles of one step are gone in the next.
    fetched = saved(ranked.join(asked, row).select("doc", "text", "asked").mapInArrow(_fetch(kind), _FETCHED))
    runs = _resolved(fetched.where("not large"), kind, index, max(1, -(-total // kind.shard_symbols)))
    if any_large:
        block = max(1, (kind.window - kind.gram + 1) // FINER)
        runs = runs.unionByName(_split(fetched.where("large").withColumn("place", F.lit(None).cast("int")), kind, index, block, most))
    seen = live.join(saved(runs), ["anchor", "content"]).select(*row, "start", F.explode("runs").alias("r"))
    earlier = F.col("r.doc") < F.col("doc")
    if kind.within:
        earlier = earlier | ((F.col("r.doc") == F.col("doc")) & (F.col("r.base") < F.col("start")))
    span = F.struct((F.col("start") + F.col("r.from")).alias("from"), (F.col("start") + F.col("r.to") + kind.window - 1).alias("to"))
    spans = seen.where(earlier).groupBy(row).agg(F.collect_set(span).alias("spans"))
    return ranked.join(saved(spans), row, "left")


def covered(spans, n: int) -> np.ndarray:
    """Mask of the symbols under any span."""
    change = np.zeros(n + 1, np.int32)
    for s in spans or ():
        change[s["from"]] += 1
        change[s["to"]] -= 1
    return np.cumsum(change[:-1]) > 0


__all__ = ["Bytes", "SPACE", "Words", "covered", "repeated_spans", "runs_of", "segments"]
