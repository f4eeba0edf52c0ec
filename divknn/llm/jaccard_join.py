"""Join of similar shingle sets by filters under many global token orders.

Token space is cut into K slices by a hash; order k puts the tokens of slice k first. A set's prefix
under order k is its part in slice k, kept as one hash. Two sets of sizes n and m with a Jaccard
similarity of at least t differ in at most d = (n + m)(1 - t) / (1 + t) tokens, and each such token
spoils the agreement under one order only, so linked sets share their prefix under K - d orders at
least. K exceeds the largest d of a size class by a few spare ones: a pair is found by any shared prefix,
kept if it agrees under all the orders that it must, and only then verified by its whole sets. No link is
lost.

Sizes are in classes; a set that may have a partner in the class below is also cut as that class is.
Empty parts are no keys (they would be shared by strangers). There are more spare orders than a set has
empty parts, so linked sets agree in one that is not empty; the few sets with as many empty parts as spare
orders also carry the classic prefix of one order, so that pairs which agree in empty parts alone still meet.

Sets that are equal form one node. Nodes that share keys go to the group of their heaviest neighbour and
are compared by way of the group's centre, so that a group of copies costs in proportion to its size (see
``centres``). Pairs of different groups are counted by the orders under which they agree; those that agree
enough are held against parity sketches - bit b says whether the set has an odd number of tokens of hash
b - which differ in d bits at most for linked sets; whole sets meet last.

Shingles are 64-bit hashes of word hashes. Null or empty texts have an empty set and link with nothing.
A null ``doc_id`` counts as no candidate for the smallest id. Repeated rows are one node. Other columns
are not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from statistics import NormalDist

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import _mix, gram_hashes, saved, text_slices, table, word_hashes
from .centres import hubs, linked_in_groups
from .components import connected

SHINGLE, PERCENT = 3, 90
#: What the stage of the pipeline takes; the pair above is the contract of op3_jaccard_join alone.
STAGE_SHINGLE, STAGE_PERCENT = 5, 80
CLASS_RATIO = 1.25
#: Share of the sets of a class that may need keys besides their slices.
RARE = 0.05
_SIGNED = "doc_id long, row long, n_shingles long, node long, size_class int, own array<long>, below array<long>, rest array<long>, need_own int, need_below int, fresh boolean"
#: Nodes that a task remembers at most to tell copies apart.
KNOWN = 1 << 20
#: Parts of key space, a power of two.
ROUNDS = 4
#: Bits of a set's parity sketch.
SKETCH = 4096


class Classes:
    """Size classes, each with the number of slices its sets are cut into: ``spare`` more than linked sets can differ in."""

    def __init__(self, percent: int):
        self.percent = percent
        self.first = self._least(percent)  # smaller sets can only link with equal ones
        self.starts = [self.first]
        while self.starts[-1] < 1 << 40:
            self.starts.append(int(self.starts[-1] * CLASS_RATIO) + 1)
        self.starts = np.array(self.starts)
        differ = [self.most(int(e) - 1, (int(e) - 1) * 100 // percent) for e in self.starts[1:]]
        self.spare = np.array([self._spare(d, int(n)) for d, n in zip(differ, self.starts, strict=False)])
        self.slices = np.array(differ) + self.spare

    @staticmethod
    def _spare(differ: int, n: int) -> int:
        """The least that makes sets of the class's least size with as many empty slices rare (their number is about Poisson)."""

        def share(spare: int) -> float:
            mean = (differ + spare) * math.exp(-n / (differ + spare))
            if mean > 50 or spare > 100:
                return 1 - NormalDist(mean, math.sqrt(mean) + 1e-9).cdf(spare - 0.5)
            term, under = math.exp(-mean), 0.0
            for i in range(spare):
                under, term = under + term, term * mean / (i + 1)
            return 1 - under

        tried = [2]
        while tried[-1] < 3 + differ // 4:
            tried.append(tried[-1] + 1 + tried[-1] // 16)
        return next((x for x in tried if share(x) <= RARE), min(tried, key=share))

    def most(self, n: int, m: int) -> int:
        """Most tokens in which linked sets of these sizes differ."""
        return (n + m) * (100 - self.percent) // (100 + self.percent)

    @staticmethod
    def _least(percent: int) -> int:
        n = 1
        while (n * 100 // percent) == n and percent < 100:
            n += 1
        return n

    def of(self, n: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.starts, n, "right") - 1

    def has_below(self, n: np.ndarray, c: np.ndarray) -> np.ndarray:
        """Whether a smaller partner can be in the class below."""
        return (c > 0) & (n * self.percent < self.starts[np.maximum(c, 0)] * 100)


def shingle_sets(texts: list[bytes], k: int = SHINGLE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hashes of the distinct shingles, sorted in each text; offsets of the texts; size in bytes of each)."""
    h, offsets, codes, distinct = word_hashes([t.lower() for t in texts])
    count = np.diff(offsets)
    sizes = np.fromiter(map(len, distinct), np.int64, len(distinct))[codes] if len(codes) else np.zeros(0, np.int64)
    owner = np.repeat(np.arange(len(texts)), count)
    n = len(h) - k + 1
    if n > 0:
        grams, inside = gram_hashes(h, k), owner[:n] == owner[k - 1 :]
        long = np.concatenate(([0], np.cumsum(sizes)))
        grams, who, long = grams[inside], owner[:n][inside], (long[k:] - long[:-k])[inside]
    else:
        grams, who, long = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    few = np.flatnonzero((count > 0) & (count < k))
    if len(few):
        extra = [gram_hashes(h[offsets[i] : offsets[i + 1]], int(count[i]))[0] for i in few]
        grams, who, long = np.concatenate((grams, np.array(extra, np.uint64))), np.concatenate((who, few)), np.concatenate((long, np.zeros(len(few), np.int64)))
    order = np.lexsort((grams, who))
    grams, who, long = grams[order], who[order], long[order]
    first = np.ones(len(grams), bool)
    first[1:] = (grams[1:] != grams[:-1]) | (who[1:] != who[:-1])
    grams, who, long = grams[first], who[first], long[first]
    return grams, np.concatenate(([0], np.cumsum(np.bincount(who, minlength=len(texts))))), long


def _part_keys(grams: np.ndarray, who: np.ndarray, slices_of: np.ndarray, tag: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(key of each slice of each set, 0 where empty; offsets): sums of mixed hashes, so order plays no part."""
    edge = np.concatenate(([0], np.cumsum(slices_of)))
    cut = slices_of[who] > 0
    grams, who = grams[cut], who[cut]
    part = edge[who] + (_mix(grams ^ np.uint64(0xA5A5)) % slices_of.astype(np.uint64)[who]).astype(np.int64)
    mixed = _mix(grams + np.uint64(0x51ED27))
    total = int(edge[-1])
    low = np.bincount(part, (mixed & np.uint64(0xFFFFFFFF)).astype(np.float64), total).astype(np.uint64)
    high = np.bincount(part, (mixed >> np.uint64(32)).astype(np.float64), total).astype(np.uint64)
    own = np.repeat(np.arange(len(slices_of)), slices_of)
    place = (tag[own].astype(np.uint64) << np.uint64(40)) + (np.arange(total) - edge[own]).astype(np.uint64)
    keys = _mix(_mix(low + (high << np.uint64(32))) + _mix(high + np.uint64(7)) + _mix(place))
    keys[np.bincount(part, minlength=total) == 0] = 0
    return keys, edge


def _lists(values: np.ndarray, edge: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(edge.astype(np.int32)), pa.array(values.view(np.int64)))


def _node(grams: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """A hash of each set."""
    total = np.concatenate((np.zeros(1, np.uint64), np.cumsum(_mix(grams + np.uint64(0x1234567)), dtype=np.uint64)))
    return _mix(total[offsets[1:]] - total[offsets[:-1]] + np.diff(offsets).astype(np.uint64))


def _row() -> Column:
    """A hash of id and text: equal for repeated rows only."""
    return F.xxhash64(F.col("doc_id").cast("long"), "text")


def signed(docs: DataFrame, percent: int = PERCENT, k: int = SHINGLE) -> DataFrame:
    """One row a document; ``fresh`` marks the first of its node in its task: copies beside it have no keys of their own."""
    classes = Classes(percent)

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: set[int] = set()
        for batch in batches:
            ids = batch.column("doc_id")
            for a, b, texts in text_slices(batch):
                grams, offsets, long = shingle_sets(texts, k)
                n = np.diff(offsets)
                who = np.repeat(np.arange(b - a), n)
                c = classes.of(n)
                keys, edge = _part_keys(grams, who, np.where(c >= 0, classes.slices[c], 0), c)
                low = classes.has_below(n, c)
                keys2, edge2 = _part_keys(grams, who, np.where(low, classes.slices[np.maximum(c - 1, 0)], 0), c - 1)
                empty, empty2 = (np.bincount(np.repeat(np.arange(b - a), np.diff(e))[k == 0], minlength=b - a) for k, e in ((keys, edge), (keys2, edge2)))
                hollow = ((c >= 0) & (empty >= classes.spare[c])) | (low & (empty2 >= classes.spare[np.maximum(c - 1, 0)]))
                rest = np.where(hollow, n, 0)
                need, need2 = np.maximum(classes.spare[c] - empty, 1), np.maximum(classes.spare[np.maximum(c - 1, 0)] - empty2, 1)
                node = _node(grams, offsets).view(np.int64)
                fresh = np.zeros(b - a, bool)
                fresh[[i for v, i in zip(*map(np.ndarray.tolist, np.unique(node, return_index=True)), strict=True) if v not in known]] = True
                known = known if len(known) < KNOWN else set()
                known.update(node.tolist())
                cols = [ids[a:b], batch.column("row")[a:b], pa.array(n), pa.array(node, mask=n == 0), pa.array(c.astype(np.int32)), _lists(keys, edge), _lists(keys2, edge2), _lists(grams[hollow[who]], np.concatenate(([0], np.cumsum(rest)))), pa.array(need.astype(np.int32)), pa.array(need2.astype(np.int32)), pa.array(fresh)]
                yield pa.RecordBatch.from_arrays(cols, names=[x.split()[0] for x in _SIGNED.split(", ")])

    return docs.select(F.col("doc_id").cast("long"), "text", _row().alias("row")).mapInArrow(sign, _SIGNED)


def _node_sets(docs: DataFrame, wanted: DataFrame, k: int) -> DataFrame:
    """``(node, tokens, sketch)`` of the wanted nodes, from the text of one document each; wanted: (node, doc_id)."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, texts in text_slices(batch):
                grams, offsets, _ = shingle_sets(texts, k)
                cell = np.repeat(np.arange(len(texts)), np.diff(offsets)) * SKETCH + (_mix(grams + np.uint64(0xB17)) % np.uint64(SKETCH)).astype(np.int64)
                odd = np.packbits((np.bincount(cell, minlength=len(texts) * SKETCH) & 1).astype(np.uint8)).view(np.uint64)
                yield pa.RecordBatch.from_arrays([pa.array(_node(grams, offsets).view(np.int64)), _lists(grams, offsets), _lists(odd, np.arange(len(texts) + 1) * (SKETCH // 64))], names=["node", "tokens", "sketch"])

    texts = docs.select(F.col("doc_id").cast("long"), "text").alias("d").join(wanted.select("doc_id").distinct().alias("w"), F.col("d.doc_id").eqNullSafe(F.col("w.doc_id")), "left_semi")
    return texts.mapInArrow(read, "node long, tokens array<long>, sketch array<long>").join(wanted.select("node"), "node", "left_semi").dropDuplicates(["node"])


def _facts(rows: DataFrame, wanted: DataFrame) -> DataFrame:
    """Per node: its size, class, and of each cut the slices and how many are empty."""
    empty = lambda c: F.size(F.filter(c, lambda x: x == 0))
    cuts = [F.size("own").alias("k_own"), empty("own").alias("e_own"), F.size("below").alias("k_below"), empty("below").alias("e_below")]
    return rows.join(wanted.select("node"), "node", "left_semi").select("node", "n_shingles", "size_class", *cuts).dropDuplicates(["node"])


def _must_agree(percent: int) -> Column:
    """Non-empty slices of the cut ``c`` under which the sets x and y must agree to be linked."""
    own = lambda t: F.col(f"{t}.size_class") == F.col("c")
    empty = lambda t: F.when(own(t), F.col(f"{t}.e_own")).otherwise(F.col(f"{t}.e_below"))
    k = F.when(own("x"), F.col("x.k_own")).otherwise(F.col("x.k_below"))
    d = F.floor((F.col("x.n_shingles") + F.col("y.n_shingles")) * (100 - percent) / (100 + percent))
    return F.when(F.col("c") < 0, F.lit(1)).otherwise(F.greatest(k - d - F.least(empty("x"), empty("y")), F.lit(1)))


def _verified(pairs: DataFrame, facts: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The linked ones of (a, b, c) pairs, which come once for each key that both have."""
    x, y = facts.alias("x"), facts.alias("y")
    counted = pairs.groupBy("a", "b", "c").agg(F.count("*").alias("n"))
    near = counted.join(x, F.col("a") == F.col("x.node")).join(y, F.col("b") == F.col("y.node"))
    alike = F.least("x.n_shingles", "y.n_shingles") * 100 >= F.greatest("x.n_shingles", "y.n_shingles") * percent
    most = F.floor((F.col("x.n_shingles") + F.col("y.n_shingles")) * (100 - percent) / (100 + percent))
    near = saved(near.where(alike & (F.col("n") >= _must_agree(percent))).select("a", "b", most.alias("most")).distinct())
    s, t = sets.select("node", "sketch").alias("s"), sets.select("node", "sketch").alias("t")
    apart = F.aggregate(F.zip_with("s.sketch", "t.sketch", lambda p, q: F.bit_count(p.bitwiseXOR(q))), F.lit(0), lambda u, v: u + v)
    near = saved(near.join(s, F.col("a") == F.col("s.node")).join(t, F.col("b") == F.col("t.node")).where(apart <= F.col("most")).select("a", "b"))
    s, t = sets.select("node", "tokens").alias("s"), sets.select("node", "tokens").alias("t")
    both = near.join(s, F.col("a") == F.col("s.node")).join(t, F.col("b") == F.col("t.node"))
    common = F.size(F.array_intersect("s.tokens", "t.tokens"))
    union = F.size("s.tokens") + F.size("t.tokens") - common
    return saved(both.where(100 * common >= percent * union).select("a", "b"))


def _links(met: DataFrame, facts: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) that connect what links connect; met: (key, node, c)."""
    hub_of = hubs(met)
    named = met.join(hub_of, "node")
    x, y = named.alias("x"), named.alias("y")
    apart = (F.col("x.hub") != F.col("y.hub")) & (F.col("x.hub") != F.col("y.node")) & (F.col("y.hub") != F.col("x.node"))
    meet = (F.col("x.key") == F.col("y.key")) & (F.col("x.node") < F.col("y.node")) & apart
    found = _verified(x.join(y, meet).select(F.col("x.node").alias("a"), F.col("y.node").alias("b"), F.col("x.c").alias("c")), facts, sets, percent)
    for edges in linked_in_groups(hub_of, sets, percent):
        found = found.unionByName(edges)
    return found


def _rarest(nodes: DataFrame, percent: int) -> DataFrame:
    """Keys (node, key, c = -1) of the sets that are named by tokens: the prefix of one order, rarest first among those sets."""
    rows = nodes.where(F.size("rest") > 0).select("node", F.size("rest").alias("n"), F.explode("rest").alias("token"))
    often = saved(rows.groupBy("token").agg(F.count("*").alias("f")).where("f > 1"))
    held = rows.join(often, "token").groupBy("node", "n").agg(F.sort_array(F.collect_list(F.struct("f", "token"))).alias("held"))
    # Tokens that no other such set has come first and meet nobody.
    length = F.col("n") - F.ceil(F.col("n") * percent / 100) + 1 - (F.col("n") - F.size("held"))
    first = F.slice("held", 1, F.least(F.size("held"), F.greatest(length, F.lit(0))).cast("int"))
    return held.select("node", F.explode(F.transform(first, lambda t: t["token"])).alias("token")).select("node", F.xxhash64("token", F.lit("rest")).alias("key"), F.lit(-1).alias("c"), F.lit(1).alias("need"))


def _shared_keys(rows: DataFrame, percent: int) -> DataFrame:
    """(node, key, c): keys that two nodes have, of nodes with as many such keys in the cut as any linked pair agrees in.

    A set needs its spare orders less its empty parts: who shares fewer is linked with nobody by that cut.
    Key space is gone through in ``ROUNDS`` parts, so that the keys of all sets are never shuffled at once.
    """
    held = rows.where("node is not null and fresh")
    named = held.where(F.size("rest") > 0).select("node", "rest").dropDuplicates(["node"])
    key = lambda x, c, need: F.struct(x.alias("key"), c.cast("int").alias("c"), F.col(need).alias("need"))
    met = None
    for i in range(ROUNDS):
        mine = lambda c, i=i: F.filter(c, lambda k: (k != 0) & (k.bitwiseAND(ROUNDS - 1) == i))
        keys = F.concat(F.transform(mine("own"), lambda x: key(x, F.col("size_class"), "need_own")), F.transform(mine("below"), lambda x: key(x, F.col("size_class") - 1, "need_below")))
        part = _met(held.select("node", F.explode(keys).alias("k")).select("node", "k.key", "k.c", "k.need"))
        met = part if met is None else met.unionByName(part)
    met = met.unionByName(_met(_rarest(named, percent)))
    enough = saved(met.groupBy("node", "c").agg(F.count("*").alias("n"), F.max("need").alias("need")).where("n >= need").select("node", "c"))
    return _met(met.join(enough, ["node", "c"], "left_semi")).select("node", "key", "c")


def _met(posted: DataFrame) -> DataFrame:
    """Distinct rows whose key another node has too, by one shuffle: a key's rows are sorted, and spilled where they are many."""
    w = Window.partitionBy("key")
    both = posted.withColumn("lo", F.min("node").over(w)).withColumn("hi", F.max("node").over(w))
    return saved(both.where("lo < hi").drop("lo", "hi").distinct())


def _components(docs: DataFrame, percent: int, k: int) -> tuple[DataFrame, DataFrame]:
    """(signed rows; (node, comp) of the nodes that are linked with others)."""
    rows = saved(signed(docs, percent, k))
    met = _shared_keys(rows, percent)
    wanted = saved(rows.join(met.select("node").distinct(), "node", "left_semi").groupBy("node").agg(F.min("doc_id").alias("doc_id")))
    sets = saved(_node_sets(docs, wanted, k))
    facts = saved(_facts(rows, wanted))

    edges = _links(met, facts, sets, percent)
    return rows, saved(connected(edges))


def similar_components(docs: DataFrame, percent: int = PERCENT, k: int = SHINGLE) -> DataFrame:
    """``(doc_id, n_shingles, component_id)`` per row of ``docs``."""
    rows, labels = _components(docs, percent, k)
    least = rows.where("node is not null").groupBy("node").agg(F.min("doc_id").alias("least"))
    least = least.join(labels, "node", "left").withColumn("comp", F.coalesce("comp", "node"))
    named = least.select("node", "comp").join(least.groupBy("comp").agg(F.min("least").alias("component_id")), "comp").select("node", "component_id")
    return rows.select("doc_id", "n_shingles", "node").join(named, "node", "left").select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))


def one_per_group(docs: DataFrame, percent: int = STAGE_PERCENT, k: int = STAGE_SHINGLE) -> DataFrame:
    """One row of each group of linked rows: of smallest ``doc_id``, null last, then of smallest hash.

    Rows without a word are linked with nothing and stay; of those with an id, repeated ones are one.
    """
    rows, labels = _components(docs, percent, k)
    best = rows.where("node is not null").groupBy("node").agg(F.min(F.struct(F.col("doc_id").isNull().alias("nameless"), "doc_id", "row")).alias("best"))
    best = best.join(labels, "node", "left").groupBy(F.coalesce("comp", "node").alias("comp")).agg(F.min("best").alias("best"))
    stay = saved(best.select("best.row").unionByName(rows.where("node is null").select("row").distinct()))
    apart = F.col("doc_id").isNull() & ~F.coalesce("text", F.lit("")).rlike(r"[^\x20\x09-\x0D]")
    marked = docs.withColumn("_row", _row()).withColumn("_apart", F.when(apart, F.monotonically_increasing_id()).otherwise(-1))
    return marked.join(stay.withColumnRenamed("row", "_row"), "_row", "left_semi").dropDuplicates(["_row", "_apart"]).select(docs.columns)


def op3_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similar_components(table(spark, sf_dir, "documents"))
