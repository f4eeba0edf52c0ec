"""Vector sets derived from the given tables: ``(id long, vec array<double>)``.

Each view is also given as SQL in long form ``(id, i, x)`` for engines that check results.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from string import ascii_lowercase, digits

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


#: Texts that are cut into words at once: about so many bytes, and rows at most.
TEXT_BYTES, TEXT_ROWS = 2 << 20, 2048
_LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
#: The only letters beyond ASCII whose lower case holds an ASCII letter: the Kelvin sign and the dotted capital I.
_ODD = (("\u212a".encode(), b"k"), ("\u0130".encode(), "i\u0307".encode()))


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def emb(spark: SparkSession, sf_dir: str, shift: float = 0.0, d: int = 64) -> DataFrame:
    return read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.expr(f"transform(slice(embedding, 1, {d}), v -> double(v) + {float(shift)!r}D)").alias("vec"))


def _dense(long: DataFrame, d: int, fill: str) -> DataFrame:
    """(id, i, x) to (id, vec): one aggregation, no pivot."""
    packed = long.groupBy("id").agg(F.map_from_entries(F.collect_list(F.struct("i", "x"))).alias("m"))
    return packed.select("id", F.expr(f"transform(sequence(0, {d - 1}), i -> coalesce(m[i], 0D))").alias("c")).select("id", F.expr(fill).alias("vec"))


def _some_rows(sizes: np.ndarray) -> Iterator[tuple[int, int]]:
    """(from, to) of consecutive rows of about ``TEXT_BYTES`` together, ``TEXT_ROWS`` at most; one long text stays whole."""
    start, size = 0, 0
    for i, n in enumerate(sizes.tolist()):
        if i > start and (size + n > TEXT_BYTES or i - start == TEXT_ROWS):
            yield start, i
            start, size = i, 0
        size += n
    if start < len(sizes):
        yield start, len(sizes)


def _lower(text: bytes) -> bytes:
    """UTF-8 in which the ASCII letters are those of the text in lower case; other letters stay as they are."""
    for odd, low in () if text.isascii() else _ODD:
        text = text.replace(odd, low)
    return text.translate(_LOWER)


def _md5_steps() -> list[tuple[int, int, int]]:
    """(word of the block, constant, turn) of the 64 steps of MD5."""
    turns, steps = ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)), []
    for i in range(64):
        at = (i, 5 * i + 1, 3 * i + 5, 7 * i)[i // 16] % 16
        steps.append((at, int(abs(math.sin(i + 1)) * (1 << 32)), turns[i // 16][i % 4]))
    return steps


_STEPS = _md5_steps()
#: Words hashed at once: what a core's cache holds.
HASHED = 1 << 13


def _word_hashes(words: pa.BinaryArray) -> np.ndarray:
    """The first 32 bits of each word's MD5, many words a step; those beyond one block (56 bytes or more) one by one."""
    ends = np.frombuffer(words.buffers()[1], np.int32)[words.offset : words.offset + len(words) + 1].astype(np.int64)
    data, out = np.frombuffer(words.buffers()[2] or b"", np.uint8), np.zeros(len(words), np.uint32)
    start = tuple(np.uint32(v) for v in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476))
    for lo in range(0, len(words), HASHED):
        own, long = ends[lo : lo + HASHED + 1], np.diff(ends[lo : lo + HASHED + 1])
        n, fits = len(long), long < 56
        block = np.zeros((n, 64), np.uint8)
        row = np.repeat(np.arange(n), long)
        column = np.arange(len(row)) - np.repeat(own[:-1] - own[0], long)
        if not fits.all():
            row, column, text = row[fits[row]], column[fits[row]], data[own[0] : own[-1]][fits[row]]
        else:
            text = data[own[0] : own[-1]]
        block[row, column] = text
        block[np.arange(n)[fits], long[fits]] = 0x80
        part = np.ascontiguousarray(block.view("<u4").T)
        part[14] = long * 8
        a, b, c, e = (np.full(n, v) for v in start)
        for i, (at, plus, turn) in enumerate(_STEPS):
            f = _mix(i // 16, b, c, e)
            f += a
            f += part[at]
            f += np.uint32(plus)
            a, e, c, b = e, c, b, b + ((f << np.uint32(turn)) | (f >> np.uint32(32 - turn)))
        own_hash = (a + start[0]).byteswap()
        for i in np.flatnonzero(~fits):
            own_hash[i] = int.from_bytes(hashlib.md5(data[own[i] : own[i + 1]].tobytes()).digest()[:4], "big")
        out[lo : lo + n] = own_hash
    return out


def _mix(quarter: int, b: np.ndarray, c: np.ndarray, e: np.ndarray) -> np.ndarray:
    if quarter == 0:
        return e ^ (b & (c ^ e))
    if quarter == 1:
        return c ^ (e & (b ^ c))
    return b ^ c ^ e if quarter == 2 else c ^ (b | ~e)


def _word_counts(rows: DataFrame, letters: str, d: int, empty: bool, finish: Callable[[np.ndarray, np.ndarray], np.ndarray] = lambda c, _: c) -> DataFrame:
    """(id, c, total): of rows (id, text) the dense counts of the words of ``letters`` (ASCII) in lower case, by the hash of the word.

    A text is counted where it lies and leaves its task as one row, not a row a word; texts that share an id
    are added up. Without ``empty`` an id without words has no row. Many texts are cut into words at once.
    ``finish`` makes c of the counts (rows, d) and totals.
    """

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        letter = np.zeros(256, bool)
        letter[list(letters.encode())] = True
        for whole in batches:
            sizes = pc.fill_null(pc.binary_length(whole.column("text")), 0).to_numpy(zero_copy_only=False)
            for lo, hi in _some_rows(sizes):
                texts = [_lower(t or b"") for t in whole.column("text").slice(lo, hi - lo).cast(pa.binary()).to_pylist()]
                raw = np.frombuffer(b" ".join([b"", *texts, b""]), np.uint8)
                inside = letter[raw]
                edges = np.flatnonzero(inside[1:] != inside[:-1])
                begin, long = edges[::2] + 1, edges[1::2] - edges[::2]
                owner = np.searchsorted(np.cumsum([1] + [len(t) + 1 for t in texts]), begin, "right") - 1
                ends = np.concatenate(([0], np.cumsum(long))).astype(np.int32)
                words = pa.Array.from_buffers(pa.binary(), len(long), [None, pa.py_buffer(ends), pa.py_buffer(np.ascontiguousarray(raw[inside]))]).dictionary_encode()
                slot = _word_hashes(words.dictionary).astype(np.int64) % d
                counts = np.bincount(owner * d + slot[words.indices.to_numpy()], minlength=len(texts) * d)
                cell = np.flatnonzero(counts)
                edge = np.searchsorted(cell, np.arange(len(texts) + 1) * d)
                # Bytes: the engine takes a list of numbers apart for each element.
                pairs = np.ascontiguousarray(np.stack((cell % d, counts[cell]), axis=1).astype(np.int64))
                held = pa.Array.from_buffers(pa.large_binary(), len(texts), [None, pa.py_buffer((16 * edge).astype(np.int64)), pa.py_buffer(pairs)]).cast(pa.binary())
                yield pa.RecordBatch.from_arrays([whole.column("id").slice(lo, hi - lo), held], names=["id", "held"])

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for lo in range(0, whole.num_rows, 2048):
                b = whole.slice(lo, 2048)
                parts = b.column("parts")
                own = parts.flatten()
                sizes = pc.binary_length(own).to_numpy() // 16
                i, x = np.frombuffer(b"".join(own.to_pylist()), np.int64).reshape(-1, 2).T
                row = np.repeat(np.repeat(np.arange(b.num_rows), parts.value_lengths().to_numpy()), sizes)
                c = np.bincount(row * d + i, x, b.num_rows * d).reshape(-1, d)
                total = c.sum(1)
                c = np.ascontiguousarray(finish(c, total))
                yield pa.RecordBatch.from_arrays([b.column("id"), pa.ListArray.from_arrays(pa.array(np.arange(0, c.size + 1, d), pa.int32()), pa.array(c.ravel())), pa.array(total)], names=["id", "c", "total"])

    counted = rows.select(F.col("id").cast("long").alias("id"), "text").mapInArrow(count, "id long, held binary")
    if not empty:
        counted = counted.where(F.octet_length("held") > 0)
    return counted.groupBy("id").agg(F.collect_list("held").alias("parts")).mapInArrow(spread, "id long, c array<double>, total double")


def doc_hash(spark: SparkSession, sf_dir: str, d: int = 100) -> DataFrame:
    """Hashed word counts, smoothed by a half and scaled to mean 1."""
    rows = read(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text")
    return _word_counts(rows, ascii_lowercase, d, True, lambda c, total: (c + 0.5) * d / (total[:, None] + 0.5 * d)).select("id", F.col("c").alias("vec"))


def doc_hash_sql(d: int) -> str:
    return f"""(WITH w AS (SELECT doc_id id, unnest(list_filter(regexp_split_to_array(lower(text), '[^a-z]+'), lambda v: v <> '')) w FROM documents),
 c AS (SELECT id, (('0x' || substr(md5(w), 1, 8))::BIGINT % {d}) i, count(*)::DOUBLE x FROM w GROUP BY ALL),
 t AS (SELECT d.id, coalesce(sum(x), 0) s FROM (SELECT DISTINCT doc_id id FROM documents) d LEFT JOIN c USING (id) GROUP BY d.id)
 SELECT t.id, r.i, (coalesce(c.x, 0) + 0.5) * {d} / (t.s + 0.5 * {d}) x FROM t CROSS JOIN (SELECT unnest(range({d})) i) r LEFT JOIN c ON c.id = t.id AND c.i = r.i)"""


def page_hash(spark: SparkSession, sf_dir: str, d: int = 256) -> DataFrame:
    """Hashed tokens of the markup, log1p, scaled to [0, 1] by log1p of 10,000."""
    rows = read(spark, sf_dir, "pages").select(F.col("page_id").alias("id"), F.col("html").alias("text"))
    return _word_counts(rows, ascii_lowercase + digits, d, False).select("id", F.expr("transform(c, v -> least(ln(1 + v) / ln(10001), 1D))").alias("vec"))


def page_hash_sql(d: int = 256) -> str:
    return f"""(WITH w AS (SELECT page_id id, unnest(list_filter(regexp_split_to_array(lower(html), '[^a-z0-9]+'), lambda v: v <> '')) w FROM pages),
 c AS (SELECT id, (('0x' || substr(md5(w), 1, 8))::BIGINT % {d}) i, count(*)::DOUBLE x FROM w GROUP BY ALL)
 SELECT t.id, r.i, least(ln(1 + coalesce(c.x, 0)) / ln(10001), 1) x FROM (SELECT DISTINCT id FROM c) t CROSS JOIN (SELECT unnest(range({d})) i) r LEFT JOIN c ON c.id = t.id AND c.i = r.i)"""


def event_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Value by hour of the week and by hour of the day, per user and type; 192 coordinates in [0, 1]."""
    e = read(spark, sf_dir, "events").where("user_id is not null and event_type is not null and ts is not null and value is not null")
    kinds = F.pmod(F.conv(F.substring(F.md5("event_type"), 1, 6), 16, 10).cast("long"), F.lit(1000))
    e = e.select((F.col("user_id") * 1000 + kinds).alias("id"), F.dayofweek("ts").alias("w"), F.hour("ts").alias("h"), F.abs("value").alias("v"))
    slots = e.select("id", F.explode(F.array(((F.col("w") - 1) * 24 + F.col("h")), F.lit(168) + F.col("h"))).alias("i"), "v")
    return _dense(slots.groupBy("id", "i").agg(F.sum("v").alias("x")), 192, "transform(c, v -> least(ln(1 + v) / ln(100001), 1D))")


def event_profile_sql() -> str:
    return """(WITH e AS (SELECT user_id * 1000 + ('0x' || substr(md5(event_type), 1, 6))::BIGINT % 1000 id, dayofweek(ts) w, hour(ts) h, abs(value) v FROM events WHERE user_id IS NOT NULL AND event_type IS NOT NULL AND ts IS NOT NULL AND value IS NOT NULL),
 c AS (SELECT id, i, sum(v) x FROM (SELECT id, w * 24 + h i, v FROM e UNION ALL SELECT id, 168 + h, v FROM e) GROUP BY ALL)
 SELECT t.id, r.i, least(ln(1 + coalesce(c.x, 0)) / ln(100001), 1) x FROM (SELECT DISTINCT id FROM c) t CROSS JOIN (SELECT unnest(range(192)) i) r LEFT JOIN c ON c.id = t.id AND c.i = r.i)"""


_LINE = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]


def line(spark: SparkSession, sf_dir: str, d: int = 4, shift: float = 0.0) -> DataFrame:
    """Measures of order lines in [0, 1]; the id hashes the whole row, as no shorter key is unique."""
    t = read(spark, sf_dir, "lineitem")
    row = F.md5(F.concat_ws("|", *[F.date_format(c, "yyyy-MM-dd") if c == "l_shipdate" else F.format_number(c, 2) if c in ("l_quantity", "l_extendedprice", "l_discount", "l_tax") else F.col(c).cast("string") for c in _LINE]))
    q, p, s, x = "l_quantity/50", "l_extendedprice/105000", "l_discount*10", "l_tax*12.5"
    cols = [q, p, s, x, f"({q})*({p})", f"({p})*({s})", f"({p})*(1-l_discount)", f"({p})*(1+l_tax)"][:d]
    return t.select(F.conv(F.substring(row, 1, 15), 16, 10).cast("long").alias("id"), F.array(*[F.expr(f"double({c}) + {float(shift)!r}D") for c in cols]).alias("vec"))


def line_sql(d: int = 4, shift: float = 0.0) -> str:
    q, p, s, x = "l_quantity/50", "l_extendedprice/105000", "l_discount*10", "l_tax*12.5"
    cols = [q, p, s, x, f"({q})*({p})", f"({p})*({s})", f"({p})*(1-l_discount)", f"({p})*(1+l_tax)"][:d]
    text = [f"strftime({c}, '%Y-%m-%d')" if c == "l_shipdate" else f"format('{{:,.2f}}', {c})" if c in ("l_quantity", "l_extendedprice", "l_discount", "l_tax") else f"{c}::VARCHAR" for c in _LINE]
    return f"(SELECT ('0x' || substr(md5(concat_ws('|', {', '.join(text)})), 1, 15))::BIGINT id, unnest(range({d})) i, unnest([{', '.join(f'({c})::DOUBLE + {shift!r}' for c in cols)}]) x FROM lineitem)"


def _mix_weight(i: int, j: int) -> float:
    import hashlib

    return int(hashlib.md5(f"{i},{j}".encode()).hexdigest()[:6], 16) / 0xFFFFFF


def line_mix(spark: SparkSession, sf_dir: str, d: int = 64, shift: float = 0.0) -> DataFrame:
    """Order-line measures mixed to ``d`` correlated coordinates by fixed non-negative weights."""
    rows = [[_mix_weight(i, j) / 2 for j in range(4)] for i in range(d)]
    weights = "array(" + ",".join("array(" + ",".join(f"{w!r}D" for w in r) + ")" for r in rows) + ")"
    return line(spark, sf_dir).select("id", F.expr(f"transform({weights}, w -> w[0]*vec[0] + w[1]*vec[1] + w[2]*vec[2] + w[3]*vec[3] + {float(shift)!r}D)").alias("vec"))


def part_month(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Monthly quantity of a part from 1995 to 2001, smoothed; 84 positive coordinates."""
    t = read(spark, sf_dir, "lineitem").where("l_shipdate >= '1995-01-01' and l_shipdate < '2002-01-01'")
    t = t.select(F.col("l_partkey").alias("id"), ((F.year("l_shipdate") - 1995) * 12 + F.month("l_shipdate") - 1).alias("i"), "l_quantity")
    sums = t.groupBy("id", "i").agg(F.sum("l_quantity").cast("double").alias("x"))
    every = read(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), F.lit(0).alias("i"), F.lit(0.0).alias("x"))
    return _dense(sums.unionByName(every).groupBy("id", "i").agg(F.sum("x").alias("x")), 84, "transform(c, v -> (v + 1D) / 50)")


def part_month_sql() -> str:
    return """(WITH c AS (SELECT l_partkey id, (year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 i, sum(l_quantity)::DOUBLE x FROM lineitem WHERE l_shipdate >= '1995-01-01' AND l_shipdate < '2002-01-01' GROUP BY ALL),
 t AS (SELECT p_partkey id FROM part UNION SELECT id FROM c)
 SELECT t.id, r.i, (coalesce(c.x, 0) + 1) / 50 x FROM t CROSS JOIN (SELECT unnest(range(84)) i) r LEFT JOIN c ON c.id = t.id AND c.i = r.i)"""


def _hash_unit(salt: int) -> str:
    return f"(pmod(xxhash64(id, j, {salt}), 9007199254740992L) + 0.5D) / 9007199254740992D"


def gauss(spark: SparkSession, n: int, d: int = 200, scale: float = 1.0) -> DataFrame:
    """Standard normal coordinates from hashes of (id, coordinate); the same whatever the partitioning."""
    cell = f"{float(scale)!r}D * sqrt(-2 * ln({_hash_unit(1)})) * cos(6.283185307179586D * {_hash_unit(2)})"
    return spark.range(n).select("id", F.expr(f"transform(sequence(0, {d - 1}), j -> {cell})").alias("vec"))


def uniform(spark: SparkSession, n: int, d: int = 200, lo: float = 1.0, hi: float = 2.0) -> DataFrame:
    return spark.range(n).select("id", F.expr(f"transform(sequence(0, {d - 1}), j -> {float(lo)!r}D + {float(hi - lo)!r}D * ({_hash_unit(3)}))").alias("vec"))


@dataclass(frozen=True)
class View:
    d: int
    generator: str
    load: object
    sql: str | None = None


def catalogue() -> dict[str, View]:
    """Views by name, with the generator of the role they play and long-form SQL where engines agree on it."""
    emb_sql = lambda s, d=64: f"(SELECT vec_id id, unnest(range({d})) i, unnest(list_transform(embedding[1:{d}], lambda v: v::DOUBLE + {s})) x FROM embeddings)"
    out = {
        "emb64": View(64, "exponential", lambda s, d: emb(s, d), emb_sql("0.0")),
        "emb64_pos": View(64, "itakura_saito", lambda s, d: emb(s, d, 1.0), emb_sql("1.0")),
        "page_hash256": View(256, "exponential", page_hash, page_hash_sql()),
        "event_profile192": View(192, "exponential", event_profile, event_profile_sql()),
        "line4": View(4, "exponential", lambda s, d: line(s, d, 4), line_sql(4)),
        "line8": View(8, "itakura_saito", lambda s, d: line(s, d, 8, 0.05), line_sql(8, 0.05)),
        "line_mix64": View(64, "exponential", lambda s, d: line_mix(s, d, 64)),
        "line_mix128": View(128, "exponential", lambda s, d: line_mix(s, d, 128)),
        "part_month": View(84, "itakura_saito", part_month, part_month_sql()),
        "gauss200": View(200, "exponential", lambda s, d: gauss(s, 50_000, scale=0.3)),
        "unif200": View(200, "itakura_saito", lambda s, d: uniform(s, 50_000)),
    }
    for d in (8, 16, 32):
        out[f"emb{d}"] = View(d, "exponential", lambda s, p, d=d: emb(s, p, 0.0, d), emb_sql("0.0", d))
    for d in (10, 50, 100, 200, 400):
        out[f"doc_hash{d}"] = View(d, "itakura_saito", lambda s, p, d=d: doc_hash(s, p, d), doc_hash_sql(d))
    return out


def sample_queries(points: DataFrame, n: int = 50) -> DataFrame:
    """The ``n`` points of smallest hash of their id: ``(qid, yvec)``."""
    return points.orderBy(F.md5(F.col("id").cast("string")), "id").limit(n).select(F.col("id").alias("qid"), F.col("vec").alias("yvec"))


def queries_from_json(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("qid long, yvec array<double>").json(path)


def queries_from_csv(spark: SparkSession, path: str) -> DataFrame:
    """Lines of ``qid,v;v;...``."""
    raw = spark.read.schema("qid long, v string").csv(path)
    return raw.select("qid", F.expr("transform(split(v, ';'), x -> double(x))").alias("yvec"))
