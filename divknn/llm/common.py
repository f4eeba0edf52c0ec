"""Helpers shared by the text operators: tables, shared folders, byte-level tokenising."""

from __future__ import annotations

import tempfile
import uuid

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession

#: Byte classes of the word definition ``[^\x20\x09-\x0D]+``; ``bytes.split()`` cuts at just these.
SPACE = np.zeros(256, bool)
SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True

_FALLBACK: list[str] = []
_OWN: set[str] = set()
_FREE = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """A fresh folder name in the shared folder of ``spark.checkpoint.dir``, deleted when the application ends.

    Without that setting a temporary folder serves a local master; on a cluster, whose executors could not
    see it, an error is raised.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        if not _FALLBACK:
            _FALLBACK.append("file://" + tempfile.mkdtemp(prefix="divknn-"))
        base = _FALLBACK[0]
    own = f"{base.rstrip('/')}/divknn-{spark.sparkContext.applicationId}"
    if own not in _OWN:
        jvm = spark.sparkContext._jvm
        path = jvm.org.apache.hadoop.fs.Path(own)
        files = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        files.mkdirs(path)
        files.deleteOnExit(path)
        _OWN.add(own)
    return f"{own}/{uuid.uuid4().hex}"


def saved(df: DataFrame) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: computed once, safe against lost executors."""
    spark = df.sparkSession
    path = shared_dir(spark)
    before = spark.conf.get(_FREE, "false")
    spark.conf.set(_FREE, "true")  # the shuffles behind a written table are not needed again
    try:
        df.write.option("compression", "zstd").parquet(path)
    finally:
        spark.conf.set(_FREE, before)
    return spark.read.schema(df.schema).parquet(path)


def text_slices(batch: pa.RecordBatch, name: str = "text", limit: int = 2 << 20):
    """(from, to, UTF-8 texts) of consecutive rows of about ``limit`` bytes together; one long text stays whole.

    Null becomes empty. Only one slice is held as Python objects at a time.
    """
    column = batch.column(name)
    sizes = pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False)
    start, size = 0, 0
    for i, n in enumerate(sizes.tolist() + [None]):
        if i > start and (n is None or size + n > limit):
            yield start, i, [t or b"" for t in column.slice(start, i - start).cast(pa.binary()).to_pylist()]
            start, size = i, 0
        size += n or 0


def word_codes(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, list[bytes]]:
    """(code of each word, offsets of the texts in it, distinct words): equal words share a code."""
    raw = np.frombuffer(b" ".join([b"", *texts, b""]), np.uint8)
    inside = ~SPACE[raw]
    edges = np.flatnonzero(inside[1:] != inside[:-1])
    begin, size = edges[::2] + 1, edges[1::2] - edges[::2]
    text_start = np.cumsum([1] + [len(t) + 1 for t in texts])
    offsets = np.searchsorted(begin, text_start)
    where = np.concatenate(([0], np.cumsum(size))).astype(np.int32)
    words = pa.Array.from_buffers(pa.binary(), len(size), [None, pa.py_buffer(where), pa.py_buffer(np.ascontiguousarray(raw[inside]))])
    coded = words.dictionary_encode()
    return coded.indices.to_numpy().astype(np.int64), offsets, coded.dictionary.to_pylist()


def _mix(x: np.ndarray) -> np.ndarray:
    """64-bit finaliser, a bijection."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def word_hashes(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray, list[bytes]]:
    """(64-bit hash of each word, offsets, codes, distinct words); the same hash in every process."""
    import xxhash

    codes, offsets, distinct = word_codes(texts)
    table = np.fromiter((xxhash.xxh3_64_intdigest(w) for w in distinct), np.uint64, len(distinct))
    return (table[codes] if len(codes) else np.zeros(0, np.uint64)), offsets, codes, distinct


def gram_hashes(h: np.ndarray, k: int, seed: int = 0) -> np.ndarray:
    """Hash of every run of ``k`` consecutive values; length ``len(h)-k+1`` (0 at least)."""
    n = len(h) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    with np.errstate(over="ignore"):
        out = np.full(n, (seed * 0x9E3779B97F4A7C15 + k) & 0xFFFFFFFFFFFFFFFF, np.uint64)
        for i in range(k):
            out = _mix(out * np.uint64(0x9E3779B97F4A7C15) + h[i : i + n])
    return out


def runs_of(mask: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the maximal runs of True."""
    edges = np.flatnonzero(np.diff(np.concatenate(([0], mask.astype(np.int8), [0]))))
    return edges[::2], edges[1::2]


#: For comparing words whatever their case and signs: ASCII letters in lower case, other ASCII but digits as spaces.
FOLD = bytes(b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256))


class HashSet:
    """Membership of 64-bit hashes: a bit table first, then a sorted array. Its size is that of what it holds."""

    def __init__(self, values: np.ndarray, bits: int = 22):
        self.values = np.unique(values.astype(np.uint64))
        self.table, self.mask = np.zeros(1 << bits, bool), np.uint64((1 << bits) - 1)
        self.table[(self.values & self.mask).astype(np.int64)] = True

    def where(self, x: np.ndarray) -> np.ndarray:
        """Places in ``x`` whose value is held."""
        maybe = np.flatnonzero(self.table[(x & self.mask).astype(np.int64)])
        at = np.minimum(np.searchsorted(self.values, x[maybe]), len(self.values) - 1)
        return maybe[self.values[at] == x[maybe]] if len(self.values) else maybe[:0]
