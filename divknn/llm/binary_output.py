"""Token ids in Arrow files of fixed-size-list batches.

Each shard is one Arrow file that holds a contiguous range of ``doc_id``: rows of ``length`` ids
(uint16, the vocabulary is below 65,536) and a mask, false only on the padding of the last row. Row i is
at a fixed byte place, so a memory map reads any sequence without copying. The documents' extents are in
an Arrow file of their own beside it. Files are written under a name of the attempt and only counted
when the task's manifest row is committed, so a lost or repeated task leaves no half file behind.

A null text is one end id. Rows with equal ``doc_id`` stay in one shard beside each other, a null
``doc_id`` comes first. An empty table gives no shard and no row. Other columns are not read.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import saved, shared_dir, text_slices, table
from .tokens import encoder, vocabulary_path

LENGTH, END = 2048, 2
_MANIFEST = "shard int, ids string, extents string, n_docs long, n_ids long"
_RESULT = "doc_id long, start long, n_tokens long, ids_crc32 long"
_EXTENTS = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64())])


def _schema(length: int) -> pa.Schema:
    return pa.schema([("ids", pa.list_(pa.uint16(), length)), ("mask", pa.list_(pa.bool_(), length))])


def _filesystem(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri if "://" in uri or uri.startswith("file:") else f"file://{uri}")


class _Writer:
    """Appends ids to one Arrow file in rows of ``length``; holds less than one batch."""

    def __init__(self, sink, length: int):
        self.out, self.length = pa.ipc.new_file(sink, _schema(length)), length
        self.rest, self.total = np.zeros(0, np.uint16), 0

    def _rows(self, ids: np.ndarray, real: int) -> None:
        mask = np.arange(len(ids)) < real
        lists = [pa.FixedSizeListArray.from_arrays(pa.array(v), self.length) for v in (ids, mask)]
        self.out.write_batch(pa.RecordBatch.from_arrays(lists, schema=_schema(self.length)))

    def add(self, ids: np.ndarray) -> None:
        self.total += len(ids)
        ids = np.concatenate((self.rest, ids))
        whole = len(ids) // self.length * self.length
        if whole:
            self._rows(ids[:whole], whole)
        self.rest = ids[whole:]

    def close(self) -> None:
        if n := len(self.rest):
            self._rows(np.concatenate((self.rest, np.zeros(self.length - n, np.uint16))), n)
        self.out.close()


def write_shards(docs: DataFrame, folder: str, path: str, length: int = LENGTH, end: int = END) -> DataFrame:
    """Write all documents in ``doc_id`` order; the manifest, one row a shard."""

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task = TaskContext.get()
        files, root = _filesystem(folder)
        files.create_dir(root, recursive=True)
        stem = f"{root}/{task.partitionId():06d}-{task.taskAttemptId()}"
        writer = extents = None
        encode = encoder(path).encode
        n_docs = 0
        for batch in batches:
            ids_of = batch.column("doc_id")
            for a, b, texts in text_slices(batch):
                if writer is None:
                    sinks = [files.open_output_stream(f"{stem}.{kind}.arrow") for kind in ("ids", "extents")]
                    writer, extents = _Writer(sinks[0], length), pa.ipc.new_file(sinks[1], _EXTENTS)
                ids, offsets = encode(texts, end)
                extents.write_batch(pa.RecordBatch.from_arrays([ids_of[a:b], pa.array(offsets[:-1] + writer.total), pa.array(np.diff(offsets))], schema=_EXTENTS))
                writer.add(ids)
                n_docs += b - a
        if writer is not None:
            writer.close()
            extents.close()
            for s in sinks:
                s.close()
            yield pa.RecordBatch.from_pydict({"shard": pa.array([task.partitionId()], pa.int32()), "ids": [f"{stem}.ids.arrow"], "extents": [f"{stem}.extents.arrow"], "n_docs": [n_docs], "n_ids": [writer.total]})

    ordered = docs.select(F.col("doc_id").cast("long"), "text").repartitionByRange("doc_id").sortWithinPartitions("doc_id")
    return saved(ordered.mapInArrow(write, _MANIFEST))


class Sequences:
    """Random access to the rows of one ids file, without copying where the store can map memory."""

    def __init__(self, folder: str, name: str):
        files, _ = _filesystem(folder)
        source = pa.memory_map(name) if files.type_name == "local" else files.open_input_file(name)
        self.reader = pa.ipc.open_file(source)
        self.length = self.reader.schema.field("ids").type.list_size
        self.first = [0]  # row at which each batch starts

    def batches(self) -> Iterator[np.ndarray]:
        for i in range(self.reader.num_record_batches):
            yield self.reader.get_batch(i).column("ids").flatten().to_numpy()

    def row(self, i: int) -> tuple[np.ndarray, np.ndarray]:
        """(ids, mask) of sequence ``i``."""
        k = 0
        while True:
            if k + 1 == len(self.first):
                self.first.append(self.first[k] + self.reader.get_batch(k).num_rows)
            if i < self.first[k + 1]:
                batch, at = self.reader.get_batch(k), i - self.first[k]
                return batch.column("ids")[at].values.to_numpy(), np.asarray(batch.column("mask")[at].values)
            k += 1


def read_documents(manifest: DataFrame, folder: str) -> DataFrame:
    """Each document's place among all ids, and a checksum of its ids, from the files."""
    spark = manifest.sparkSession
    rows = sorted(manifest.collect(), key=lambda r: r["shard"])  # one row a file
    plan, base = [], 0
    for r in rows:
        plan.append((r["ids"], r["extents"], base))
        base += r["n_ids"]
    if not plan:
        return spark.createDataFrame([], _RESULT)

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for ids_name, extents_name, before in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                files, _ = _filesystem(folder)
                held, at = np.zeros(0, np.uint16), 0
                blocks = Sequences(folder, ids_name).batches()
                listed = pa.ipc.open_file(files.open_input_file(extents_name))
                for k in range(listed.num_record_batches):
                    own = listed.get_batch(k)
                    starts, sizes = own.column("start").to_numpy(), own.column("n_tokens").to_numpy()
                    held, at = held[starts[0] - at :], starts[0]
                    more, need = [held], starts[-1] + sizes[-1] - at - len(held)
                    while need > 0:
                        more.append(next(blocks))
                        need -= len(more[-1])
                    held = np.concatenate(more)
                    wide = held.astype("<u4")
                    sums = [zlib.crc32(wide[s - at : s - at + n].data) for s, n in zip(starts, sizes, strict=True)]
                    yield pa.RecordBatch.from_arrays([own.column("doc_id"), pa.array(starts + before), pa.array(sizes), pa.array(sums, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    return spark.createDataFrame(plan, "ids string, extents string, before long").repartition(len(plan)).mapInArrow(read, _RESULT)


def op7_arrow_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = shared_dir(spark)
    manifest = write_shards(table(spark, sf_dir, "documents"), folder, vocabulary_path())
    return read_documents(manifest, folder)
