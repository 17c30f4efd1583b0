"""Token ids in Arrow files: equal-length sequences as fixed-size lists, with masks, mapped without copies."""

from __future__ import annotations

import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .bpe import ended, fast_encoder, vocabulary_path
from .shared import arrow_map, new_path, small_batches, to_batch, written

SEQUENCE, ROWS_PER_BATCH = 2048, 64


class TokenWriter:
    """Appends ids to one Arrow file. A record batch holds ``rows`` sequences of ``length`` ids and their masks."""

    def __init__(self, sink, dtype: pa.DataType, length: int = SEQUENCE, rows: int = ROWS_PER_BATCH):
        self.length, self.room, self.dtype = length, length * rows, dtype
        self.schema = pa.schema([("ids", pa.list_(dtype, length)), ("mask", pa.list_(pa.bool_(), length))])
        self.file, self.held, self.count = pa.ipc.new_file(sink, self.schema), [], 0

    def add(self, ids: np.ndarray) -> None:
        self.held.append(ids)
        self.count += len(ids)
        if self.count >= self.room:
            flat = np.concatenate(self.held)
            full = len(flat) // self.room * self.room
            for at in range(0, full, self.room):
                self._put(flat[at : at + self.room])
            self.held, self.count = [flat[full:]], len(flat) - full

    def _put(self, flat: np.ndarray) -> None:
        padded = -(-len(flat) // self.length) * self.length
        mask = np.arange(padded) < len(flat)
        values = np.concatenate([flat, np.zeros(padded - len(flat), flat.dtype)]).astype(self.dtype.to_pandas_dtype())
        self.file.write_batch(pa.RecordBatch.from_arrays([pa.FixedSizeListArray.from_arrays(pa.array(v), self.length) for v in (values, mask)], schema=self.schema))

    def close(self) -> None:
        if self.count:
            self._put(np.concatenate(self.held))
        self.file.close()


class TokenReader:
    """Random access to a file of :class:`TokenWriter`; local files are memory-mapped."""

    def __init__(self, uri: str):
        store, path = fs.FileSystem.from_uri(uri)
        self.source = pa.memory_map(path) if isinstance(store, fs.LocalFileSystem) else store.open_input_file(path)
        self.file = pa.ipc.open_file(self.source)
        first = self.file.get_batch(0) if self.file.num_record_batches else None
        self.length = self.file.schema.field("ids").type.list_size
        self.per_batch = first.num_rows * self.length if first is not None else 1
        self.at, self.values = -1, None

    def _batch(self, i: int) -> np.ndarray:
        if i != self.at:
            self.at, self.values = i, self.file.get_batch(i).column(0).flatten().to_numpy()
        return self.values

    def sequence(self, row: int) -> tuple[np.ndarray, np.ndarray]:
        """The ids and mask of one sequence, as views of the file."""
        batch = self.file.get_batch(row * self.length // self.per_batch)
        at = row % (self.per_batch // self.length)
        return tuple(batch.column(c).slice(at, 1).flatten().to_numpy(zero_copy_only=c == 0) for c in (0, 1))

    def ids(self, start: int, length: int):
        """Views of the ids of a document, one for each record batch that it touches."""
        while length > 0:
            values, at = self._batch(start // self.per_batch), start % self.per_batch
            part = values[at : at + length]
            yield part
            start, length = start + len(part), length - len(part)

    def close(self) -> None:
        self.values = None
        self.source.close()


def write(docs: DataFrame, uri: str, path: str | None = None, engine: str = "tokenizers", length: int = SEQUENCE) -> DataFrame:
    """Encodes every text (null: empty) and end id into files under ``uri``; returns the index of documents.

    An empty table gives no files and no rows; other columns of the input play no part; texts of any
    length are one document. Documents are dealt to files by ranges of doc_id (null ids first, equal ids in order of
    a hash of the text). The index has doc_id, shard, file, local_start and n_tokens. A file's
    name is new for each attempt, and the index that Spark commits names the files of the
    attempts that count, so repeated or lost tasks do no harm.
    """
    path = path or vocabulary_path()

    def run(batches):
        store, root = fs.FileSystem.from_uri(uri)
        shard = TaskContext.get().partitionId()
        name = f"{shard:06d}-{uuid.uuid4().hex}.arrow"
        out = sink = None
        at = 0
        for batch in small_batches(batches, rows=2048, size=2 << 20):
            encoder = fast_encoder(path, engine)
            if out is None:
                store.create_dir(root, recursive=True)
                sink = store.open_output_stream(f"{root}/{name}")
                out = TokenWriter(sink, pa.uint16() if encoder.size <= 1 << 16 else pa.uint32(), length)
            ids, begins = ended(batch.column(1), encoder)
            out.add(ids)
            n = batch.num_rows
            yield to_batch({"doc_id": batch.column(0), "shard": pa.array([shard] * n, pa.int32()), "file": pa.array([f"{uri}/{name}"] * n), "local_start": pa.array(begins[:-1] + at), "n_tokens": pa.array(np.diff(begins))})
            at += len(ids)
        if out is not None:
            out.close()
            sink.close()

    ordered = docs.select("doc_id", "text").repartitionByRange("doc_id").sortWithinPartitions("doc_id", F.xxhash64("text"))
    return arrow_map(ordered, run, "doc_id long, shard int, file string, local_start long, n_tokens long")


def with_starts(index: DataFrame) -> DataFrame:
    """Adds ``start``: ids of all documents before. Only one row per file is summed in order."""
    sizes = index.groupBy("shard").agg(F.sum("n_tokens").alias("_size"))
    before = sizes.select("shard", (F.sum("_size").over(Window.orderBy("shard")) - F.col("_size")).alias("_before"))
    # One row for each file, however many documents there are.
    return index.join(F.broadcast(before), "shard").withColumn("start", F.col("_before") + F.col("local_start")).drop("_before")


def read_checksums(index: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens and the crc32 of the ids, read from the files that ``index`` names."""

    def run(batches):
        reader, name = None, None
        for batch in batches:
            rows = batch.to_pydict()
            sums = []
            for file, at, n in zip(rows["file"], rows["local_start"], rows["n_tokens"]):
                if file != name:
                    if reader:
                        reader.close()
                    reader, name = TokenReader(file), file
                crc = 0
                for part in reader.ids(at, n):
                    crc = zlib.crc32(part.astype("<u4").tobytes(), crc)
                sums.append(crc)
            yield to_batch({"doc_id": batch.column(0), "start": batch.column(1), "n_tokens": batch.column(2), "ids_crc32": pa.array(sums, pa.int64())})
        if reader:
            reader.close()

    dealt = index.select("doc_id", "start", "n_tokens", "file", "local_start").repartition("file").sortWithinPartitions("file", "local_start")
    return arrow_map(dealt, run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def store_and_read(docs: DataFrame, uri: str | None = None, path: str | None = None, engine: str = "tokenizers") -> DataFrame:
    uri = uri or new_path(docs.sparkSession, "token-files")
    return read_checksums(with_starts(written(write(docs, uri, path, engine), "token-index")))
