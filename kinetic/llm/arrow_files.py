"""Token ids in Arrow IPC files of fixed-size-list batches.

Each shard holds the ids of a range of documents one after the other, cut into
rows of equal length with a mask that marks what is padding, and beside it an
index of its documents. Rows and documents are read by position through the
file's footer, without copying where the store can be mapped.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kinetic.llm.common import fresh_path, rows_of, text_or_empty, written
from kinetic.llm.tokens import crc32, default_tokenizer, encoder

SEQUENCE = 1024
#: Rows of a batch; all batches of a file but the last have as many.
BATCH_ROWS = 1024
_INDEX = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64())])


def _open(uri: str, mode: str):
    from pyarrow import fs

    store, path = fs.FileSystem.from_uri(uri)
    if mode == "w":
        store.create_dir(path.rpartition("/")[0], recursive=True)
        return store.open_output_stream(path)
    if isinstance(store, fs.LocalFileSystem):
        return pa.memory_map(path)
    return store.open_input_file(path)


class SequenceWriter:
    """Writes ids that come in pieces as rows of ``length`` ids and their mask."""

    def __init__(self, uri: str, dtype: np.dtype, length: int = SEQUENCE, batch_rows: int = BATCH_ROWS):
        self.length, self.dtype, self.most = length, dtype, batch_rows * length
        self.schema = pa.schema([("ids", pa.list_(pa.from_numpy_dtype(dtype), length)), ("mask", pa.list_(pa.bool_(), length))])
        self.sink = _open(uri, "w")
        self.file = pa.ipc.new_file(self.sink, self.schema)
        self.held: list[np.ndarray] = []
        self.size = self.total = 0

    def add(self, ids: np.ndarray) -> None:
        self.held.append(ids)
        self.size += len(ids)
        self.total += len(ids)
        if self.size >= self.most:
            flat = np.concatenate(self.held)
            whole = len(flat) // self.most * self.most
            for at in range(0, whole, self.most):
                self._write(flat[at : at + self.most], self.most)
            self.held, self.size = [flat[whole:]], len(flat) - whole

    def _write(self, ids: np.ndarray, used: int) -> None:
        mask = np.arange(len(ids)) < used
        self.file.write_batch(pa.record_batch([pa.FixedSizeListArray.from_arrays(pa.array(x), self.length) for x in (ids, mask)], schema=self.schema))

    def close(self) -> None:
        if self.size:
            rows = -(-self.size // self.length)
            flat = np.zeros(rows * self.length, self.dtype)
            flat[: self.size] = np.concatenate(self.held)
            self._write(flat, self.size)
        self.file.close()
        self.sink.close()


class SequenceFile:
    """Random access to a shard: sequence(i) and tokens(start, n)."""

    def __init__(self, uri: str):
        self.source = _open(uri, "r")
        self.file = pa.ipc.open_file(self.source)
        self.length = self.file.schema.field("ids").type.list_size
        first = self.file.get_batch(0) if self.file.num_record_batches else None
        self.batch_rows = first.num_rows if first is not None else 1
        self.at, self.ids = -1, np.zeros(0, np.uint16)

    def _flat(self, batch: int) -> np.ndarray:
        if self.at != batch:
            self.at, self.ids = batch, self.file.get_batch(batch).column("ids").flatten().to_numpy(zero_copy_only=True)
        return self.ids

    def sequence(self, i: int) -> tuple[np.ndarray, np.ndarray]:
        """ids and mask of row i."""
        b, r = divmod(i, self.batch_rows)
        mask = self.file.get_batch(b).column("mask").slice(r, 1).flatten().to_numpy(zero_copy_only=False)
        return self._flat(b)[r * self.length : (r + 1) * self.length], mask

    def tokens(self, start: int, n: int) -> np.ndarray:
        """n ids from the start-th on; a view where they lie in one batch."""
        per, out = self.batch_rows * self.length, []
        while n > 0:
            b, at = divmod(start, per)
            part = self._flat(b)[at : at + n]
            out.append(part)
            start, n = start + len(part), n - len(part)
        return out[0] if len(out) == 1 else np.concatenate([*out, self.ids[:0]])

    def __enter__(self):
        return self

    def __exit__(self, *_):
        self.ids = self.ids[:0]
        self.source.close()


def write_token_files(df: DataFrame, folder: str, id_col: str = "doc_id", text_col: str = "text", tokenizer: str | None = None, length: int = SEQUENCE, docs_per_shard: int = 20_000) -> DataFrame:
    """Writes every whole text's ids in ascending id order; returns a row for each shard: part, ids, index, first, n_docs, n_tokens, start.

    Null texts are empty documents; null ids come first; equal ids follow each
    other by a hash of their text and their place in the table, so that a
    repeated id is no single shard. ``start`` counts the ids of all shards
    before, which ``part`` orders. A task that
    is run again writes files of another name, and only those that the shard
    table names count.
    """
    tokenizer = tokenizer or default_tokenizer()
    rows = df.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("t"))
    n = max(1, -(-rows.select("doc_id").count() // docs_per_shard))
    order = [F.asc_nulls_first("doc_id"), F.asc("h"), F.asc("at")]
    rows = rows.withColumn("h", F.xxhash64("t")).withColumn("at", F.monotonically_increasing_id()).repartitionByRange(n, *order).sortWithinPartitions(*order).select("doc_id", "t")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec, writer, docs, first = encoder(tokenizer), None, 0, None
        for b in batches:
            ids, texts = b.column("doc_id").to_pylist(), b.column("t").to_pylist()
            if not ids:
                continue
            if writer is None:
                name = f"{folder}/{uuid.uuid4().hex}"
                writer, first = SequenceWriter(f"{name}.ids.arrow", codec.dtype, length), ids[0]
                sink = _open(f"{name}.index.arrow", "w")
                index = pa.ipc.new_file(sink, _INDEX)
            for at in range(0, len(texts), 500):
                encoded = codec.documents(texts[at : at + 500])
                sizes = np.fromiter(map(len, encoded), np.int64, len(encoded))
                index.write_batch(pa.record_batch([pa.array(ids[at : at + 500], pa.int64()), pa.array(writer.total + np.cumsum(sizes) - sizes), pa.array(sizes)], schema=_INDEX))
                writer.add(np.concatenate(encoded))
                docs += len(encoded)
        if writer is not None:
            writer.close()
            index.close()
            sink.close()
            yield pa.RecordBatch.from_pydict({"part": [TaskContext.get().partitionId()], "ids": [f"{name}.ids.arrow"], "index": [f"{name}.index.arrow"], "first": pa.array([first], pa.int64()), "n_docs": [docs], "n_tokens": [writer.total]})

    # tasks of one stage are numbered in the order of their ranges
    shards = written(rows.mapInArrow(run, "part long, ids string, index string, first long, n_docs long, n_tokens long"), "shards")
    from pyspark.sql import Window

    # a row for each shard, not for each document
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    return shards.withColumn("start", F.coalesce(F.sum("n_tokens").over(before), F.lit(0)))


def read_token_files(shards: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, from the files alone; a task for each shard."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, index, start in rows_of(batches, ["ids", "index", "start"]):
            with SequenceFile(ids) as shard, _open(index, "r") as source:
                docs = pa.ipc.open_file(source)
                for k in range(docs.num_record_batches):
                    b = docs.get_batch(k)
                    sums = [crc32(shard.tokens(s, n)) for s, n in zip(b.column("start").to_pylist(), b.column("n_tokens").to_pylist(), strict=True)]
                    yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(b.column("start").to_numpy() + start), b.column("n_tokens"), pa.array(sums, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    # dealt by name: a few rows, each of which stands for a file
    return shards.select("ids", "index", "start").repartition(_tasks(shards.sparkSession), "ids").mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def _tasks(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def token_files_round_trip(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", tokenizer: str | None = None) -> DataFrame:
    """Writes the files to the shared folder and reads every document back."""
    return read_token_files(write_token_files(df, fresh_path(df.sparkSession, "tokens"), id_col, text_col, tokenizer))
