"""Token ids as Arrow IPC files of fixed-size lists, with masks and a document index.

Documents are range-partitioned and sorted by id; each range becomes one token file (record batches of
``fixed_size_list`` sequences of 16-bit ids, or 32-bit for a vocabulary over 65,536, and of mask bits; the last
sequence is padded) and one index
file (doc_id, start in the file, n_tokens). Files are named by task attempt; only those in the manifest count, which
Spark commits, so a lost or repeated task leaves at most an unused file. Any store that Arrow knows can hold them.
"""

from __future__ import annotations

import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyarrow import fs, ipc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import shared_dir, stage, table
from .tokens import token_ids, tokenizer

SEQUENCE = 1024
BATCH_SEQUENCES = 256
END_ID = 1
MANIFEST = "range int, tokens string, docs string, n_docs long, n_tokens long"


def token_schema(length: int, wide: bool) -> pa.Schema:
    return pa.schema([("ids", pa.list_(pa.uint32() if wide else pa.uint16(), length)), ("mask", pa.list_(pa.bool_(), length))])


class TokenWriter:
    """Streams ids into equal-length sequences; holds one record batch."""

    def __init__(self, sink, length: int = SEQUENCE, wide: bool = False):
        self.length, self.block, self.kind = length, length * BATCH_SEQUENCES, np.uint32 if wide else np.uint16
        self.schema = token_schema(length, wide)
        self.out = ipc.new_file(sink, self.schema)
        self.held, self.size, self.total = [], 0, 0

    def add(self, ids: np.ndarray) -> None:
        self.total += len(ids)
        while len(ids):
            part = ids[: self.block - self.size]
            self.held.append(part)
            self.size += len(part)
            ids = ids[len(part) :]
            if self.size == self.block:
                self._flush()

    def _flush(self) -> None:
        if self.size:
            rows = -(-self.size // self.length)
            values, mask = np.zeros(rows * self.length, self.kind), np.zeros(rows * self.length, bool)
            values[: self.size], mask[: self.size] = np.concatenate(self.held), True
            lists = [pa.FixedSizeListArray.from_arrays(pa.array(x), self.length) for x in (values, mask)]
            self.out.write_batch(pa.RecordBatch.from_arrays(lists, schema=self.schema))
            self.held, self.size = [], 0

    def close(self) -> None:
        self._flush()
        self.out.close()


class TokenFile:
    """Random access to a token file: sequences and masks are slices of the file's buffers (memory-mapped where local)."""

    def __init__(self, uri: str):
        store, path = fs.FileSystem.from_uri(uri)
        self.source = pa.memory_map(path) if isinstance(store, fs.LocalFileSystem) else store.open_input_file(path)
        self.file = ipc.open_file(self.source)
        self.length = self.file.schema.field("ids").type.list_size

    def __len__(self) -> int:
        n = self.file.num_record_batches
        return (n - 1) * BATCH_SEQUENCES + self.file.get_batch(n - 1).num_rows if n else 0

    def _row(self, name: str, i: int) -> pa.Array:
        batch = self.file.get_batch(i // BATCH_SEQUENCES)
        return batch.column(name).flatten().slice(i % BATCH_SEQUENCES * self.length, self.length)

    def sequence(self, i: int) -> np.ndarray:
        """A view of the ids of sequence ``i``; nothing is copied."""
        return self._row("ids", i).to_numpy()

    def mask(self, i: int) -> pa.BooleanArray:
        """A slice of the mask bits of sequence ``i``; nothing is copied."""
        return self._row("mask", i)

    def blocks(self) -> Iterator[np.ndarray]:
        """The ids of each record batch, without padding."""
        for i in range(self.file.num_record_batches):
            batch = self.file.get_batch(i)
            yield batch.column("ids").flatten().to_numpy()[: batch.column("mask").flatten().true_count]

    def spans(self, bounds: Iterator[tuple[int, int]]) -> Iterator[Iterator[np.ndarray]]:
        """For each (start, length), in ascending order and end to end, the arrays that make it up."""
        blocks, block = self.blocks(), np.zeros(0, np.uint16)
        for _, n in bounds:
            parts = []
            while n:
                if not len(block):
                    block = next(blocks)
                parts.append(block[:n])
                block = block[len(parts[-1]) :]
                n -= len(parts[-1])
            yield iter(parts)


def write_tokens(
    df: DataFrame, tokenizer_file: str, out_dir: str, end_id: int = END_ID, length: int = SEQUENCE, id_col: str = "doc_id", text_col: str = "text"
) -> DataFrame:
    """Write the files now; return the manifest (range, tokens, docs, n_docs, n_tokens), a staged table.

    A null or empty text is the end id alone. Rows go in ascending id order, nulls first; rows with one id by text, and
    repeated rows are all written. An empty table writes no files. Other columns are ignored.
    """
    spark = df.sparkSession
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    spread = F.xxhash64("__text")
    rows = df.select(F.col(id_col).cast("long").alias("__id"), F.col(text_col).alias("__text"))
    ranged = rows.repartitionByRange(n, "__id", spread).sortWithinPartitions("__id", "__text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task = TaskContext.get()
        name = f"{out_dir}/range-{task.partitionId():06d}-{task.taskAttemptId()}-{uuid.uuid4().hex[:8]}"
        writer = index = None
        count = 0
        for batch in batches:
            if not batch.num_rows:
                continue
            if writer is None:
                store, path = fs.FileSystem.from_uri(name)
                store.create_dir(path.rpartition("/")[0], recursive=True)
                sink, side = store.open_output_stream(f"{path}.arrow"), store.open_output_stream(f"{path}.docs.arrow")
                writer = TokenWriter(sink, length, tokenizer(tokenizer_file).library.get_vocab_size() > 1 << 16 or end_id >= 1 << 16)
                index = ipc.new_file(side, pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64())]))
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                starts, sizes = [], []
                for ids in token_ids(tokenizer_file, part.column(1).to_pylist(), end_id):
                    starts.append(writer.total)
                    sizes.append(len(ids))
                    writer.add(ids)
                index.write_batch(pa.RecordBatch.from_arrays([part.column(0), pa.array(starts, pa.int64()), pa.array(sizes, pa.int64())], schema=index_schema))
                count += part.num_rows
        if writer is not None:
            writer.close()
            index.close()
            sink.close()
            side.close()
            yield pa.RecordBatch.from_pydict(
                {"range": pa.array([task.partitionId()], pa.int32()), "tokens": [f"{name}.arrow"], "docs": [f"{name}.docs.arrow"], "n_docs": pa.array([count], pa.int64()), "n_tokens": pa.array([writer.total], pa.int64())}
            )

    index_schema = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64())])
    return stage(ranged.mapInArrow(run, MANIFEST), "manifest")


def read_documents(manifest: DataFrame) -> DataFrame:
    """One row for each document, read back from the files: doc_id, start (over all files), n_tokens, ids_crc32."""
    spark = manifest.sparkSession
    before = Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)  # one row a file
    files = manifest.withColumn("base", F.coalesce(F.sum("n_tokens").over(before), F.lit(0)))
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                store, path = fs.FileSystem.from_uri(row["docs"])
                with store.open_input_file(path) as side:
                    index = ipc.open_file(side)
                    bounds = ((s, k) for i in range(index.num_record_batches) for s, k in zip(*(index.get_batch(i).column(c).to_pylist() for c in ("start", "n_tokens")), strict=True))
                    spans = TokenFile(row["tokens"]).spans(bounds)
                    for i in range(index.num_record_batches):
                        docs = index.get_batch(i)
                        sums = []
                        for _ in range(docs.num_rows):
                            crc = 0
                            for part in next(spans):
                                crc = zlib.crc32(part.astype(np.uint32), crc)
                            sums.append(crc)
                        starts = docs.column("start").to_numpy() + row["base"]
                        yield pa.RecordBatch.from_arrays(
                            [docs.column("doc_id"), pa.array(starts), docs.column("n_tokens"), pa.array(sums, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"]
                        )

    return files.repartition(n, "tokens").mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def op6_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    out = f"{shared_dir(spark)}/tokens-{uuid.uuid4().hex[:12]}"
    return read_documents(write_tokens(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"), out))
