"""Token ids in Arrow IPC files of equal-length sequences.

Documents are range-partitioned and sorted by id (equal ids by a hash of their text, then
the text), into as many shards as keep one near ``SHARD_BYTES``, whatever the input; they
are tokenized, and each partition writes one shard: an Arrow file whose record batches hold ``input_ids``
(fixed-size list of unsigned 16- or 32-bit ids, by vocabulary size) and ``mask``
(fixed-size list of booleans, false on the padding of the shard's last sequence).
A second small Arrow file lists the shard's documents with their first position and
length.  A memory-mapped reader reaches sequence i, or any document, at computed
offsets and copies nothing but documents that straddle two record batches.

Files are written under a name of the task's attempt and then moved, so a task that
is run again leaves one shard.  The shard list is the only thing the driver sees.

Edge cases: null or empty text is the end id alone; null doc_id comes first; equal
ids, however many, are dealt to shards by their texts, equal rows by their place in the
input; an empty table gives no shard and no rows.
"""

from __future__ import annotations

import json
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lossygrad.llm import common, tokenizer

SEQUENCE = 2048
#: Sequences in a record batch.
BATCH_SEQUENCES = 256
#: Text of a shard, each document counted ``DOC_BYTES`` longer.
SHARD_BYTES, DOC_BYTES = 32 << 20, 64
#: Documents in a record batch of the index.
INDEX_ROWS = 1 << 14
SHARDS = "shard long, path string, n_tokens long, n_docs long"
DOCS = "doc_id long, start long, n_tokens long, ids_crc32 long"


def open_folder(uri: str) -> tuple[fs.FileSystem, str]:
    """The file system of a URI or plain path, and the path there."""
    if "://" not in uri and not uri.startswith("file:"):
        return fs.LocalFileSystem(), uri
    if uri.startswith("file:") and not uri.startswith("file://"):
        uri = "file://" + uri.removeprefix("file:")
    return fs.FileSystem.from_uri(uri)


def shard_schema(sequence: int, id_type: pa.DataType, **about: object) -> pa.Schema:
    return pa.schema(
        [
            pa.field("input_ids", pa.list_(pa.field("item", id_type, nullable=False), sequence), nullable=False),
            pa.field("mask", pa.list_(pa.field("item", pa.bool_(), nullable=False), sequence), nullable=False),
        ],
        metadata={"tokens": json.dumps({"sequence": sequence} | about)},
    )


class ShardWriter:
    """Collects ids and writes record batches of ``BATCH_SEQUENCES`` sequences."""

    def __init__(self, sink, sequence: int, dtype: np.dtype):
        self.sequence, self.dtype = sequence, np.dtype(dtype)
        self.id_type = pa.from_numpy_dtype(self.dtype)
        self.schema = shard_schema(sequence, self.id_type, batch_sequences=BATCH_SEQUENCES)
        self.writer = pa.ipc.new_file(sink, self.schema)
        self.parts: list[bytes] = []
        self.held, self.total = 0, 0

    def add(self, ids: bytes) -> None:
        """``ids``: little-endian unsigned 32-bit."""
        self.parts.append(ids)
        n = len(ids) // 4
        self.held += n
        self.total += n
        if self.held >= self.sequence * BATCH_SEQUENCES:
            self._flush(False)

    def _flush(self, last: bool) -> None:
        flat = np.frombuffer(b"".join(self.parts), dtype="<u4")
        size = self.sequence * BATCH_SEQUENCES
        whole = len(flat) // size * size
        for at in range(0, whole, size):
            self._write(flat[at : at + size], size)
        rest = flat[whole:]
        self.parts, self.held = [rest.tobytes()] if len(rest) else [], len(rest)
        if last and len(rest):
            padded = -(-len(rest) // self.sequence) * self.sequence
            self._write(rest, padded)

    def _write(self, ids: np.ndarray, size: int) -> None:
        values, mask = np.zeros(size, self.dtype), np.zeros(size, bool)
        values[: len(ids)] = ids
        mask[: len(ids)] = True
        arrays = [
            pa.FixedSizeListArray.from_arrays(pa.array(v), type=self.schema.field(i).type)
            for i, v in enumerate((values, mask))
        ]
        self.writer.write_batch(pa.RecordBatch.from_arrays(arrays, schema=self.schema))

    def close(self) -> None:
        self._flush(True)
        self.writer.close()


class ShardReader:
    """Random access to a shard; local files are memory-mapped."""

    def __init__(self, uri: str):
        files, path = open_folder(uri)
        self.source = pa.memory_map(path) if isinstance(files, fs.LocalFileSystem) else files.open_input_file(path)
        self.file = pa.ipc.open_file(self.source)
        about = json.loads(self.file.schema.metadata[b"tokens"])
        self.sequence, self.per_batch = about["sequence"], about["batch_sequences"]

        self.held: tuple[int, np.ndarray, pa.Array] | None = None  # the batch last read

    def _batch(self, batch: int) -> tuple[np.ndarray, pa.Array]:
        """All ids of a record batch, as a view of the file, and its masks."""
        if self.held is None or self.held[0] != batch:
            b = self.file.get_batch(batch)
            self.held = batch, b.column(0).flatten().to_numpy(zero_copy_only=True), b.column(1)
        return self.held[1:]

    def sequence_at(self, i: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids (a view of the file) and mask of sequence i."""
        b, at = divmod(i, self.per_batch)
        ids, mask = self._batch(b)
        return ids[at * self.sequence : (at + 1) * self.sequence], mask[at].values.to_numpy(zero_copy_only=False)

    def views(self, start: int, length: int) -> Iterator[np.ndarray]:
        """The ids of a span as views, one for each record batch it touches."""
        size = self.sequence * self.per_batch
        while length:
            b, at = divmod(start, size)
            n = min(length, size - at)
            yield self._batch(b)[0][at : at + n]
            start, length = start + n, length - n


def write_shards(docs: DataFrame, folder: str, vocabulary_path: str | None = None, end_id: int = 2, sequence: int = SEQUENCE, shard_bytes: int = SHARD_BYTES) -> list[dict]:
    """Writes the files; returns a row for each shard, in document order."""
    spark = common.session_of(docs)
    common.ship_package(spark)
    text = tokenizer.vocabulary(vocabulary_path)
    content = spark.sparkContext.broadcast(text)
    from tokenizers import Tokenizer

    size = Tokenizer.from_str(text).get_vocab_size(with_added_tokens=True)
    dtype = "<u2" if max(size, end_id + 1) <= 1 << 16 else "<u4"
    files, root = open_folder(folder)
    files.create_dir(root, recursive=True)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = tokenizer.encoder(content.value, end_id)
        context = TaskContext.get()
        shard, attempt = context.partitionId(), context.taskAttemptId()
        store, base = open_folder(folder)
        rough = f"{base}/.attempt-{shard:06d}-{attempt}"
        final = f"{base}/shard-{shard:06d}"
        writer, names, sizes = None, [], []
        for batch in batches:
            if not batch.num_rows:
                continue
            if writer is None:
                sink = store.open_output_stream(f"{rough}.arrow")
                writer = ShardWriter(sink, sequence, dtype)
            names += batch.column("doc_id").to_pylist()
            for _, raw, ends in enc.rounds(batch.column("text").cast(pa.string())):
                sizes += (np.diff(ends) // 4).tolist()
                writer.add(raw)
        if writer is None:
            return
        writer.close()
        sink.close()
        starts = np.concatenate([[0], np.cumsum(sizes)[:-1]]).astype(np.int64)
        index = pa.table({"doc_id": pa.array(names, pa.int64()), "start": starts, "n_tokens": pa.array(sizes, pa.int64())})
        with store.open_output_stream(f"{rough}.index.arrow") as out, pa.ipc.new_file(out, index.schema) as w:
            w.write_table(index, max_chunksize=INDEX_ROWS)
        for kind in (".index.arrow", ".arrow"):
            store.move(rough + kind, final + kind)
        row = {"shard": [shard], "path": [f"{folder}/shard-{shard:06d}"], "n_tokens": [writer.total], "n_docs": [len(sizes)]}
        yield pa.RecordBatch.from_pydict(row, schema=pa.schema([("shard", pa.int64()), ("path", pa.string()), ("n_tokens", pa.int64()), ("n_docs", pa.int64())]))

    rows = common.only(docs, "doc_id", "text")
    bytes_ = rows.agg(F.sum(F.coalesce(F.octet_length("text"), F.lit(0)) + F.lit(DOC_BYTES).cast("long"))).first()[0] or 0
    parts = max(1, -(-bytes_ // shard_bytes))
    # The range's sample holds hashes instead of texts.
    keyed = rows.select("doc_id", "text", F.xxhash64("text").alias("drawn"), F.monotonically_increasing_id().alias("row"))
    order = [F.col("doc_id").asc_nulls_first(), F.col("drawn")]
    ordered = keyed.repartitionByRange(parts, *order, F.col("row")).sortWithinPartitions(*order, F.col("text").asc_nulls_first()).select("doc_id", "text")
    # Sorted here: ordering by Spark would sample, and so run, the writing tasks twice.
    return sorted((r.asDict() for r in ordered.mapInArrow(run, SHARDS).collect()), key=lambda s: s["shard"])


def read_documents(spark: SparkSession, shards: list[dict]) -> DataFrame:
    """Reads every shard back: a row for each document, with its place among all ids."""
    common.ship_package(spark)
    before, rows = 0, []
    for s in shards:
        rows.append((s["path"], before))
        before += s["n_tokens"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path, base in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                reader = ShardReader(f"{path}.arrow")
                store, at = open_folder(f"{path}.index.arrow")
                with store.open_input_file(at) as f:
                    listed = pa.ipc.open_file(f)
                    for i in range(listed.num_record_batches):
                        index = listed.get_batch(i)
                        crcs = []
                        for start, n in zip(index["start"].to_pylist(), index["n_tokens"].to_pylist(), strict=True):
                            crc = 0
                            for view in reader.views(start, n):
                                crc = zlib.crc32(view.astype("<u4"), crc)
                            crcs.append(crc)
                        yield pa.RecordBatch.from_arrays(
                            [index["doc_id"], pa.array(np.asarray(index["start"]) + base, pa.int64()), index["n_tokens"], pa.array(crcs, pa.int64())],
                            names=["doc_id", "start", "n_tokens", "ids_crc32"],
                        )

    if not rows:
        return spark.createDataFrame([], DOCS)
    listed = spark.createDataFrame(rows, "path string, base long").repartition(len(rows))
    return listed.mapInArrow(run, DOCS)


def encode_and_read_back(docs: DataFrame, vocabulary_path: str | None = None, end_id: int = 2, sequence: int = SEQUENCE) -> DataFrame:
    spark = common.session_of(docs)
    folder = common.fresh_path(spark, "tokens")
    return read_documents(spark, write_shards(docs, folder, vocabulary_path, end_id, sequence))
