"""Token ids in length-delimited binary record files, with a separate offset index.

A record is: length (unsigned 64-bit), masked checksum of the length's bytes,
payload, masked checksum of the payload.  The mask keeps a checksum that is
itself stored as data from checking out.  A payload is the document id (signed
64-bit, and a byte that is 1 where the id is null), the width of an id in
bytes, and the ids, all little-endian.  Ids below 65,536 take two bytes.

Files are written by the executors to the shared folder under names of their
own, and named in a manifest that is itself a table: a task that is run again
leaves a file that no manifest names, so readers see each document once.  The
index holds the byte offset and token count of each record, for shuffled reads.
"""

from __future__ import annotations

import struct
import uuid
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from overlapix.llm.byte_bpe import encoder, small_parts
from overlapix.llm.storage import materialise, new_path

#: Rotation and offset of the mask.
MASK_ROTATION, MASK_DELTA = 15, 0xA282EAD8
HEAD = struct.Struct("<qBB")
FRAME = struct.Struct("<QI")
#: A file is closed beyond this size.
FILE_BYTES = 64 << 20
MANIFEST = "part int, seq int, data string, offsets string, n_docs bigint, n_tokens bigint, n_bytes bigint"


def masked_checksum(data: bytes) -> int:
    c = zlib.crc32(data)
    return (((c >> MASK_ROTATION) | (c << (32 - MASK_ROTATION))) + MASK_DELTA) & 0xFFFFFFFF


def frame(doc_id: int | None, ids: np.ndarray) -> bytes:
    width = 2 if not len(ids) or ids.max() < 1 << 16 else 4
    payload = HEAD.pack(doc_id or 0, doc_id is None, width) + ids.astype(f"<u{width}").tobytes()
    length = struct.pack("<Q", len(payload))
    return length + struct.pack("<I", masked_checksum(length)) + payload + struct.pack("<I", masked_checksum(payload))


def unframe(source, offset: int | None = None) -> tuple[int | None, np.ndarray] | None:
    """The record at the stream's place (or at ``offset``); None at the end.
    Raises ValueError where a checksum fails or the file stops short."""
    if offset is not None:
        source.seek(offset)
    head = source.read(FRAME.size)
    if not head:
        return None
    if len(head) < FRAME.size:
        raise ValueError("record cut short")
    size, check = FRAME.unpack(head)
    if masked_checksum(bytes(head[:8])) != check:
        raise ValueError("length checksum")
    body = source.read(size + 4)
    if len(body) < size + 4 or masked_checksum(bytes(body[:size])) != struct.unpack("<I", body[size:])[0]:
        raise ValueError("payload checksum")
    doc_id, missing, width = HEAD.unpack(body[: HEAD.size])
    return None if missing else doc_id, np.frombuffer(body[HEAD.size : size], f"<u{width}").astype("<u4")


def _open(uri: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(uri if "://" in uri else uri.replace("file:/", "file:///", 1))


class _Files:
    """Rolls data and index files; collects a manifest row for each pair."""

    def __init__(self, folder: str) -> None:
        self.fs, self.path = _open(folder)
        self.fs.create_dir(self.path, recursive=True)
        self.folder, self.rows, self.data = folder, [], None
        self.part = TaskContext.get().partitionId()

    def add(self, doc_id: int | None, ids: np.ndarray) -> None:
        if self.data is None:
            stem = f"part-{self.part:06d}-{len(self.rows):04d}-{uuid.uuid4().hex[:8]}"
            self.names = (f"{stem}.rec", f"{stem}.idx")
            self.data, self.index = (self.fs.open_output_stream(f"{self.path}/{n}", buffer_size=1 << 20) for n in self.names)
            self.n_docs = self.n_tokens = self.n_bytes = 0
        raw = frame(doc_id, ids)
        self.data.write(raw)
        self.index.write(struct.pack("<QI", self.n_bytes, len(ids)))
        self.n_docs, self.n_tokens, self.n_bytes = self.n_docs + 1, self.n_tokens + len(ids), self.n_bytes + len(raw)
        if self.n_bytes >= FILE_BYTES:
            self.close()

    def close(self) -> None:
        if self.data is not None:
            self.data.close()
            self.index.close()
            self.rows.append((self.part, len(self.rows), *(f"{self.folder}/{n}" for n in self.names), self.n_docs, self.n_tokens, self.n_bytes))
            self.data = None


def _write_batches(path: str, end_id: int, folder: str) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tool, files = encoder(path), _Files(folder)
        for batch in batches:
            for part in small_parts(batch, 1):
                encoded = tool.encode(x or "" for x in part.column(1).to_pylist())
                for doc_id, raw in zip(part.column(0).to_pylist(), encoded, strict=True):
                    files.add(doc_id, np.append(np.frombuffer(raw, "<u4"), np.uint32(end_id)))
        files.close()
        if files.rows:
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*files.rows, strict=True), [pa.int32(), pa.int32(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.int64()], strict=True)], names=["part", "seq", "data", "offsets", "n_docs", "n_tokens", "n_bytes"])

    return run


def write_records(docs: DataFrame, path: str, end_id: int = 2, text: str = "text", doc_id: str = "doc_id", folder: str | None = None) -> DataFrame:
    """Encode whole texts and write them in ascending ``doc_id`` order; returns the manifest.

    Null texts count as empty: a record with the end id alone.  Null ids come
    first; rows that share an id follow one another by text.  The manifest lists
    files in order (``part``, ``seq``); an empty table gives no file.
    """
    spark = docs.sparkSession
    folder = folder or new_path(spark, "records")
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    rows = docs.select(F.col(doc_id).cast("bigint").alias("doc_id"), F.col(text).cast("string").alias("text"))
    dealt = rows.repartitionByRange(parts, F.col("doc_id").asc_nulls_first()).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "text")
    return materialise(dealt.mapInArrow(_write_batches(path, end_id, folder), MANIFEST), "manifest")


def _read_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for data, base in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            fs, name = _open(data)
            rows: list[tuple] = []
            with fs.open_input_stream(name, buffer_size=1 << 20) as source:
                while (record := unframe(source)) is not None:
                    doc_id, ids = record
                    rows.append((doc_id, base, len(ids), zlib.crc32(ids.tobytes())))
                    base += len(ids)
                    if len(rows) == 10_000:
                        yield _digest_batch(rows)
                        rows = []
            if rows:
                yield _digest_batch(rows)


def _digest_batch(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*rows, strict=True)], names=["doc_id", "start", "n_tokens", "ids_crc32"])


def file_starts(manifest: DataFrame) -> DataFrame:
    """Adds ``base``: the tokens in all files before.  One row a file passes through the window."""
    before = Window.orderBy("part", "seq").rowsBetween(Window.unboundedPreceding, -1)
    return manifest.withColumn("base", F.coalesce(F.sum("n_tokens").over(before), F.lit(0)).cast("bigint"))


def read_digests(manifest: DataFrame) -> DataFrame:
    """Read every file back, checking all checksums: ``(doc_id, start, n_tokens, ids_crc32)``."""
    parts = int(manifest.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return file_starts(manifest).select("data", "base").repartition(parts).mapInArrow(_read_batches, "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint")


def read_record(spark: SparkSession, data: str, index: str, row: int) -> tuple[int | None, np.ndarray] | None:
    """One record by its place in the file, found through the offset index."""
    fs, name = _open(index)
    with fs.open_input_file(name) as source:
        source.seek(12 * row)
        offset, _ = struct.unpack("<QI", source.read(12))
    fs, name = _open(data)
    with fs.open_input_file(name) as source:
        return unframe(source, offset)
