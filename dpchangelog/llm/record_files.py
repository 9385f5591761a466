"""Operator 1: token ids in length-delimited binary records with masked checksums, and a separate offset index.

File format. A data file is a sequence of frames, each followed by one newline byte (the writer is Spark's line writer, so
the files go through Hadoop's commit protocol: a lost or repeated task leaves no half file, and any Hadoop store works):

    length   8 bytes  little-endian unsigned, bytes of the payload
    check    4 bytes  masked CRC-32 of the length field
    payload
    check    4 bytes  masked CRC-32 of the payload
    newline  1 byte

    payload: doc_id (8 bytes, signed), flags (1 byte; 1: doc_id is null), id width (1 byte: 2 or 4), ids

A checksum c is stored as ((c >> 15 | c << 17) + 0xA282EAD8) mod 2^32, so a checksum over data that holds checksums stays
useful. Frames stand in ascending doc_id order (null first), within files and across files in name order.

A file holds frames of FILE_BYTES at most, or one longer frame; its name tells its place (file=<n>/part-<partition>: partitions in
order, and files in order within a partition).

Index: a Parquet table (shard, seq, doc_id, start, n_tokens, byte_offset, byte_length, ids_crc32), one row a frame.
"""

from __future__ import annotations

import re
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .byte_bpe import byte_bpe
from .common import discard, prepare, quoted, shared_path

HEAD, TAIL = struct.Struct("<QI"), struct.Struct("<I")
LEAD = struct.Struct("<qBB")
#: Bytes of frames in one file at most (a longer frame has a file of its own), so that one reader can hold a file.
FILE_BYTES = 64 << 20


def masked(data: bytes) -> int:
    c = zlib.crc32(data)
    return ((c >> 15 | c << 17) + 0xA282EAD8) & 0xFFFFFFFF


def record(doc_id: int | None, width: int, ids: bytes) -> bytes:
    return frame(LEAD.pack(doc_id or 0, doc_id is None, width) + ids)


def frame_size(payload: bytes) -> int:
    return HEAD.size + len(payload) + TAIL.size


def frame(payload: bytes) -> bytes:
    n = struct.pack("<Q", len(payload))
    return b"".join((n, TAIL.pack(masked(n)), payload, TAIL.pack(masked(payload))))


def frames(content: bytes) -> Iterator[tuple[int, bytes]]:
    """(offset, payload) of each frame; a damaged file raises ValueError."""
    at, view, end = 0, memoryview(content), len(content)
    while at < end:
        if end - at < HEAD.size:
            raise ValueError(f"frame at {at} is cut off")
        n, check = HEAD.unpack_from(view, at)
        if masked(bytes(view[at : at + 8])) != check:
            raise ValueError(f"length at {at} does not match its checksum")
        to = at + HEAD.size + n
        if to + TAIL.size + 1 > end:
            raise ValueError(f"frame at {at} is cut off")
        payload = bytes(view[at + HEAD.size : to])
        if masked(payload) != TAIL.unpack_from(view, to)[0]:
            raise ValueError(f"payload at {at} does not match its checksum")
        yield at, payload
        at = to + TAIL.size + 1


def ids_of(payload: bytes) -> tuple[int | None, np.ndarray]:
    doc_id, flags, width = LEAD.unpack_from(payload)
    return None if flags & 1 else doc_id, np.frombuffer(payload, f"<u{width}", offset=LEAD.size)


def write_records(docs: DataFrame, folder: str, vocabulary: str, end_id: int = 2, id_col: str = "doc_id", text_col: str = "text") -> None:
    """Encode every whole text, append end_id, and write frames in ascending id order.

    Null text counts as empty (one record with the end id alone). Repeated ids each get a record, one after another in
    no stated order, and may span files. Null ids come first. An empty table writes no frames. Other columns are not read.
    """
    prepare(docs.sparkSession)
    rows = docs.select(F.col(quoted(id_col)).cast("long").alias("doc_id"), F.col(quoted(text_col)).alias("text"))
    spread = rows.repartitionByRange(F.col("doc_id").asc_nulls_first(), F.xxhash64("text"))  # the hash parts ties

    def encode(batches):
        """Rows arrive in order; they are numbered, and given to the next file once one is full."""
        bpe = byte_bpe(vocabulary)
        last = np.array([end_id], bpe.kind).tobytes()
        file = held = seq = 0
        for b in batches:
            out, files = [], []
            for i, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                out.append(record(i, bpe.width, bpe.encode(t) + last))
                if held and held + len(out[-1]) + 1 > FILE_BYTES:
                    file, held = file + 1, 0
                held += len(out[-1]) + 1
                files.append(file)
            yield pa.RecordBatch.from_arrays([pa.array(files, pa.int32()), pa.array(range(seq, seq + len(out)), pa.int64()), pa.array(out, pa.binary())], ["file", "seq", "frame"])
            seq += len(out)

    ordered = spread.sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "text")
    framed = ordered.mapInArrow(encode, "file int, seq long, frame binary").sortWithinPartitions("file", "seq")
    framed.select(F.col("frame").cast("string").alias("value"), "file").write.option("lineSep", "\n").partitionBy("file").text(folder)


_PART = re.compile(r"file=(\d+)/part-(\d+)-[^/]*\.txt$")


def _files(spark: SparkSession, folder: str) -> DataFrame:
    return spark.read.format("binaryFile").option("pathGlobFilter", "part-*.txt").option("recursiveFileLookup", "true").load(folder)


def index_records(spark: SparkSession, folder: str, index_folder: str | None = None) -> DataFrame:
    """Read the files back, check every frame, and return (and write, if a folder is given) the offset index.

    start counts the ids of all frames before a frame. Only one row a file passes through one task for it.
    """
    files = _files(spark, folder).select("path", "content")

    def read(batches):
        for b in batches:
            for path, content in zip(b.column(0), b.column(1), strict=True):
                m = _PART.search(path.as_py())
                shard, rows, before = (int(m[2]) << 24) + int(m[1]), [], 0
                for seq, (at, payload) in enumerate(frames(content.as_py())):
                    doc_id, ids = ids_of(payload)
                    rows.append((shard, seq, doc_id, before, len(ids), at, frame_size(payload), zlib.crc32(ids.astype("<u4").tobytes())))
                    before += len(ids)
                for k in range(0, len(rows), 20_000):
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows[k : k + 20_000], strict=True), [pa.int64()] * 8, strict=True)], names)

    names = ["shard", "seq", "doc_id", "before", "n_tokens", "byte_offset", "byte_length", "ids_crc32"]
    found = files.mapInArrow(read, ", ".join(f"{n} long" for n in names))
    raw = shared_path(spark, "frames")
    found.write.parquet(raw)
    found = spark.read.schema(found.schema).parquet(raw)
    totals = found.groupBy("shard").agg(F.sum("n_tokens").alias("n"))  # one row a file
    starts = totals.select("shard", (F.sum("n").over(Window.orderBy("shard")) - F.col("n")).alias("shard_start"))
    index = found.join(starts, "shard").select("doc_id", (F.col("shard_start") + F.col("before")).alias("start"), "n_tokens", "ids_crc32", "shard", "seq", "byte_offset", "byte_length")
    if index_folder:
        index.write.parquet(index_folder)
        discard(spark, [raw])
        return spark.read.schema(index.schema).parquet(index_folder)
    return index


def read_records(spark: SparkSession, folder: str) -> DataFrame:
    """(doc_id, ids) of every frame."""

    def read(batches):
        for b in batches:
            for content in b.column(0):
                out = [ids_of(p) for _, p in frames(content.as_py())]
                for k in range(0, len(out), 1000):
                    part = out[k : k + 1000]
                    yield pa.RecordBatch.from_arrays([pa.array([i for i, _ in part], pa.int64()), pa.array([x.astype(np.int32) for _, x in part], pa.list_(pa.int32()))], ["doc_id", "ids"])

    return _files(spark, folder).select("content").mapInArrow(read, "doc_id long, ids array<int>")


def shuffled_order(index: DataFrame, seed: int) -> DataFrame:
    """The index in a random order that depends on the seed alone: readers seek to byte_offset in turn."""
    return index.withColumn("draw", F.xxhash64(F.lit(seed), "shard", "seq")).orderBy("draw", "shard", "seq")


def read_at(path: str, byte_offset: int, byte_length: int) -> tuple[int | None, np.ndarray]:
    """One frame by seeking, from any file system that pyarrow opens."""
    from pyarrow import fs

    store, at = fs.FileSystem.from_uri(path)
    with store.open_input_file(at) as f:
        f.seek(byte_offset)
        return ids_of(next(frames(f.read(byte_length) + b"\n"))[1])


def op1(spark: SparkSession, docs: DataFrame, vocabulary: str, end_id: int = 2) -> DataFrame:
    """Write, index and return (doc_id, start, n_tokens, ids_crc32, ...) as read from the files."""
    prepare(spark)
    folder = shared_path(spark, "records")
    write_records(docs, folder, vocabulary, end_id)
    return index_records(spark, folder, folder + "-index")
