"""Token-id files: independent zstandard frames, a trailing seek table, per-frame checksums.

Layout of a file (all numbers little-endian):

1. data frames: the id stream (unsigned 32-bit) cut into equal runs of ``frame_ids``
   ids, each an independent zstandard frame;
2. a skippable frame with the document index: a zstandard frame of int64 doc ids
   followed by int64 bounds in the id stream (documents + 1), after one int64 count;
3. a skippable frame with the seek table in the public seekable layout: for each
   data frame compressed size, decompressed size and the low 32 bits of XXH64 of its
   content, then the frame count, one descriptor byte and the closing magic number.

A reader finds the seek table from the file's end, the index from the table, and
decompresses only frames that hold ids of the requested documents. Ordinary
zstandard tools skip parts 2 and 3 and decompress the plain id stream.
"""

from __future__ import annotations

import struct
import uuid
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import new_path, tidied
from .word_ids import encoder, text_lists

#: Fixed values of the seekable layout.
SKIPPABLE_INDEX = 0x184D2A50
SKIPPABLE_SEEK = 0x184D2A5E
SEEKABLE_MAGIC = 0x8F92EAB1
CHECKSUM_FLAG = 0x80

_MANIFEST = pa.schema([("part", pa.int32()), ("path", pa.string()), ("n_docs", pa.int64()), ("n_ids", pa.int64())])
_READ = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())])


class TokenFileWriter:
    """Streams documents into one file; memory is one frame plus the index."""

    def __init__(self, sink, frame_ids: int = 1 << 16, level: int = 1):
        self.sink, self.frame_ids = sink, frame_ids
        self.compress = zstandard.ZstdCompressor(level=level).compress
        self.rest, self.held = [], 0
        self.table: list[tuple[int, int, int]] = []
        self.doc_ids: list[np.ndarray] = []
        self.sizes: list[np.ndarray] = []

    def add(self, doc_ids: np.ndarray, ids: np.ndarray, bounds: np.ndarray) -> None:
        self.doc_ids.append(np.asarray(doc_ids, np.int64))
        self.sizes.append(np.diff(bounds))
        self.rest.append(np.ascontiguousarray(ids, "<u4"))
        self.held += len(ids)
        if self.held >= self.frame_ids:
            flat = np.concatenate(self.rest)
            whole = len(flat) // self.frame_ids * self.frame_ids
            for i in range(0, whole, self.frame_ids):
                self._frame(flat[i : i + self.frame_ids])
            self.rest, self.held = [flat[whole:]], len(flat) - whole

    def _frame(self, ids: np.ndarray) -> None:
        raw = ids.tobytes()
        packed = self.compress(raw)
        self.sink.write(packed)
        self.table.append((len(packed), len(raw), xxhash.xxh64_intdigest(raw) & 0xFFFFFFFF))

    def close(self) -> tuple[int, int]:
        if self.held:
            self._frame(np.concatenate(self.rest))
        doc_ids = np.concatenate(self.doc_ids) if self.doc_ids else np.zeros(0, np.int64)
        bounds = np.zeros(len(doc_ids) + 1, np.int64)
        if len(doc_ids):
            np.cumsum(np.concatenate(self.sizes), out=bounds[1:])
        index = self.compress(np.int64(len(doc_ids)).tobytes() + doc_ids.tobytes() + bounds.tobytes())
        self.sink.write(struct.pack("<II", SKIPPABLE_INDEX, len(index)) + index)
        seek = b"".join(struct.pack("<III", *row) for row in self.table) + struct.pack("<IBI", len(self.table), CHECKSUM_FLAG, SEEKABLE_MAGIC)
        self.sink.write(struct.pack("<II", SKIPPABLE_SEEK, len(seek)) + seek)
        self.sink.close()
        return len(doc_ids), int(bounds[-1])


class TokenFileReader:
    """Random access: ``read(i)`` decompresses only the frames of document i."""

    def __init__(self, source):
        self.source = source
        size = source.size()
        count, flag, magic = struct.unpack("<IBI", self._at(size - 9, 9))
        if magic != SEEKABLE_MAGIC or flag != CHECKSUM_FLAG:
            raise ValueError("not a token file: wrong closing magic number")
        table_at = size - 9 - 12 * count
        rows = np.frombuffer(self._at(table_at, 12 * count), "<u4").reshape(-1, 3).astype(np.int64)
        self.packed = np.concatenate([[0], np.cumsum(rows[:, 0])])
        self.plain = np.concatenate([[0], np.cumsum(rows[:, 1])]) // 4
        self.checks = rows[:, 2]
        index_at = int(self.packed[-1])
        magic, length = struct.unpack("<II", self._at(index_at, 8))
        if magic != SKIPPABLE_INDEX:
            raise ValueError("not a token file: no document index")
        index = np.frombuffer(zstandard.ZstdDecompressor().decompress(self._at(index_at + 8, length)), "<i8")
        n = int(index[0])
        self.doc_ids, self.bounds = index[1 : 1 + n], index[1 + n :]
        self.frames_read = 0

    def _at(self, place: int, n: int) -> bytes:
        self.source.seek(place)
        return self.source.read(n)

    def frame(self, k: int) -> np.ndarray:
        raw = zstandard.ZstdDecompressor().decompress(self._at(int(self.packed[k]), int(self.packed[k + 1] - self.packed[k])), max_output_size=int(self.plain[k + 1] - self.plain[k]) * 4)
        if xxhash.xxh64_intdigest(raw) & 0xFFFFFFFF != self.checks[k]:
            raise ValueError(f"frame {k} does not match its checksum")
        self.frames_read += 1
        return np.frombuffer(raw, "<u4")

    def ids(self, first: int, last: int) -> np.ndarray:
        """Ids first to last (exclusive) of the stream."""
        if first >= last:
            return np.zeros(0, np.uint32)
        a = int(np.searchsorted(self.plain, first, "right")) - 1
        b = int(np.searchsorted(self.plain, last, "left"))
        flat = np.concatenate([self.frame(k) for k in range(a, b)])
        return flat[first - self.plain[a] : last - self.plain[a]]

    def read(self, i: int) -> np.ndarray:
        return self.ids(int(self.bounds[i]), int(self.bounds[i + 1]))

    def checksums(self):
        """Every document in turn: (index, crc32 of its ids); one frame in memory at a time."""
        doc, crc = 0, 0
        for k in range(len(self.checks)):
            ids, at = self.frame(k), int(self.plain[k])
            end = int(self.plain[k + 1])
            while doc < len(self.doc_ids):
                a, b = max(at, int(self.bounds[doc])), min(end, int(self.bounds[doc + 1]))
                if b > a:
                    crc = zlib.crc32(ids[a - at : b - at].tobytes(), crc)
                if int(self.bounds[doc + 1]) > end:
                    break
                yield doc, crc
                doc, crc = doc + 1, 0
        while doc < len(self.doc_ids):
            yield doc, 0
            doc += 1


def write_token_files(docs: DataFrame, out: str, tokenizer: str, end_id: int = 2, frame_ids: int = 1 << 16) -> list[dict]:
    """Writes docs (doc_id, text) in ascending doc_id order, one file for each range partition.

    Equal doc_ids are ordered by a hash of their texts, then by text. Files get their
    final name by a rename and a name of their own for each attempt, so repeated or
    speculative tasks are harmless. Returns the manifest in file order (one small row
    for each partition) with ``start``, the ids in all files before.
    """

    def write(batches):
        part = TaskContext.get().partitionId()
        fs, folder = pafs.FileSystem.from_uri(out)
        fs.create_dir(folder, recursive=True)
        place = f"{folder}/part-{part:06d}-{uuid.uuid4().hex[:8]}.ids"
        writer, coder = TokenFileWriter(fs.open_output_stream(place + ".tmp"), frame_ids), encoder(tokenizer)
        for batch in batches:
            doc_ids = batch.column(0).fill_null(-(1 << 63)).to_numpy(zero_copy_only=False)
            for first, texts in text_lists(batch):
                writer.add(doc_ids[first : first + len(texts)], *coder.encode(texts, end_id))
        n_docs, n_ids = writer.close()
        fs.move(place + ".tmp", place)
        yield pa.RecordBatch.from_arrays([pa.array([x], f.type) for x, f in zip((part, place, n_docs, n_ids), _MANIFEST, strict=True)], schema=_MANIFEST)

    ordered = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").repartitionByRange("doc_id", F.xxhash64("text")).sortWithinPartitions("doc_id", F.xxhash64("text"), "text")
    rows = [r.asDict() for r in ordered.mapInArrow(tidied(write), "part int, path string, n_docs long, n_ids long").collect()]
    rows.sort(key=lambda r: r["part"])
    start = 0
    for r in rows:
        r["start"] = start
        start += r["n_ids"]
    return rows


def read_token_files(spark, out: str, manifest: list[dict]) -> DataFrame:
    """One row for each document, read back from the files: doc_id, start, n_tokens, ids_crc32."""
    scheme = out

    def read(batches):
        fs, _ = pafs.FileSystem.from_uri(scheme)
        for batch in batches:
            for path, base in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                with fs.open_input_file(path) as source:
                    reader = TokenFileReader(source)
                    crcs = np.fromiter((crc for _, crc in reader.checksums()), np.int64, len(reader.doc_ids))
                    ids = pa.array(reader.doc_ids, pa.int64(), mask=reader.doc_ids == -(1 << 63))
                    yield pa.RecordBatch.from_arrays([ids, pa.array(reader.bounds[:-1] + base), pa.array(np.diff(reader.bounds)), pa.array(crcs)], schema=_READ)

    rows = [(r["path"], r["start"]) for r in manifest if r["n_docs"]]
    files = spark.createDataFrame(rows, "path string, start long").repartition(max(1, len(rows)))
    return files.mapInArrow(tidied(read), "doc_id long, start long, n_tokens long, ids_crc32 long")


def token_files(docs: DataFrame, tokenizer: str, end_id: int = 2, out: str | None = None, frame_ids: int = 1 << 16) -> DataFrame:
    """Writes token files under ``out`` (a fresh shared folder by default) and reads them back.

    Null and empty texts give documents of the end id alone; repeated rows are separate
    documents; an empty table gives no rows; a null doc_id sorts first and stays null.
    """
    spark = docs.sparkSession
    out = out or new_path(spark, "token-files")
    return read_token_files(spark, out, write_token_files(docs, out, tokenizer, end_id, frame_ids))
