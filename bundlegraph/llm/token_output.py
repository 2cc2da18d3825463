"""Token-ID output: independent zstandard frames, a document index and a trailing seek table.

File layout (all integers little-endian): data frames, each a zstandard frame with content
checksum over at most FRAME_IDS ids of 4 bytes; a skippable frame with the document index; a
skippable seek table in the public seekable layout (per frame: compressed size, plain size,
checksum; then frame count, flags, magic). The checksum of a frame is the crc32 of its
compressed bytes. A reader needs the tail, then only the frames that hold a wanted document.

Nulls: a null text has no ids but the end id; a null doc_id sorts first and stays null. Repeated
doc_ids stay as separate rows, ordered by a hash of their text. Empty tables give no files and
no rows. Other columns are ignored.
"""

from __future__ import annotations

import struct
import uuid
import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bpe import encoder, groups
from .common import scratch_path, written

# fixed values of the public formats
SKIPPABLE_SEEK = 0x184D2A5E
SKIPPABLE_INDEX = 0x184D2A5D
SEEK_MAGIC = 0x8F92EAB1
CHECKSUM_FLAG = 0x80

FRAME_IDS = 1 << 17


def filesystem(uri: str):
    """(file system, path) of a folder or file that all nodes reach."""
    from pyarrow import fs

    if "://" not in uri and not uri.startswith("file:"):
        return fs.LocalFileSystem(), uri
    if uri.startswith("file:"):
        return fs.LocalFileSystem(), "/" + uri[5:].lstrip("/")
    return fs.FileSystem.from_uri(uri)


class FrameWriter:
    """Writes one file; documents must come in their final order."""

    def __init__(self, sink, level: int = 1):
        import zstandard

        self.sink = sink
        self.zip = zstandard.ZstdCompressor(level=level, write_checksum=True, write_content_size=True)
        self.room = bytearray()
        self.seek: list[tuple[int, int, int]] = []
        self.doc_ids: list[int | None] = []
        self.lengths: list[int] = []

    def add(self, doc_id: int | None, ids: bytes) -> None:
        self.doc_ids.append(doc_id)
        self.lengths.append(len(ids) // 4)
        self.room += ids
        while len(self.room) >= 4 * FRAME_IDS:
            self._frame(bytes(self.room[: 4 * FRAME_IDS]))
            del self.room[: 4 * FRAME_IDS]

    def _frame(self, raw: bytes) -> None:
        packed = self.zip.compress(raw)
        self.seek.append((len(packed), len(raw), zlib.crc32(packed)))
        self.sink.write(packed)

    def close(self) -> None:
        if self.room:
            self._frame(bytes(self.room))
        null = np.array([d is None for d in self.doc_ids], dtype=np.uint8)
        ids = np.array([0 if d is None else d for d in self.doc_ids], dtype="<i8")
        index = self.zip.compress(null.tobytes() + ids.tobytes() + np.array(self.lengths, dtype="<i8").tobytes())
        body = struct.pack("<QI", len(ids), zlib.crc32(index)) + index
        body += struct.pack("<I", len(body) + 4)  # found from the seek table, going back
        self.sink.write(struct.pack("<II", SKIPPABLE_INDEX, len(body)) + body)
        table = b"".join(struct.pack("<III", *x) for x in self.seek) + struct.pack("<IBI", len(self.seek), CHECKSUM_FLAG, SEEK_MAGIC)
        self.sink.write(struct.pack("<II", SKIPPABLE_SEEK, len(table)) + table)
        self.sink.close()


class FrameReader:
    """Random access to one file; `frames_read` counts the frames that were decompressed."""

    def __init__(self, source):
        import zstandard

        self.source, self.unzip, self.frames_read = source, zstandard.ZstdDecompressor(), 0
        end = source.size()
        n, flags, magic = struct.unpack("<IBI", self._at(end - 9, 9))
        if magic != SEEK_MAGIC or flags != CHECKSUM_FLAG:
            raise ValueError("no seek table at the end of the file")
        table_at = end - 9 - 12 * n - 8
        table = self._at(table_at, 8 + 12 * n)
        if struct.unpack("<II", table[:8]) != (SKIPPABLE_SEEK, 12 * n + 9):
            raise ValueError("the seek table's frame is damaged")
        self.seek = np.frombuffer(table[8:], dtype="<u4").reshape(n, 3)
        self.frame_at = np.concatenate([[0], np.cumsum(self.seek[:, 0], dtype=np.int64)])
        self.plain_at = np.concatenate([[0], np.cumsum(self.seek[:, 1], dtype=np.int64)])
        body = struct.unpack("<I", self._at(table_at - 4, 4))[0]
        index = self._at(table_at - body, body - 4)
        docs, crc = struct.unpack("<QI", index[:12])
        if zlib.crc32(index[12:]) != crc:
            raise ValueError("the document index is damaged")
        plain = self.unzip.decompress(index[12:], max_output_size=17 * docs + 16) if docs else b""
        self.null = np.frombuffer(plain[:docs], dtype=np.uint8).astype(bool)
        self.doc_ids = np.frombuffer(plain[docs : 9 * docs], dtype="<i8")
        self.lengths = np.frombuffer(plain[9 * docs : 17 * docs], dtype="<i8")
        self.starts = np.concatenate([[0], np.cumsum(self.lengths)])

    def _at(self, at: int, size: int) -> bytes:
        self.source.seek(at)
        return self.source.read(size)

    def frame(self, k: int) -> bytes:
        packed = self._at(int(self.frame_at[k]), int(self.seek[k, 0]))
        if zlib.crc32(packed) != int(self.seek[k, 2]):
            raise ValueError(f"frame {k} is damaged")
        self.frames_read += 1
        return self.unzip.decompress(packed, max_output_size=int(self.seek[k, 1]))

    def __iter__(self) -> Iterator[tuple[int | None, int, bytes]]:
        """(doc_id, ids before it in this file, id bytes) of every document, frame by frame."""
        held, at = bytearray(), 0
        k = 0
        for i in range(len(self.doc_ids)):
            need = 4 * int(self.lengths[i])
            while len(held) - at < need:
                if k >= len(self.seek):
                    raise ValueError("the file ends within a document")
                held = held[at:] + self.frame(k)
                at, k = 0, k + 1
            yield (None if self.null[i] else int(self.doc_ids[i])), int(self.starts[i]), bytes(held[at : at + need])
            at += need

    def document(self, i: int) -> bytes:
        """Ids of the i-th document; only the frames that it touches are decompressed."""
        lo, hi = 4 * int(self.starts[i]), 4 * int(self.starts[i + 1])
        if lo == hi:
            return b""
        first = int(np.searchsorted(self.plain_at, lo, side="right")) - 1
        last = int(np.searchsorted(self.plain_at, hi, side="left")) - 1
        plain = b"".join(self.frame(k) for k in range(first, last + 1))
        off = lo - int(self.plain_at[first])
        return plain[off : off + hi - lo]

    def find(self, doc_id: int) -> list[int]:
        return [int(i) for i in np.flatnonzero((self.doc_ids == doc_id) & ~self.null)]


_MANIFEST = "part int, path string, n_docs long, n_tokens long"


def write_token_files(docs: DataFrame, folder: str, tokenizer: str, end_id: int) -> DataFrame:
    """Encode (doc_id, text) and write one file for each range of doc_id. Returns the manifest.

    A task writes to a name of its own; only the names in the committed manifest count, so a
    task that ran twice leaves at most an unread file.
    """
    fs, root = filesystem(folder)
    fs.create_dir(root, recursive=True)
    ordered = docs.select("doc_id", "text").repartitionByRange(F.col("doc_id").asc_nulls_first()).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), F.xxhash64("text"))

    def write(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, out, docs_, total = TaskContext.get().partitionId(), None, 0, 0
        end, enc = struct.pack("<I", end_id), encoder(tokenizer)
        for b in batches:
            if not b.num_rows:
                continue
            if out is None:
                where, root_ = filesystem(folder)
                path = f"{root_}/ids-{part:06d}-{uuid.uuid4().hex}.zst"
                out = FrameWriter(where.open_output_stream(path, compression=None))
            texts, ids = b.column(1).to_pylist(), b.column(0).to_pylist()
            for lo, hi in groups(texts):
                for d, x in zip(ids[lo:hi], enc.encode(texts[lo:hi])):
                    out.add(d, x + end)
                    docs_, total = docs_ + 1, total + len(x) // 4 + 1
        if out is not None:
            out.close()
            yield pa.RecordBatch.from_pydict({"part": pa.array([part], pa.int32()), "path": [path], "n_docs": [docs_], "n_tokens": [total]})

    return written(ordered.mapInArrow(write, _MANIFEST), "token-manifest")


def read_token_files(spark: SparkSession, manifest: DataFrame, folder: str) -> DataFrame:
    """Every document of the files: doc_id, start, n_tokens, ids_crc32, read frame by frame.

    The manifest has one row for each file, which bounds what the driver holds.
    """
    files, before = [], 0
    for r in sorted(manifest.collect(), key=lambda r: r.part):
        files.append((r.path, before))
        before += r.n_tokens
    schema = "doc_id long, start long, n_tokens long, ids_crc32 long"
    if not files:
        return spark.createDataFrame([], schema)

    def read(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for path, base in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                where, _ = filesystem(folder)
                rows = []
                with where.open_input_file(path) as source:
                    for d, start, ids in FrameReader(source):
                        rows.append((d, base + start, len(ids) // 4, zlib.crc32(ids)))
                        if len(rows) == 20_000:
                            yield _rows(rows)
                            rows = []
                yield _rows(rows)

    def _rows(rows):
        cols = list(zip(*rows)) or [[]] * 4
        return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], ["doc_id", "start", "n_tokens", "ids_crc32"])

    listed = spark.createDataFrame(files, "path string, base long").repartition(min(len(files), 4096))
    return listed.mapInArrow(read, schema)


def token_table(docs: DataFrame, tokenizer: str, end_id: int = 2) -> DataFrame:
    """Write the files to the shared folder and return what they hold, one row a document."""
    spark = docs.sparkSession
    folder = scratch_path(spark, "token-files")
    return read_token_files(spark, write_token_files(docs, folder, tokenizer, end_id), folder)
