"""Token ids in seekable zstandard files.

A file holds independent zstandard frames of little-endian unsigned 32-bit ids, a
skippable frame with the document table, and, last, a skippable frame with the public
seek table: compressed size, decompressed size and checksum (low half of XXH64) of each
frame. A reader that wants some documents reads the two tables and only their frames.

Documents are range-partitioned by id into as many tasks as their bytes ask for (``file_bytes``
of text each; ties by a row number, so neither a repeated id nor a repeated row can fill a
task). A task streams its rows into files that it closes at
``file_bytes`` of ids. File names are a task's own and only those reported by finished tasks
enter the manifest, so retries leave no half files in it. The manifest is a written table with
one row per file; ``start`` is a sum over those rows.

A null text is empty, a null id sorts first, repeated rows are separate documents, other columns
(whatever their names) are not read; very long texts make a frame of their own; an empty table
gives no files and no rows.
"""

from __future__ import annotations

import io
import struct
import uuid
from array import array

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tierbit.llm.common import lean, scratch, stored
from tierbit.llm.tokens import batches_of, encoder

#: Fixed values of the public seekable format.
SKIPPABLE, SEEK_SKIPPABLE, SEEK_MAGIC, HAS_CHECKSUMS = 0x184D2A50, 0x184D2A5E, 0x8F92EAB1, 0x80

#: Stands for a null id in a file.
NO_ID = np.iinfo(np.int64).min


class FrameWriter:
    """Appends documents to an open binary stream."""

    def __init__(self, sink, frame_bytes: int = 256 << 10, level: int = 3):
        self.sink, self.frame_bytes, self.zip = sink, frame_bytes, zstandard.ZstdCompressor(level=level)
        self.held: list[bytes] = []
        self.size = self.tokens = 0
        self.frames: list[tuple[int, int, int]] = []
        self.docs = array("q"), array("I"), array("I")  # id, tokens, frame

    def add(self, doc_id: int | None, ids: bytes) -> None:
        for column, x in zip(self.docs, (NO_ID if doc_id is None else doc_id, len(ids) // 4, len(self.frames))):
            column.append(x)
        self.held.append(ids)
        self.size += len(ids)
        self.tokens += len(ids) // 4
        if self.size >= self.frame_bytes:
            self.flush()

    def flush(self) -> None:
        if self.held:
            raw = b"".join(self.held)
            out = self.zip.compress(raw)
            self.sink.write(out)
            self.frames.append((len(out), len(raw), xxhash.xxh64_intdigest(raw) & 0xFFFFFFFF))
            self.held, self.size = [], 0

    def close(self) -> None:
        self.flush()
        ids, counts, owners = (np.asarray(d, dtype=t).tobytes() for d, t in zip(self.docs, ("<i8", "<u4", "<u4")))
        docs = zstandard.ZstdCompressor(level=3).compress(struct.pack("<Q", len(self.docs[0])) + ids + counts + owners)
        self.sink.write(struct.pack("<II", SKIPPABLE, len(docs)) + docs)
        entries = [*self.frames, (len(docs) + 8, 0, 0)]
        body = b"".join(struct.pack("<III", *e) for e in entries) + struct.pack("<IBI", len(entries), HAS_CHECKSUMS, SEEK_MAGIC)
        self.sink.write(struct.pack("<II", SEEK_SKIPPABLE, len(body)) + body)


class FrameReader:
    """Random access to a file's documents; ``frames_read`` counts what was decompressed."""

    def __init__(self, source):
        self.source, self.frames_read = source, 0
        end = source.seek(0, io.SEEK_END)
        n, flags, magic = struct.unpack("<IBI", self._at(end - 9, 9))
        if magic != SEEK_MAGIC or not flags & HAS_CHECKSUMS:
            raise ValueError("no seek table with checksums at the end of the file")
        table = self._at(end - 9 - 12 * n, 12 * n)
        self.entries = [struct.unpack_from("<III", table, 12 * i) for i in range(n)]
        self.offsets = np.concatenate([[0], np.cumsum([e[0] for e in self.entries], dtype=np.int64)])
        packed = self._at(int(self.offsets[-2]) + 8, self.entries[-1][0] - 8)
        raw = zstandard.ZstdDecompressor().decompress(packed)
        k = struct.unpack_from("<Q", raw)[0]
        self.ids, self.counts, self.owner = np.frombuffer(raw, "<i8", k, 8), np.frombuffer(raw, "<u4", k, 8 + 8 * k), np.frombuffer(raw, "<u4", k, 8 + 12 * k)

    def _at(self, offset: int, size: int) -> bytes:
        self.source.seek(offset)
        return self.source.read(size)

    def frame(self, i: int) -> bytes:
        packed, size, check = self.entries[i]
        raw = zstandard.ZstdDecompressor().decompress(self._at(int(self.offsets[i]), packed), max_output_size=size)
        self.frames_read += 1
        if len(raw) != size or xxhash.xxh64_intdigest(raw) & 0xFFFFFFFF != check:
            raise ValueError(f"frame {i} doesn't match its checksum")
        return raw

    def documents(self, wanted: set[int] | None = None):
        """(doc_id, ids) in file order; with ``wanted``, only frames that hold one are read."""
        frames = np.arange(len(self.entries) - 1)
        bounds = np.searchsorted(self.owner, [*frames, len(frames)])  # owners ascend
        if wanted is not None:
            rows = np.flatnonzero(np.isin(self.ids, np.array(sorted(wanted), np.int64)))
            frames = np.unique(self.owner[rows])
        for i in frames.tolist():
            low, high = int(bounds[i]), int(bounds[i + 1])
            raw, at = self.frame(i), 0
            for key, n in zip(self.ids[low:high].tolist(), self.counts[low:high].tolist()):
                if wanted is None or key in wanted:
                    yield None if key == NO_ID else key, raw[at : at + 4 * n]
                at += 4 * n


def write_tokens(docs: DataFrame, tokenizer: str, end_id: int | None, key: str = "doc_id", text: str = "text", frame_bytes: int = 256 << 10, file_bytes: int = 16 << 20, path: str | None = None) -> DataFrame:
    """Write the files below ``path``; returns the manifest: file_no, path, start, n_docs, n_tokens."""
    spark = docs.sparkSession
    path = path or scratch(spark, "tokens")
    tail = b"" if end_id is None else struct.pack("<I", end_id)

    def write(batches):
        from pyarrow.fs import FileSystem

        fs, root = FileSystem.from_uri(path)
        fs.create_dir(root, recursive=True)
        part, own, writer, sink, name, n = TaskContext.get().partitionId(), uuid.uuid4().hex, None, None, "", 0

        def closed():
            writer.close()
            sink.close()
            return pa.RecordBatch.from_pydict({"part": pa.array([part], pa.int32()), "nth": pa.array([n], pa.int32()), "path": [f"{path}/{name}"], "n_docs": pa.array([len(writer.docs[0])], pa.int64()), "n_tokens": pa.array([writer.tokens], pa.int64())})

        for batch in batches:
            ids = batch.column("doc_id").to_pylist()
            for run, texts in batches_of(batch.column("text")):
                for i, e in zip(run, encoder(tokenizer).encode(texts)):
                    if writer is None:
                        name, n = f"part-{part:06d}-{n:04d}-{own}.zst", n + 1
                        sink = fs.open_output_stream(f"{root}/{name}", compression=None)
                        writer = FrameWriter(sink, frame_bytes)
                    writer.add(ids[i], e + tail)
                    if writer.tokens * 4 >= file_bytes:
                        yield closed()
                        writer = None
        if writer:
            yield closed()

    rows = docs.select(F.col(f"`{key}`").cast("long").alias("doc_id"), F.col(f"`{text}`").alias("text"))
    tasks = max(1, -(-(rows.agg(F.sum(F.coalesce(F.octet_length("text"), F.lit(0)) + 8)).first()[0] or 0) // file_bytes))
    ranged = lean(rows).select("doc_id", "text", F.monotonically_increasing_id().alias("nth")).repartitionByRange(tasks, "doc_id", "nth").sortWithinPartitions("doc_id", "nth")
    files = stored(ranged.select("doc_id", "text").mapInArrow(write, "part int, nth int, path string, n_docs long, n_tokens long"), "files")
    order = W.orderBy("part", "nth")  # one row per file, whatever the number of documents
    before = F.coalesce(F.sum("n_tokens").over(order.rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    return stored(files.select((F.row_number().over(order) - 1).alias("file_no"), "path", before.cast("long").alias("start"), "n_docs", "n_tokens"), "manifest")


def open_file(path: str) -> FrameReader:
    from pyarrow.fs import FileSystem

    fs, name = FileSystem.from_uri(path)
    return FrameReader(fs.open_input_file(name))


def read_tokens(spark: SparkSession, manifest: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids (bytes) of every document, one task for each file."""

    def read(batches):
        for batch in batches:
            for path, start in zip(batch.column("path").to_pylist(), batch.column("start").to_pylist()):
                rows, held = [], 0
                for doc_id, ids in open_file(path).documents():
                    rows.append((doc_id, start, len(ids) // 4, ids))
                    start += len(ids) // 4
                    held += len(ids) + 64
                    if held > 4 << 20:
                        yield _rows(rows)
                        rows, held = [], 0
                if rows:
                    yield _rows(rows)

    return manifest.select("path", "start").repartition(max(1, manifest.count())).mapInArrow(read, "doc_id long, start long, n_tokens long, ids binary")


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.int64(), pa.int64(), pa.int64(), pa.binary()))], ["doc_id", "start", "n_tokens", "ids"])


def read_some(spark: SparkSession, manifest: DataFrame, wanted: list[int]) -> list[tuple[int, bytes, int]]:
    """The named documents and how many frames each file gave up: for point lookups."""
    out = []
    for row in manifest.collect():
        reader = open_file(row["path"])
        for doc_id, ids in reader.documents(set(wanted)):
            out.append((doc_id, ids, reader.frames_read))
    return out
