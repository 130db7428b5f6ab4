"""Token-id files: independent zstandard frames, a document index, a trailing seek table and per-frame checksums.

Layout of a file: frames; a skippable frame with the document index; a skippable frame with the seek table (compressed
size, plain size and checksum of every frame) whose last nine bytes are the frame count, a descriptor and the magic
number of the public seekable format. A frame's plain bytes: u32 number of documents, then per document its id (i64),
a flag for a null id (u8), its ids' count (u32) and then all ids (u32), all little-endian. A reader takes the tail,
finds frames by document id in the index and decompresses those alone. A document never spans frames.

Rows are dealt by ranges of doc_id and sorted, one file a task, named by the task's number; a task that runs again
replaces its file by the same bytes, by way of a temporary name. The manifest (a row per file) gives file bases.

Defined results: null or empty text is one end id; null doc_ids come first; rows that share a doc_id follow each other
in the order of their text's hash; an empty table gives no files and an empty result.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_map, fresh_path, materialise, text_or_empty
from .tokens import encode_with_end, tokenizer_path

#: Fixed values of the public formats.
SKIPPABLE_INDEX, SKIPPABLE_SEEK, SEEK_MAGIC = 0x184D2A50, 0x184D2A5E, 0x8F92EAB1
FRAME_IDS = 1 << 18


def open_store(uri: str):
    """(file system, path) of a URI; a path without a scheme is local."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


def frame_bytes(doc_ids: list[int | None], counts: np.ndarray, ids: np.ndarray) -> bytes:
    n = len(doc_ids)
    numbers = np.array([x or 0 for x in doc_ids], "<i8")
    empty = np.array([x is None for x in doc_ids], "u1")
    return struct.pack("<I", n) + numbers.tobytes() + empty.tobytes() + counts.astype("<u4").tobytes() + ids.astype("<u4").tobytes()


def parse_frame(raw: bytes) -> tuple[list[int | None], np.ndarray, np.ndarray]:
    (n,) = struct.unpack_from("<I", raw)
    numbers, empty = np.frombuffer(raw, "<i8", n, 4), np.frombuffer(raw, "u1", n, 4 + 8 * n)
    counts = np.frombuffer(raw, "<u4", n, 4 + 9 * n)
    return [None if e else int(x) for x, e in zip(numbers, empty)], counts, np.frombuffer(raw, "<u4", -1, 4 + 13 * n)


class Writer:
    """Writes one file to an open stream."""

    def __init__(self, stream, level: int = 3):
        import zstandard

        self.stream, self.zstd = stream, zstandard.ZstdCompressor(level=level, write_checksum=True, write_content_size=True)
        self.seek: list[tuple[int, int, int]] = []
        self.index: list[tuple[int, int, int]] = []

    def add(self, doc_ids: list[int | None], counts: np.ndarray, ids: np.ndarray) -> None:
        raw = frame_bytes(doc_ids, counts, ids)
        packed = self.zstd.compress(raw)
        self.stream.write(packed)
        self.seek.append((len(packed), len(raw), zlib.crc32(raw)))
        known = [x for x in doc_ids if x is not None]
        self.index.append((min(known, default=2**63 - 1), max(known, default=-(2**63)), len(doc_ids)))

    def close(self) -> None:
        body = b"".join(struct.pack("<qqI", *x) for x in self.index)
        self.stream.write(struct.pack("<II", SKIPPABLE_INDEX, len(body)) + body)
        body = b"".join(struct.pack("<III", *x) for x in self.seek) + struct.pack("<IBI", len(self.seek), 0x80, SEEK_MAGIC)
        self.stream.write(struct.pack("<II", SKIPPABLE_SEEK, len(body)) + body)


class Reader:
    """Reads frames, or single documents, of one file."""

    def __init__(self, uri: str):
        store, path = open_store(uri)
        self.file = store.open_input_file(path)
        size = self.file.size()
        n, _, magic = struct.unpack("<IBI", self.file.read_at(9, size - 9))
        if magic != SEEK_MAGIC:
            raise ValueError(f"no seek table in {uri}")
        table = self.file.read_at(12 * n, size - 9 - 12 * n)
        self.seek = list(struct.iter_unpack("<III", table))
        end = size - 9 - 12 * n - 8
        self.index = list(struct.iter_unpack("<qqI", self.file.read_at(20 * n, end - 20 * n)))
        self.starts = np.concatenate([[0], np.cumsum([x[0] for x in self.seek])]).astype(np.int64)

    def frame(self, k: int) -> tuple[list[int | None], np.ndarray, np.ndarray]:
        import zstandard

        packed, plain, crc = self.seek[k]
        raw = zstandard.ZstdDecompressor().decompress(self.file.read_at(packed, int(self.starts[k])), max_output_size=plain)
        if zlib.crc32(raw) != crc:
            raise ValueError(f"checksum of frame {k} differs")
        return parse_frame(raw)

    def document(self, doc_id: int) -> list[np.ndarray]:
        """The ids of each document of that id; decompresses only frames whose range holds it."""
        out = []
        for k, (lo, hi, _) in enumerate(self.index):
            if lo <= doc_id <= hi:
                names, counts, ids = self.frame(k)
                ends = np.cumsum(counts.astype(np.int64))
                out += [ids[e - c : e] for x, c, e in zip(names, counts.astype(np.int64), ends) if x == doc_id]
        return out


def write_files(docs: DataFrame, folder: str, *, tokenizer: str = "word_bpe_49k.json", end_id: int = 1, level: int = 3) -> DataFrame:
    """Writes the files and returns the manifest: part, path, n_docs, n_tokens."""
    vocabulary = tokenizer_path(tokenizer)

    def write(batches):
        import itertools

        batches = (b for b in batches if b.num_rows)
        first = next(batches, None)
        if first is None:
            return
        context = TaskContext.get()
        part = context.partitionId()
        store, base = open_store(folder)
        store.create_dir(base, recursive=True)
        target, temporary = f"{base}/part-{part:08d}.ids.zst", f"{base}/.part-{part:08d}.{context.taskAttemptId()}"
        n_docs = n_tokens = 0
        with store.open_output_stream(temporary) as stream:
            writer = Writer(stream, level)
            for b in itertools.chain([first], batches):
                names = b.column("doc_id").to_pylist()
                ids, heads = encode_with_end(b.column("text"), vocabulary, end_id)
                lo = 0
                while lo < len(names):  # whole documents, about FRAME_IDS ids a frame
                    hi = max(lo + 1, int(np.searchsorted(heads, heads[lo] + FRAME_IDS, "right")) - 1)
                    hi = min(hi, len(names))
                    writer.add(names[lo:hi], np.diff(heads[lo : hi + 1]), ids[heads[lo] : heads[hi]])
                    lo = hi
                n_docs, n_tokens = n_docs + len(names), n_tokens + len(ids)
            writer.close()
        if store.get_file_info(target).is_file:
            store.delete_file(target)
        store.move(temporary, target)
        path = f"{folder}/part-{part:08d}.ids.zst"
        yield pa.RecordBatch.from_pydict({"part": pa.array([part], pa.int64()), "path": [path], "n_docs": pa.array([n_docs], pa.int64()), "n_tokens": pa.array([n_tokens], pa.int64())})

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text"))
    dealt = rows.repartitionByRange(F.col("doc_id").asc_nulls_first()).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), F.xxhash64("text"))
    return materialise(arrow_map(dealt, write, "part long, path string, n_docs long, n_tokens long"), "manifest")


def read_files(spark: SparkSession, manifest: DataFrame, *, with_ids: bool = False) -> DataFrame:
    """Reads every frame of the files of a manifest: doc_id, start (ids of all documents before), n_tokens, ids_crc32
    and, if asked for, ids. File bases are summed on the driver, a number per file."""
    files, at = [], 0
    for r in manifest.orderBy("part").collect():
        files.append((r["path"], at))
        at += r["n_tokens"]
    schema = "doc_id long, start long, n_tokens long, ids_crc32 long" + ", ids array<long>" * with_ids

    def read(batches):
        for b in batches:
            for path, at in zip(b.column("path").to_pylist(), b.column("at").to_pylist()):
                reader = Reader(path)
                for k in range(len(reader.seek)):
                    names, counts, ids = reader.frame(k)
                    ends = np.cumsum(counts.astype(np.int64))
                    begins = ends - counts
                    view = memoryview(np.ascontiguousarray(ids)).cast("B")
                    crc = [zlib.crc32(view[4 * lo : 4 * hi]) for lo, hi in zip(begins.tolist(), ends.tolist())]
                    columns = {"doc_id": pa.array(names, pa.int64()), "start": pa.array(begins + at), "n_tokens": pa.array(counts.astype(np.int64)), "ids_crc32": pa.array(crc, pa.int64())}
                    if with_ids:
                        columns["ids"] = pa.ListArray.from_arrays(pa.array(np.append(begins, len(ids)).astype(np.int32)), pa.array(ids.astype(np.int64)))
                    yield pa.RecordBatch.from_pydict(columns)
                    at += len(ids)

    listed = spark.createDataFrame(files, "path string, at long")
    return arrow_map(listed.repartition(max(1, len(files))), read, schema)


def round_trip(docs: DataFrame, **options) -> DataFrame:
    """Writes the files to a new folder of the shared store and reads them back."""
    spark = docs.sparkSession
    manifest = write_files(docs, fresh_path(spark, "token-files"), **options)
    return read_files(spark, manifest)
