"""Raw images outside tables: segment files of fixed-size blocks, written by chunk and read by offset ranges.

A segment ``part-<n>.raw`` holds the blocks n * per_segment onwards. Reading splits segments into ranges, so that no task
holds more than one piece of a range. Defined results: an empty image has no segments and reads as no rows; a last block
cut short is returned as it is; other files in the folder are ignored; null payloads cannot be written and are an error.
"""

from __future__ import annotations

import re

import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

NAME = re.compile(r"part-(\d+)\.raw$")


def write_segments(image: DataFrame, folder: str, *, per_segment: int = 65_536) -> DataFrame:
    """Writes image (pos from 0 without gaps, payload binary) and returns segment, blocks. A segment is written beside its
    place and then moved there, so that a task that runs again leaves the same file."""

    def run(rows: pa.Table) -> pa.Table:
        import uuid

        rows = rows.sort_by("pos")
        segment = rows.column("segment")[0].as_py()
        files, root = fs.FileSystem.from_uri(folder)
        files.create_dir(root, recursive=True)
        hidden = f"{root}/.{segment}-{uuid.uuid4().hex}"
        with files.open_output_stream(hidden) as out:
            for block in rows.column("payload"):
                out.write(block.as_py())
        files.move(hidden, f"{root}/part-{segment}.raw")
        return pa.table({"segment": pa.array([segment], pa.int64()), "blocks": pa.array([rows.num_rows], pa.int64())})

    rows = image.select("pos", "payload", F.expr(f"pos div {per_segment}").alias("segment"))
    return rows.groupBy("segment").applyInArrow(run, "segment long, blocks long")


class _Range(InputPartition):
    def __init__(self, path: str, offset: int, size: int, pos: int):
        self.path, self.offset, self.size, self.pos = path, offset, size, pos


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.folder, self.block = options["path"], int(options.get("block", 256))
        self.per_segment, self.piece = int(options.get("per_segment", 65_536)), int(options.get("piece", 16_384))

    def partitions(self):
        files, root = fs.FileSystem.from_uri(self.folder)
        out = []
        for info in files.get_file_info(fs.FileSelector(root, allow_not_found=True)):
            named = NAME.search(info.path)
            step = self.piece * self.block
            for offset in range(0, info.size if named else 0, step):
                out.append(_Range(info.path, offset, min(step, info.size - offset), int(named[1]) * self.per_segment + offset // self.block))
        return out or [_Range("", 0, 0, 0)]

    def read(self, partition):
        if not partition.size:
            return
        files, _ = fs.FileSystem.from_uri(self.folder)
        with files.open_input_file(partition.path) as source:
            source.seek(partition.offset)
            data = source.read(partition.size)
        blocks = [data[i : i + self.block] for i in range(0, len(data), self.block)]
        yield pa.RecordBatch.from_arrays([pa.array(range(partition.pos, partition.pos + len(blocks)), pa.int64()), pa.array(blocks, pa.binary())], names=["pos", "payload"])


class ImageSource(DataSource):
    """``spark.read.format("block_image").option("block", 256).load(folder)``: pos, payload."""

    @classmethod
    def name(cls):
        return "block_image"

    def schema(self):
        return "pos long, payload binary"

    def reader(self, schema):
        return _Reader(self.options)


def read_image(spark: SparkSession, folder: str, *, block: int = 256, per_segment: int = 65_536) -> DataFrame:
    """pos, payload of all segments in a folder."""
    spark.dataSource.register(ImageSource)
    return spark.read.format("block_image").option("block", str(block)).option("per_segment", str(per_segment)).load(folder)
