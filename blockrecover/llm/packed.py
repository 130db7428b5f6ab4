"""Exchange of packed entries: fixed-width records travel as one binary per (task flush, bucket) instead of one row each.

The number of buckets follows the input's bytes, so that a bucket fits one task; hot keys must be taken out, or combined
before, by the caller.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map

BUCKET_BYTES, LEAST, MOST = 16 << 20, 64, 65_536


def buckets_for(total_bytes: int) -> int:
    return int(min(MOST, max(LEAST, total_bytes // BUCKET_BYTES)))


def text_bytes(docs: DataFrame) -> int:
    return docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0


def split_by(bucket: np.ndarray, records: np.ndarray) -> pa.RecordBatch:
    """Rows (bucket, body) of a batch's records."""
    order = np.argsort(bucket, kind="stable")
    sorted_, body = bucket[order], np.ascontiguousarray(records[order])
    heads = np.flatnonzero(np.r_[True, sorted_[1:] != sorted_[:-1]]) if len(sorted_) else np.zeros(0, np.int64)
    width = records.dtype.itemsize
    offsets = np.append(heads, len(sorted_)) * width
    bodies = pa.BinaryArray.from_buffers(pa.binary(), len(heads), [None, pa.py_buffer(offsets.astype(np.int32)), pa.py_buffer(body.view(np.uint8).reshape(-1))])
    return pa.RecordBatch.from_arrays([pa.array(sorted_[heads].astype(np.int32)), bodies], names=["bucket", "body"])


def runs_of(batches, key: str):
    """Yields (value, table) of each run of rows with equal ``key``, across batches."""
    held, parts = None, []
    for b in batches:
        values = b.column(key).to_numpy()
        heads = np.flatnonzero(np.r_[True, values[1:] != values[:-1]]) if len(values) else []
        for lo, hi in zip(heads, np.append(heads[1:], len(values)) if len(values) else []):
            if parts and values[lo] != held:
                yield held, pa.Table.from_batches(parts)
                parts = []
            held = values[lo]
            parts.append(b.slice(lo, hi - lo))
    if parts:
        yield held, pa.Table.from_batches(parts)


def regroup(rows: DataFrame, buckets: int, kind: np.dtype, handle, schema: str) -> DataFrame:
    """rows: (bucket, body). ``handle(bucket, records)`` gets all records of a bucket and yields record batches."""

    def merge(batches):
        held, bodies = None, []
        for b in batches:
            for bucket, body in zip(b.column("bucket").to_pylist(), b.column("body")):
                if bucket != held and bodies:
                    yield from handle(held, np.concatenate(bodies))
                    bodies = []
                held = bucket
                bodies.append(np.frombuffer(body.as_buffer(), kind))
        if bodies:
            yield from handle(held, np.concatenate(bodies))

    return arrow_map(rows.repartition(buckets, "bucket").sortWithinPartitions("bucket"), merge, schema)
