"""Shared helpers: intermediate tables, Arrow text buffers, word hashing and distributed ranks."""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import uuid
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
WORD = r"[^\x20\x09-\x0D]+"

# ---------------------------------------------------------------- intermediate tables


def shared_dir(spark: SparkSession) -> str:
    """Folder for intermediate tables: the cluster's spark.checkpoint.dir; only where that is unset
    (local runs and tests) a temporary folder of this process."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        base = getattr(shared_dir, "own", None)
        if base is None:
            base = shared_dir.own = tempfile.mkdtemp(prefix="blockrecover-")
            atexit.register(shutil.rmtree, base, ignore_errors=True)
    return base.rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    """A new path under the shared folder; the random part only names files, never results."""
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def materialise(df: DataFrame, name: str, *, wide: bool = False) -> DataFrame:
    """Cuts the lineage of ``df`` by a Parquet table in the shared folder, which outlives any executor. ``wide``: for rows of
    megabytes; else up to a hundred rows are one page, whatever they hold, and pages are packed and unpacked whole, outside the heap."""
    spark = df.sparkSession
    path = fresh_path(spark, name)
    df.write.options(**{"parquet.page.size.row.check.min": "1"} if wide else {}).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def lower_ascii(col: Column) -> Column:
    """Lower-cases A-Z and nothing else."""
    return F.translate(col, UPPER, UPPER.lower())


def text_or_empty(col: str = "text") -> Column:
    return F.coalesce(F.col(col), F.lit(""))


# ---------------------------------------------------------------- Arrow functions

#: Rows of an Arrow batch: texts may be long, and a task holds a few batches at once.
BATCH_ROWS = 1000
#: Bytes of an Arrow batch where rows are wide: the JVM holds a batch outside its heap, beside the workers.
BATCH_BYTES = 4 << 20


def lean(function):
    """``function`` over record batches; what a task has freed goes back to the system when it ends, as workers wait
    for further tasks beside the executor's own memory."""

    def run(batches):
        yield from function(batches)
        pa.default_memory_pool().release_unused()
        try:
            import ctypes

            ctypes.CDLL("libc.so.6").malloc_trim(0)
        except (OSError, AttributeError):
            pass  # another C library

    return run


def arrow_map(df: DataFrame, function, schema) -> DataFrame:
    """mapInArrow in batches of at most BATCH_ROWS rows (a smaller session setting stays)."""
    conf, key = df.sparkSession.conf, "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(conf.get(key)) <= BATCH_ROWS:
        conf.set(key, str(BATCH_ROWS))
    return df.mapInArrow(lean(function), schema)


def bound_batches(spark: SparkSession) -> None:
    """Arrow batches of this session hold about BATCH_BYTES at most from now on (a smaller session setting stays)."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    now = re.fullmatch(r"(\d+)([kmgtp]?)b?", spark.conf.get(key).lower())
    if not now or int(now[1]) << 10 * " kmgtp".index(now[2] or " ") > BATCH_BYTES:
        spark.conf.set(key, str(BATCH_BYTES))


# ---------------------------------------------------------------- Arrow text buffers

_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
#: Odd 64-bit base of the rolling hash and the finaliser's multipliers (fixed values).
_BASE = np.uint64(0x9E3779B97F4A7C15)
_MIX1, _MIX2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
_LEN = np.uint64(0xD6E8FEB86659FD93)
#: Bytes hashed at a time, so that the position tables stay small; one longer text is taken whole.
SLAB = 1 << 20


def buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a text column without copying; null texts count as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    kind = np.int64 if pa.types.is_large_string(column.type) else np.int32
    _, offs, data = column.buffers()
    n = len(column)
    if n == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(offs, dtype=kind)[column.offset : column.offset + n + 1].astype(np.int64)
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def slabs(offsets: np.ndarray, limit: int = SLAB):
    """Row ranges (lo, hi) of at most ``limit`` bytes; a longer text stands alone."""
    lo, n = 0, len(offsets) - 1
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + limit, "right")) - 1)
        yield lo, min(hi, n)
        lo = min(hi, n)


def mix64(x: np.ndarray) -> np.ndarray:
    """Bijective finaliser over unsigned 64-bit values."""
    x = x ^ (x >> np.uint64(30))
    x = x * _MIX1
    x ^= x >> np.uint64(27)
    x *= _MIX2
    x ^= x >> np.uint64(31)
    return x


class Powers:
    """Powers of the base and of its inverse modulo 2**64, grown on demand and reused."""

    up = np.ones(1, np.uint64)
    down = np.ones(1, np.uint64)

    @classmethod
    def of(cls, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(cls.up) <= n:
            m = max(n + 1, SLAB + 1)
            inverse = np.uint64(pow(int(_BASE), -1, 1 << 64))
            step_up, step_down = np.full(m, _BASE), np.full(m, inverse)
            step_up[0] = step_down[0] = 1
            up, down = np.cumprod(step_up, dtype=np.uint64), np.cumprod(step_down, dtype=np.uint64)
            if n > 4 * SLAB:  # not kept: one very long text must not cost memory for good
                return up, down
            cls.up, cls.down = up, down
        return cls.up, cls.down


def word_bounds(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of words (runs of bytes outside the six ASCII white-space bytes) and, per text, the index
    of its first word (one more entry than texts). Words never cross texts."""
    inside = ~_SPACE[data]
    first = inside.copy()
    first[1:] &= ~inside[:-1]
    last = inside.copy()
    last[:-1] &= ~inside[1:]
    cuts = offsets[1:-1]
    cuts = cuts[(cuts > 0) & (cuts < len(data))]
    first[cuts] = inside[cuts]
    last[cuts - 1] = inside[cuts - 1]
    starts = np.flatnonzero(first)
    return starts, np.flatnonzero(last) + 1, np.searchsorted(starts, offsets)


def span_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each byte span, by differences of one running polynomial."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    up, down = Powers.of(len(data))
    run = np.zeros(len(data) + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[: len(data)], out=run[1:])
    return mix64((run[ends] - run[starts]) * down[starts] + (ends - starts).astype(np.uint64) * _LEN)


def words_of(column: pa.Array, limit: int = SLAB):
    """Yields (first row, word hashes, first word per row) for slabs of a text column, A-Z lower-cased."""
    data, offsets = buffers(column)
    for lo, hi in slabs(offsets, limit):
        part = _LOWER[data[offsets[lo] : offsets[hi]]]
        inner = offsets[lo : hi + 1] - offsets[lo]
        starts, ends, heads = word_bounds(part, inner)
        yield lo, span_hashes(part, starts, ends), heads


def gram_hashes(words: np.ndarray, order: int) -> np.ndarray:
    """Hashes of all runs of ``order`` words (fewer than ``order`` words: none)."""
    n = len(words) - order + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    total = np.zeros(n, np.uint64)
    factor = 1
    for k in range(order):
        factor = factor * int(_LEN) % (1 << 64)
        total += words[k : k + n] * np.uint64(factor)
    return mix64(total + np.uint64(order))


def as_long(x: np.ndarray) -> pa.Array:
    return pa.array(np.ascontiguousarray(x).view(np.int64))


# ---------------------------------------------------------------- distributed ranks


def numbered(df: DataFrame, group: list[str], order: list[str], value: str | None = None, *, spread: Column | None = None, rows_a_bucket: int = 4_000, most_buckets: int = 65_536) -> DataFrame:
    """Adds ``before``: in each group, the rows (or the sum of ``value``) that precede a row, from 0.

    Two levels, so that no group meets in one task: rows of a group are dealt by a hash of ``order`` over a number of
    buckets that follows the group's rows; windows run inside buckets; bucket totals, at most ``most_buckets`` plus
    one per group, are summed on the driver and joined back by broadcast. ``spread`` gives a number in [0, 2**32) that
    rises with ``order``: buckets are then its ranges, and a group's order is ``order`` itself. Rows with equal ``order`` get any of their
    common places. ``df`` must be cheap to read twice (a table). Without ``spread`` the order of a group is by
    (bucket, ``order``), which depends on data and sizes alone.
    """
    spark = df.sparkSession
    counts = {tuple(r[:-1]): r[-1] for r in df.groupBy(*group).agg(F.count(F.lit(1)).alias("n")).collect()}
    total = sum(counts.values())
    each = max(rows_a_bucket, -(-total // most_buckets))
    plan = [(*k, max(1, -(-n // each))) for k, n in counts.items()]
    kinds = [df.schema[c] for c in group]
    schema = T.StructType([T.StructField(f"g_{f.name}", f.dataType) for f in kinds] + [T.StructField("parts", T.LongType())])
    dealt = spark.createDataFrame(plan, schema)
    same = reduce(lambda a, b: a & b, [df[c].eqNullSafe(dealt[f"g_{c}"]) for c in group])
    out = df.join(F.broadcast(dealt), same, "left").drop(*[f"g_{c}" for c in group])
    bucket = F.pmod(F.xxhash64(*order), F.col("parts")) if spread is None else F.floor(spread * F.col("parts") / 2**32).cast("long")
    out = out.withColumn("bucket", bucket).drop("parts")
    amount = F.lit(1).cast("long") if value is None else F.col(value)
    sums = out.groupBy(*group, "bucket").agg(F.sum(amount).alias("s")).collect()
    base, at = [], {}
    for r in sorted(sums, key=lambda r: (repr(tuple(r[:-2])), r[-2])):
        k = tuple(r[:-2])
        base.append((*k, r[-2], at.get(k, 0)))
        at[k] = at.get(k, 0) + r[-1]
    schema = T.StructType([T.StructField(f"g_{f.name}", f.dataType) for f in kinds] + [T.StructField("g_bucket", T.LongType()), T.StructField("base", T.LongType())])
    bases = spark.createDataFrame(base, schema)
    w = W.partitionBy(*group, "bucket").orderBy(*order)
    inside = F.row_number().over(w) - 1 if value is None else F.sum(value).over(w.rowsBetween(W.unboundedPreceding, 0)) - F.col(value)
    out = out.withColumn("inside", inside.cast("long"))
    same = reduce(lambda a, b: a & b, [out[c].eqNullSafe(bases[f"g_{c}"]) for c in group] + [out["bucket"] == bases["g_bucket"]])
    out = out.join(F.broadcast(bases), same, "left").drop("g_bucket", *[f"g_{c}" for c in group])
    return out.withColumn("before", F.col("base") + F.col("inside")).drop("base", "inside", "bucket")
