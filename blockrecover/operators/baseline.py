"""Baselines: header-to-footer copying, a contiguous signature carver, exhaustive search on tiny inputs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .contiguous import footer_spans, gather


def header_footer(image: DataFrame, boundary: DataFrame) -> DataFrame:
    """header_pos, content: a copy of what lies between each header and the nearest footer at or after it, without
    coverage, validation or lengths."""
    view = image.select("pos", F.col("pos").alias("live"))
    spans = footer_spans(boundary, view)
    return gather(image.withColumn("live", F.col("pos")), spans, ["header_pos"])


def brute_force(prefix: str, suffix: str, pool: DataFrame, k: int, target: int) -> DataFrame:
    """All ordered choices of k pool blocks (pos, payload) between prefix and suffix whose checksum is ``target``. The
    work grows as the pool's size to the power k: pools beyond 64 blocks or k beyond 3 are refused."""
    if k > 3 or pool.count() > 64:
        raise ValueError("exhaustive search is for tiny inputs")
    rows = pool.select(F.array("pos").alias("chosen"), F.col("payload").alias("text"))
    for _ in range(k - 1):
        rows = rows.crossJoin(pool.select(F.col("pos").alias("n_pos"), F.col("payload").alias("n_text"))).where(~F.array_contains("chosen", F.col("n_pos"))).select(F.array_append("chosen", F.col("n_pos")).alias("chosen"), F.concat("text", "n_text").alias("text"))
    return rows.where(F.crc32(F.concat(F.lit(prefix), "text", F.lit(suffix))) == target).select("chosen")
