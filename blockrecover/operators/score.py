"""Accuracy against the key table and measures over progress logs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..formats.framed import file_number
from ..layout import BLOCK, slices


def classify(outputs: DataFrame, truth: DataFrame) -> DataFrame:
    """outputs: file_id, blocks (hashes of all but the last one's padding), sha256. truth: file_id, blocks, sha256,
    first_break (index of the first block after a break, null if none). One row per output: class complete, partial
    or incorrect; prefix (right leading blocks); crossed (the prefix passes the first break)."""
    t = truth.select("file_id", F.col("blocks").alias("e"), F.col("sha256").alias("e_sha"), "first_break")
    rows = outputs.join(t, "file_id")
    n_e, n_o = F.size("e"), F.size("blocks")
    least = F.least(n_e, n_o)
    same = F.zip_with(F.slice("e", F.lit(1), least), F.slice("blocks", F.lit(1), least), lambda a, b: a == b)
    bad = F.array_position(same, False)
    prefix = F.when(bad > 0, bad - 1).otherwise(least.cast("long"))
    partial = ((n_o == n_e) & (prefix == n_e - 1)) | ((prefix == least) & (n_o != n_e) & (n_o > 0)) | ((prefix == n_e) & (n_o == n_e))
    kind = F.when(F.col("sha256") == F.col("e_sha"), "complete").when(partial, "partial").otherwise("incorrect")
    return rows.select("file_id", "out_id", kind.alias("class"), prefix.cast("long").alias("prefix"), F.coalesce(prefix > F.col("first_break"), F.lit(False)).alias("crossed"))


def best(classes: DataFrame, truth: DataFrame) -> DataFrame:
    """One row per truth file: its best output's class, or not recovered."""
    order = F.struct(F.when(F.col("class") == "complete", 2).when(F.col("class") == "partial", 1).otherwise(0), F.col("prefix"), -F.col("out_id"))
    top = classes.groupBy("file_id").agg(F.max_by(F.struct("class", "prefix", "crossed"), order).alias("b"))
    return truth.select("file_id", "type", "layout").join(top, "file_id", "left").select("file_id", "type", "layout", F.coalesce("b.class", F.lit("not recovered")).alias("class"), F.coalesce("b.prefix", F.lit(0).cast("long")).alias("prefix"), F.coalesce("b.crossed", F.lit(False)).alias("crossed"))


def breakdown(scored: DataFrame) -> DataFrame:
    """Counts by type and layout, and over the corpus (type and layout null)."""
    rows = scored.groupingSets([[F.col("type"), F.col("layout")], []], F.col("type"), F.col("layout"))
    count = lambda c: F.count_if(F.col("class") == c)
    return rows.agg(F.count(F.lit(1)).alias("files"), count("complete").alias("complete"), count("partial").alias("partial"), count("incorrect").alias("incorrect"), count("not recovered").alias("not_recovered"))


def curve(log: DataFrame, grid: DataFrame) -> DataFrame:
    """Validated counts of each run (run, t, validated) at grid times by linear interpolation, averaged over runs."""
    points = log.select("run", F.col("t").cast("double").alias("t"), F.col("validated").cast("double").alias("y"), F.lit(False).alias("ask"))
    asks = log.select("run").distinct().join(F.broadcast(grid), F.lit(True)).select("run", F.col("t").cast("double").alias("t"), F.lit(None).cast("double").alias("y"), F.lit(True).alias("ask"))
    w = W.partitionBy("run").orderBy("t", "ask")
    back, ahead = w.rowsBetween(W.unboundedPreceding, 0), w.rowsBetween(0, W.unboundedFollowing)
    at = F.when(F.col("y").isNotNull(), F.struct("t", "y"))
    rows = points.unionByName(asks).withColumn("a", F.last(at, ignorenulls=True).over(back)).withColumn("b", F.first(at, ignorenulls=True).over(ahead)).where("ask")
    value = F.when(F.col("a").isNull(), 0.0).when(F.col("b").isNull() | (F.col("b.t") == F.col("a.t")), F.col("a.y")).otherwise(F.col("a.y") + (F.col("b.y") - F.col("a.y")) * (F.col("t") - F.col("a.t")) / (F.col("b.t") - F.col("a.t")))
    return rows.groupBy("t").agg(F.avg(value).alias("validated"))


def time_to(log: DataFrame, n: float) -> DataFrame:
    """run, t: first time at which the interpolated count reaches n."""
    w = W.partitionBy("run").orderBy("t")
    rows = log.withColumn("t0", F.lag("t").over(w)).withColumn("y0", F.lag("validated").over(w)).where((F.col("validated") >= n) & ((F.col("y0") < n) | F.col("y0").isNull()))
    at = F.when(F.col("y0").isNull(), F.col("t")).otherwise(F.col("t0") + (n - F.col("y0")) * (F.col("t") - F.col("t0")) / (F.col("validated") - F.col("y0")))
    return rows.groupBy("run").agg(F.min(at).alias("t"))


def speedup(times: DataFrame) -> DataFrame:
    """workers, seconds, speedup over one worker (times: workers, seconds; the mean of repeated runs)."""
    mean = times.groupBy("workers").agg(F.avg("seconds").alias("seconds"))
    one = mean.where("workers = 1").select(F.col("seconds").alias("one"))
    return mean.join(F.broadcast(one), F.lit(True)).select("workers", "seconds", F.round(F.col("one") / F.col("seconds"), 2).alias("speedup"))


def key_of(image: DataFrame, truth: DataFrame) -> DataFrame:
    """The key as ``classify`` reads it: file_id, type, layout, blocks (hashes in order), first_break, sha256."""
    t = truth.join(image, "pos").groupBy("file_id").agg(F.array_sort(F.collect_list(F.struct("logical_block", "pos", F.md5("payload").alias("h")))).alias("b"), F.max("fragmented").alias("fragmented"))
    pos = F.transform("b", lambda x: x.pos)
    breaks = F.filter(F.sequence(F.lit(1), F.size("b") - 1), lambda i: F.get(pos, i) != F.get(pos, i - 1) + 1)
    t = t.withColumn("blocks", F.transform("b", lambda x: x.h)).withColumn("first_break", F.when(F.size("b") > 1, F.get(breaks, 0)))
    return t.select("file_id", F.lit("framed").alias("type"), F.when(F.col("fragmented"), "split").otherwise("whole").alias("layout"), "blocks", "first_break", F.sha2(F.array_join("blocks", ""), 256).alias("sha256"))


def outputs_of(files: DataFrame) -> DataFrame:
    """Recovered framed files (header_pos, content) as ``classify`` reads outputs."""
    blocks = F.transform(slices(F.col("content"), BLOCK), lambda x: F.md5(x))
    rows = files.select(file_number(F.col("content")).alias("file_id"), F.col("header_pos").alias("out_id"), blocks.alias("blocks"))
    return rows.withColumn("sha256", F.sha2(F.array_join("blocks", ""), 256))


def differences(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row that says whether two runs gave the same rows: only_first, only_second, first (rows of the first)."""
    count = lambda d, n: d.agg(F.count(F.lit(1)).alias(n))
    both = count(a.exceptAll(b), "only_first").join(F.broadcast(count(b.exceptAll(a), "only_second")), F.lit(True))
    return both.join(F.broadcast(count(a, "first")), F.lit(True))
