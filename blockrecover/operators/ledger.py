"""The block ledger: coverage, duplicates, exemplars, zero blocks, reference counts and holds.

One row per block. ``covered`` means that a written file uses the block. Blocks of equal content form a group whose
lowest position is the exemplar; ``refcount`` of a group is its number of uncovered members. Zero blocks are flagged by
comparison with a literal before any hashing, so that the largest group of most images never meets in one task.
Operations return new ledgers; nothing is updated in place.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans import range_join


def zero_flag(payload: Column, size: int, zero: str = "0") -> Column:
    return payload == F.lit(zero * size)


def constant_fill(image: DataFrame) -> DataFrame:
    """Blocks of one repeated character: fill, n."""
    first = F.substring("payload", 1, 1)
    return image.where((F.length("payload") > 0) & (F.regexp_replace("payload", "(?s)^(.)\\1*$", "") == "")).groupBy(first.alias("fill")).agg(F.count(F.lit(1)).alias("n"))


def digest(payload: Column) -> Column:
    return F.unhex(F.sha2(payload, 256))


def duplicate_groups(image: DataFrame, *, prefilter: bool = False) -> DataFrame:
    """hash, n, exemplar_pos of contents that occur more than once. ``prefilter`` counts an 8-byte hash first and pays
    for SHA-256 only where that repeats."""
    rows = image
    if prefilter:
        short = image.select(F.xxhash64("payload").alias("x")).groupBy("x").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("x")
        rows = image.withColumn("x", F.xxhash64("payload")).join(short, "x", "left_semi")
    return rows.groupBy(digest(F.col("payload")).alias("hash")).agg(F.count(F.lit(1)).alias("n"), F.min("pos").alias("exemplar_pos")).where("n > 1")


def confirm_duplicates(image: DataFrame) -> DataFrame:
    """exemplar_pos, n, equal: members of each group that equal the exemplar byte by byte."""
    rows = image.withColumn("hash", digest(F.col("payload")))
    groups = duplicate_groups(image)
    first = rows.join(groups, (rows["hash"] == groups["hash"]) & (rows["pos"] == groups["exemplar_pos"])).select(rows["hash"].alias("e_hash"), F.col("payload").alias("e_payload"), "exemplar_pos")
    both = rows.join(first, rows["hash"] == first["e_hash"])
    return both.groupBy("exemplar_pos").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("payload").eqNullSafe(F.col("e_payload"))).alias("equal"))


def build(image: DataFrame, *, size: int, zero: str = "0", dedup: bool = True) -> DataFrame:
    """pos, covered, dup, exemplar, zero, exemplar_pos, refcount for every block."""
    rows = image.select("pos", zero_flag(F.col("payload"), size, zero).alias("zero"), digest(F.col("payload")).alias("hash"))
    if not dedup:
        return rows.select("pos", F.lit(False).alias("covered"), F.lit(False).alias("dup"), F.lit(False).alias("exemplar"), "zero", F.col("pos").alias("exemplar_pos"), F.lit(1).cast("long").alias("refcount"))
    groups = rows.where("not zero").groupBy("hash").agg(F.count(F.lit(1)).alias("n"), F.min("pos").alias("e"))
    others = groups.where("n > 1").withColumnRenamed("hash", "g_hash")
    zeros = rows.where("zero").agg(F.count(F.lit(1)).alias("zn"), F.min("pos").alias("ze"))
    out = rows.join(others, (rows["hash"] == others["g_hash"]) & ~rows["zero"], "left").join(F.broadcast(zeros), F.lit(True), "left")
    n = F.when(F.col("zero"), F.col("zn")).otherwise(F.coalesce("n", F.lit(1)))
    e = F.when(F.col("zero"), F.col("ze")).otherwise(F.coalesce("e", F.col("pos")))
    return out.select("pos", F.lit(False).alias("covered"), (n > 1).alias("dup"), ((n > 1) & (e == F.col("pos"))).alias("exemplar"), "zero", e.alias("exemplar_pos"), n.cast("long").alias("refcount"))


def state(covered: str = "covered", dup: str = "dup", exemplar: str = "exemplar") -> Column:
    """Name of the flag combination; an exemplar that is no duplicate is an error."""
    covered, dup, exemplar = F.col(covered), F.col(dup), F.col(exemplar)
    legal = F.when(dup & exemplar, "exemplar").when(dup, "duplicate").when(~exemplar, "unique").otherwise(F.raise_error(F.lit("exemplar without duplicates")))
    return F.concat(F.when(covered, "covered ").otherwise("free "), legal)


def recount(ledger: DataFrame) -> DataFrame:
    """The ledger with reference counts recomputed from coverage."""
    counts = ledger.groupBy("exemplar_pos").agg(F.count_if(~F.col("covered")).alias("refcount"))
    return ledger.drop("refcount").join(counts, "exemplar_pos").select(*ledger.columns)


def holds(ledger: DataFrame, layouts: DataFrame) -> DataFrame:
    """exemplar_pos, holds: slots of unfinished layouts (cand_id, positions) charged to exemplars; always recomputed."""
    slots = layouts.select("cand_id", F.explode("positions").alias("pos"))
    return slots.join(ledger.select("pos", "exemplar_pos"), "pos").groupBy("exemplar_pos").agg(F.count(F.lit(1)).alias("holds"))


def merge(base: DataFrame, delta: DataFrame) -> DataFrame:
    """The ledger after a barrier: delta (pos, covered) replaces coverage; of several claims on a block true wins."""
    d = delta.groupBy("pos").agg(F.max("covered").alias("now"))
    out = base.join(d, "pos", "left").withColumn("covered", F.coalesce("now", "covered")).drop("now").select(*base.columns)
    return recount(out)


def available(base: DataFrame, delta: DataFrame, *, phase: str = "C") -> DataFrame:
    """Positions that a selection may use within an epoch: free in the base and not claimed in the delta. Phase F offers
    one block per content only."""
    free = base.where("not covered").join(delta.where("covered").select("pos"), "pos", "left_anti")
    if phase == "F":
        free = free.where("refcount > 0 and (not dup or exemplar)")
    return free.select("pos")


def edit(ledger: DataFrame, ranges: DataFrame, *, width: int = 1024) -> DataFrame:
    """Covers or uncovers ranges (lo, hi inclusive, cover): of overlapping ranges cover wins."""
    spans = ranges.select("lo", (F.col("hi") + 1).alias("hi"), "cover")
    hit = range_join(ledger.select("pos"), spans, "pos", "lo", "hi", width=width)
    return merge(ledger, hit.select("pos", F.col("cover").alias("covered")))


def ingest_log(lines: DataFrame) -> DataFrame:
    """Ranges (lo, hi, cover) of another tool's log lines ``... blocks <a>-<b>`` or ``... block <a>``."""
    a, b = F.regexp_extract("value", r"blocks? (\d+)", 1), F.regexp_extract("value", r"blocks \d+-(\d+)", 1)
    return lines.where(a != "").select(a.cast("long").alias("lo"), F.when(b != "", b).otherwise(a).cast("long").alias("hi"), F.lit(True).alias("cover"))


def diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """pos, change of blocks that differ between two ledgers."""
    x, y = a.select("pos", F.col("covered").alias("x")), b.select("pos", F.col("covered").alias("y"))
    both = x.join(y, "pos", "full_outer").where(~F.col("x").eqNullSafe(F.col("y")))
    return both.select("pos", F.when(F.col("x").isNull(), "added").when(F.col("y").isNull(), "removed").when(F.col("y"), "covered").otherwise("uncovered").alias("change"))


def coverage_map(ledger: DataFrame, width: int) -> DataFrame:
    """bucket, covered, total over ``width`` equal position ranges."""
    end = ledger.agg(F.max("pos").alias("top"))
    rows = ledger.join(F.broadcast(end), F.lit(True))
    bucket = F.expr(f"cast(pos * {width} div (top + 1) as int)")
    return rows.groupBy(bucket.alias("bucket")).agg(F.count_if("covered").alias("covered"), F.count(F.lit(1)).alias("total"))


def bitmaps(ledger: DataFrame) -> DataFrame:
    """chunk, covered as 4,096-byte bitmaps of 32,768 blocks each."""
    return ledger.where("covered").groupBy(F.bitmap_bucket_number("pos").alias("chunk")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("pos")).alias("bitmap"))


def residual(image: DataFrame, ledger: DataFrame) -> DataFrame:
    """What another tool should see: the image without covered blocks."""
    return image.join(ledger.where("covered").select("pos"), "pos", "left_anti")
