"""Plan builders for joins and ranks that Spark has no operator for."""

from __future__ import annotations

from collections.abc import Callable
from functools import lru_cache, wraps

from pyspark import SparkContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

#: Rows of per-chunk counters that may be summed on the driver.
MOST_CHUNKS = 1 << 21


def once(make: Callable) -> Callable:
    """For functions whose columns follow from their arguments alone: made once for each JVM and arguments, as every part of a
    column is several calls to the JVM and the same searches are planned round after round."""
    made = lru_cache(maxsize=256)(lambda jvm, *args: make(*args))
    return wraps(make)(lambda *args: made(SparkContext._jvm, *args))


def held(df: DataFrame, *names: str) -> DataFrame:
    """The same rows behind a generator, which keeps the optimizer from making the named columns anew at each of their uses."""
    made = df.select(*[c for c in df.columns if c not in names], F.explode(F.array(F.struct(*names))).alias("held"))
    return made.select(*[c for c in df.columns if c not in names], "held.*").select(*df.columns)


def ranked(df: DataFrame, chunk: Column, order: list, out: str) -> DataFrame:
    """A global rank from 0 in two levels: rows in windows of one chunk, chunk counts summed on the driver (a counter
    per chunk, checked) and broadcast back. ``chunk`` must rise with the order."""
    spark = df.sparkSession
    rows = df.withColumn("rk_chunk", chunk)
    counts = rows.groupBy("rk_chunk").agg(F.count(F.lit(1)).alias("n")).limit(MOST_CHUNKS + 1).collect()
    if len(counts) > MOST_CHUNKS:
        raise ValueError("more chunks than the driver may sum: use larger chunks")
    base, at = [], 0
    for r in sorted(counts, key=lambda r: r["rk_chunk"]):
        base.append((r["rk_chunk"], at))
        at += r["n"]
    kind = rows.schema["rk_chunk"].dataType.simpleString()
    bases = spark.createDataFrame(base, f"rk_chunk {kind}, rk_base long")
    inside = F.row_number().over(W.partitionBy("rk_chunk").orderBy(*order)) - 1
    return rows.withColumn("rk_inside", inside).join(F.broadcast(bases), "rk_chunk").withColumn(out, (F.col("rk_base") + F.col("rk_inside")).cast("long")).drop("rk_chunk", "rk_base", "rk_inside")


def offsets(df: DataFrame, chunk: Column, order: list, size: str, out: str) -> DataFrame:
    """The sum of ``size`` over all rows before each in the order, in two levels as ``ranked`` does it."""
    spark = df.sparkSession
    rows = df.withColumn("of_chunk", chunk)
    sums = rows.groupBy("of_chunk").agg(F.sum(size).alias("n")).limit(MOST_CHUNKS + 1).collect()
    if len(sums) > MOST_CHUNKS:
        raise ValueError("more chunks than the driver may sum: use larger chunks")
    base, at = [], 0
    for r in sorted(sums, key=lambda r: r["of_chunk"]):
        base.append((r["of_chunk"], at))
        at += r["n"]
    bases = spark.createDataFrame(base, f"of_chunk {rows.schema['of_chunk'].dataType.simpleString()}, of_base long")
    before = F.sum(size).over(W.partitionBy("of_chunk").orderBy(*order).rowsBetween(W.unboundedPreceding, W.currentRow)) - F.col(size)
    return rows.withColumn("of_inside", before).join(F.broadcast(bases), "of_chunk").withColumn(out, (F.col("of_base") + F.col("of_inside")).cast("long")).drop("of_chunk", "of_base", "of_inside")


def range_join(points: DataFrame, ranges: DataFrame, at: str, lo: str, hi: str, *, width: int, how: str = "inner") -> DataFrame:
    """points with lo <= at < hi: ranges are exploded over bins of ``width`` and meet points by an equi-join on the
    bin; cost follows ranges times bins each covers."""
    left = points.withColumn("rj_bin", F.expr(f"{at} div {width}"))
    right = ranges.where(F.col(hi) > F.col(lo)).withColumn("rj_bin", F.explode(F.expr(f"sequence({lo} div {width}, ({hi} - 1) div {width})")))
    return left.join(right, (left["rj_bin"] == right["rj_bin"]) & (left[at] >= right[lo]) & (left[at] < right[hi]), how).drop("rj_bin")


def asof_join(left: DataFrame, right: DataFrame, by: list[str], at: str, value: list[str], *, forward: bool = False) -> DataFrame:
    """For each left row the nearest right row at or before ``at`` (or at or after), within equal ``by``: one union and a
    window, no range join. Right columns come with the prefix r_; of right rows at one place the largest values win."""
    names = [f"r_{c}" for c in [at, *value]]
    a = left.select("*", F.lit(0).alias("aj_side"), *[F.lit(None).cast(right.schema[c].dataType).alias(n) for c, n in zip([at, *value], names)])
    b = right.groupBy(*by, at).agg(F.max(F.struct(*value)).alias("aj_v")) if value else right.select(*by, at).distinct().withColumn("aj_v", F.struct(F.lit(0)))
    own = [c for c in left.columns if c not in (*by, at)]
    b = b.select(*by, at, *[F.lit(None).cast(left.schema[c].dataType).alias(c) for c in own], F.lit(1).alias("aj_side"), F.col(at).alias(names[0]), *[F.col(f"aj_v.{c}").alias(n) for c, n in zip(value, names[1:])])
    both = a.select(*by, at, *own, "aj_side", *names).unionByName(b)
    order = [F.col(at).desc() if forward else F.col(at).asc(), F.col("aj_side").desc()]
    w = W.partitionBy(*by).orderBy(*order).rowsBetween(W.unboundedPreceding, W.currentRow)
    carried = both
    packed = F.last(F.when(F.col("aj_side") == 1, F.struct(*names)), ignorenulls=True).over(w)
    carried = both.withColumn("aj_last", packed).where("aj_side = 0")
    return carried.select(*left.columns, *[F.col(f"aj_last.{n}").alias(n) for n in names])


def next_on_axis(left: DataFrame, right: DataFrame, at: str, out: str, *, chunk: int = 32_768) -> DataFrame:
    """left with ``out``: the least ``at`` of right at or after a row's own, null without one; for one axis that has no key
    to part it by. Windows run inside chunks of the axis; what a chunk has none of comes from the chunk after it that has
    one: the chunks' first values meet on the driver (a number for each chunk, checked) and go back by broadcast."""
    spark = left.sparkSession
    names = left.columns
    a = left.withColumn("na_side", F.lit(0)).withColumn("na_chunk", F.expr(f"{at} div {chunk}"))
    b = right.select(F.col(at)).distinct().withColumn("na_side", F.lit(1)).withColumn("na_chunk", F.expr(f"{at} div {chunk}"))
    firsts = b.groupBy("na_chunk").agg(F.min(at).alias("f")).limit(MOST_CHUNKS + 1).collect()
    if len(firsts) > MOST_CHUNKS:
        raise ValueError("more chunks than the driver may hold: use larger chunks")
    firsts = sorted((r["na_chunk"], r["f"]) for r in firsts)
    # a chunk without a later one's value reads the next listed chunk
    spans = [(lo + 1 if k else -(1 << 62), hi, f) for k, ((lo, _), (hi, f)) in enumerate(zip([(0, 0), *firsts], firsts))]
    chunks = a.select("na_chunk").distinct().select(F.col("na_chunk").alias("c"), (F.col("na_chunk") + 1).alias("n"))
    table = spark.createDataFrame(spans, "s_lo long, s_hi long, s_first long")
    later = chunks.join(F.broadcast(table), (F.col("n") >= F.col("s_lo")) & (F.col("n") <= F.col("s_hi"))).select("c", "s_first")
    w = W.partitionBy("na_chunk").orderBy(F.col(at).desc(), F.col("na_side").desc()).rowsBetween(W.unboundedPreceding, W.currentRow)
    both = a.unionByName(b, allowMissingColumns=True)
    near = both.withColumn("na_own", F.last(F.when(F.col("na_side") == 1, F.col(at)), ignorenulls=True).over(w)).where("na_side = 0")
    return near.join(later, near["na_chunk"] == later["c"], "left").select(*names, F.coalesce("na_own", "s_first").alias(out))
