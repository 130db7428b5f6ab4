"""The work pool: least service first, with bias, staleness, kill list and duplicates."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def dispatch(pool: DataFrame, k: int, *, bias: DataFrame | None = None) -> DataFrame:
    """The k candidates with the highest priority (pool: cand_id, type, priority, created), older ones first among
    equals; ``bias`` (type, bias) is added to the priority. A top-k, never a full sort."""
    rows = pool if bias is None else pool.join(F.broadcast(bias), "type", "left").withColumn("priority", F.col("priority") + F.coalesce("bias", F.lit(0))).drop("bias")
    return rows.orderBy(F.col("priority").desc(), "created", "cand_id").limit(k)


def requeue(pool: DataFrame, served: DataFrame) -> DataFrame:
    """Priorities fall by the service a candidate has had (served: cand_id, service)."""
    s = served.groupBy("cand_id").agg(F.sum("service").alias("s"))
    return pool.join(s, "cand_id", "left").withColumn("priority", F.col("priority") - F.coalesce("s", F.lit(0))).select(*pool.columns)


def service_of(validated_bytes, proposals):
    """Service units: bytes given to validators and 64 per proposal."""
    return validated_bytes + 64 * proposals


def maintain(pool: DataFrame, layouts: DataFrame, ledger: DataFrame, killed: DataFrame | None = None) -> DataFrame:
    """The pool without candidates of which a content has no free member left, without killed ones (cand_id), and with
    one candidate, the oldest, per layout (layouts: cand_id, positions)."""
    gone = ledger.where("refcount = 0").select("pos")
    stale = layouts.select("cand_id", F.explode("positions").alias("pos")).join(gone, "pos", "left_semi").select("cand_id").distinct()
    rows = pool.join(stale, "cand_id", "left_anti")
    if killed is not None:
        rows = rows.join(killed.select("cand_id"), "cand_id", "left_anti")
    named = rows.join(layouts.select("cand_id", F.xxhash64("positions").alias("shape")), "cand_id", "left")
    first = named.where("shape is not null").groupBy("shape").agg(F.min_by("cand_id", F.struct("created", "cand_id")).alias("keep"))
    kept = named.join(first, "shape", "left").where("shape is null or keep = cand_id")
    return kept.select(*pool.columns)


def seed(boundary: DataFrame, consumed: DataFrame) -> DataFrame:
    """Headers and footers that no candidate or file has used: kind, pos, priority by header first, then position."""
    unused = boundary.join(consumed.select("pos"), "pos", "left_anti")
    return unused.select("type", "kind", "pos", F.when(F.col("kind") == "header", 1).otherwise(0).alias("priority")).distinct()


def choices(proposals: DataFrame, *, hold_policy: str = "prefer_free") -> DataFrame:
    """Ranks the blocks proposed for each slot (cand_id, slot, pos, adjacent, confidence, holds, distance): the live
    neighbour first, then confidence, free of holds, near; ``ignore`` leaves holds out."""
    from pyspark.sql import Window as W

    order = [F.col("adjacent").desc(), F.col("confidence").desc()] + ([F.col("holds").asc()] if hold_policy == "prefer_free" else []) + [F.col("distance").asc(), F.col("pos").asc()]
    return proposals.withColumn("rank", F.row_number().over(W.partitionBy("cand_id", "slot").orderBy(*order)))


def untried(ranked_choices: DataFrame, tried: DataFrame) -> DataFrame:
    """Choices whose block has not been tried in that slot."""
    return ranked_choices.join(tried, ["cand_id", "slot", "pos"], "left_anti")


def gallop_calls(run_lengths: DataFrame) -> DataFrame:
    """For runs of n consecutive right blocks (cand_id, n): validator calls one block at a time and by doubling."""
    doubling = F.ceil(F.log2(F.col("n") + 1)).cast("long")
    return run_lengths.select("cand_id", F.col("n").cast("long").alias("single"), F.when(F.col("n") > 0, doubling).otherwise(F.lit(0).cast("long")).alias("gallop"))
