"""Block validators and the frozen state that they leave by content.

Defined results: null payloads score 0; empty ones 0 as well; the state table holds a content once, however often it occurs.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .ledger import digest

#: Characters that files of the text lane are made of.
ALPHABET = "A-Za-z0-9+/=~:."


def framed_score(payload: Column) -> Column:
    """0: cannot belong to a framed file; 100: begins one; 1: one character only; else 2 to 99 by the share of the
    alphabet that occurs. Only what no file can hold is excluded."""
    kinds = F.size(F.array_distinct(F.split(payload, "")))
    graded = F.least(F.lit(99), 2 + F.floor(kinds * 97 / 64)).cast("int")
    return F.when(F.coalesce(~payload.rlike(f"^[{ALPHABET}]+$"), F.lit(True)), 0).when(payload.startswith("~H1:"), 100).when(kinds == 1, 1).otherwise(graded)


def block_state(image: DataFrame, state: Column, *, zero: str) -> DataFrame:
    """hash, state: ``state`` of each content, computed once, from its first block. Blocks that equal ``zero`` are set apart
    before hashing, as they may be most of an image."""
    rows = image.where(F.col("payload") != F.lit(zero)).groupBy(digest(F.col("payload")).alias("hash")).agg(F.min_by("payload", "pos").alias("payload"))
    none = image.where(F.col("payload") == F.lit(zero)).limit(1).select(digest(F.col("payload")).alias("hash"), "payload")
    return rows.unionByName(none).select("hash", state.alias("state"))


def with_state(image: DataFrame, states: DataFrame, *, zero: str) -> DataFrame:
    """image with the state of each block's content; the zero block's state comes by broadcast of its one row."""
    keyed = image.withColumn("hash", digest(F.col("payload"))).withColumn("z", F.col("payload") == F.lit(zero))
    own = states.withColumnRenamed("hash", "s_hash")
    one = own.where(F.col("s_hash") == digest(F.lit(zero))).select(F.col("state").alias("z_state"))
    rows = keyed.join(own, (keyed["hash"] == own["s_hash"]) & ~keyed["z"], "left").join(F.broadcast(one), F.col("z"), "left")
    return rows.select(*image.columns, F.when(F.col("z"), F.col("z_state")).otherwise(F.col("state")).alias("state"))
