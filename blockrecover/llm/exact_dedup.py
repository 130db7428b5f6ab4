"""Exact deduplication by skew-safe combining.

Local stage: Spark's map-side aggregation keeps one row per (digest, salt, full text) of each input partition, the salt
being a hash of the doc_id. Salted stage: those rows meet by (digest, salt, full text), so that a text which a third of
all rows share is spread over ``salts`` tasks, each of which gets it at most once per input partition. (A salt from the
partition's number would be undetermined to the planner, which could then not reuse the exchange.) Global stage: digests found under
one salt only are done; the salt winners of the others meet by (digest, full text). Each stage groups by the text
itself, not by its digest alone.

Defined results: null text counts as empty; rows with a null doc_id are grouped too and lose against any id (a group of
nulls only keeps null); repeated (doc_id, text) rows count each in ``group_size`` and all carry the same verdict;
an empty table gives an empty result; other columns of the input do not matter.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import lower_ascii, text_or_empty


def default_digest(text: Column) -> Column:
    # never null, so that no null filter sets one reader of an exchange apart from another
    return F.coalesce(F.unhex(F.sha2(text, 256)), F.lit(b""))


def groups(docs: DataFrame, *, salts: int = 16, digest=default_digest) -> DataFrame:
    """One row per distinct normalised text: digest, check (second hash), bytes, keep_id, group_size, and the salts under
    which it occurs as a bit mask."""
    norm = lower_ascii(text_or_empty())
    rows = docs.select(F.col("doc_id"), norm.alias("body")).select("doc_id", "body", digest(F.col("body")).alias("digest"), F.pmod(F.xxhash64("doc_id"), F.lit(salts)).alias("salt"))
    salted = rows.groupBy("digest", "salt", "body").agg(F.max("doc_id").alias("top"), F.count(F.lit(1)).alias("n"))
    bit = F.expr("shiftleft(1L, cast(salt as int))")
    brief = salted.select("digest", F.xxhash64("body").alias("check"), F.octet_length("body").alias("bytes"), "top", "n", "salt")
    by_digest = brief.groupBy("digest").agg(F.count(F.lit(1)).alias("rows"), F.max("top").alias("keep_id"), F.sum("n").alias("group_size"), F.max("check").alias("check"), F.max("bytes").alias("bytes"), F.bit_or(bit).alias("salt_mask"))
    single = by_digest.where("rows = 1").drop("rows")
    # asking for all columns, though rows alone decide, keeps this reader's exchange the same as the others'
    whole = (F.col("group_size") > 1) & (F.coalesce("keep_id", F.lit(0)) >= F.lit(-(2**63)))
    shared = by_digest.where((F.col("rows") > 1) & whole).select(F.col("digest").alias("many"))
    merged = (
        salted.join(shared, salted["digest"] == shared["many"], "left_semi")
        .groupBy("digest", "body")
        .agg(F.max("top").alias("keep_id"), F.sum("n").alias("group_size"), F.bit_or(bit).alias("salt_mask"))
        .select("digest", "keep_id", "group_size", F.xxhash64("body").alias("check"), F.octet_length("body").alias("bytes"), "salt_mask")
    )
    return single.select("digest", "check", "bytes", "keep_id", "group_size", "salt_mask").unionByName(merged)


def deduplicate(docs: DataFrame, *, salts: int = 16, digest=default_digest) -> DataFrame:
    """One row per input row: doc_id, keep_id, group_size, kept, text_sha256.

    Rows find their group by digest, second hash, length and salt: a group stands once under each salt that its rows
    have, so that the rows of one text are spread over ``salts`` tasks here too. ``groups`` has compared whole texts. Should two different
    texts ever agree in all three, the query stops with an error rather than merge them.
    """
    found = groups(docs, salts=salts, digest=digest)
    found = (
        found.groupBy("digest", "check", "bytes")
        .agg(F.max("keep_id").alias("keep_id"), F.max("group_size").alias("group_size"), F.bit_or("salt_mask").alias("salt_mask"), F.count(F.lit(1)).alias("texts"))
        .withColumn("group_size", F.when(F.col("texts") == 1, F.col("group_size")).otherwise(F.raise_error(F.lit("two texts share all digests")).cast("long")))
        .drop("texts")
        .withColumn("salt", F.explode(F.filter(F.sequence(F.lit(0), F.lit(salts - 1)), lambda k: F.expr("salt_mask").bitwiseAND(F.call_function("shiftleft", F.lit(1).cast("long"), k)) != 0)))
        .withColumn("salt", F.col("salt").cast("long"))
        .drop("salt_mask")
    )
    body = lower_ascii(text_or_empty())
    rows = docs.select("doc_id", body.alias("body")).select("doc_id", digest(F.col("body")).alias("digest"), F.xxhash64("body").alias("check"), F.octet_length("body").alias("bytes"), F.sha2("body", 256).alias("text_sha256"), F.pmod(F.xxhash64("doc_id"), F.lit(salts)).cast("long").alias("salt"))
    return rows.join(found, ["digest", "check", "bytes", "salt"], "left").select(
        "doc_id", "keep_id", F.col("group_size").cast("long").alias("group_size"), F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256"
    )


def survivors(docs: DataFrame, *, salts: int = 16) -> DataFrame:
    """The rows of ``docs`` that stay, with all their columns; of rows that repeat both the kept doc_id and the text,
    one stays. A null doc_id takes the place of the least id here."""
    body = lower_ascii(text_or_empty())
    number = lambda c: F.coalesce(c, F.lit(-(2**63)))
    keys = ["dedup_digest", "dedup_check", "dedup_bytes", "dedup_id"]
    # asking for sizes, of no use here, lets all readers of the salted texts share one exchange of them
    found = groups(docs, salts=salts).where("group_size > 0").select(F.col("digest").alias(keys[0]), F.col("check").alias(keys[1]), F.col("bytes").alias(keys[2]), number(F.col("keep_id")).alias(keys[3]))
    rows = docs.select(F.struct(*docs.columns).alias("dedup_row"), body.alias("body"), number(F.col("doc_id")).alias(keys[3])).select(
        "dedup_row", default_digest(F.col("body")).alias(keys[0]), F.xxhash64("body").alias(keys[1]), F.octet_length("body").alias(keys[2]), keys[3]
    )
    # the join leaves rows dealt by all four keys, so that dropping repeats needs no further exchange
    return rows.join(found, keys, "left_semi").dropDuplicates(keys).select("dedup_row.*")
