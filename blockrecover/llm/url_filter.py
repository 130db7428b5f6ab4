"""URL filter: a blocked Bloom filter over listed entries, then an exact hash join that removes its false positives.

An entry is a host and a path prefix with a verdict; it fits its host, all subdomains, and paths that start with its
path. A canonical URL listed as such fits that URL alone. Of the entries that fit, the one with the longest host wins, of these
the one with the longest path. The filter's blocks hold 512 bits; a key sets eight bits inside one block, so a
probe costs one cache line. Per page the keys to probe are few: one for each parent domain and each path length that
occurs in the list. Only keys the filter passes reach the join.

The bit table is built by a distributed bitwise-or aggregation and broadcast; its size is computed from the count of
entries and checked against ``most_bytes``; beyond that all keys go to the exact join, which gives the same verdicts.

Defined results: null url, or one without ``://``: host and path empty, no entry fits, verdict ``allow``; empty table:
empty result; repeated rows each get their verdict; a url's other columns do not matter; of equal entries ``block``
wins over ``allow``.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import UPPER, arrow_map

#: (host, path, verdict), fixed values of the query's contract.
RULES = (("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"), ("com", "/fr/", "allow"), ("com", "/de/", "block"))
PROBES, BLOCK_BITS, BITS_A_KEY = 8, 512, 16


def url_parts(url: Column) -> tuple[Column, Column]:
    """(host, path): the host between the first ``://`` and the next ``/``, ``?`` or ``#``, A-Z lower-cased; the path
    from there up to ``?`` or ``#``. Both empty without ``://``."""
    rest = F.substring(url, F.locate("://", url) + 3, F.length(url))
    has = F.coalesce(F.locate("://", url) > 0, F.lit(False))
    host = F.regexp_extract(rest, r"^[^/?#]*", 0)
    path = F.regexp_extract(F.substring(rest, F.length(host) + 1, F.length(rest)), r"^[^?#]*", 0)
    return F.when(has, F.translate(host, UPPER, UPPER.lower())).otherwise(""), F.when(has, path).otherwise("")


def canonical(host: Column, path: Column) -> Column:
    """Canonical form of a listed URL: host without port, final dot and leading ``www.``; path without a final ``/``."""
    return F.concat(F.regexp_replace(F.regexp_replace(host, r"(:\d*)?$", ""), r"^www\.|\.$", ""), F.regexp_replace(path, "/+$", ""))


class Filter:
    """A blocked Bloom filter; ``words`` holds its bit table as unsigned 64-bit numbers, eight to a block."""

    def __init__(self, words: np.ndarray):
        self.words = words

    @staticmethod
    def blocks_for(keys: int) -> int:
        return max(1, -(-keys * BITS_A_KEY // BLOCK_BITS))

    @classmethod
    def build(cls, keys: DataFrame, blocks: int) -> Filter:
        """keys: one column ``key`` (64-bit hashes). Bits are joined by aggregation, block by block."""
        bit = [F.pmod(F.shiftrightunsigned(F.xxhash64("key", F.lit(1)), 7 * i), F.lit(BLOCK_BITS)) for i in range(PROBES)]
        set_ = keys.select(F.pmod("key", F.lit(blocks)).alias("block"), F.explode(F.array(*bit)).alias("bit"))
        words = [F.coalesce(F.bit_or(F.when(F.floor(F.col("bit") / 64) == w, F.expr("shiftleft(1L, cast(bit % 64 as int))"))), F.lit(0)).alias(f"w{w}") for w in range(8)]
        rows = set_.groupBy("block").agg(*words).toArrow()  # a row of nine numbers for each block that has a key
        out = np.zeros((blocks, 8), np.int64)
        for w in range(8):
            out[rows.column("block").to_numpy(), w] = rows.column(f"w{w}").to_numpy()
        return cls(out.reshape(-1).view(np.uint64))

    def passes(self, keys: np.ndarray, second: np.ndarray) -> np.ndarray:
        """keys and second: the two hashes of each probed key, signed 64-bit."""
        start = np.mod(keys, len(self.words) // 8) * 8
        bits, ok = second.view(np.uint64), np.ones(len(keys), bool)
        for i in range(PROBES):
            bit = (bits >> np.uint64(7 * i)) % np.uint64(BLOCK_BITS)
            word = self.words[start + (bit >> np.uint64(6)).astype(np.int64)]
            ok &= (word >> (bit & np.uint64(63))) & np.uint64(1) == 1
        return ok


def judge(pages: DataFrame, rules: DataFrame, listed: DataFrame | None = None, *, most_bytes: int = 64 << 20) -> DataFrame:
    """pages: page_id, url. rules: host, path, verdict. listed: urls (column ``url``) that are blocked as such.
    Returns page_id, url, host, path, rule, listed (whether the exact URL is listed), verdict."""
    spark = pages.sparkSession
    entries = rules.select(F.lower("host").alias("e_host"), F.col("path").alias("e_path"), "verdict").withColumn("kind", F.lit("p")).withColumn("e_key", F.concat("e_host", "e_path"))
    if listed is not None:
        host, path = url_parts(F.col("url"))
        exact = listed.select(host.alias("e_host"), path.alias("e_path")).where("e_host <> ''")
        entries = entries.unionByName(exact.select("e_host", "e_path", F.lit("block").alias("verdict"), F.lit("u").alias("kind"), canonical(F.col("e_host"), F.col("e_path")).alias("e_key")))
    entries = entries.groupBy("kind", "e_key").agg(F.max("verdict").alias("verdict"), F.first("e_host").alias("e_host")).withColumn("key", F.xxhash64("kind", "e_key"))
    # how many entries, and at which path lengths: a few numbers
    facts = rules.agg(F.collect_set(F.length("path"))).first()[0] or []
    n = entries.count()
    lengths = sorted(facts)
    host, path = url_parts(F.col("url"))
    rows = pages.select("page_id", "url", host.alias("host"), path.alias("path"))
    labels = F.split("host", r"\.")
    parents = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.concat_ws(".", F.slice(labels, i, F.size(labels))))
    heads = F.array(*[F.when(F.length("path") >= k, F.substring("path", 1, k)) for k in lengths]) if lengths else F.array().cast("array<string>")
    heads = F.filter(heads, lambda p: p.isNotNull())
    keys = F.flatten(F.transform(parents, lambda h: F.transform(heads, lambda p: F.struct(F.lit("p").alias("kind"), F.concat(h, p).alias("e_key"), F.length(h).alias("h"), F.length(p).alias("p")))))
    if listed is not None:
        keys = F.concat(keys, F.array(F.struct(F.lit("u").alias("kind"), canonical(F.col("host"), F.col("path")).alias("e_key"), F.lit(1 << 30).alias("h"), F.lit(0).alias("p"))))
    # each distinct (host, path) once: a third of all pages may share one
    urls = rows.where("host <> ''").select("host", "path").distinct()
    probes = urls.select("host", "path", F.explode(keys).alias("k")).select("host", "path", "k.*").withColumn("key", F.xxhash64("kind", "e_key"))
    blocks = Filter.blocks_for(n)
    if n == 0:
        probes = probes.where("false")
    elif blocks * 64 <= most_bytes:
        bloom = spark.sparkContext.broadcast(Filter.build(entries.select("key"), blocks).words)
        columns = probes.columns
        probes = probes.withColumn("second", F.xxhash64("key", F.lit(1)))

        def pass_on(batches):
            bits = Filter(bloom.value)
            for b in batches:
                ok = bits.passes(b.column("key").to_numpy(zero_copy_only=False), b.column("second").to_numpy(zero_copy_only=False))
                yield b.select(columns).filter(pa.array(ok))

        probes = arrow_map(probes, pass_on, probes.drop("second").schema)
    fits = probes.join(entries.select("kind", "e_key", "verdict"), ["kind", "e_key"])
    best = fits.groupBy("host", "path").agg(
        F.max(F.when(F.col("kind") == "p", F.struct("h", "p", F.col("e_key").alias("rule"), "verdict"))).alias("r"), F.max((F.col("kind") == "u").cast("int")).alias("u")
    )
    found = best.select(F.col("host").alias("f_host"), F.col("path").alias("f_path"), "r", "u")
    out = rows.join(found, (rows["host"] == found["f_host"]) & (rows["path"] == found["f_path"]), "left")
    named = F.coalesce(F.col("u") == 1, F.lit(False))
    return out.select("page_id", "url", "host", "path", F.col("r.rule").alias("rule"), named.alias("listed"), F.coalesce(F.col("r.verdict"), F.when(named, "block").otherwise("allow")).alias("verdict"))
