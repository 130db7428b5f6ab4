"""Exact top-k inner-product search over an impact-ordered index, score at a time.

Components become integers floor(256 x). The index splits every component into a signed impact level (quantum
``step``) and a remainder of 0 to step - 1; a posting segment of a shard is the list of rows that have one level in one
dimension, none for level 0. Segments are processed by descending |level|, for all queries of a block at once: a segment
adds level * step * weight of the query to the accumulators of its rows. What is unprocessed bounds what a score can still
change; a query stops when at most a few candidates can reach its k-th proven score, and only these are rescored exactly in
integers. A query whose proof never comes goes through all segments, then rescores those that the remainders leave
possible. No result is approximate.

Shards are batches of candidates; each gives its k best for each query, then the best k are taken over shards. Queries
come in blocks of at most ``block`` rows, each a broadcast of a checked size.

Defined results: vectors null, empty, or with a null or non-finite component take no part, nor do rows with a null
vec_id as queries; shorter vectors count as padded by zeros; a query's own row (same vec_id) is no candidate; repeated
rows of one vec_id are each candidates; ties go to the smaller vec_id; fewer candidates than k give fewer rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import arrow_map
from pyspark.sql import Window as W

SCALE = 256


def usable(col: Column) -> Column:
    fine = F.forall(col, lambda x: F.coalesce((F.abs(x.cast("double")) < float("inf")) & ~F.isnan(x.cast("double")), F.lit(False)))
    return F.coalesce((F.size(col) > 0) & fine, F.lit(False))


def quantised(col: Column) -> Column:
    return F.transform(col, lambda x: F.floor(F.lit(float(SCALE)) * x.cast("double")).cast("long"))


def as_matrix(column: pa.Array, width: int) -> np.ndarray:
    """Rows of a list column, padded by zeros to ``width``."""
    flat, heads = column.flatten().to_numpy(zero_copy_only=False), np.asarray(column.offsets)
    heads = heads - heads[0]
    n = np.diff(heads)
    if len(n) and (n == width).all():
        return flat.reshape(-1, width)
    out = np.zeros((len(n), width), np.int64)
    row = np.repeat(np.arange(len(n)), n)
    out[row, np.arange(len(flat)) - np.repeat(heads[:-1], n)] = flat
    return out


class Index:
    """The impact-ordered index of one shard: for each (level, dimension) that occurs, level 0 apart, the list of its rows."""

    def __init__(self, rows: np.ndarray, step: int = 16):
        self.rows, self.step, self.rest = rows, step, step - 1  # remainders lie in 0..rest
        n, width = rows.shape
        level = np.floor_divide(rows, step).T.reshape(-1)  # one dimension after the other
        at = np.flatnonzero(level)
        dimension, row = np.divmod(at, max(n, 1))
        level = level[at]
        order = np.lexsort((row, dimension, level, -np.abs(level)))
        self.postings, dimension, level = row[order], dimension[order], level[order]
        heads = np.flatnonzero(np.r_[True, (level[1:] != level[:-1]) | (dimension[1:] != dimension[:-1])]) if len(level) else np.zeros(0, np.int64)
        self.heads, self.ends = heads, np.append(heads[1:], len(level))
        self.level, self.dimension = level[heads], dimension[heads]

    def segments(self):
        """Yields (bound, lists) by descending impact: the lists of sizes in one octave, and the largest |level| that is left
        after them."""
        size = np.abs(self.level)
        lo = 0
        while lo < len(size):
            low = 1 << (int(size[lo]).bit_length() - 1)
            hi = int(np.searchsorted(-size, -low, "right"))
            yield int(size[hi]) if hi < len(size) else 0, range(lo, hi)
            lo = hi

    def search(self, queries: np.ndarray, k: int, own: np.ndarray, spare: int = 64) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(query number, row number, score) of the k best rows for each query; own[q] lists rows to leave out as a
        mask. Ties are kept: all rows that score as the k-th does come back."""
        n, none = len(self.rows), np.iinfo(np.int64).min // 2
        active, found = np.arange(len(queries)), {}
        acc = np.zeros((n, len(queries)), np.int64)
        q = np.ascontiguousarray(queries.T)  # dimension by query
        for left, lists in self.segments():
            for i in lists:
                acc[self.postings[self.heads[i] : self.ends[i]]] += self.level[i] * self.step * q[self.dimension[i]]
            # a component whose list is still to come, and any remainder, bound what a score can gain or lose
            reach = left * self.step
            positive, negative = np.maximum(q, 0).sum(axis=0), np.minimum(q, 0).sum(axis=0)
            up, down = positive * (reach + self.rest) - negative * reach, negative * (reach + self.rest) - positive * reach
            scores = np.where(own[active].T, none, acc)
            kth = np.partition(scores, n - k, axis=0)[n - k] if n > k else np.full(len(active), none)
            may = scores + up >= kth + down
            proved = (may.sum(axis=0) <= max(spare, 4 * k)) | (left == 0)
            for i in np.flatnonzero(proved):
                found[active[i]] = np.flatnonzero(may[:, i] & ~own[active[i]])
            if proved.any():
                active, acc, q = active[~proved], np.ascontiguousarray(acc[:, ~proved]), np.ascontiguousarray(q[:, ~proved])
            if not len(active):
                break
        for a in active:  # no list at all: every row is possible
            found.setdefault(a, np.flatnonzero(~own[a]))
        out_q, out_r, out_s = [], [], []
        for a, members in found.items():
            exact = self.rows[members] @ queries[a]
            if len(members) > k:
                edge = np.partition(exact, len(exact) - k)[len(exact) - k]
                members, exact = members[exact >= edge], exact[exact >= edge]
            out_q.append(np.full(len(members), a))
            out_r.append(members)
            out_s.append(exact)
        cat = lambda x: np.concatenate(x) if x else np.zeros(0, np.int64)
        return cat(out_q), cat(out_r), cat(out_s)


def top_k(vectors: DataFrame, *, every: int = 50, k: int = 5, block: int = 16_384, step: int = 16, shard: int = 4096) -> DataFrame:
    """query_id, rank, vec_id, score for queries whose vec_id is divisible by ``every``, against all rows."""
    spark = vectors.sparkSession
    fine = vectors.where(usable(F.col("embedding"))).select(F.col("vec_id").cast("long").alias("vec_id"), quantised(F.col("embedding")).alias("v"))
    width = fine.agg(F.max(F.size("v"))).first()[0] or 1
    chosen = fine.where(F.col("vec_id").isNotNull() & (F.pmod("vec_id", F.lit(every)) == 0))
    total = chosen.count()
    parts = max(1, -(-total // block))
    out = None
    for p in range(parts):  # each block of queries is one bounded broadcast
        own = chosen if parts == 1 else chosen.where(F.pmod(F.xxhash64("vec_id"), F.lit(parts)) == p)
        mine = own.select("vec_id", "v").toArrow()
        names = mine.column("vec_id").to_numpy()
        wanted = spark.sparkContext.broadcast((names, as_matrix(mine.column("v").combine_chunks() if len(names) else pa.array([], pa.list_(pa.int64())), width)))

        def search(batches):
            names, queries = wanted.value
            for b in batches:
                for lo in range(0, b.num_rows if len(names) else 0, shard):
                    part = b.slice(lo, shard)
                    column = part.column("v")
                    index = Index(as_matrix(column, width), step)
                    ids, named = part.column("vec_id").fill_null(0).to_numpy(), part.column("vec_id").is_valid().to_numpy(zero_copy_only=False)
                    for at in range(0, len(names), 256):
                        q, r, s = index.search(queries[at : at + 256], k, (names[at : at + 256, None] == ids[None, :]) & named[None, :])
                        yield pa.RecordBatch.from_pydict({"query_id": pa.array(names[at + q]), "vec_id": part.column("vec_id").take(pa.array(r)), "score": pa.array(s)})

        found = arrow_map(fine, search, "query_id long, vec_id long, score long")
        best = found.withColumn("rank", F.row_number().over(W.partitionBy("query_id").orderBy(F.col("score").desc(), F.col("vec_id").asc_nulls_last()))).where(F.col("rank") <= k)
        out = best if out is None else out.unionByName(best)
    return out.select("query_id", "rank", "vec_id", "score")
