"""Exact Jaccard join of word-shingle sets as a metric-space join over pivots.

The distance is 1 - |x and y| / |x or y|, a metric. Documents with one and the same set are one point.

First level: the pivots are the single shingles. A point is equally near to all of its own shingles; the tie goes to the
first in a common order (frequent shingles of a sample last, then by hash), whose Voronoi region it joins. Points within
the radius share one of the first n - ceil(0.8 n) + 1 shingles of that order, so the boundary windows replicate a point into
exactly those regions. The windows reach a tenth of the set further; then points within the radius share a tenth of their
sizes more. Only the number of shared windows of each point leaves this level: a point with too few has no partner.

Second level: the regions join recursively among the points that are left, with pivots of their own. The exact number of
these points that hold a shingle gives a new order, rarest first; a shingle that one point alone holds is no pivot. What a
family of near copies has in common so comes last, and passages shared by otherwise different texts open no window at all.
Points are dropped by the same count, and the connected pieces of what overlaps are the new regions.

Inside a region the join goes on with whole sets (``matched``): points near a first pivot are one class at once; for the others
the triangle inequality over a few pivots and the windows of the region's own order leave few pairs, whose distances are
measured where they lie. Pairs of one class are never compared. A region gives the links that join its classes, fewer than
its points; pairs that fail never become rows.

A region too large for a task first meets four pivots; the class around them is settled, and only the points outside it are
compared with all others, block by block. No partner or candidate is capped.

Distances are computed on whole sets of 64-bit shingle hashes. A very frequent shingle's region is dealt by points, not
kept in one task.

Defined results: null or empty text, or one without words: set size 0, linked with nothing; fewer words than
``order``: the whole sequence is one shingle; rows with a null doc_id take no part (component null); rows that share a
doc_id are one node; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, as_long, gram_hashes, materialise, mix64, text_or_empty, words_of
from .components import components
from .packed import buckets_for, regroup, runs_of, split_by, text_bytes

MOST_BROADCAST = 2_000_000
#: Shingles of a region, or of a block of a larger one, that one task joins.
CELL_SHINGLES = 2_000_000
#: Shingles looked up at a time in ``matched``.
SLICE = 1 << 21
#: A point is (id, tag): rows that share a doc_id but not their text differ in the tag, 32 bits of the set's digest.
ENTRY = np.dtype([("h", "<u8"), ("id", "<i8"), ("n", "<u4"), ("tag", "<u4")])
SHARED = np.dtype([("id", "<i8"), ("n", "<u4"), ("tag", "<u4"), ("k", "<u4")])
HELD = np.dtype([("h", "<u8"), ("id", "<i8"), ("n", "<u4"), ("tag", "<u4"), ("c", "<u4")])
_SALT = np.uint64(0xA0761D6478BD642F)


def shingle_sets(column: pa.Array, order: int):
    """Yields (row, sorted distinct shingle hashes) for every text."""
    for lo, words, heads in words_of(column):
        grams = gram_hashes(words, order)
        for i in range(len(heads) - 1):
            a, b = int(heads[i]), int(heads[i + 1])
            if b - a >= order:
                yield lo + i, np.unique(grams[a : b - order + 1])
            elif b > a:
                yield lo + i, gram_hashes(words[a:b], b - a)
            else:
                yield lo + i, words[:0]


def digests(s: np.ndarray) -> tuple[int, int]:
    """Two 64-bit digests of a set."""
    return (int(mix64(s ^ _SALT).sum(dtype=np.uint64)), int(mix64(s + _SALT).sum(dtype=np.uint64))) if len(s) else (0, 0)


def least_windows(n, percent: int):
    """Shingles in a common order of which two points within the radius share one."""
    return n + percent * n // -100 + 1


def prefix_length(n, percent: int):
    """Shingles that a point's windows cover: ``least_windows`` and a tenth of the set."""
    return least_windows(n, percent) + n // 10


def least_shared(n, percent: int):
    """Windows that a point with a partner shares at least: a partner may be smaller, and its extension shorter."""
    return 1 + -(percent * n // -100) // 10


def late_ranks(h: np.ndarray, frequent: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """1 + the rank of each shingle among the frequent ones, 0 for others."""
    names, ranks = frequent
    if not len(names):
        return np.zeros(len(h), np.int64)
    at = np.searchsorted(names, h)
    at[at == len(names)] = 0
    return np.where(names[at] == h, 1 + ranks[at], 0)


def frequent_shingles(docs: DataFrame, order: int, *, sample: int, most: int, least: int = 4) -> tuple[np.ndarray, np.ndarray]:
    """Hashes, sorted, that recur in a bounded sample of documents, and their ranks by rising frequency; they only move
    regions, never results."""
    n = docs.count()
    some = docs.where(F.pmod(F.xxhash64("doc_id"), F.lit(max(1, n // sample))) == 0)

    def emit(batches):
        for b in batches:
            sets = [s for _, s in shingle_sets(b.column("text"), order) if len(s)]
            if sets:
                h, c = np.unique(np.concatenate(sets), return_counts=True)
                yield pa.RecordBatch.from_arrays([as_long(h), pa.array(c.astype(np.int64))], names=["h", "c"])

    rows = arrow_map(some.select(text_or_empty().alias("text")), emit, "h long, c long").groupBy("h").agg(F.sum("c").alias("c")).where(F.col("c") >= least)
    top = rows.orderBy(F.col("c").desc(), "h").limit(most).select("h", "c").toArrow()
    h, c = top.column("h").to_numpy().view(np.uint64), top.column("c").to_numpy()
    by_count = np.empty(len(h), np.int64)
    by_count[np.lexsort((h, c))] = np.arange(len(h))
    by_hash = np.argsort(h)
    return h[by_hash], by_count[by_hash]


def points_of(docs: DataFrame, order: int, percent: int, frequent) -> DataFrame:
    """doc_id, n, k1, k2 (digests of the set) and the prefix in the common order as packed hashes."""
    common = docs.sparkSession.sparkContext.broadcast(frequent)

    def shingle(batches):
        for b in batches:
            size, k1, k2, prefix = [], [], [], []
            for _, s in shingle_sets(b.column("text"), order):
                size.append(len(s))
                for keys, k in zip((k1, k2), digests(s)):
                    keys.append(k)
                if len(s):
                    s = s[np.argsort(late_ranks(s, common.value), kind="stable")]
                prefix.append(s[: prefix_length(len(s), percent) if len(s) else 0].tobytes())
            to_long = lambda x: as_long(np.array(x, np.uint64))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(size, pa.int64()), to_long(k1), to_long(k2), pa.array(prefix, pa.binary())], names=["doc_id", "n", "k1", "k2", "prefix"])

    return arrow_map(docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text")), shingle, "doc_id long, n long, k1 long, k2 long, prefix binary")


def _entries(b: pa.RecordBatch, column: str) -> np.ndarray:
    """The packed hashes of a batch's rows (id, tag, n, column) as entries."""
    bodies = b.column(column).to_pylist()
    counts = np.array([len(x) // 8 for x in bodies], np.int64)
    out = np.zeros(int(counts.sum()), ENTRY)
    out["h"] = np.frombuffer(b"".join(bodies), "<u8")
    for k in ("id", "tag", "n"):
        out[k] = np.repeat(b.column(k).to_numpy(), counts)
    return out


def _buckets(entries: np.ndarray, buckets: int, frequent) -> tuple[np.ndarray, np.ndarray]:
    """(bucket, late rank): by hash, but a frequent shingle's entries are dealt by points over buckets of their own."""
    late = late_ranks(entries["h"], frequent)
    return np.where(late > 0, buckets + _home(entries, buckets), ((entries["h"] >> np.uint64(20)) % np.uint64(buckets)).astype(np.int64)), late


def _home(entries: np.ndarray, buckets: int) -> np.ndarray:
    return (mix64(entries["id"].astype(np.uint64)) % np.uint64(buckets)).astype(np.int64)


def _groups(*columns: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First row of each run of equal values, and the runs' lengths."""
    change = np.zeros(len(columns[0]), bool)
    change[:1] = True
    for c in columns:
        change[1:] |= c[1:] != c[:-1]
    heads = np.flatnonzero(change)
    return heads, np.diff(np.append(heads, len(columns[0])))


def promising(points: DataFrame, percent: int, frequent, buckets: int) -> DataFrame:
    """id of the points (id, tag, n, prefix) that share enough first-level windows to have a partner."""
    common = points.sparkSession.sparkContext.broadcast(frequent)

    def emit(batches):
        for b in batches:
            out = _entries(b, "prefix")
            yield split_by(_buckets(out, buckets, common.value)[0], out)

    def count(bucket, got):
        if bucket < buckets:  # windows of one point alone are not shared
            got = got[np.lexsort((got["tag"], got["id"], got["h"]))]
            got = got[_groups(got["h"], got["id"], got["tag"])[0]]
            _, size = _groups(got["h"])
            got = got[np.repeat(size, size) > 1]
        if len(got):
            got = got[np.lexsort((got["tag"], got["id"]))]
            heads, size = _groups(got["id"], got["tag"])
            out = np.zeros(len(heads), SHARED)
            for k in ("id", "n", "tag"):
                out[k] = got[k][heads]
            out["k"] = size
            yield split_by(_home(out, buckets), out)

    def total(bucket, got):
        got = got[np.lexsort((got["tag"], got["id"]))]
        heads, _ = _groups(got["id"], got["tag"])
        enough = np.add.reduceat(got["k"].astype(np.int64), heads) >= least_shared(got["n"][heads].astype(np.int64), percent)
        yield pa.RecordBatch.from_arrays([pa.array(np.unique(got["id"][heads[enough]]))], names=["id"])

    windows = regroup(arrow_map(points, emit, "bucket int, body binary"), buckets, ENTRY, count, "bucket int, body binary")
    return regroup(windows, buckets, SHARED, total, "id long")


def small(ids: DataFrame) -> DataFrame:
    """A table of numbers, to be broadcast if it has at most MOST_BROADCAST rows, else joined by a shuffle."""
    return F.broadcast(ids) if ids.count() <= MOST_BROADCAST else ids


def gather_sets(docs: DataFrame, ids: DataFrame, order: int) -> DataFrame:
    """id, tag, n, body: the whole shingle sets of the documents in ``ids`` only."""
    wanted = small(ids.select(F.col("id").alias("want")))

    def shingle(batches):
        for b in batches:
            sets = [s for _, s in shingle_sets(b.column("text"), order)]
            tags = pa.array([digests(s)[0] & 0xFFFFFFFF for s in sets], pa.int64())
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), tags, pa.array([len(s) for s in sets], pa.int64()), pa.array([s.tobytes() for s in sets], pa.binary())], names=["id", "tag", "n", "body"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text"))
    found = rows.join(wanted, rows["doc_id"] == F.col("want"), "left_semi")
    return materialise(arrow_map(found, shingle, "id long, tag long, n long, body binary").where("n > 0"), "sets")


def overlaps(sets: DataFrame, percent: int, frequent, buckets: int) -> DataFrame:
    """a, b: edges from points to the second-level windows that they share, for points that share enough of them."""
    common = sets.sparkSession.sparkContext.broadcast(frequent)

    def emit(batches):
        for b in batches:
            out = _entries(b, "body")
            yield split_by(_buckets(out, buckets, common.value)[0], out)

    def count(bucket, got):
        out = np.zeros(len(got), HELD)
        for k in ENTRY.names:
            out[k] = got[k]
        if bucket < buckets:
            out = out[np.lexsort((out["tag"], out["id"], out["h"]))]
            out = out[_groups(out["h"], out["id"], out["tag"])[0]]
            _, size = _groups(out["h"])
            out["c"] = np.repeat(np.minimum(size, 1 << 31), size)
            out = out[out["c"] > 1]
        else:
            out["c"] = (1 << 31) + late_ranks(out["h"], common.value)
        if len(out):
            yield split_by(_home(out, buckets), out)

    def window(bucket, got):
        got = got[np.lexsort((got["h"], got["c"], got["tag"], got["id"]))]
        got = got[_groups(got["id"], got["tag"], got["h"])[0]]
        heads, size = _groups(got["id"], got["tag"])
        n = got["n"][heads].astype(np.int64)
        # the shingles that no other point holds come first in the order
        place = np.arange(len(got)) - np.repeat(heads, size) + np.repeat(n - size, size)
        shared = np.add.reduceat((place < np.repeat(prefix_length(n, percent), size)).astype(np.int64), heads)
        edge = (place < np.repeat(least_windows(n, percent), size)) & np.repeat(shared >= least_shared(n, percent), size)
        a, b = spanning(got["id"][edge], got["h"][edge].view(np.int64))
        yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["a", "b"])

    held = regroup(arrow_map(sets, emit, "bucket int, body binary"), buckets, ENTRY, count, "bucket int, body binary")
    return regroup(held, buckets, HELD, window, "a long, b long")


def spanning(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Edges that connect what the edges (a, b) connect, at most one for each node."""
    names, code = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = code[: len(a)], code[len(a) :]
    label = np.arange(len(names))
    while True:
        least = np.minimum(label[x], label[y])
        new = label.copy()
        np.minimum.at(new, label[x], least)
        np.minimum.at(new, label[y], least)
        while (new[new] != new).any():
            new = new[new]
        new = new[label]
        if (new == label).all():
            break
        label = new
    rest = label != np.arange(len(names))
    return names[rest], names[label[rest]]


def ranges(starts: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """All places of the ranges (starts, counts), one after the other."""
    ends = np.cumsum(counts)
    return np.arange(int(ends[-1]) if len(ends) else 0) + np.repeat(starts - (ends - counts), counts)


def matched(bodies: list[np.ndarray], label: np.ndarray, seeks: np.ndarray, percent: int, pivots: int = 4) -> list[tuple[int, int]]:
    """Links that join the classes of the given sets: every pair within the radius, one of which seeks, has one class
    in the end. label: classes known before."""
    m, size = len(bodies), np.array([len(x) for x in bodies], np.int64)
    names, flat = np.unique(np.concatenate(bodies), return_inverse=True)
    count = np.bincount(flat)
    rank = np.empty(len(names), np.int64)
    rank[np.argsort(count, kind="stable")] = np.arange(len(names))
    owner = np.repeat(np.arange(m), size)
    flat = np.sort(rank[flat] + owner * len(names)) - owner * len(names)  # each set in the region's own order
    heads = np.cumsum(size) - size
    # windows: for each shingle held twice, the points that have it in their prefix
    prefix = np.arange(len(flat)) - np.repeat(heads, size) < np.repeat(least_windows(size, percent), size)
    prefix &= np.sort(count)[flat] > 1
    by_shingle = np.flatnonzero(prefix)[np.argsort(flat[prefix], kind="stable")]
    posted, at = owner[by_shingle], np.searchsorted(flat[by_shingle], np.arange(len(names) + 1))
    mark, label, links = np.zeros(len(names), bool), label.copy(), []

    def shared(i: int, others: np.ndarray) -> np.ndarray:
        mark[flat[heads[i] : heads[i] + size[i]]] = True
        out = np.empty(len(others), np.int64)
        ends = np.cumsum(size[others])
        lo = 0
        while lo < len(others):
            hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + SLICE, "right")))
            some = others[lo:hi]
            out[lo:hi] = np.add.reduceat(mark[flat[ranges(heads[some], size[some])]].astype(np.int64), np.cumsum(size[some]) - size[some])
            lo = hi
        mark[flat[heads[i] : heads[i] + size[i]]] = False
        return out

    def link(i: int, others: np.ndarray, both: np.ndarray) -> None:
        near = others[100 * both >= percent * (size[i] + size[others] - both)]
        classes = label[near]
        for x in np.unique(classes[classes != label[i]]):
            links.append((i, int(near[np.flatnonzero(classes == x)[0]])))
        label[np.isin(label, classes)] = label[i]

    far, width = [], (100 - percent) / 100 + 1e-9
    for i in np.flatnonzero(seeks):
        if len(far) < pivots and m > 32:  # a pivot: all distances, and a class around it
            others = np.flatnonzero(np.arange(m) != i)
            both = shared(i, others)
            d = np.zeros(m)
            d[others] = 1 - both / (size[i] + size[others] - both)
            far.append(d)
            link(i, others, both)
            continue
        own = flat[heads[i] : heads[i] + size[i]][: least_windows(int(size[i]), percent)]
        others = posted[ranges(at[own], at[own + 1] - at[own])]
        others = others[(label[others] != label[i]) & (~seeks[others] | (others > i))]
        others = others[(100 * size[others] >= percent * size[i]) & (100 * size[i] >= percent * size[others])]
        for d in far:
            others = others[np.abs(d[others] - d[i]) <= width]
        if len(others):
            others = np.unique(others)
            link(i, others, shared(i, others))
    return links


def regions_joined(rows: DataFrame, percent: int) -> DataFrame:
    """a, b: the links of every cell (cell, id, tag, label, seeks, body)."""

    def run(batches):
        for _, part in runs_of(batches, "cell"):
            ids, tags = part.column("id").to_numpy(), part.column("tag").to_numpy()
            _, first = np.unique(np.stack([ids, tags]), axis=1, return_index=True)
            if len(first) < 2:
                continue
            part, ids = part.take(pa.array(first)), ids[first]
            bodies = [np.frombuffer(x.as_buffer(), "<u8") for x in part.column("body")]
            seeks = np.array(part.column("seeks").to_pylist(), bool)
            got = np.array(matched(bodies, part.column("label").to_numpy(), seeks, percent), np.int64).reshape(-1, 2)
            yield pa.RecordBatch.from_arrays([pa.array(ids[got[:, 0]]), pa.array(ids[got[:, 1]])], names=["a", "b"])

    return arrow_map(rows.repartition("cell").sortWithinPartitions("cell"), run, "a long, b long")


def pivot_links(rows: DataFrame, percent: int, pivots: int) -> DataFrame:
    """a, b: the points of each large region (region, id, tag, n, body) within the radius of one of its pivots, which are
    the points with the least hashes. Four links a point at most."""
    least = [F.min(F.struct(F.xxhash64("id", "tag", F.lit(k)).alias("o"), "id", "tag", "body")).alias(f"p{k}") for k in range(pivots)]
    chosen = rows.groupBy("region").agg(*least).select("region", F.explode(F.array(*[f"p{k}" for k in range(pivots)])).alias("p")).select("region", F.col("p.id").alias("p_id"), F.col("p.body").alias("p_body"))
    chosen = materialise(chosen.dropDuplicates(["region", "p_id"]), "pivots")

    def compare(batches):
        for b in batches:
            near = []
            for x, y in zip(b.column("body"), b.column("p_body")):
                x, y = np.frombuffer(x.as_buffer(), "<u8"), np.frombuffer(y.as_buffer(), "<u8")
                both = len(np.intersect1d(x, y, assume_unique=True)) if 100 * len(x) >= percent * len(y) and 100 * len(y) >= percent * len(x) else 0
                near.append(100 * both >= percent * (len(x) + len(y) - both))
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("p_id")], names=["a", "b"]).filter(pa.array(near, pa.bool_()))

    pairs = rows.join(F.broadcast(chosen) if chosen.count() <= 64 else chosen, "region").where("id <> p_id").select("id", "p_id", "body", "p_body")
    return arrow_map(pairs, compare, "a long, b long")


def region_links(sets: DataFrame, regions: DataFrame, percent: int, *, limit: int, pivots: int = 4) -> DataFrame:
    """a, b: links that join the classes inside the regions (node, label)."""
    held = sets.join(small(regions), sets["id"] == regions["node"]).select(F.col("label").alias("region"), "id", "tag", "n", "body")
    weight = materialise(held.groupBy("region").agg(F.sum("n").alias("weight"), F.count(F.lit(1)).alias("points")).where("points > 1").drop("points"), "weights")
    large = weight.where(F.col("weight") > limit)
    alone = held.join(weight.where(F.col("weight") <= limit), "region", "left_semi")
    cells = alone.select(F.col("region").alias("cell"), "id", "tag", F.col("id").alias("label"), F.lit(True).alias("seeks"), "body")
    if large.isEmpty():
        return materialise(regions_joined(cells, percent), "links")
    wide = materialise(held.join(F.broadcast(large), "region"), "large")  # at most the corpus over the limit
    near = materialise(pivot_links(wide, percent, pivots), "links")
    known = components(near)
    classed = wide.join(small(known), wide["id"] == known["node"], "left").select("region", "id", "tag", "n", "weight", F.coalesce("label", "id").alias("label"), "body")
    main = classed.groupBy("region", "label").agg(F.sum("n").alias("w")).groupBy("region").agg(F.max_by("label", F.struct("w", "label")).alias("main"))
    classed = materialise(classed.join(F.broadcast(main), "region").withColumn("seeks", F.col("label") != F.col("main")).drop("main"), "classed")
    # blocks of those outside the main class meet blocks of all
    some = classed.where("seeks").groupBy("region").agg(F.sum("n").alias("open"))
    spread = classed.join(F.broadcast(some), "region").withColumn("rows", F.expr(f"1 + open div {limit}")).withColumn("columns", F.expr(f"1 + weight div {limit}"))
    block = lambda k, of: F.pmod(F.xxhash64("id", F.lit(k)), F.col(of))
    own = F.transform(F.sequence(F.lit(0).cast("long"), F.col("columns") - 1), lambda j: F.struct(block(1, "rows").alias("i"), j.alias("j"), F.lit(True).alias("seeks")))
    met = F.transform(F.sequence(F.lit(0).cast("long"), F.col("rows") - 1), lambda i: F.struct(i.alias("i"), block(2, "columns").alias("j"), F.lit(False).alias("seeks")))
    dealt = spread.select("region", "id", "tag", "label", "body", F.explode(F.when(F.col("seeks"), F.concat(own, met)).otherwise(met)).alias("c"))
    # a seeking point also stands among all in its own cell: once is enough there
    dealt = dealt.groupBy(F.xxhash64("region", "c.i", "c.j").alias("cell"), "id", "tag").agg(F.first("label").alias("label"), F.max("c.seeks").alias("seeks"), F.first("body").alias("body"))
    return materialise(regions_joined(cells.unionByName(dealt), percent).unionByName(near), "links")


def links(docs: DataFrame, *, order: int = 5, percent: int = 80, sample: int = 8192, most_frequent: int = 100_000, limit: int | None = None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(points, links, labels). points: doc_id, n, rep (the smallest doc_id of its set); links: verified pairs a, b of
    different sets, enough to connect every component; labels: node, label."""
    frequent = frequent_shingles(docs, order, sample=sample, most=most_frequent)
    table = materialise(points_of(docs, order, percent, frequent), "points")
    known = table.where("doc_id is not null")
    groups = known.where("n > 0").groupBy("k1", "k2", "n").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("copies"))
    many = groups.where("copies > 1").drop("copies")
    # copies join their group's first document; a row of no larger group stands for itself
    points = known.select("doc_id", "n", "k1", "k2").join(many, ["k1", "k2", "n"], "left").select("doc_id", "n", "k1", F.coalesce("rep", "doc_id").alias("rep"))
    points = materialise(points, "reps")
    others = points.where("rep <> doc_id").select("doc_id", "k1")
    single = known.where("n > 0").join(small(others), ["doc_id", "k1"], "left_anti").select(F.col("doc_id").alias("id"), F.col("k1").bitwiseAND(F.lit(0xFFFFFFFF)).alias("tag"), "n", "prefix")
    left = materialise(promising(single, percent, frequent, buckets_for(text_bytes(docs))), "promising")
    sets = gather_sets(docs, left, order)
    total = sets.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    regions = components(overlaps(sets, percent, frequent, buckets_for(16 * total)))
    found = region_links(sets, regions, percent, limit=limit or CELL_SHINGLES)
    return points, found, components(found)


def classes(docs: DataFrame, **options) -> DataFrame:
    """doc_id, n_shingles, component_id for every document."""
    points, _, labels = links(docs, **options)
    whole = points.join(labels.withColumnRenamed("node", "rep"), "rep", "left").select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.coalesce("label", "rep")).otherwise(F.col("doc_id")).alias("component_id"))
    nameless = docs.where("doc_id is null")
    # rows without an id keep their place in the result
    empty = nameless.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text"))
    order = options.get("order", 5)

    def sizes(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array([len(s) for _, s in shingle_sets(b.column("text"), order)], pa.int64()), b.column("doc_id")], names=["doc_id", "n_shingles", "component_id"])

    return whole.unionByName(arrow_map(empty, sizes, "doc_id long, n_shingles long, component_id long"))


def representatives(docs: DataFrame, **options) -> DataFrame:
    """The rows of ``docs`` with one document of each component: the one with the smallest doc_id; repeated rows of
    that id all stay only if their texts differ."""
    found = classes(docs, **options).where("doc_id = component_id").select(F.col("doc_id").alias("keep_doc")).distinct()
    kept = docs.join(found, docs["doc_id"] == found["keep_doc"], "left_semi")
    return kept.unionByName(docs.where("doc_id is null"))
