"""Mixing sources to target weights by a multivariate-hypergeometric splitting tree.

Each source's documents, in an order fixed by a keyed digest, form one stream of words, cut into blocks of equal length
(the last one shorter). A source's quota is the whole blocks in its target; what remains below a block is taken from one or
a few more blocks, so that targets are met to the word. A binary tree over the output shards splits the quotas of all
sources at once: at each node the left half gets a multivariate hypergeometric draw of the node's blocks, the right half
the rest, so shards are equally large and hold chance mixtures. numpy draws the law exactly below 1e9 blocks; block
lengths grow with the input so that there are never more than about 5e8.

The leaves decide what is taken. A source's blocks are permuted by a keyed one-to-one map, one for each time round. Where a
quota exceeds the blocks, a first time round takes each block once, dealt to shards by the leaves' cumulative counts; of the last
round only a part is taken: the permuted blocks are cut into territories in proportion to the leaves, and a shard draws
its leaf's count from its territory, from a keyed start on. So blocks are disjoint within a round, none is taken more than
twice, and another tree draws other blocks. A shard shuffles its pieces by another keyed digest. The tree has
2 * shards - 1 nodes of one integer per source and lives on the driver, as do four integers per shard and source;
documents never do.

Defined results: null text has size 0, as has an empty one: taken 0; a null source is a source of its own, last in
order; a source of size 0 gets target 0; an empty table gives an empty result. doc_id repeated: each row is a document.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import WORD, materialise, numbered, text_or_empty, word_bounds

WEIGHTS = (5, 2, 1)
#: Blocks of all sources together; twice as many may be drawn, below numpy's bound of 1e9.
MOST_BLOCKS = 1 << 28


def word_count(text: Column) -> Column:
    return F.regexp_count(text, F.lit(WORD)).cast("long")


def in_order(names) -> list:
    """By code point, null last."""
    return sorted(names, key=lambda s: (s is None, (s or "").encode("utf-32-be")))


def targets(sizes: list[tuple[str | None, int]], *, weights=WEIGHTS, share=1.5, cap=2.0) -> dict[str | None, float]:
    """Words to take of each source: ``share`` of all, dealt by weight, none above ``cap`` times its own size."""
    names = in_order(s for s, _ in sizes)
    size = dict(sizes)
    weight = {s: weights[i % len(weights)] for i, s in enumerate(names)}
    left, out, open_ = share * sum(size.values()), {}, set(names)
    while open_:
        unit = left / sum(weight[s] for s in open_)
        full = {s for s in open_ if unit * weight[s] >= cap * size[s]}
        for s in full:
            out[s] = cap * size[s]
        if not full:
            return out | {s: unit * weight[s] for s in open_}
        open_ -= full
        left = max(0.0, share * sum(size.values()) - sum(out.values()))
    return out


def splitting_tree(quotas: list[int], shards: int, seed: int) -> np.ndarray:
    """Blocks of each source for each shard (shards x sources); columns sum to the quotas exactly."""
    out = np.zeros((shards, len(quotas)), np.int64)
    todo = [(0, shards, np.asarray(quotas, np.int64))]
    while todo:
        lo, hi, have = todo.pop()
        if hi - lo == 1:
            out[lo] = have
            continue
        mid, total = (lo + hi) // 2, int(have.sum())
        rng = np.random.default_rng([seed, lo, hi])
        draw = total * (mid - lo) // (hi - lo)
        left = np.zeros_like(have)
        for i, n in enumerate(have):  # one conditional hypergeometric draw per source
            rest = total - int(n)
            if n and draw:
                left[i] = rng.hypergeometric(int(n), rest, draw)
            draw -= int(left[i])
            total = rest
        todo += [(lo, mid, left), (mid, hi, have - left)]
    return out


def keyed(*parts) -> int:
    return int.from_bytes(hashlib.sha256("|".join(map(repr, parts)).encode()).digest()[:7], "little")


class Draw:
    """What the leaves of one source take of its ``blocks`` blocks; all places are permuted ones."""

    def __init__(self, leaves: list[int], blocks: int, name: str | None, seed: int):
        self.blocks, self.quota = blocks, sum(leaves)
        self.rounds = min(1, self.quota // blocks) if self.quota else 0  # whole times round
        self.maps = []
        for k in (0, 1):
            step = 1 + keyed(seed, name, k, "step") % blocks
            while math.gcd(step, blocks) > 1:
                step = step % blocks + 1
            self.maps.append((step, keyed(seed, name, k, "start") % blocks))
        before, part = 0, self.quota - self.rounds * blocks
        self.ends, self.first, self.width, self.start, self.count = [], [], [], [], []
        for shard, n in enumerate(leaves):
            lo, hi = (max(0, x - self.rounds * blocks) for x in (before, before + n))
            before += n
            self.ends.append(min(before, self.rounds * blocks))
            # of the last round: the territory, where the shard starts in it, and how many blocks it takes
            a, b = (blocks * lo // part, blocks * hi // part) if part else (0, blocks * (shard == len(leaves) - 1))
            self.first.append(a)
            self.width.append(b - a)
            self.start.append(keyed(seed, name, shard, n, "draw") % (b - a) if b > a else 0)
            self.count.append(hi - lo)

    def place(self, block: int, round_: int) -> int:
        step, start = self.maps[round_]
        return (block * step + start) % self.blocks

    def drawn(self, place: int) -> bool:
        """Whether the last round takes the place."""
        k = int(np.searchsorted(self.first, place, "right")) - 1
        return (place - self.first[k] - self.start[k]) % self.width[k] < self.count[k]

    def spare(self):
        """Places of the last round that no shard has drawn."""
        for a, w, s, n in zip(self.first, self.width, self.start, self.count):
            for i in range(n, w):
                yield a + (s + i) % w


def plan(size: dict, goal: dict, *, cap: float, shards: int, block_words: int, seed: int, tree=splitting_tree) -> list[tuple]:
    """A row for each source: name, its words, target, words to take, block length, blocks, rounds, both maps, the ends
    of shards in the whole round, their territories and draws in the last one, and the rest: (place, words) taken below a block."""
    names = in_order(goal)
    longest = max(block_words, -(-sum(size.values()) // MOST_BLOCKS))
    words = {s: min(math.floor(goal[s] + 0.5), math.floor(cap * size[s])) for s in names}
    length = {s: max(1, min(longest, size[s] // shards)) for s in names}
    leaves = tree([words[s] // length[s] for s in names], shards, seed)
    out = []
    for i, s in enumerate(names):
        if not size[s]:
            continue
        blocks, short = -(-size[s] // length[s]), size[s] % length[s] or length[s]
        draw = Draw(leaves[:, i].tolist(), blocks, s, seed)
        span = lambda p: short if p == draw.place(blocks - 1, draw.rounds) else length[s]
        lost = length[s] - short  # words that a whole block has more than the last one
        left = words[s] - draw.quota * length[s] + draw.rounds * lost + draw.drawn(draw.place(blocks - 1, draw.rounds)) * lost
        rest = []
        for p in draw.spare():
            if left <= 0:
                break
            rest.append((p, min(left, span(p))))
            left -= rest[-1][1]
        out.append((s, size[s], float(goal[s]), words[s], length[s], blocks, draw.rounds, *draw.maps[0], *draw.maps[1], draw.ends, draw.first, draw.width, draw.start, draw.count, rest))
    return out


PLAN = (
    "t_source string, t_size long, t_goal double, t_words long, t_length long, t_blocks long, t_rounds int, t_step0 long, t_start0 long, t_step1 long, t_start1 long, "
    "t_ends array<long>, t_first array<long>, t_width array<long>, t_start array<long>, t_count array<long>, t_rest array<struct<place:long,words:long>>"
)


def mix(docs: DataFrame, *, weights=WEIGHTS, share=1.5, cap=2.0, shards: int = 64, block_words: int = 4096, seed: int = 17, tree=splitting_tree, keys: list[str] | None = None) -> tuple[DataFrame, DataFrame]:
    """(documents, pieces). documents: doc_id, source, size, before (place in its source's stream), source_size,
    target. pieces: the runs of words that the shards draw: doc_id, source, size, before, round, block, start_word, n_words,
    shard, place (order inside the shard). ``keys`` names more columns of ``docs`` to carry in both."""
    keys = keys or []
    spark = docs.sparkSession
    turn = F.sha2(F.concat(F.lit(f"{seed}|"), F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.lit("|"), F.md5(text_or_empty())), 256)
    base = materialise(docs.select("doc_id", "source", word_count(text_or_empty()).alias("size"), F.substring(turn, 1, 32).alias("turn"), *keys), "mix-sizes")
    size = {r[0]: r[1] for r in base.groupBy("source").agg(F.sum("size")).collect()}
    goal = targets(list(size.items()), weights=weights, share=share, cap=cap)
    facts = F.broadcast(spark.createDataFrame(plan(size, goal, cap=cap, shards=shards, block_words=block_words, seed=seed, tree=tree), PLAN))
    placed = numbered(base, ["source"], ["turn", "doc_id", "size"], "size", spread=F.conv(F.substring("turn", 1, 8), 16, 10).cast("long"))
    named = placed.join(facts, placed["source"].eqNullSafe(F.col("t_source")), "left")
    of = lambda name: F.col(f"t_{name}")
    first, last = F.floor(F.col("before") / of("length")), F.floor((F.col("before") + F.col("size") - 1) / of("length"))
    cut = named.where("size > 0").withColumn("block", F.explode(F.sequence(first.cast("long"), last.cast("long"))))
    at = lambda k: F.pmod(F.col("block") * of(f"step{k}") + of(f"start{k}"), of("blocks"))
    # the whole round: places go to shards by cumulative counts
    whole = F.struct(F.lit(0).alias("round"), F.size(F.filter(of("ends"), lambda e: e <= at(0))).alias("shard"), of("length").alias("most"))
    # the last round: the shard whose territory holds the place, if its draw does
    place = F.when(of("rounds") == 1, at(1)).otherwise(at(0))
    shard = F.size(F.filter(of("first"), lambda a: a <= place)) - 1
    cell = lambda name: F.get(of(name), F.col("l_shard"))
    cut = cut.withColumn("l_place", place).withColumn("l_shard", shard)
    inside = F.pmod(F.col("l_place") - cell("first") - cell("start"), cell("width"))
    rest = F.get(F.filter(of("rest"), lambda r: r.place == F.col("l_place")), F.lit(0)).words
    most = F.when(inside < cell("count"), of("length")).otherwise(rest)
    part = F.struct(of("rounds").alias("round"), F.col("l_shard").alias("shard"), most.alias("most"))
    taken = F.filter(F.array(F.when(of("rounds") == 1, whole), F.when(most.isNotNull(), part)), lambda x: x.isNotNull())
    cut = cut.withColumn("draw", F.explode(taken))
    lo = F.greatest(F.col("before"), F.col("block") * of("length"))
    hi = F.least(F.col("before") + F.col("size"), F.col("block") * of("length") + F.col("draw.most"))
    pieces = cut.select(
        "doc_id", "source", "size", "before", F.col("draw.round").alias("round"), "block", (lo - F.col("before")).cast("long").alias("start_word"), (hi - lo).cast("long").alias("n_words"), F.col("draw.shard").cast("long").alias("shard"),
        F.xxhash64(F.lit(seed), "source", "block", "turn", F.col("draw.round")).alias("place"), *keys,
    ).where("n_words > 0")
    documents = named.select("doc_id", "source", "size", "before", F.coalesce(of("size"), F.lit(0)).cast("long").alias("source_size"), F.coalesce(of("goal"), F.lit(0.0)).alias("target"), *keys)
    return documents, pieces


def taken_words(docs: DataFrame, **options) -> DataFrame:
    """doc_id, size, source_size, target, taken for every row: what the shards' pieces hold of each document."""
    documents, pieces = mix(docs, **options)
    drawn = pieces.groupBy(F.col("source").alias("p_source"), F.col("before").alias("p_before")).agg(F.sum("n_words").alias("drawn"))
    same = documents["source"].eqNullSafe(drawn["p_source"]) & (documents["before"] == drawn["p_before"]) & (documents["size"] > 0)
    return documents.join(drawn, same, "left").select("doc_id", "size", "source_size", "target", F.coalesce("drawn", F.lit(0)).cast("long").alias("taken"))


def mixed_documents(docs: DataFrame, *, slice_words: int = 4_000_000, **options) -> DataFrame:
    """The mix as rows with the columns of ``docs``, a row for each piece, shard by shard in their shuffled orders: partitions
    hold whole shards, or runs of ``slice_words`` words of one. A piece holds its words and the white space between them; a
    document drawn whole keeps its text as it is. n_chars, if present, follows the text. Clashing column names of the
    input are kept as they are: the operator carries the row as one struct."""
    columns = docs.columns
    rows = docs.withColumn("mix_row", F.struct(*columns)).select("doc_id", "source", "text", "mix_row").withColumn("mix_key", F.sha2(F.to_json("mix_row"), 256))
    _, pieces = mix(rows, keys=["mix_key"], **options)
    pieces = materialise(pieces.select("mix_key", "size", "start_word", "n_words", "shard", "place"), "pieces")
    amount = pieces.agg(F.coalesce(F.sum("n_words"), F.lit(0)), F.coalesce(F.max("shard"), F.lit(0)) + 1).first()
    slices = max(1, -(-amount[0] // (slice_words * amount[1])))
    # rows equal in all columns stand for each other
    texts = rows.select(F.col("mix_key").alias("row_key"), "mix_row").dropDuplicates(["row_key"])
    parts = pieces.join(texts, F.col("mix_key") == F.col("row_key"))

    @F.pandas_udf("string")
    def run(texts: pd.Series, starts: pd.Series, counts: pd.Series) -> pd.Series:
        out = []
        for text, lo, n in zip(texts, starts, counts):
            data = text.encode()
            begins, ends, _ = word_bounds(np.frombuffer(data, np.uint8), np.array([0, len(data)]))
            out.append(data[begins[lo] : ends[lo + n - 1]].decode())
        return pd.Series(out, dtype=object)

    # whole documents never leave the JVM: the function sees a text only where a block ends inside it
    place = [F.col("shard"), F.floor((F.col("place") / 2.0**64 + 0.5) * slices).alias("slice"), F.col("place")]
    body = F.struct(*[F.col("mix_text").alias(c) if c == "text" else F.length("mix_text").cast(docs.schema[c].dataType).alias(c) if c == "n_chars" else F.col("mix_row")[c].alias(c) for c in columns])
    cut = parts.where("n_words < size").withColumn("mix_text", run(F.col("mix_row.text"), F.col("start_word"), F.col("n_words"))).select(*place, body.alias("row"))
    whole = parts.where("n_words = size").select(*place, F.col("mix_row").alias("row"))
    return whole.unionByName(cut).repartition("shard", "slice").sortWithinPartitions("shard", "slice", "place").select("row.*")
