"""Language-model scoring from a log-frequency Bloom filter of quantised n-gram counts.

A count c is stored as its level: levels are the intervals between powers of ``base`` that hold a whole number. The
filter holds the n-gram together with each level up to its own, so a count is read back by probing levels until probes
fail; counts from 1 are stored. Such a read never falls below the stored level; it may exceed it by a false positive. Counts come from all training
text: every task counts its n-grams, counts meet by hash bucket, each bucket builds the filter segments of its hashes (one
for about SEGMENT_BYTES of text). No count is dropped at any size: where the bits surely fit ``most_bytes`` the filter is broadcast, else each bucket probes
its own segment for the n-grams that slabs of text ask for, and the levels go back to the slabs. Both give equal results.

Model: p1(w) = (c(w) + 1) / (N + V + 1); p(w | v) = share * c(v w) / c(v) + (1 - share) * p1(w), all counts as the filter gives
them: numerators take the lower edge of a level, the denominator the upper edge, so probabilities of a context sum to at
most one, but for false positives. A text is its words and one end; its first context is a start mark.

The base score is exact: its unigram counts are broadcast as hashes and counts if they fit ``most_base_bytes``, else
joined by hash with the words of each text.

Defined results: null or empty text: one end token; a null doc_id counts as the empty string for the fold, so trains;
an empty table gives an empty result; repeated rows train and are scored each.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import BATCH_ROWS, SLAB, arrow_map, as_long, bound_batches, buffers, materialise, mix64, slabs, text_or_empty, words_of
from .packed import buckets_for, regroup, runs_of, split_by

#: Hashes of the end token and of the start mark: no words.
END, START = np.uint64(0xE7037ED1A0B428DB), np.uint64(0x8EBC6AF09C88C6E3)
_PAIR, _LEVEL = np.uint64(0x589965CC75374CC3), np.uint64(0x1D8E4E27C47D124F)
ENTRY = np.dtype([("h", "<u8"), ("c", "<u4"), ("order", "<u4")])
PROBES = 6
#: Bytes of text whose n-grams are asked for together where buckets answer: longer runs repeat fewer n-grams.
WIDE = 4 * SLAB
#: Bytes of text whose n-grams make a segment of the filter: making and reading one takes many times their bytes.
SEGMENT_BYTES = 2 << 20


def narrow(x: np.ndarray) -> bytes:
    """Counts as bytes of the least width that holds them all; ``widened`` reads them back."""
    return x.astype(np.min_scalar_type(int(x.max(initial=0)))).tobytes()


def widened(body, n: int) -> np.ndarray:
    return np.frombuffer(body, f"<u{len(body) // n}").astype(np.int64) if n else np.zeros(0, np.int64)


def token_stream(column: pa.Array, limit: int = SLAB):
    """Yields (first row, tokens, contexts, first token per row): words and an end per text; the context is the word
    before, or the start mark."""
    for lo, words, heads in words_of(column, limit):
        n = len(heads) - 1
        tokens = np.full(len(words) + n, END, np.uint64)
        at = heads + np.arange(n + 1)
        is_word = np.ones(len(tokens), bool)
        is_word[at[1:] - 1] = False
        tokens[is_word] = words
        contexts = np.empty_like(tokens)
        contexts[1:] = tokens[:-1]
        contexts[at[:-1]] = START
        yield lo, tokens, contexts, at


def pair_hash(contexts: np.ndarray, tokens: np.ndarray) -> np.ndarray:
    return mix64(contexts * _PAIR + tokens)


@lru_cache(maxsize=8)
def least_counts(base: float) -> np.ndarray:
    """The least count of each level, from level 1 up."""
    powers = [1.0]
    while powers[-1] < 2.0**53:
        powers.append(base ** len(powers))
    return np.unique(np.ceil(np.array(powers) - 1e-9))


def level_of(counts: np.ndarray, base: float) -> np.ndarray:
    return np.searchsorted(least_counts(base), np.maximum(counts, 1), "right").astype(np.int64)


def edges(levels: np.ndarray, base: float) -> tuple[np.ndarray, np.ndarray]:
    """Least and largest count of each level; level 0: none."""
    least = least_counts(base)
    levels = np.minimum(levels, len(least) - 1)
    low = np.where(levels > 0, least[levels - 1], 0)
    return low, np.where(levels > 0, least[levels] - 1, 0)


class LogBloom:
    """Segments by hash bucket. bits: all segments; start and size: their first bit and number of bits."""

    def __init__(self, bits: np.ndarray, start: np.ndarray, size: np.ndarray, base: float):
        self.bits, self.start, self.size, self.base = bits, start, size, base

    @staticmethod
    def probes(h: np.ndarray, level: np.ndarray | int):
        """Yields PROBES 32-bit values for each n-gram at a level."""
        key = mix64(h ^ (np.asarray(level, np.uint64) * _LEVEL))
        step = (key << np.uint64(1)) | np.uint64(1)
        for _ in range(PROBES):
            yield key >> np.uint64(32)
            key = key + step

    @staticmethod
    def place(probe: np.ndarray, size) -> np.ndarray:
        return ((probe * size) >> np.uint64(32)).astype(np.int64)

    def holds(self, salt: np.ndarray, start: np.ndarray, size: np.ndarray, level: np.ndarray) -> np.ndarray:
        """Whether n-grams are stored with a level each. They leave at their first unset bit."""
        out = np.zeros(len(salt), bool)
        alive = np.arange(len(salt))
        key = mix64(salt ^ (level.astype(np.uint64) * _LEVEL))
        step = (key << np.uint64(1)) | np.uint64(1)
        for _ in range(PROBES):
            pos = start + self.place(key >> np.uint64(32), size)
            ok = (self.bits[pos >> 3] >> (pos & 7).astype(np.uint8)) & 1 == 1
            if not ok.all():
                alive, start, size, key, step = alive[ok], start[ok], size[ok], key[ok], step[ok]
            key = key + step
        out[alive] = True
        return out

    def level(self, h: np.ndarray, order: int) -> np.ndarray:
        """Level of each n-gram by repeated membership probes, 0 if the first is absent. All levels up to
        an n-gram's own are stored, so after the first the probes go up by doubling steps until one fails, then halve
        what lies between."""
        out = np.zeros(len(h), np.int64)
        bucket = ((h >> np.uint64(20)) % np.uint64(len(self.size))).astype(np.int64)
        there = np.flatnonzero(self.size[bucket] > 0)

        def facts(rows):
            return (h ^ np.uint64(order))[rows], self.start[bucket[rows]], self.size[bucket[rows]].astype(np.uint64)

        there = there[self.holds(*facts(there), np.full(len(there), 1))]
        # frequent n-grams come many times: each is followed up once
        _, one, code = np.unique(h[there], return_index=True, return_inverse=True)
        salt, start, size = facts(there[one])
        low, high = np.zeros(len(one), np.int64), np.full(len(one), -1, np.int64)
        rows, k = np.arange(len(one)), 1
        while len(rows):
            ok = self.holds(salt[rows], start[rows], size[rows], np.full(len(rows), 1 + k))
            high[rows[~ok]] = k
            rows = rows[ok]
            low[rows] = k
            k = 2 * k + 1
        rows = np.flatnonzero(high - low > 1)
        while len(rows):
            mid = (low[rows] + high[rows]) // 2
            ok = self.holds(salt[rows], start[rows], size[rows], 1 + mid)
            low[rows[ok]], high[rows[~ok]] = mid[ok], mid[~ok]
            rows = rows[high[rows] - low[rows] > 1]
        out[there] = 1 + low[code]
        return out


def count_grams(docs: DataFrame, training: Column, buckets: int) -> DataFrame:
    """order, h, c of all uni- and bigrams of training text, packed: a row per bucket and order, h and c as binaries."""

    def emit(batches):
        for b in batches:
            for _, tokens, contexts, at in token_stream(b.column("text")):
                parts = []
                starts = np.array([len(at) - 1], np.uint32)
                for order, grams in ((1, tokens), (2, pair_hash(contexts, tokens))):
                    h, c = np.unique(grams, return_counts=True)
                    part = np.zeros(len(h), ENTRY)
                    part["h"], part["c"], part["order"] = h, c, order
                    parts.append(part)
                mark = np.zeros(1, ENTRY)  # the start mark's count: one per text
                mark["h"], mark["c"], mark["order"] = START, starts, 1
                every = np.concatenate([*parts, mark])
                yield split_by(((every["h"] >> np.uint64(20)) % np.uint64(buckets)).astype(np.int64), every)

    def handle(bucket, got):
        for order in (1, 2):
            part = got[got["order"] == order]
            h, inverse = np.unique(part["h"], return_inverse=True)
            c = np.bincount(inverse, weights=part["c"], minlength=len(h)).astype(np.int64)
            total, kinds = (int(c[h != START].sum()), int((h != START).sum())) if order == 1 else (0, 0)
            yield pa.RecordBatch.from_arrays(
                [pa.array([bucket], pa.int32()), pa.array([order], pa.int32()), pa.array([total], pa.int64()), pa.array([kinds], pa.int64()), pa.array([h.tobytes()], pa.binary()), pa.array([c.astype("<u4").tobytes()], pa.binary())],
                names=["bucket", "order", "total", "kinds", "h", "c"],
            )

    rows = arrow_map(docs.where(training).select(text_or_empty().alias("text")), emit, "bucket int, body binary")
    return regroup(rows, buckets, ENTRY, handle, "bucket int, order int, total long, kinds long, h binary, c binary")


def segment_of(parts, *, base: float, bits_a_key: int) -> np.ndarray:
    """The packed bits of one bucket's segment from its (order, hashes, counts)."""
    keys, levels = [], []
    for o, h, c in parts:
        n = level_of(c[c > 0], base)
        keys.append(np.repeat(h[c > 0] ^ np.uint64(o), n))
        levels.append(1 + np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n))
    hh, level = np.concatenate(keys), np.concatenate(levels)
    size = -(-max(64, len(hh) * bits_a_key) // 8) * 8 if len(hh) else 0
    bits = np.zeros(size, np.uint8)
    if size:
        for probe in LogBloom.probes(hh, level):
            bits[LogBloom.place(probe, np.uint64(size))] = 1
    return np.packbits(bits, bitorder="little")


def build_filter(counts: DataFrame, buckets: int, *, base: float, bits_a_key: int, most_bytes: int) -> LogBloom:
    """The filter of all stored counts on the driver; ``most_bytes`` bounds its bits."""

    def segment(batches):
        for b in batches:
            for bucket, order, h, c in zip(*(b.column(x).to_pylist() for x in ("bucket", "orders", "hs", "cs"))):
                bits = segment_of([(o, np.frombuffer(hh, "<u8"), np.frombuffer(cc, "<u4")) for o, hh, cc in zip(order, h, c)], base=base, bits_a_key=bits_a_key)
                yield pa.RecordBatch.from_arrays([pa.array([bucket], pa.int32()), pa.array([bits.tobytes()], pa.binary())], names=["bucket", "bits"])

    grouped = counts.groupBy("bucket").agg(F.collect_list(F.struct("order", "h", "c")).alias("x")).select("bucket", F.col("x.order").alias("orders"), F.col("x.h").alias("hs"), F.col("x.c").alias("cs"))
    got = {r["bucket"]: r["bits"] for r in arrow_map(grouped, segment, "bucket int, bits binary").collect()}
    if sum(map(len, got.values())) > most_bytes:
        raise ValueError("the filter passes most_bytes: score such tables by scored_by_bucket")
    size = np.array([8 * len(got.get(k, b"")) for k in range(buckets)], np.int64)
    bits = np.frombuffer(b"".join(bytes(got.get(k, b"")) for k in range(buckets)) or b"\0", np.uint8)
    return LogBloom(bits, np.cumsum(size) - size, size, base)


def ratings(code, at, unigrams, pairs, *, whole: float, share: float, base: float) -> np.ndarray:
    """The score of each text of a slab. code: each token's place among the kinds; unigrams: levels of the kinds and,
    last, of the start mark; pairs: level of each token with its context."""
    low, high = edges(unigrams, base)
    p1 = (low[:-1] + 1.0) / whole
    # a token's context is the token before it, or the start mark
    lead = np.append(len(low) - 1, code[:-1])
    lead[at[:-1]] = len(low) - 1
    context = high[lead]
    p = (1 - share) * p1[code] + share * np.minimum(edges(pairs, base)[0], context) / np.maximum(context, 1)
    return np.add.reduceat(np.log10(p), at[:-1])


def base_ratings(code, at, count, whole: float) -> tuple[np.ndarray, np.ndarray]:
    """n_known and base_score of each text of a slab from the exact counts of its kinds."""
    return np.add.reduceat((count > 0)[code].astype(np.int64), at[:-1]), np.add.reduceat(np.log10((count + 1.0) / whole)[code], at[:-1])


# ---------------------------------------------------------------- probes by bucket


class Slab:
    """The distinct n-grams of a slab of text in the order in which buckets are asked for them."""

    def __init__(self, texts, buckets: int):
        # tokens come in narrow slabs, as hashing takes many times the bytes of a text; only they are kept together
        parts = [x[1:] for x in token_stream(texts)]
        tokens, contexts = (np.concatenate([x[k] for x in parts]) for k in (0, 1))
        self.at = np.cumsum(np.concatenate([[0], *(np.diff(x[2]) for x in parts)]))
        del parts
        self.kinds, self.code = np.unique(tokens, return_inverse=True)
        self.pairs, self.pair_code = np.unique(pair_hash(contexts, tokens), return_inverse=True)
        self.h = np.concatenate([self.kinds, [START], self.pairs])
        bucket = ((self.h >> np.uint64(20)) % np.uint64(buckets)).astype(np.int64)
        self.order = np.argsort(bucket, kind="stable")
        self.unigrams = len(self.kinds) + 1
        self.bucket = bucket[self.order]

    def counts(self, train: np.ndarray) -> np.ndarray:
        each = np.repeat(train, np.diff(self.at)).astype(np.float64)
        return np.concatenate([np.bincount(self.code, each, len(self.kinds)), [train.sum()], np.bincount(self.pair_code, each, len(self.pairs))]).astype("<u4")


def in_slabs(rows: DataFrame) -> DataFrame:
    """A table (slab, rows): texts of one slab are one row, so that later passes see the same slabs."""
    kind = "array<struct<doc_id:bigint,held_out:boolean,text:string>>"

    def cut(batches):
        from pyspark import TaskContext

        at = TaskContext.get().partitionId() << 32
        for b in batches:
            ranges = list(slabs(buffers(b.column("text"))[1], WIDE))
            offsets = pa.array([0, *(hi for _, hi in ranges)], pa.int32())
            body = pa.StructArray.from_arrays([b.column(k) for k in ("doc_id", "held_out", "text")], ["doc_id", "held_out", "text"])
            yield pa.RecordBatch.from_arrays([pa.array(at + np.arange(len(ranges))), pa.ListArray.from_arrays(offsets, body)], names=["slab", "rows"])
            at += len(ranges)

    return materialise(arrow_map(rows.select("doc_id", "held_out", "text"), cut, f"slab long, rows {kind}"), "slabs", wide=True).select("slab", F.posexplode("rows").alias("pos", "row")).select("slab", "pos", "row.*")


def answers_of(bucket: int, part: pa.Table, buckets: int, slices: int, *, base: float, bits_a_key: int):
    """What a bucket answers to its askers (slab, single, h, c). The bucket's segments are made and read one after the other,
    so that only the asked n-grams and their answers are held for the whole bucket."""
    slab, single = part.column("slab").to_numpy(), part.column("single").to_pylist()
    asked = [np.frombuffer(x.as_buffer(), "<u8") for x in part.column("h")]
    length = np.array([len(x) for x in asked])
    starts = np.cumsum(length) - length
    segment = np.concatenate([((x >> np.uint64(20)) % np.uint64(buckets * slices) // np.uint64(buckets)).astype("<u4") for x in asked])
    c = np.concatenate([widened(x.as_buffer(), n).astype("<u4") for x, n in zip(part.column("c"), length)])
    h = np.concatenate(asked)
    pair = np.ones(len(h), bool)
    for a, n in zip(starts, single):  # a row's unigrams come first
        pair[a : a + n] = False
    levels, counts = np.zeros(len(h), "<u2"), np.zeros(len(h), "<u4")
    total = known = 0
    for k in range(slices):
        rows = [np.flatnonzero((segment == k) & (pair == (o == 2))) for o in (1, 2)]
        whole, places = [], []
        for o, own_rows in zip((1, 2), rows):
            kinds, place = np.unique(h[own_rows], return_inverse=True)
            whole.append((o, kinds, np.bincount(place, c[own_rows], len(kinds)).astype(np.int64)))
            places.append(place)
        bits = segment_of(whole, base=base, bits_a_key=bits_a_key)
        own = LogBloom(bits, np.zeros(1, np.int64), np.array([8 * len(bits)], np.int64), base)
        for (o, kinds, _), own_rows, place in zip(whole, rows, places):
            levels[own_rows] = own.level(kinds, o)[place]
        _, kinds, count = whole[0]
        counts[rows[0]] = count[places[0]]
        word = kinds != START
        total, known = total + int(count[word].sum()), known + int((count[word] > 0).sum())
    for lo in range(0, len(slab), BATCH_ROWS):
        some = np.arange(lo, min(lo + BATCH_ROWS, len(slab)))
        read = lambda x, n: pa.array([narrow(x[starts[i] : starts[i] + n[i]]) for i in some], pa.binary())
        yield pa.RecordBatch.from_arrays(
            [pa.array(slab[some]), pa.array(np.full(len(some), bucket, np.int32)), pa.array(np.where(some == 0, total, 0)), pa.array(np.where(some == 0, known, 0)), pa.array(length[some].astype(np.int32)), pa.array(np.array(single)[some].astype(np.int32)), read(levels, length), read(counts, single)],
            names=["slab", "pos", "total", "kinds", "n_levels", "n_counts", "levels", "counts"],
        )


def scored_by_bucket(rows: DataFrame, buckets: int, slices: int = 1, *, share: float, base: float, bits_a_key: int) -> DataFrame:
    """As ``score``, with nothing of the input's size on the driver or in a broadcast. A slab sends each bucket its distinct
    n-grams with their training counts; the bucket adds them up, builds its segments, one for each of ``slices`` ranges of its
    hashes, and answers with the level of each n-gram and the exact count of each unigram, in the order asked."""
    texts = in_slabs(rows)

    def ask(batches):
        for slab, part in runs_of(batches, "slab"):
            own = Slab(part.column("text"), buckets)
            h, c = own.h[own.order], own.counts(~part.column("held_out").to_numpy(zero_copy_only=False))[own.order]
            heads = np.flatnonzero(np.r_[True, own.bucket[1:] != own.bucket[:-1]])
            ends = np.append(heads[1:], len(h))
            single = np.add.reduceat((own.order < own.unigrams).astype(np.int32), heads)
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.full(len(heads), slab)), pa.array(own.bucket[heads].astype(np.int32)), pa.array(single.astype(np.int32)), pa.array([h[a:b].tobytes() for a, b in zip(heads, ends)], pa.binary()), pa.array([narrow(c[a:b]) for a, b in zip(heads, ends)], pa.binary())],
                names=["slab", "bucket", "single", "h", "c"],
            )

    def answer(batches):
        for bucket, part in runs_of(batches, "bucket"):
            yield from answers_of(bucket, part, buckets, slices, base=base, bits_a_key=bits_a_key)

    asked = arrow_map(texts, ask, "slab long, bucket int, single int, h binary, c binary").repartition(buckets, "bucket").sortWithinPartitions("bucket", "slab")
    answers = materialise(arrow_map(asked, answer, "slab long, pos int, total long, kinds long, n_levels int, n_counts int, levels binary, counts binary"), "answers")
    total, kinds = (x or 0 for x in answers.agg(F.sum("total"), F.sum("kinds")).first())
    smooth = float(total) + float(kinds) + 1.0

    def read(batches):
        for _, part in runs_of(batches, "slab"):
            answers = part.column("levels").null_count < len(part) and part.filter(part.column("levels").is_valid())
            part = part.filter(part.column("levels").is_null())
            own = Slab(part.column("text"), buckets)
            levels, single = np.empty(len(own.h), np.int64), np.empty(len(own.h), np.int64)
            read = lambda k: np.concatenate([widened(x.as_buffer(), n) for x, n in zip(answers.column(k), answers.column(f"n_{k}").to_pylist())])
            levels[own.order] = read("levels")
            # unigrams keep their order among the asked
            single[own.order[own.order < own.unigrams]] = read("counts")
            known, base_score = base_ratings(own.code, own.at, single[: own.unigrams - 1], smooth)
            rated = ratings(own.code, own.at, levels[: own.unigrams], levels[own.unigrams :][own.pair_code], whole=smooth, share=share, base=base)
            yield pa.RecordBatch.from_arrays(
                [part.column("doc_id").combine_chunks(), part.column("held_out").combine_chunks(), pa.array(np.diff(own.at).astype(np.int64)), pa.array(known), pa.array(np.full(len(part), int(total))), pa.array(base_score), pa.array(rated)],
                names=["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"],
            )

    both = texts.withColumn("after", F.lit(1)).unionByName(answers.select("slab", "pos", "n_levels", "n_counts", "levels", "counts", F.lit(0).alias("after")), allowMissingColumns=True)
    return arrow_map(both.repartition("slab").sortWithinPartitions("slab", "after", "pos"), read, "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")


# ---------------------------------------------------------------- whole tables


def score(
    docs: DataFrame, *, held_modulus: int = 7, held_remainder: int = 2, share: float = 0.2, base: float = 1.15, bits_a_key: int = 12, most_bytes: int = 96 << 20, most_base_bytes: int = 96 << 20
) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score for every row of ``docs``."""
    spark = docs.sparkSession
    bound_batches(spark)
    fold = F.pmod(F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))), F.lit(held_modulus))
    held = (fold == held_remainder).alias("held_out")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), held, F.xxhash64(text_or_empty()).alias("text_key"), text_or_empty().alias("text"))
    n_bytes, n_rows = docs.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0)), F.count(F.lit(1))).first()
    buckets = buckets_for(n_bytes)
    # segments follow the bytes of text alone, so that they are the same whoever is asked
    slices = max(1, -(-n_bytes // (buckets * SEGMENT_BYTES)))
    # a token adds at most one key for itself and one with its context, a text one more for its start
    if (n_bytes + 4 * n_rows) * bits_a_key // 8 + 16 * buckets * slices > most_bytes:
        return scored_by_bucket(rows, buckets, slices, share=share, base=base, bits_a_key=bits_a_key)
    counts = materialise(count_grams(docs, fold != held_remainder, buckets * slices), "grams")
    total, kinds = (x or 0 for x in counts.where("order = 1").agg(F.sum("total"), F.sum("kinds")).first())
    bloom = build_filter(counts, buckets * slices, base=base, bits_a_key=bits_a_key, most_bytes=most_bytes)
    shared = spark.sparkContext.broadcast((bloom.bits, bloom.start, bloom.size))
    exact = None
    if kinds * 12 <= most_base_bytes:
        table = counts.where("order = 1").select("h", "c").toArrow()
        h = np.frombuffer(b"".join(table.column("h").to_pylist()), "<u8")
        c = np.frombuffer(b"".join(table.column("c").to_pylist()), "<u4")
        order = np.argsort(h)
        exact = spark.sparkContext.broadcast((h[order], c[order]))
    whole = float(total) + float(kinds) + 1.0

    def read(batches):
        filter_ = LogBloom(*shared.value, base)
        for b in batches:
            out = {k: [] for k in ("n_tokens", "n_known", "base_score", "score")}
            for _, tokens, contexts, at in token_stream(b.column("text")):
                kind, code = np.unique(tokens, return_inverse=True)
                if exact is not None:
                    h, c = exact.value
                    place = np.minimum(np.searchsorted(h, kind), max(len(h) - 1, 0))
                    count = np.where(h[place] == kind, c[place], 0) if len(h) else np.zeros(len(kind), np.int64)
                    known, base_score = base_ratings(code, at, count, whole)
                    out["n_known"].append(known)
                    out["base_score"].append(base_score)
                out["n_tokens"].append(np.diff(at))
                out["score"].append(ratings(code, at, filter_.level(np.append(kind, START), 1), filter_.level(pair_hash(contexts, tokens), 2), whole=whole, share=share, base=base))
            join = lambda k, t: pa.array(np.concatenate(out[k]).astype(t)) if out[k] else pa.nulls(b.num_rows, pa.from_numpy_dtype(t))
            yield pa.RecordBatch.from_arrays(
                [b.column("doc_id"), b.column("held_out"), b.column("text_key"), join("n_tokens", np.int64), join("n_known", np.int64), join("base_score", np.float64), join("score", np.float64)],
                names=["doc_id", "held_out", "text_key", "n_tokens", "n_known", "base_score", "score"],
            )

    scored = arrow_map(rows, read, "doc_id long, held_out boolean, text_key long, n_tokens long, n_known long, base_score double, score double")
    if exact is None:
        scored = scored.drop("n_known", "base_score").join(joined_base(rows, counts, whole), ["text_key"], "left")
    return scored.select("doc_id", "held_out", "n_tokens", "n_known", F.lit(int(total)).cast("long").alias("train_tokens"), "base_score", "score")


def joined_base(rows: DataFrame, counts: DataFrame, whole: float) -> DataFrame:
    """text_key, n_known, base_score by a join of each distinct text's words with the counts, for vocabularies beyond
    the broadcast bound."""

    def emit(batches):
        for b in batches:
            keys = b.column("text_key").to_numpy()
            for lo, tokens, _, at in token_stream(b.column("text")):
                for i in range(len(at) - 1):
                    h, n = np.unique(tokens[at[i] : at[i + 1]], return_counts=True)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(h), keys[lo + i])), as_long(h), pa.array(n.astype(np.int64))], names=["text_key", "h", "n"])

    def unpack(batches):
        for b in batches:
            for h, c in zip(b.column("h").to_pylist(), b.column("c").to_pylist()):
                yield pa.RecordBatch.from_arrays([as_long(np.frombuffer(h, "<u8")), pa.array(np.frombuffer(c, "<u4").astype(np.int64))], names=["h", "c"])

    words = arrow_map(rows.select("text_key", "text").dropDuplicates(["text_key"]), emit, "text_key long, h long, n long")
    known = arrow_map(counts.where("order = 1").select("h", "c"), unpack, "h long, c long")
    both = words.join(known, "h", "left").withColumn("c", F.coalesce("c", F.lit(0)))
    return both.groupBy("text_key").agg(F.sum(F.when(F.col("c") > 0, F.col("n")).otherwise(0)).alias("n_known"), F.sum(F.col("n") * F.log10((F.col("c") + 1.0) / F.lit(whole))).alias("base_score"))
