"""Toxicity by multiple-instance learning: sentence scores joined by noisy-or, trained from document labels.

A sentence's score is a logistic function of its features: the words (A-Z lower-cased, cut at white space and ASCII
punctuation) and their first four and five bytes, hashed. A document is clean only if all of its sentences are:
1 - product of (1 - sentence score). The weights maximise the likelihood of document labels alone; sentence scores then
locate the offending sentences.

Training reads a bounded sample of labelled rows: of each label the ``most_rows`` training rows whose doc_id hashes
lowest. All rows are scored on their whole texts.

Defined results: null or empty text has no sentence, score 0; a doc_id with contradicting labels trains as toxic; labels
null or beyond 0 and 1 do not train; without both labels in training every score is 0; a null doc_id counts as the empty string for the fold.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import _LOWER, _SPACE, arrow_map, buffers, slabs, span_hashes, text_or_empty

BITS = 18
_CUT = _SPACE.copy()
_CUT[[b for b in range(33, 127) if not chr(b).isalnum()]] = True
_STOP = np.zeros(256, bool)
_STOP[[ord(x) for x in ".!?\n"]] = True


def sentences(data: np.ndarray, offsets: np.ndarray):
    """(feature ids, sentence of each feature, document of each sentence, byte range of each sentence)."""
    part = _LOWER[data]
    inside = ~_CUT[part]
    first, last = inside.copy(), inside.copy()
    first[1:] &= ~inside[:-1]
    last[:-1] &= ~inside[1:]
    cuts = offsets[1:-1]
    cuts = cuts[(cuts > 0) & (cuts < len(data))]
    first[cuts], last[cuts - 1] = inside[cuts], inside[cuts - 1]
    starts, ends = np.flatnonzero(first), np.flatnonzero(last) + 1
    # a sentence ends after a stop, or with its text
    bounds = np.zeros(len(data) + 1, bool)
    bounds[np.flatnonzero(_STOP[part]) + 1] = True
    bounds[offsets[:-1]] = True
    bounds[len(data)] = False
    number = np.cumsum(bounds) - 1
    raw = number[starts] if len(starts) else np.zeros(0, np.int64)
    kept, sentence = np.unique(raw, return_inverse=True)  # sentences without a word have no score
    begins = np.flatnonzero(bounds)[kept] if len(kept) else np.zeros(0, np.int64)
    stops = np.append(np.flatnonzero(bounds), len(data))
    finish = stops[np.searchsorted(stops, begins, "right")] if len(begins) else begins
    document = np.searchsorted(offsets, begins, "right") - 1
    mask = np.uint64((1 << BITS) - 1)
    ids, owner = [], []
    for k, length in enumerate((None, 4, 5)):
        long_enough = np.ones(len(starts), bool) if length is None else ends - starts > length
        s = starts[long_enough]
        e = ends[long_enough] if length is None else s + length
        h = span_hashes(part, s, e) ^ np.uint64(0x5851F42D4C957F2D * (k + 1) % (1 << 64))
        ids.append(((h >> np.uint64(9)) & mask).astype(np.int64))
        owner.append(sentence[long_enough])
    return np.concatenate(ids), np.concatenate(owner), document, begins, finish


class Model:
    def __init__(self, weights: np.ndarray, bias: float):
        self.weights, self.bias = weights, bias

    def sentence_logits(self, ids, owner, n) -> np.ndarray:
        return self.bias + np.bincount(owner, weights=self.weights[ids], minlength=n)

    def read(self, data, offsets):
        """(score of each document, document, byte range in it and own score of each sentence)."""
        ids, owner, document, begins, finish = sentences(data, offsets)
        logits = self.sentence_logits(ids, owner, len(document))
        scores = -np.expm1(-np.bincount(document, weights=np.logaddexp(0, logits), minlength=len(offsets) - 1))
        return scores, document, begins - offsets[document], finish - offsets[document], 1 / (1 + np.exp(-np.clip(logits, -700, 700)))

    def scores(self, data, offsets) -> np.ndarray:
        return self.read(data, offsets)[0]


def train(texts: pa.Array, labels: np.ndarray, *, rounds: int = 25, batch: int = 128, rate: float = 0.5, least_odds: float = 4.0, seed: int = 11) -> Model:
    """Stochastic ascent of the noisy-or likelihood with per-weight rates. Features not ``least_odds`` times as
    frequent in toxic documents get no weight, nor those that tell so little of the labels that chance among all features
    would do it: a feature's gain in log-likelihood over the share of toxic rows must reach half the log of the number of
    features. So the documents it needs follow from the labels and not from a fixed count."""
    weights, bias = np.zeros(1 << BITS), -7.0
    if len(set(labels.tolist())) < 2:
        return Model(weights, -np.inf)
    data, offsets = buffers(texts)
    rng = np.random.default_rng(seed)
    order = rng.permutation(len(labels))
    groups = []
    for at in range(0, len(order), batch):
        pick = order[at : at + batch]
        part = np.concatenate([data[offsets[i] : offsets[i + 1]] for i in pick])
        inner = np.concatenate([[0], np.cumsum(offsets[pick + 1] - offsets[pick])])
        ids, owner, document, _, _ = sentences(part, inner)
        groups.append((ids.astype(np.int32), owner.astype(np.int32), document, labels[pick].astype(float)))
    spread = np.zeros((2, 1 << BITS))
    for ids, owner, document, y in groups:
        feature, doc = np.divmod(np.unique(ids.astype(np.int64) * len(y) + document[owner]), len(y))
        for side in (0, 1):
            spread[side] += np.bincount(feature[y[doc] == side], minlength=1 << BITS)
    odds = (spread[1] / labels.sum()) / ((spread[0] + 0.5) / (labels == 0).sum())
    n, share = spread.sum(axis=0), labels.mean()
    rate_of = np.clip(spread[1] / np.maximum(n, 1), 1e-12, 1 - 1e-12)
    gain = n * (rate_of * np.log(rate_of / share) + (1 - rate_of) * np.log((1 - rate_of) / (1 - share)))
    fit_ = (gain >= 0.5 * np.log(max(2, int((n > 1).sum())))) & (odds >= least_odds)
    groups = [(ids[k], owner[k], document, y) for ids, owner, document, y in groups for k in [fit_[ids]]]
    square, square_bias = np.full(1 << BITS, 1e-2), 1e-2
    for _ in range(rounds):
        for g in rng.permutation(len(groups)):
            ids, owner, document, y = groups[g]
            z = bias + np.bincount(owner, weights=weights[ids], minlength=len(document))
            total = np.bincount(document, weights=np.logaddexp(0, z), minlength=len(y))
            # d likelihood / d total: -1 for clean documents, exp(-t) / (1 - exp(-t)) for toxic ones
            pull = np.where(y == 1, np.minimum(1 / np.expm1(np.clip(total, 1e-6, 50)), 1e3), -1.0)
            by_sentence = pull[document] / (1 + np.exp(-np.clip(z, -40, 40)))
            grad = np.bincount(ids, weights=by_sentence[owner], minlength=1 << BITS)
            square += grad * grad
            weights = np.maximum(weights + rate * grad / np.sqrt(square), 0)  # evidence is of harm only
            g0 = by_sentence.sum()
            square_bias += g0 * g0
            bias += rate * g0 / square_bias**0.5
    return Model(weights, float(bias))


def fold(modulus: int):
    return F.pmod(F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))), F.lit(modulus))


def fit(docs: DataFrame, labels: DataFrame, *, modulus: int = 5, most_rows: int = 3000) -> Model:
    """Trains on the rows whose fold is not 0; ``most_rows`` bounds the rows of each label."""
    own = labels.where(F.col("toxic").isin(0, 1) & (fold(modulus) != 0)).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    wanted = None
    for y in (0, 1):
        part = own.where(F.col("toxic") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most_rows)
        wanted = part if wanted is None else wanted.unionByName(part)
    wanted = wanted.select(F.col("doc_id").alias("l_id"), F.col("toxic").cast("int").alias("y"))
    rows = docs.select("doc_id", "text").join(F.broadcast(wanted), F.col("doc_id") == F.col("l_id")).groupBy("doc_id").agg(F.max("text").alias("text"), F.max("y").alias("y")).toArrow()
    rows = rows.sort_by("doc_id")
    return train(rows.column("text").combine_chunks() if len(rows) else pa.array([], pa.string()), rows.column("y").to_numpy())


def predict(docs: DataFrame, model: Model, *, modulus: int = 5, least: float = 0.5) -> DataFrame:
    """doc_id, held_out, score, predicted for every row, and offending: the sentences whose own score is at least ``least``,
    as start, end (bytes of the text) and score."""
    shared = docs.sparkSession.sparkContext.broadcast((model.weights.astype(np.float32), model.bias))
    spans = pa.struct([("start", pa.int64()), ("end", pa.int64()), ("score", pa.float64())])

    def run(batches):
        own = Model(*shared.value)
        for b in batches:
            data, offsets = buffers(b.column("text"))
            scores, counts, found = [np.zeros(0)], [np.zeros(0, np.int64)], [[np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0)]]
            for lo, hi in slabs(offsets):
                s, document, start, end, p = own.read(data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo])
                hit = p >= least
                scores.append(s)
                counts.append(np.bincount(document[hit], minlength=hi - lo))
                for parts, x in zip(found, (start, end, p)):
                    parts.append(x[hit])
            s = np.concatenate(scores)
            ends = np.concatenate([[0], np.cumsum(np.concatenate(counts))]).astype(np.int32)
            where = pa.ListArray.from_arrays(pa.array(ends), pa.StructArray.from_arrays([pa.array(np.concatenate(x)) for x in found], fields=list(spans)))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("held_out"), pa.array(s), pa.array((s >= 0.5).astype(np.int32)), where], names=["doc_id", "held_out", "score", "predicted", "offending"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (fold(modulus) == 0).alias("held_out"), text_or_empty().alias("text"))
    return arrow_map(rows, run, "doc_id long, held_out boolean, score double, predicted int, offending array<struct<start:bigint,end:bigint,score:double>>")


def offending(docs: DataFrame, model: Model, *, least: float = 0.5) -> DataFrame:
    """The sentences of each document whose own score is at least ``least``: doc_id, start, end (bytes), score."""
    return predict(docs, model, least=least).select("doc_id", F.explode("offending").alias("s")).select("doc_id", "s.start", "s.end", "s.score")


def clean(docs: DataFrame, model: Model) -> DataFrame:
    """The rows of ``docs`` that the model does not reject, with all their columns."""
    shared = docs.sparkSession.sparkContext.broadcast((model.weights.astype(np.float32), model.bias))

    def run(batches):
        own = Model(*shared.value)
        for b in batches:
            data, offsets = buffers(b.column("text"))
            parts = [own.scores(data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]) for lo, hi in slabs(offsets)]
            yield b.filter(pa.array(np.concatenate(parts) < 0.5)) if parts else b

    return arrow_map(docs, run, docs.schema)
