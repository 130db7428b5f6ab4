"""Packing token sequences by cutting-stock column generation.

Documents are cut at multiples of the capacity; what is left of each is an item. The histogram of item lengths (at most
``capacity`` numbers, whatever the corpus) defines a linear program: fill the demand of every length with as few
patterns (multisets of lengths that fit the capacity) as possible. Columns are generated: the duals of the current
basis price lengths, a knapsack recurrence over capacities finds the pattern worth most, until none is worth more than
one sequence or a bound proves the gap small. Multiplicities are rounded down; the few items this leaves are packed by
best fit in decreasing order. Items are then ranked inside their length, in two distributed levels, and each rank
interval of a length is assigned to a pattern's slots by a small broadcast table.

Defined results: null or empty text is one end id; repeated rows are packed each; an empty table gives an empty result;
extra columns are ignored.
"""

from __future__ import annotations

import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, materialise, numbered, text_or_empty
from .tokens import encode_with_end, tokenizer_path


def best_pattern(values: np.ndarray, lengths: np.ndarray, capacity: int) -> tuple[float, dict[int, int]]:
    """The multiset of items worth most within the capacity: (value, {index: copies})."""
    useful = np.flatnonzero(values > 1e-12)
    if not len(useful):
        return 0.0, {}
    size, worth = lengths[useful], values[useful]
    best, pick = np.zeros(capacity + 1), np.full(capacity + 1, -1)
    upto = np.searchsorted(size, np.arange(capacity + 1), "right")
    for c in range(1, capacity + 1):
        best[c] = best[c - 1]
        if k := upto[c]:
            total = best[c - size[:k]] + worth[:k]
            i = int(total.argmax())
            if total[i] > best[c]:
                best[c], pick[c] = total[i], i
    out: Counter = Counter()
    c = capacity
    while c > 0:
        if pick[c] < 0:
            c -= 1
        else:
            out[int(useful[pick[c]])] += 1
            c -= int(size[pick[c]])
    return float(best[capacity]), dict(out)


def first_basis(lengths: np.ndarray, need: np.ndarray, capacity: int) -> tuple[list[dict[int, int]], np.ndarray]:
    """Patterns ({index: copies}) and multiplicities that meet the demand and form a basis. Each is filled with the
    longest lengths left and used until one of them is exhausted; later patterns lack that length, so the matrix is triangular."""
    left = need.astype(float).copy()
    open_ = list(range(len(lengths)))  # ascending
    columns, x = [], []
    while open_:
        room, pattern = capacity, Counter()
        sizes = lengths[open_]
        while room >= sizes[0]:
            i = open_[int(np.searchsorted(sizes, room, "right")) - 1]
            copies = max(1, min(room // int(lengths[i]), int(left[i])))
            pattern[i] += copies
            room -= copies * int(lengths[i])
            if copies < room // int(lengths[i]) + copies and room >= sizes[0]:
                below = int(np.searchsorted(sizes, min(room, int(lengths[i]) - 1), "right"))
                if below == 0:
                    break
                sizes = sizes[:below]
        done = min(pattern, key=lambda i: left[i] / pattern[i])
        step = left[done] / pattern[done]
        for i, k in pattern.items():
            left[i] = max(0.0, left[i] - step * k)
        columns.append(dict(pattern))
        x.append(step)
        open_.remove(done)
    return columns, np.array(x)


def generate_columns(demand: dict[int, int], capacity: int, *, gap: float = 1e-3, most_columns: int = 600) -> list[tuple[dict[int, int], float]]:
    """Patterns ({length: copies}) with their multiplicities in a solution of the linear program within ``gap`` of its
    optimum, or after ``most_columns`` generated columns."""
    lengths = np.array(sorted(demand), np.int64)
    need = np.array([demand[x] for x in lengths.tolist()], float)
    m = len(lengths)
    if not m:
        return []
    columns, x = first_basis(lengths, need, capacity)
    matrix = np.zeros((m, m))
    for k, pattern in enumerate(columns):
        for i, copies in pattern.items():
            matrix[i, k] = copies
    inverse = np.linalg.inv(matrix)
    bound = max(float(lengths @ need) / capacity, float(need[lengths * 2 > capacity].sum()))
    for _ in range(most_columns):
        duals = inverse.sum(axis=0)
        if x.sum() <= (1 + gap) * bound:
            break
        value, pattern = best_pattern(duals, lengths, capacity)
        bound = max(bound, x.sum() / max(value, 1.0))
        if value <= 1 + 1e-9 or x.sum() <= (1 + gap) * bound:
            break
        column = np.zeros(m)
        for i, k in pattern.items():
            column[i] = k
        move = inverse @ column
        up = move > 1e-9
        if not up.any():
            break
        ratio = np.where(up, x / np.where(up, move, 1), np.inf)
        out = int(ratio.argmin())
        step = ratio[out]
        x = np.maximum(x - step * move, 0)
        x[out] = step
        row = inverse[out] / move[out]
        inverse -= np.outer(move, row)
        inverse[out] = row
        columns[out] = pattern
    return [({int(lengths[i]): k for i, k in p.items()}, float(v)) for p, v in zip(columns, x)]


def best_fit(items: dict[int, int], capacity: int) -> list[dict[int, int]]:
    """Best fit in decreasing order of the items a rounding leaves."""
    rooms: dict[int, list[Counter]] = {}
    for length in sorted(items, reverse=True):
        for _ in range(items[length]):
            room = min((r for r in rooms if r >= length), default=None)
            if room is None:
                bin_, room = Counter(), capacity
            else:
                bin_ = rooms[room].pop()
                if not rooms[room]:
                    del rooms[room]
            bin_[length] += 1
            rooms.setdefault(room - length, []).append(bin_)
    return [dict(b) for bins in rooms.values() for b in bins]


def patterns_for(demand: dict[int, int], capacity: int, **options) -> list[tuple[dict[int, int], int]]:
    """Patterns with whole multiplicities that meet the demand exactly."""
    demand = {n: k for n, k in demand.items() if k}
    out: Counter = Counter()
    kept = {n: k for n, k in demand.items() if n < capacity}
    if demand.get(capacity):
        out[((capacity, 1),)] += demand[capacity]
    left = Counter(kept)
    for pattern, x in generate_columns(kept, capacity, **options):
        if n := int(x + 1e-7):
            n = min([n, *(left[length] // k for length, k in pattern.items())])
        if n > 0:
            out[tuple(sorted(pattern.items()))] += n
            left.subtract({length: k * n for length, k in pattern.items()})
    for pattern in best_fit({n: k for n, k in left.items() if k > 0}, capacity):
        out[tuple(sorted(pattern.items()))] += 1
    return [(dict(p), n) for p, n in sorted(out.items(), reverse=True)]


def slots(patterns: list[tuple[dict[int, int], int]]) -> list[tuple[int, int, int, int, int, int]]:
    """(length, first rank, ranks, first sequence, copies, offset) for each length of each pattern."""
    out, used, sequence = [], Counter(), 0
    for pattern, n in patterns:
        at = 0
        for length, copies in sorted(pattern.items(), reverse=True):
            out.append((length, used[length], copies * n, sequence, copies, at))
            used[length] += copies * n
            at += length * copies
        sequence += n
    return out


def cut_documents(docs: DataFrame, tokenizer: str, end_id: int, capacity: int, *, keep_ids: bool = False) -> DataFrame:
    """Pieces of at most ``capacity`` ids: doc_id, start, length, ids_crc32, doc_tokens and, if asked for, ids."""
    path = tokenizer_path(tokenizer)
    schema = "doc_id long, start long, length int, ids_crc32 long, doc_tokens long" + ", ids array<int>" * keep_ids

    def cut(batches):
        for b in batches:
            if not b.num_rows:
                continue
            ids, heads = encode_with_end(b.column("text"), path, end_id)
            n = np.diff(heads)
            pieces = -(-n // capacity)
            doc = np.repeat(np.arange(len(n)), pieces)
            start = (np.arange(len(doc)) - np.repeat(np.cumsum(pieces) - pieces, pieces)) * capacity
            length = np.minimum(capacity, n[doc] - start)
            at = heads[doc] + start
            view = memoryview(np.ascontiguousarray(ids.astype("<u4"))).cast("B")
            crc = [zlib.crc32(view[4 * a : 4 * (a + k)]) for a, k in zip(at.tolist(), length.tolist())]
            columns = [b.column("doc_id").take(pa.array(doc)), pa.array(start), pa.array(length.astype(np.int32)), pa.array(crc, pa.int64()), pa.array(n[doc])]
            if keep_ids:  # pieces follow each other without gaps
                columns.append(pa.ListArray.from_arrays(pa.array(np.append(at, len(ids)).astype(np.int32)), pa.array(ids.astype(np.int32))))
            yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "start", "length", "ids_crc32", "doc_tokens", *["ids"] * keep_ids])

    return arrow_map(docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text")), cut, schema)


def pack(pieces: DataFrame, capacity: int, *, order: list[str], **options) -> DataFrame:
    """Adds sequence_id and offset to ``pieces`` (a table with a ``length`` of 1 to ``capacity``)."""
    spark = pieces.sparkSession
    demand = {r[0]: r[1] for r in pieces.groupBy("length").agg(F.count(F.lit(1))).collect()}
    table = spark.createDataFrame(slots(patterns_for(demand, capacity, **options)), "s_length int, s_first long, s_ranks long, s_sequence long, s_copies long, s_offset long")
    ranked = numbered(pieces, ["length"], order)
    fits = (ranked["length"] == table["s_length"]) & (ranked["before"] >= table["s_first"]) & (ranked["before"] < table["s_first"] + table["s_ranks"])
    k = F.col("before") - F.col("s_first")
    return (
        ranked.join(F.broadcast(table), fits)
        .withColumn("sequence_id", F.expr("s_sequence + (before - s_first) div s_copies"))
        .withColumn("offset", (F.col("s_offset") + F.pmod(k, F.col("s_copies")) * F.col("length")).cast("long"))
        .select(*pieces.columns, "sequence_id", "offset")
    )


def pack_documents(docs: DataFrame, *, tokenizer: str = "byte_bpe_50k.json", end_id: int = 0, capacity: int = 1024, keep_ids: bool = False, **options) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, padding (of its sequence)
    and, with ``keep_ids``, the ids themselves. A sequence is padded to the capacity unless its length is a power of
    two."""
    pieces = materialise(cut_documents(docs, tokenizer, end_id, capacity, keep_ids=keep_ids), "pieces")
    return pack(pieces, capacity, order=["doc_id", "start", "ids_crc32"], **options).withColumn("length", F.col("length").cast("long"))
