"""Token ids of whole texts by a public tokenizer file, encoding each distinct piece of a batch once.

A text is cut before every space that follows a character other than white space. Both tokenizer files split texts
there themselves before merging bytes, so the ids of the pieces, in order, are the ids of the text (tested against
whole-text encoding). Pieces of a batch go through Arrow's dictionary encoding; only pieces not seen before by this
worker reach the tokenizer.
"""

from __future__ import annotations

from itertools import chain

import numpy as np
import pyarrow as pa

from .common import buffers, slabs, span_hashes

#: Distinct pieces whose ids a worker remembers (about 28 bytes each, found by 64-bit hash); beyond, new ones are encoded
#: each time they come.
REMEMBERED = 1_000_000
_BLANK = np.zeros(256, bool)
_BLANK[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D, 0x1C, 0x1D, 0x1E, 0x1F, 0x00]] = True


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def piece_bounds(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Where pieces begin; every text begins one, empty texts none of their own."""
    n = len(data)
    cut = np.zeros(n, bool)
    if n > 3:
        # the byte before must not end a white-space character: none in ASCII, nor in the ranges of wider ones
        safe = (data[3:] == 0x20) & ~_BLANK[data[2:-1]]
        wide = (data[2:-1] >= 0x80) & ((data[1:-2] == 0xC2) | (data[:-3] == 0xE1) | (data[:-3] == 0xE2) | (data[:-3] == 0xE3))
        cut[3:] = safe & ~wide
    heads = offsets[:-1][offsets[1:] > offsets[:-1]]
    cut[heads] = True
    return np.flatnonzero(cut)


class Encoder:
    """encode(column) -> (ids of all texts in order, first id of each text, one more entry than texts)."""

    def __init__(self, path: str):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # tasks share the machine already
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.forget()

    def forget(self):
        self.keys = np.zeros(0, np.uint64)  # sorted hashes of known pieces
        self.at = np.zeros(0, np.int32)  # first id of each in the pool
        self.size = np.zeros(0, np.int32)
        self.pool = np.zeros(0, np.uint32)

    def __call__(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        data, offsets = buffers(column)
        ids, counts = [], []
        for lo, hi in slabs(offsets, 1 << 22):
            a, b = self.slab(data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo])
            ids.append(a)
            counts.append(b)
        heads = np.concatenate([[0], np.cumsum(np.concatenate(counts))]) if counts else np.zeros(1, np.int64)
        return (np.concatenate(ids) if ids else np.zeros(0, np.uint32)), heads.astype(np.int64)

    def slab(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        begins = piece_bounds(data, offsets)
        if not len(begins):
            return np.zeros(0, np.uint32), np.zeros(len(offsets) - 1, np.int64)
        edges = np.append(begins, len(data)).astype(np.int32)
        pieces = pa.StringArray.from_buffers(len(begins), pa.py_buffer(edges), pa.py_buffer(np.ascontiguousarray(data)))
        coded = pieces.dictionary_encode()
        raw, at = buffers(coded.dictionary)
        keys = span_hashes(raw, at[:-1], at[1:])
        place = np.searchsorted(self.keys, keys)
        known = np.zeros(len(keys), bool)
        inside = place < len(self.keys)
        known[inside] = self.keys[place[inside]] == keys[inside]
        sizes, pool_at, pool = np.zeros(len(keys), np.int64), np.zeros(len(keys), np.int64), self.pool
        sizes[known], pool_at[known] = self.size[place[known]], self.at[place[known]]
        new = np.flatnonzero(~known)
        if len(new):
            encoded = [e.ids for e in self.tokenizer.encode_batch_fast(coded.dictionary.take(pa.array(new)).to_pylist(), add_special_tokens=False)]
            sizes[new] = np.fromiter(map(len, encoded), np.int64, len(new))
            fresh = np.fromiter(chain.from_iterable(encoded), np.uint32, int(sizes[new].sum()))
            pool_at[new] = len(pool) + np.cumsum(sizes[new]) - sizes[new]
            pool = np.concatenate([pool, fresh])
            if len(self.keys) + len(new) <= REMEMBERED:
                order = np.argsort(keys[new])
                where = place[new][order]
                self.keys = np.insert(self.keys, where, keys[new][order])
                self.at = np.insert(self.at, where, pool_at[new][order])
                self.size = np.insert(self.size, where, sizes[new][order])
                self.pool = pool
        codes = coded.indices.to_numpy()
        n = sizes[codes]
        ends = np.cumsum(n)
        total = int(ends[-1])
        # flat index: start of each piece's ids in the pool, plus the place inside the piece
        index = np.repeat(pool_at[codes] - (ends - n), n) + np.arange(total)
        piece_heads = np.searchsorted(begins, offsets)
        before = np.append(0, ends)[piece_heads]
        return pool[index], np.diff(before)


_encoders: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    """This worker's encoder of a file, loaded once."""
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    return _encoders[path]


def encode_with_end(column: pa.Array, path: str, end_id: int) -> tuple[np.ndarray, np.ndarray]:
    """As Encoder, with ``end_id`` after each text (empty ones too)."""
    ids, heads = encoder(path)(column)
    n = len(heads) - 1
    out = np.full(len(ids) + n, end_id, np.uint32)
    new = heads + np.arange(n + 1)
    keep = np.ones(len(out), bool)
    keep[new[1:] - 1] = False
    out[keep] = ids
    return out, new
