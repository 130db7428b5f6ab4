import random
import zlib
from collections import defaultdict

import numpy as np
import pyarrow as pa
import pytest

from blockrecover.llm import packing, token_files
from blockrecover.llm.tokens import Encoder, tokenizer_path

ODD = ["", " ", "  a  b ", "a  b\n\n c", "it's  fine\t x", "x <|endoftext|> y", "ΑΣ ΑΣ Σ", "　 a　 b", " ́b c", "a\u0085 b", "a\x00 b", "​ a ᠎ b", "naïve — “quotes” … 12,345.67", "word " * 3000]


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_pieces_encode_like_whole_texts(spark, data, name):
    from tokenizers import Tokenizer

    texts = ODD + [r.text for r in spark.read.parquet(f"{data}/documents.parquet").collect()]
    whole, own = Tokenizer.from_file(tokenizer_path(name)), Encoder(tokenizer_path(name))
    for _ in range(2):  # fresh, then remembered
        ids, heads = own(pa.array(texts))
        for i, t in enumerate(texts):
            assert ids[heads[i] : heads[i + 1]].tolist() == whole.encode(t, add_special_tokens=False).ids


def documents(spark, texts):
    return spark.createDataFrame([(i, t, "s", 1, 2) for i, t in texts], "doc_id long, text string, length string, start int, bucket int")


def ids_of(texts, name, end):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenizer_path(name))
    return [t.encode(x or "", add_special_tokens=False).ids + [end] for x in texts]


def crc(ids):
    return zlib.crc32(np.array(ids, "<u4").tobytes())


def test_packing_covers_each_id_once(spark, data):
    texts = [(i, t) for i, t in enumerate(ODD)] + [(r.doc_id + 1000, r.text) for r in spark.read.parquet(f"{data}/documents.parquet").collect()] + [(5000, None), (5000, None), (None, "no id")]
    got = packing.pack_documents(documents(spark, texts), keep_ids=True).collect()
    want = sorted((str(i), x) for (i, _), x in zip(texts, ids_of([t for _, t in texts], "byte_bpe_50k.json", 0)))
    parts, sequences = defaultdict(list), defaultdict(list)
    for r in got:
        assert crc(r.ids) == r.ids_crc32 and len(r.ids) == r.length
        parts[r.doc_id].append(r)
        sequences[r.sequence_id].append(r)
    rebuilt = []
    for i, rs in parts.items():
        rs.sort(key=lambda r: r.start)
        starts = [r for r in rs if r.start == 0]
        if len(starts) == 1:
            rebuilt.append((str(i), sum((r.ids for r in rs), [])))
            assert all(r.doc_tokens == len(rebuilt[-1][1]) for r in rs)
        else:
            rebuilt += [(str(i), r.ids) for r in rs]
    assert sorted(rebuilt) == want
    padding = 0
    for rs in sequences.values():
        at = 0
        for r in sorted(rs, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= 1024
        padding += 0 if at & (at - 1) == 0 else 1024 - at
    assert padding <= 0.05 * sum(len(x) for _, x in want) + 1024  # few items: best fit does most of it


def test_column_generation_near_optimal():
    rng = random.Random(3)
    demand = {n: rng.randrange(1, 4000) for n in rng.sample(range(1, 1024), 300)}
    patterns = packing.patterns_for(demand, 1024)
    made = defaultdict(int)
    for p, n in patterns:
        assert sum(k * c for k, c in p.items()) <= 1024
        for k, c in p.items():
            made[k] += c * n
    assert dict(made) == demand
    bound = max(-(-sum(k * c for k, c in demand.items()) // 1024), sum(c for k, c in demand.items() if k > 512))
    assert sum(n for _, n in patterns) <= 1.02 * bound


def test_best_pattern_is_exact_knapsack():
    rng = random.Random(5)
    for _ in range(20):
        lengths = np.array(sorted(rng.sample(range(1, 40), 6)))
        values = np.array([rng.random() for _ in lengths])
        best = [0.0] * 61
        for c in range(1, 61):
            best[c] = max([best[c - 1]] + [best[c - n] + v for n, v in zip(lengths, values) if n <= c])
        got, pattern = packing.best_pattern(values, lengths, 60)
        assert abs(got - best[60]) < 1e-9
        assert sum(lengths[i] * k for i, k in pattern.items()) <= 60


def test_files_round_trip(spark, data):
    texts = [(r.doc_id, r.text) for r in spark.read.parquet(f"{data}/documents.parquet").collect()] + [(10**6 + i, t) for i, t in enumerate(ODD)] + [(10**7, None)]
    random.Random(1).shuffle(texts)
    docs = documents(spark, texts)
    from blockrecover.llm.common import fresh_path

    manifest = token_files.write_files(docs, fresh_path(spark, "files"))
    got = sorted((tuple(r) for r in token_files.read_files(spark, manifest, with_ids=True).collect()))
    at, want = 0, []
    ordered = sorted(texts)
    for (i, _), ids in zip(ordered, ids_of([t for _, t in ordered], "word_bpe_49k.json", 1)):
        want.append((i, at, len(ids), crc(ids), ids))
        at += len(ids)
    assert got == want
    # a reader of one document decompresses the frames that may hold it
    for row in manifest.collect():
        reader = token_files.Reader(row.path)
        names, counts, ids = reader.frame(0)
        assert [x.tolist() for x in reader.document(names[-1])][0] == ids[len(ids) - counts[-1] :].tolist()


def test_damaged_frame_is_noticed(tmp_path):
    path = tmp_path / "f"
    with open(path, "wb") as f:
        w = token_files.Writer(f)
        w.add([1, None], np.array([2, 1]), np.array([5, 6, 7]))
        w.close()
    r = token_files.Reader(str(path))
    assert r.frame(0)[0] == [1, None] and r.document(1)[0].tolist() == [5, 6]
    r.seek[0] = (r.seek[0][0], r.seek[0][1], r.seek[0][2] ^ 1)
    with pytest.raises(ValueError):
        r.frame(0)


def test_empty_tables(spark):
    none = documents(spark, [])
    assert packing.pack_documents(none).count() == 0
    assert token_files.round_trip(none).count() == 0
