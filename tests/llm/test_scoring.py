import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest

from blockrecover.llm import lm_scoring, mixing, topk_search, toxicity, url_filter

DOCS = "doc_id long, text string, lang string, source string, held_out string, score int, size int, turn int"


def frame(spark, rows):
    return spark.createDataFrame([(i, t, "en", s, "x", 1, 2, 3) for i, t, s in rows], DOCS)


def tokens(t):
    return re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))


def texts(seed=1, n=120):
    rng = random.Random(seed)
    words = ["w%d" % int(rng.paretovariate(0.7)) for _ in range(3000)]
    rows = [(i, " ".join(rng.choice(words) for _ in range(rng.randrange(0, 60))), rng.choice(["a", "b", None])) for i in range(n)]
    return rows + [(n, None, "a"), (n + 1, "", "b"), (n + 2, rows[3][1], "c"), (n + 2, rows[3][1], "c"), (None, "W1 w2", "a")]


@pytest.mark.parametrize("bound", [96 << 20, 0])
def test_base_score_brute_force(spark, bound):
    rows = texts()
    got = lm_scoring.score(frame(spark, rows), most_base_bytes=bound).collect()
    held = lambda i: zlib.crc32(str("" if i is None else i).encode()) % 7 == 2
    count = Counter()
    for i, t, _ in rows:
        if not held(i):
            count.update(tokens(t) + ["</s>"])
    n, v = sum(count.values()), len(count)
    want = []
    for i, t, _ in rows:
        own = tokens(t) + ["</s>"]
        want.append((str(i), held(i), len(own), sum(count[w] > 0 for w in own), n, round(sum(math.log10((count[w] + 1) / (n + v + 1)) for w in own), 6)))
    assert sorted((str(r.doc_id), r.held_out, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 6)) for r in got) == sorted(want)
    assert all(math.isfinite(r.score) and r.score < 0 for r in got)


def test_filter_never_reads_below_and_seldom_above(spark):
    counts = [(0, 1, int(c)) for c in range(1, 200)]
    h = lm_scoring.mix64(np.arange(1, 200, dtype=np.uint64))
    c = np.array([x[2] for x in counts], "<u4")
    hist = np.bincount(c, minlength=256).tolist()
    table = spark.createDataFrame([(0, 1, 0, 0, hist, bytearray(h.tobytes()), bytearray(c.tobytes()))], "bucket int, order int, total long, kinds long, histogram array<long>, h binary, c binary")
    bloom = lm_scoring.build_filter(table, 1, base=1.3, bits_a_key=12, most_bytes=1 << 20)
    read, stored = bloom.level(h, 1), lm_scoring.level_of(c, 1.3)
    assert (read >= stored).all() and (read == stored).mean() > 0.9
    other = lm_scoring.mix64(np.arange(10**6, 10**6 + 5000, dtype=np.uint64))
    assert (bloom.level(other, 1) == 0).mean() > 0.97
    low, high = lm_scoring.edges(stored, 1.3)
    assert (low <= c).all() and (high >= c).all()


def test_model_beats_base_on_held_out(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    got = [r for r in lm_scoring.score(docs).collect() if r.held_out]
    assert sum(r.score for r in got) > sum(r.base_score for r in got)


@pytest.mark.parametrize("n", [120, 4])
def test_scores_do_not_depend_on_the_broadcast_bound(spark, n):
    rows = frame(spark, texts(5, n))
    whole, parted = (sorted(map(repr, lm_scoring.score(rows, most_bytes=bound).collect())) for bound in (96 << 20, 0))
    assert whole == parted
    assert lm_scoring.score(rows.where("false"), most_bytes=0).count() == 0


def test_slabs_are_pages_of_their_own(spark):
    docs = spark.range(0, 4000, 1, 1).selectExpr("id AS doc_id", "false AS held_out", "repeat(sha2(cast(id AS string), 256), 80) AS text")
    path = lm_scoring.in_slabs(docs).inputFiles()[0]
    jvm = spark._jvm.org.apache.parquet.hadoop
    reader = jvm.ParquetFileReader.open(jvm.util.HadoopInputFile.fromPath(spark._jvm.org.apache.hadoop.fs.Path(path), spark._jsc.hadoopConfiguration()))
    texts_ = next(c for c in reader.getFooter().getBlocks().get(0).getColumns() if "text" in c.getPath().toDotString())
    pages, size = reader.readOffsetIndex(texts_).getPageCount(), texts_.getTotalUncompressedSize()
    reader.close()
    # else one page holds all of 20 MB
    assert size > 20_000_000 and size / pages <= lm_scoring.WIDE + 1_000_000


def test_a_large_bucket_is_answered_segment_by_segment(spark, monkeypatch):
    import tracemalloc

    import pyarrow as pa

    rng = np.random.default_rng(2)
    asked = [np.concatenate([np.unique(rng.integers(0, 1 << 40, n, np.uint64)) for n in (5_000, 45_000)]) for _ in range(10)]
    single = [int(np.flatnonzero(np.diff(x.astype(np.int64)) < 0)[0]) + 1 for x in asked]
    part = pa.table({"slab": range(10), "single": pa.array(single, pa.int32()), "h": [x.tobytes() for x in asked], "c": [np.ones(len(x), np.uint8).tobytes() for x in asked]}, pa.schema([("slab", pa.int64()), ("single", pa.int32()), ("h", pa.binary()), ("c", pa.binary())]))
    peak = []
    for slices in (1, 8):
        tracemalloc.start()
        got = pa.Table.from_batches(lm_scoring.answers_of(3, part, 64, slices, base=1.15, bits_a_key=12))
        peak.append(tracemalloc.get_traced_memory()[1] / 500_000)
        tracemalloc.stop()
        assert got.column("n_counts").to_pylist() == single and sum(got.column("kinds").to_pylist()) == len({h for x, n in zip(asked, single) for h in x[:n].tolist()})
        for n, levels in zip(got.column("n_levels").to_pylist(), got.column("levels").to_pylist()):
            assert (lm_scoring.widened(levels, n) >= 1).all()
    # bytes for each n-gram asked
    assert peak[1] < 60 < peak[0]
    rows = frame(spark, texts(5))
    monkeypatch.setattr(lm_scoring, "SEGMENT_BYTES", 150)
    whole, parted = (sorted(map(repr, lm_scoring.score(rows, most_bytes=bound).collect())) for bound in (96 << 20, 0))
    assert whole == parted


@pytest.mark.parametrize("bound", [96 << 20, 0])
def test_a_passage_seen_once_in_training_scores_higher(spark, bound):
    is_held = lambda i: zlib.crc32(str(i).encode()) % 7 == 2
    held, trains = [i for i in range(100) if is_held(i)], [i for i in range(100) if not is_held(i)]
    rows = [(trains[0], "the old mill by a river turns", "a"), (held[0], "the old mill by a river turns", "a"), (held[1], "turns a by mill the river old", "a")]
    got = {r.doc_id: r for r in lm_scoring.score(frame(spark, rows), most_bytes=bound).collect()}
    assert math.isclose(got[held[0]].base_score, got[held[1]].base_score)
    # each of the eight pairs has come once, as has its context: share * 1 / 1 at least
    assert got[held[0]].score > 8 * math.log10(0.2) > got[held[1]].score


def test_topk_brute_force(spark):
    rng = np.random.default_rng(3)
    rows = [(i, [float(x) for x in v]) for i, v in enumerate(rng.normal(size=(300, 16)))]
    rows += [(300, None), (350, [float("nan")] * 16), (400, [1.0, None] + [0.0] * 14), (450, []), (500, [0.5] * 16), (501, [0.5] * 16), (501, [0.5] * 16), (550, [0.5] * 8), (600, [float("inf")] * 16), (None, [9.0] * 16)]
    df = spark.createDataFrame([(i, v, 5) for i, v in rows], "vec_id long, embedding array<float>, score int")
    fine = [(i, np.floor(256 * np.pad(np.array(v, np.float32).astype(float), (0, 16 - len(v)))).astype(int)) for i, v in rows if v and all(x is not None and np.isfinite(x) for x in v)]
    want = []
    for i, q in fine:
        if i is not None and i % 50 == 0:
            own = sorted(((-int(q @ v), math.inf if j is None else j) for j, v in fine if j != i))[:5]
            want += [(i, k + 1, None if j == math.inf else j, -s) for k, (s, j) in enumerate(own)]
    for block in (16_384, 3):
        got = topk_search.top_k(df, block=block, shard=64).collect()
        assert sorted(map(tuple, got)) == sorted(want)
    few = topk_search.top_k(df.where("vec_id in (0, 1, 2)"), shard=64).collect()
    assert [(r.query_id, r["rank"]) for r in sorted(few)] == [(0, 1), (0, 2)]
    assert topk_search.top_k(df.where("false")).count() == 0


def test_topk_of_large_ids_beside_null_ids(spark):
    top = 1152921504606846950
    df = spark.createDataFrame([(top, [1.0, 2.0]), (top + 1, [1.0, 1.0]), (None, [0.5, 0.5])], "vec_id long, embedding array<float>")
    got = [(r.query_id, r["rank"], r.vec_id) for r in topk_search.top_k(df).collect()]
    assert sorted(got, key=str) == [(top, 1, top + 1), (top, 2, None)]


def test_posting_lists_hold_every_component(spark):
    rows = np.random.default_rng(9).integers(-300, 300, (50, 6))
    index = topk_search.Index(rows, 16)
    back = np.zeros_like(rows)
    for i, (lo, hi) in enumerate(zip(index.heads, index.ends)):
        back[index.postings[lo:hi], index.dimension[i]] += index.level[i] * 16
    assert ((rows - back >= 0) & (rows - back < 16)).all()
    size = np.abs(index.level)
    assert (size[1:] <= size[:-1]).all()
    assert [i for _, lists in index.segments() for i in lists] == list(range(len(size)))


def plain_model(bloom, rows, n, v, share, base):
    """The interpolated score of each text word by word, over the levels that the filter reads."""
    least = [int(x) for x in lm_scoring.least_counts(base)[:200]]
    edge = lambda level: (least[level - 1], least[level] - 1) if level else (0, 0)

    def hashes(t):
        import pyarrow as pa

        ((_, own, before, _),) = lm_scoring.token_stream(pa.array([t or ""]))
        return own, before

    out = []
    for t in rows:
        own, before = hashes(t)
        total = 0.0
        for w, c in zip(own, before):
            one = int(bloom.level(np.array([w], np.uint64), 1)[0])
            context = int(bloom.level(np.array([c], np.uint64), 1)[0])
            pair = int(bloom.level(lm_scoring.pair_hash(np.array([c], np.uint64), np.array([w], np.uint64)), 2)[0])
            seen = edge(context)[1]
            p1 = (edge(one)[0] + 1) / (n + v + 1)
            total += math.log10((1 - share) * p1 + share * min(edge(pair)[0], seen) / max(seen, 1))
        out.append(total)
    return out


def test_score_row_by_row(spark):
    """Every score equals a plain loop over the filter's levels, and the levels are those of counts by a plain count."""
    rows = texts(8, 60)
    got = lm_scoring.score(frame(spark, rows)).collect()
    held = lambda i: zlib.crc32(str("" if i is None else i).encode()) % 7 == 2
    import pyarrow as pa

    one, two, starts = Counter(), Counter(), 0
    for i, t, _ in rows:
        if not held(i):
            ((_, own, before, _),) = lm_scoring.token_stream(pa.array([t or ""]))
            one.update(own.tolist())
            two.update(lm_scoring.pair_hash(before, own).tolist())
            starts += 1
    n, v = sum(one.values()), len(one)
    one[int(lm_scoring.START)] = starts
    buckets = lm_scoring.buckets_for(sum(len((t or "").encode()) for _, t, _ in rows))
    bits, sizes = [], []
    for b in range(buckets):
        mine = lambda c: sorted(h for h in c if (h >> 20) % buckets == b)  # noqa: E731, B023
        parts = [(o, np.array(mine(c), np.uint64), np.array([c[h] for h in mine(c)], np.int64)) for o, c in ((1, one), (2, two))]
        part = lm_scoring.segment_of(parts, base=1.15, bits_a_key=12)
        bits.append(part)
        sizes.append(8 * len(part))
    sizes = np.array(sizes, np.int64)
    bloom = lm_scoring.LogBloom(np.concatenate(bits), np.cumsum(sizes) - sizes, sizes, 1.15)
    want = sorted(round(x, 6) for x in plain_model(bloom, [t for _, t, _ in rows], n, v, 0.2, 1.15))
    assert np.allclose(sorted(r.score for r in got), want, atol=1e-5)


def test_targets_fill_by_weight():
    got = mixing.targets([("a", 10), ("b", 1000), ("c", 1000), (None, 100)])
    assert math.isclose(sum(got.values()), 1.5 * 2110) and got["a"] == 20 and got[None] == 200
    left = 1.5 * 2110 - 220
    assert math.isclose(got["b"], min(2000, left * 2 / 3)) or got["b"] == 2000
    assert all(got[s] <= 2 * n + 1e-9 for s, n in (("a", 10), ("b", 1000), ("c", 1000), (None, 100)))


def test_splitting_tree_keeps_quotas():
    tree = mixing.splitting_tree([1000, 7, 0, 333], 13, 5)
    assert tree.sum(axis=0).tolist() == [1000, 7, 0, 333] and (tree >= 0).all()
    assert tree.sum(axis=1).max() - tree.sum(axis=1).min() <= 4
    assert (tree == mixing.splitting_tree([1000, 7, 0, 333], 13, 5)).all()


def test_mix_takes_targets_and_pieces_agree(spark):
    rows = texts(4, 200)
    got = mixing.taken_words(frame(spark, rows), block_words=32, shards=7).collect()
    placed, pieces = mixing.mix(frame(spark, rows), block_words=32, shards=7)
    source = {(r.source, r.before, r.doc_id): r for r in placed.collect()}
    assert len(got) == len(rows) and sorted(map(repr, got)) == sorted(map(repr, mixing.taken_words(frame(spark, rows), block_words=32, shards=7).collect()))
    for r in got:
        assert 0 <= r.taken <= 2 * r.size and r.size == len(tokens(next(t for i, t, _ in rows if i == r.doc_id)))
    drawn, seen, where = Counter(), set(), Counter()
    for r in pieces.collect():
        assert 0 <= r["shard"] < 7 and (r.source, r.before, r.doc_id) in source
        drawn[r.source] += r.n_words
        where[r["shard"]] += r.n_words
        span = {(r.source, r.round, r.before + k) for k in range(r.start_word, r.start_word + r.n_words)}
        assert not span & seen  # no word twice in one time round
        seen |= span
    goal = {r.source: r.target for r in placed.collect()}
    assert all(abs(drawn[s] - goal[s]) <= 0.5 + 1e-9 for s in goal)
    assert sum(r.taken for r in got) == sum(drawn.values()) and len(where) == 7
    out = mixing.mixed_documents(frame(spark, rows), block_words=32, shards=7)
    assert out.columns == frame(spark, rows).columns
    text = {i: tokens(t) for i, t, _ in rows}
    back = Counter()
    for r in out.collect():
        own, have = tokens(r.text), text[r.doc_id]
        assert any(have[k : k + len(own)] == own for k in range(len(have) - len(own) + 1))
        back[r.source] += len(own)
    assert back == drawn
    assert mixing.mixed_documents(frame(spark, [])).count() == 0 and mixing.taken_words(frame(spark, [])).count() == 0


def test_leaves_of_the_tree_decide_what_is_drawn(spark):
    """Blocks by shard are the leaves; a tree that deals otherwise draws other words, with equal targets."""
    docs = frame(spark, texts(6, 150))

    def lopsided(quotas, shards, seed):
        out = np.zeros((shards, len(quotas)), np.int64)
        out[0], out[-1] = [q - q // 3 for q in quotas], [q // 3 for q in quotas]
        return out

    taken = []
    for tree in (mixing.splitting_tree, lopsided):
        placed, pieces = mixing.mix(docs, block_words=16, shards=5, tree=tree)
        size = {r.source: r.source_size for r in placed.collect()}
        goal = mixing.targets(list(size.items()))
        names = mixing.in_order(size)
        plan = {p[0]: p for p in mixing.plan(size, goal, cap=2.0, shards=5, block_words=16, seed=17, tree=tree)}
        leaves = tree([plan[s][3] // plan[s][4] if s in plan else 0 for s in names], 5, 17)
        whole = {s: set() for s in names}
        for r in pieces.collect():
            whole[r.source].add((r["shard"], r.round, r.block))
        for i, s in enumerate(names):
            if s in plan:
                rests = len(plan[s][-1])
                dealt = Counter(k for k, _, _ in whole[s])
                assert sum(dealt.values()) == leaves[:, i].sum() + rests
                assert sum(abs(dealt[k] - int(leaves[k, i])) for k in range(5)) == rests
        taken.append({(r.doc_id, r.size): r.taken for r in mixing.taken_words(docs, block_words=16, shards=5, tree=tree).collect()})
    assert taken[0] != taken[1] and sum(taken[0].values()) == sum(taken[1].values())


@pytest.mark.parametrize("seed", range(8))
def test_draws_cover_their_counts(seed):
    rng = np.random.default_rng(seed)
    blocks = int(rng.integers(1, 60))
    leaves = rng.multinomial(int(rng.integers(0, 2 * blocks + 1)), [0.25] * 4).tolist()
    draw = mixing.Draw(leaves, blocks, "s", seed)
    places = [p for p in range(blocks) if draw.drawn(p)]
    assert len(places) + draw.rounds * blocks == sum(leaves)
    assert sorted(places + list(draw.spare())) == list(range(blocks))
    assert all(sorted(draw.place(b, k) for b in range(blocks)) == list(range(blocks)) for k in (0, 1))


def test_toxicity_held_out_and_location(spark):
    rng = random.Random(2)
    word = lambda: "".join(rng.choice("abcdef") for _ in range(3))
    rows, labels = [], []
    for i in range(900):
        parts = [" ".join(word() for _ in range(8)).capitalize() + "." for _ in range(rng.randrange(1, 9))]
        bad = i % 3 == 0
        if bad:
            parts.insert(rng.randrange(len(parts) + 1), f"{word()} vilest{word()} {word()}.")
        rows.append((i, " ".join(parts), "a"))
        labels.append((i, int(bad)))
    rows += [(5000, None, "a"), (5001, "", "a"), (None, "vilestabc", "a")]
    docs = frame(spark, rows)
    model = toxicity.fit(docs, spark.createDataFrame(labels + [(None, 1), (3, None)], "doc_id long, toxic int"))
    got = {r.doc_id: r for r in toxicity.predict(docs, model).collect()}
    held = [i for i in range(900) if got[i].held_out]
    assert len(held) > 100 and sum(got[i].predicted == labels[i][1] for i in held) >= 0.98 * len(held)
    assert got[5000].score == got[5001].score == 0 and got[None].predicted == 1
    found = toxicity.offending(docs, model).collect()
    text = dict((i, t) for i, t, _ in rows)
    assert all("vilest" in text[r.doc_id].encode()[r.start : r.end].decode() for r in found if r.doc_id in held)
    assert toxicity.clean(docs, model).count() == sum(r.predicted == 0 for r in got.values())
    none = toxicity.fit(docs, spark.createDataFrame([], "doc_id long, toxic int"))
    assert {r.score for r in toxicity.predict(docs, none).collect()} == {0.0}


@pytest.mark.parametrize("n", [60, 240])
def test_toxicity_learns_from_few_labels(spark, n):
    rng = random.Random(4)
    word = lambda: "".join(rng.choice("abcdef") for _ in range(3))
    rows = []
    for i in range(n):
        parts = [" ".join(word() for _ in range(8)) + "." for _ in range(1 + i % 6)]
        rows.append((i, " ".join(parts + [f"{word()} vilest {word()}."] * (i % 6 == 0)), "a"))
    docs = frame(spark, rows)
    model = toxicity.fit(docs, spark.createDataFrame([(i, int(i % 6 == 0)) for i in range(n)], "doc_id long, toxic int"))
    got = toxicity.predict(docs, model).collect()
    assert sum(r.predicted == (r.doc_id % 6 == 0) for r in got) >= 0.95 * n


def test_toxicity_smallest_tables(spark, data):
    docs, labels = spark.read.parquet(f"{data}/documents.parquet"), spark.read.parquet(f"{data}/labels.parquet")
    got = toxicity.predict(docs, toxicity.fit(docs, labels)).join(labels, "doc_id").collect()
    assert sum(r.predicted for r in got if r.toxic == 1) >= 0.5 * sum(r.toxic == 1 for r in got)
    assert not any(r.predicted for r in got if r.toxic == 0)


def plain_noisy_or(model, text):
    """Sentence by sentence, word by word: (score, offending sentences)."""
    cut = b"[\\x20\\x09-\\x0D" + re.escape("".join(chr(b) for b in range(33, 127) if not chr(b).isalnum()).encode()) + b"]+"
    data, miss, found, at = re.sub(rb"[A-Z]", lambda m: m[0].lower(), (text or "").encode()), 1.0, [], 0
    for part in re.findall(rb"[^.!?\n]*[.!?\n]|[^.!?\n]+", data):
        words, logit = [w for w in re.split(cut, part) if w], model.bias
        for w in words:
            for k, piece in enumerate([w] + [w[:n] if len(w) > n else b"" for n in (4, 5)]):
                if piece:
                    h = toxicity.span_hashes(np.frombuffer(piece, np.uint8), np.array([0]), np.array([len(piece)]))[0] ^ np.uint64(0x5851F42D4C957F2D * (k + 1) % (1 << 64))
                    logit += float(model.weights[int(h >> np.uint64(9)) & ((1 << toxicity.BITS) - 1)])
        if words:
            p = 1 / (1 + math.exp(-logit))
            miss *= 1 - p
            if p >= 0.5:
                found.append((at, at + len(part)))
        at += len(part)
    return 1 - miss, found


def test_toxicity_row_by_row_and_on_given_labels(spark):
    """Scores and located sentences equal a plain noisy-or; held-out labels of the given tables are met."""
    folder = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{folder}/documents.parquet"), spark.read.parquet(f"{folder}/labels.parquet")
    model = toxicity.fit(docs, labels)
    model.weights = model.weights.astype(np.float32).astype(float)
    got = {r.doc_id: r for r in toxicity.predict(docs, model).collect()}
    text = {r.doc_id: r.text for r in docs.collect()}
    for i in sorted(text, key=lambda i: (-got[i].predicted, i))[:150]:
        score, found = plain_noisy_or(model, text[i])
        assert math.isclose(got[i].score, score, abs_tol=1e-6)
        assert [(s.start, s.end) for s in got[i].offending] == found
    held = [r for r in labels.collect() if r.doc_id in got and got[r.doc_id].held_out]
    toxic = [r for r in held if r.toxic == 1]
    assert sum(got[r.doc_id].predicted for r in toxic) >= 0.6 * len(toxic)
    assert sum(got[r.doc_id].predicted for r in held if r.toxic == 0) <= 0.01 * len(held)


def test_very_long_texts_and_urls(spark):
    """Texts and URLs of a few MB."""
    docs = frame(spark, [(1, "calm words here. " * 200_000, "a"), (2, "x" * 3_000_000, "a"), (3, "vilest word. calm.", "a")])
    model = toxicity.fit(docs, spark.createDataFrame([(1, 0), (3, 1)], "doc_id long, toxic int"))
    assert {r.doc_id for r in toxicity.predict(docs, model).collect()} == {1, 2, 3}
    pages = spark.createDataFrame([(1, "http://a.org/" + "p/" * 1_000_000), (2, "http://" + "h" * 2_000_000), (3, "://" * 500_000)], "page_id long, url string")
    rules = spark.createDataFrame(list(url_filter.RULES), "host string, path string, verdict string")
    got = {r.page_id: r for r in url_filter.judge(pages, rules).collect()}
    assert got[1].rule == "org/" and len(got[1].path) == 2_000_001 and len(got[2].host) == 2_000_000 and got[3].host == ":"


def test_url_rules_and_bloom(spark):
    urls = ["http://A.Example.org/es/x?q", "https://example.org/es/", "http://example.org/en/12", "http://example.org/en/2", "http://sub.org", "http://sub.org/", "http://x.com/fr/1", "http://x.com/fr", "http://x.com/de/#a", "com/de/", None, "", "http://www.listed.net/a/", "http://listed.net/a", "http://listed.net/a/b", "http://xcom/de/", "http://u:p@x.com:80/de/"]
    pages = spark.createDataFrame([(i, u, "r", "v") for i, u in enumerate(urls)] + [(0, urls[0], "r", "v")], "page_id long, url string, rule string, verdict string")
    rules = spark.createDataFrame(list(url_filter.RULES), "host string, path string, verdict string")
    listed = spark.createDataFrame([("http://listed.net/a",), ("nothing",)], "url string")

    def parts(u):
        if not u or "://" not in u:
            return "", ""
        rest = u.split("://", 1)[1]
        host = re.match(r"[^/?#]*", rest)[0]
        return host.lower(), re.match(r"[^?#]*", rest[len(host) :])[0]

    def want(u):
        host, path = parts(u)
        fits = [(len(h), len(p), h + p, v) for h, p, v in url_filter.RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
        best = max(fits, default=None)
        block = host.removeprefix("www.") + path.rstrip("/") == "listed.net/a"
        return host, path, best and best[2], best[3] if best else "block" if block else "allow"

    for bound in (64 << 20, 0):
        got = sorted((r.page_id, r.host, r.path, str(r["rule"]), r.verdict) for r in url_filter.judge(pages, rules, listed, most_bytes=bound).collect())
        assert got == sorted((i, *[str(x) if k == 2 else x for k, x in enumerate(want(u))]) for i, u in [*enumerate(urls), (0, urls[0])])
    assert url_filter.judge(pages.where("false"), rules, listed).count() == 0
    assert {r.verdict for r in url_filter.judge(pages, rules.where("false")).collect()} == {"allow"}


def test_bloom_has_no_misses(spark):
    keys = np.random.default_rng(1).integers(-(2**62), 2**62, 3000)
    from pyspark.sql import functions as F

    df = spark.createDataFrame([(int(k),) for k in keys], "key long").withColumn("second", F.xxhash64("key", F.lit(1)))
    bloom = url_filter.Filter.build(df.select("key"), url_filter.Filter.blocks_for(3000))
    rows = df.toPandas()
    assert bloom.passes(rows.key.to_numpy(), rows.second.to_numpy()).all()
    other = np.random.default_rng(2).integers(-(2**62), 2**62, 3000)
    assert bloom.passes(other, np.random.default_rng(3).integers(-(2**62), 2**62, 3000)).mean() < 0.02
