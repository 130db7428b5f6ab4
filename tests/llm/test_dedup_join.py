import hashlib
import itertools
import random
import re
from collections import defaultdict

import pytest
from pyspark.sql import functions as F

from blockrecover.llm import exact_dedup, jaccard_join

DOCS = "doc_id long, text string, lang string, source string, n_chars long, body string, digest string, keep_id long"


def frame(spark, rows):
    """Documents with extra columns whose names clash with the operators' own."""
    return spark.createDataFrame([(i, t, "en", "s", len(t or ""), "x", "y", 7) for i, t in rows], DOCS)


def lower(t):
    return re.sub("[A-Z]", lambda m: m[0].lower(), t or "")


ODD = [(1, "Abc É"), (2, "aBC É"), (3, "abc é"), (4, None), (5, ""), (6, "abc É"), (6, "abc É"), (7, "x" * 200_000), (8, "X" * 200_000), (None, "solo"), (None, "")]


def test_exact_dedup_brute_force(spark):
    got = exact_dedup.deduplicate(frame(spark, ODD)).collect()
    groups = defaultdict(list)
    for i, t in ODD:
        groups[lower(t)].append(i)
    want = []
    for i, t in ODD:
        ids = [x for x in groups[lower(t)] if x is not None]
        keep = max(ids) if ids else None
        want.append((i, keep, len(groups[lower(t)]), i == keep, hashlib.sha256(lower(t).encode()).hexdigest()))
    key = lambda r: tuple(str(x) for x in r)
    assert sorted(map(tuple, got), key=key) == sorted(want, key=key)


def test_exact_dedup_compares_content_under_colliding_digests(spark):
    rows = [(i, f"text {i % 7}") for i in range(40)]
    weak = lambda c: F.unhex(F.substring(F.sha2(c, 256), 1, 1).cast("string"))
    got = exact_dedup.deduplicate(frame(spark, rows), digest=lambda c: F.coalesce(F.unhex(F.lpad(F.substring(F.sha2(c, 256), 1, 1), 2, "0")), F.lit(b""))).collect()
    assert weak is not None
    assert all(r.group_size == sum(j % 7 == r.doc_id % 7 for j in range(40)) for r in got)


def test_survivors_keep_columns_and_one_row(spark):
    docs = frame(spark, ODD)
    got = exact_dedup.survivors(docs).collect()
    assert exact_dedup.survivors(docs).columns == docs.columns
    assert sorted((str(r.doc_id), lower(r.text)) for r in got) == sorted({"3": "abc é", "5": "", "6": "abc É", "8": "x" * 200_000, "None": "solo"}.items())


@pytest.mark.parametrize("f", [exact_dedup.deduplicate, exact_dedup.survivors, jaccard_join.classes, jaccard_join.representatives])
def test_empty_table(spark, f):
    assert f(frame(spark, [])).count() == 0


def shingles(text, order=5):
    words = re.findall(r"[^\x20\x09-\x0D]+", lower(text))
    if not words:
        return frozenset()
    return frozenset(zip(*(words[k:] for k in range(order)))) if len(words) >= order else frozenset([tuple(words)])


def brute(rows):
    sets = {}
    parent = {i: i for i, _ in rows if i is not None}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, t in rows:
        if i is not None:
            sets.setdefault(i, []).append(shingles(t))
    flat = [(i, s) for i, ss in sets.items() for s in ss if s]
    for (i, a), (j, b) in itertools.combinations(flat, 2):
        if 100 * len(a & b) >= 80 * len(a | b):
            x, y = find(i), find(j)
            parent[max(x, y)] = min(x, y)
    return {i: find(i) for i in parent}


def corpus(seed, n=220):
    """Clusters of near copies around the threshold, shared passages, chains, tiny texts, repeats."""
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(4))
    passages = [[word() for _ in range(40)] for _ in range(3)]
    rows, k = [], 0
    while len(rows) < n:
        base = [word() for _ in range(rng.choice([1, 3, 5, 6, 9, 30, 60, 120]))]
        if rng.random() < 0.4:
            base += passages[rng.randrange(3)]
        for _ in range(rng.choice([1, 1, 2, 3, 12])):
            copy = list(base)
            for _ in range(rng.randrange(0, max(1, len(copy) // 18) + 1)):
                copy[rng.randrange(len(copy))] = word()
            if rng.random() < 0.2:
                base = copy  # a chain
            rows.append((k, " ".join(copy) if rng.random() < 0.9 else "\t".join(copy).upper()))
            k += 1
    return rows + [(k, ""), (k + 1, None), (k + 2, " \n\t"), (k + 3, rows[0][1]), (k + 3, rows[0][1])]


@pytest.mark.parametrize("seed", [1, 2])
def test_jaccard_components_equal_brute_force(spark, seed):
    rows = corpus(seed)
    want = brute(rows)
    got = jaccard_join.classes(frame(spark, rows), sample=50).collect()
    assert len(got) == len(rows)
    assert {r.doc_id: r.component_id for r in got} == want
    size = defaultdict(set)
    for i, t in rows:
        size[i].add(len(shingles(t)))
    assert all(r.n_shingles in size[r.doc_id] for r in got)


@pytest.mark.parametrize("seed,limit", [(3, 150), (5, 600)])
def test_jaccard_of_regions_beyond_a_task(spark, seed, limit):
    """Regions of more than ``limit`` shingles meet pivots and are joined block by block."""
    rows = corpus(seed, 120)
    got = jaccard_join.classes(frame(spark, rows), sample=10, limit=limit).collect()
    assert {r.doc_id: r.component_id for r in got} == brute(rows)


@pytest.mark.parametrize("seed", range(6))
def test_matched_joins_what_brute_force_joins(seed):
    """A family around the radius in one region, all seeking or a part of it."""
    import numpy as np

    rng = np.random.default_rng(seed)
    base = rng.choice(10**6, 60, replace=False)
    bodies = []
    for _ in range(90):
        s = base.copy()
        k = int(rng.integers(0, 16))
        s[rng.choice(60, k, replace=False)] = rng.choice(40 if seed % 2 else 10**6, k) + 10**6
        bodies.append(np.unique(s).astype(np.uint64))
    seeks = rng.random(90) < (1.0 if seed < 3 else 0.3)
    got = jaccard_join.matched(bodies, np.arange(90), seeks, 80)

    def classes(pairs):
        label = list(range(90))
        for i, j in pairs:
            a, b = label[i], label[j]
            label = [min(a, b) if x in (a, b) else x for x in label]
        return label

    sets = [set(b.tolist()) for b in bodies]
    near = lambda i, j: 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j])
    assert all(near(i, j) for i, j in got) and len(got) < 90
    assert classes(got) == classes((i, j) for i, j in itertools.combinations(range(90), 2) if (seeks[i] or seeks[j]) and near(i, j))


def test_representatives(spark):
    rows = corpus(4, 60)
    want = {c for i, c in brute(rows).items()}
    docs = frame(spark, rows + [(None, "some words without an id")])
    got = jaccard_join.representatives(docs)
    assert got.columns == docs.columns
    assert {r.doc_id for r in got.collect()} == want | {None}
